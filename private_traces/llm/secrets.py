"""Secret scans: an Aho-Corasick keyword prefilter, anchored expressions only at or near hits, then checksums.

One automaton over the ASCII-lower-cased text finds every keyword. Each expression is tried only where its
keyword was hit (or shortly after it, for numbers that follow a word such as ``card``), never by scanning.
Runs of hexadecimal digits have no keyword and are found by one pass of their own. Kinds with an embedded
checksum (CRC-32 in base 62, Luhn, ISO 7064 mod 97) or structure (a decodable header) are kept only if it holds.

Spans are code points, end exclusive, ordered by start and then by kind in the order of ``KINDS``. Defined
results: a null text is the empty text (no spans); rows are never joined.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import zlib
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import pieces, widened

BASE = ("assign", "access", "hex")
KINDS = (*BASE, "github", "npm", "jwt", "pem", "card", "iban")
CHUNK = 4_000_000
NEAR = 48

# The expressions of the three base kinds and the published shapes of the others.
ASSIGN = re.compile(r"""(?ai:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
GITHUB = re.compile(r"gh[pousr]_([A-Za-z0-9]{36})(?![A-Za-z0-9])")
NPM = re.compile(r"npm_([A-Za-z0-9]{36})(?![A-Za-z0-9])")
JWT = re.compile(r"(eyJ[A-Za-z0-9_-]+)\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+")
PEM = re.compile(r"-----BEGIN (?:[A-Z]+ ){0,3}PRIVATE KEY-----")
CARD = re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9]){12,18}(?![0-9])")
IBAN = re.compile(r"(?<![A-Z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}(?![A-Z0-9])")
KEYWORDS = {
    "password": "assign", "passwd": "assign", "secret": "assign", "token": "assign", "api_key": "assign", "apikey": "assign",
    "akia": "access", "ghp_": "github", "gho_": "github", "ghu_": "github", "ghs_": "github", "ghr_": "github",
    "npm_": "npm", "eyj": "jwt", "-----begin": "pem", "card": "card", "visa": "card", "iban": "iban",
}
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"


def crc_base62(body: str) -> bool:
    """The last six characters are the CRC-32 of those before them, in base 62."""
    value, sign = zlib.crc32(body[:-6].encode()), ""
    while value:
        value, r = divmod(value, 62)
        sign = BASE62[r] + sign
    return sign.rjust(6, "0") == body[-6:]


def luhn(number: str) -> bool:
    digits = [int(c) for c in number if c.isdigit()]
    doubled = [d * 2 - 9 * (d > 4) for d in digits[-2::-2]]
    return len(set(digits)) > 1 and (sum(digits[::-2]) + sum(doubled)) % 10 == 0


def mod97(number: str) -> bool:
    plain = number.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


def headed(segment: str) -> bool:
    try:
        return "alg" in json.loads(base64.urlsafe_b64decode(segment + "=" * (-len(segment) % 4)))
    except (ValueError, TypeError):
        return False


SHAPES = {
    "assign": (ASSIGN, lambda m: len(m[2]) >= 6), "access": (ACCESS, lambda m: len(m[0]) >= 20),
    "github": (GITHUB, lambda m: crc_base62(m[1])), "npm": (NPM, lambda m: crc_base62(m[1])),
    "jwt": (JWT, lambda m: headed(m[1])), "pem": (PEM, lambda m: True),
    "card": (CARD, lambda m: luhn(m[0])), "iban": (IBAN, lambda m: mod97(m[0])),
}
FOLLOWING = ("card", "iban")


@lru_cache(maxsize=1)
def _automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for word, kind in KEYWORDS.items():
        a.add_word(word, (kind, len(word)))
    a.make_automaton()
    return a


def spans(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, kind)`` of every secret in one text."""
    low = text if text.islower() else text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")
    hits: dict[str, list[int]] = {}
    for end, (kind, n) in _automaton().iter(low):
        hits.setdefault(kind, []).append(end + 1 if kind in FOLLOWING else end - n + 1)
    found = [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    for kind, places in hits.items():
        shape, holds = SHAPES[kind]
        over = 0
        for at in sorted(places):
            if at < over:
                continue
            # a card or account number starts within NEAR characters of its word; how far it goes is its shape's affair
            starts = range(at, min(at + NEAR, len(text))) if kind in FOLLOWING else (at,)
            m = next((m for m in (shape.match(text, p) for p in starts) if m), None)
            if m and m.start() >= over:
                over = m.end()
                if holds(m):
                    found.append((m.start(), m.end(), kind))
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


def shown(found: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in found)


def _scan(batches):
    kinds = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value", pa.string())]))
    for batch, texts in pieces(batches, "text", CHUNK):
        found = [[{"kind": k, "start": a, "end": b, "value": t[a:b]} for a, b, k in spans(t)] for t in texts]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, kinds)], [*batch.schema.names, "secrets"])


def scan(docs: DataFrame) -> DataFrame:
    """``docs`` with ``secrets``: an array of (kind, start, end, value), in place of any column of that name."""
    kept = docs.drop("secrets")
    return kept.mapInArrow(_scan, widened(kept, "secrets array<struct<kind:string,start:bigint,end:bigint,value:string>>"))


def _digest(batches):
    for batch, texts in pieces(batches, "text", CHUNK):
        rows = [spans(t) for t in texts]
        base = [[s for s in r if s[2] in BASE] for r in rows]
        counts = {f"n_{k}": pa.array([sum(s[2] == k for s in r) for r in base], pa.int64()) for k in BASE}
        yield pa.RecordBatch.from_pydict({
            "doc_id": batch.column("doc_id"), **counts,
            "base_sha256": pa.array([hashlib.sha256(shown(r).encode()).hexdigest() for r in base], pa.string()),
            "spans": pa.array([shown(r) for r in rows], pa.string()),
        })


def digests(docs: DataFrame) -> DataFrame:
    """Counts, a digest of the base spans and all spans as text, per row of ``docs``."""
    return docs.select("doc_id", "text").mapInArrow(_digest, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
