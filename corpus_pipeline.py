"""From raw documents to token ids: five stages, each written as Parquet and read again by the next.

1. toxicity: documents scored 0.3 or more go.
2. line dedup: lines with an earlier equal or one-edit copy go, and documents that lose every line.
3. MinHash near-dedup: of documents linked at a similarity of 0.8 over 5-word shingles, the smallest id of each class
   stays.
4. benchmark decontamination: documents that hold a benchmark item go.
5. byte-level BPE: every document becomes token ids, which are decoded again; ``round_trip`` says that the bytes agree.

SQL cannot express the learned scores and the retrieval, so there is no ``ORACLE_SQL``; tests hold each stage against
a plain version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_traces.llm import bpe, decontaminate, lines, minhash, toxicity
from private_traces.llm.common import aside, table, written

ORACLE_SQL = None
WORDS = 5
SIMILARITY = 80


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents scored under 0.3; a null or empty text has the score of a text without any known term."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    moved, back = aside(docs, ["doc_id", "text"])
    return back(toxicity.score(moved, model).where(F.col("score") < toxicity.CUT))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with their remaining lines and length; one that had lines and lost them all goes, one without any (null
    or blank) stays as it is."""
    moved, back = aside(docs, ["doc_id", "text", "n_chars"])
    done = lines.dedup(moved).where((F.col("n_lines") == 0) | (F.col("n_removed") < F.col("n_lines")))
    chars = F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return back(done.withColumn("n_chars", chars))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each class of near duplicates and those in no class. Rows are told apart by id and text: of a
    repeated id only the rows whose text is a later copy go."""
    return minhash.drop_later(docs, width=WORDS, percent=SIMILARITY).select(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents without a benchmark item; null and empty texts hold none."""
    moved, back = aside(docs, ["doc_id", "text"])
    return back(decontaminate.find(moved, table(spark, sf_dir, "benchmark")).where(F.size("leaks") == 0))


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``doc_id, lang, source, n_tokens, token_ids, round_trip``."""
    import public_tokenizers

    coded = bpe.round_trip(docs.select("doc_id", "lang", "source", "text"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return coded.select("doc_id", "lang", "source", F.size("token_ids").cast("long").alias("n_tokens"), "token_ids", "round_trip")


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", dedup_lines),
    ("minhash", drop_near_duplicates),
    ("decontaminate", drop_leaks),
    ("byte_bpe", tokenize),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole of ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs
