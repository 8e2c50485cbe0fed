"""Private location-trace synthesis on Spark."""
