"""Near-duplicate detection and bounded-similarity clustering on Spark."""
