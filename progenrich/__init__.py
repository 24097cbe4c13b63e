"""Progressive enrichment of uncertain tags on Spark."""
