"""Enrichment of streams at ingestion and by epochs."""
