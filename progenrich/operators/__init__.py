"""The enrichment operator and its parts."""
