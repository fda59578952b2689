"""Training-data operators (deduplication, filtering, tokenising, search)."""
