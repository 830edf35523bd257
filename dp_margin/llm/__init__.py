"""Training-data operators: media, tokens, deduplication, language and page extraction."""
