"""Training-data operators: deduplication, filtering, mixing, extraction, archives, tokens."""
