"""Training-data operators: dedup, search, sharding, mixing, filtering, tokenising."""
