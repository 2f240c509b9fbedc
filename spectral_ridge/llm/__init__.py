"""Training-data operators: quality, near duplicates, mixing, archives, tokens, media, shards."""
