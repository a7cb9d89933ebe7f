"""Training-data operators: dedup, media, quality, archives, sharding, tokens, toxicity, packing, URL rules."""
