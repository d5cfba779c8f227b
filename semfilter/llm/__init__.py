"""Training-data operators: token output, dedup, search, sharding, mixing, language identification."""
