"""Training-data operators: media columns, mixing, deduplication, tokenising, sharding, search, licences, languages."""
