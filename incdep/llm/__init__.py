"""Training-data operators: token files, near-duplicates, mixing, extraction, search, archives, packing."""
