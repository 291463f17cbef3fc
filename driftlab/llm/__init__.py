"""Training-data operators: mixing, secrets, near and exact duplicates, search, tokens, quality, chat."""
