"""Training-data operators: filtering, deduplication, privacy, tokens, packing and chat."""
