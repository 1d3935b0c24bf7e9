"""Training-data operators: quality, deduplication, extraction, archives, mixing, formatting, token storage and decontamination."""
