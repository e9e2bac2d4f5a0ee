"""Training-data operators: quality, deduplication, mixing, packing, counting and token output."""
