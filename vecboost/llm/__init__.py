"""Training-data operators: quality, dedup, filters, tokens, packing, mixing, toxicity, WARC."""
