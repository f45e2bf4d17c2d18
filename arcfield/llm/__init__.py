"""Training-data operators: toxicity, dedup, mixing, packing, token output, quality and personal data."""
