"""Training-data operators: dedup, filters, classifiers, tokenization, packing, media and sharding."""
