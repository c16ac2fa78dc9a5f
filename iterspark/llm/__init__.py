"""Training-data operators: mixing, fixity, classifiers, filters, sketches, packing, sharding, near-duplicates."""
