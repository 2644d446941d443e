"""Training-data operators: counting, deduplication, fingerprints, packing, quality and mixing."""
