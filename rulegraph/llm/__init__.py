"""Training-data operators: packing, sharding, deduplication, decontamination, formats, search."""
