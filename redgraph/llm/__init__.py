"""Training-data operators: decontamination, de-duplication, sharding, mixing, scoring and repair."""
