"""Training-data operators: decontamination, fingerprints, sharding, language ID,
substring and line dedup, toxicity, mixing, near duplicates and secret scans.

Nothing else in the library imports this subpackage."""
