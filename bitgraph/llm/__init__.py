"""Training-data operators: scans, deduplication, decontamination, scoring and mixing of text tables."""
