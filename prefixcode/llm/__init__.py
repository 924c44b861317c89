"""Training-data operators: formatting, media, deduplication, scoring, mixing and packing."""
