"""Training-data operators: packing, near-duplicates, scoring, filtering, formatting, search and mixing."""
