"""Training-data operators: search, packing, cleaning, tokenising and scoring of text corpora."""
