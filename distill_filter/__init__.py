"""distill_filter: filter text corpora at a small share of a costly annotator's price."""
