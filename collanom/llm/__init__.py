"""Training-data operators: cleaning, deduplication, scanning and encoding of text tables."""
