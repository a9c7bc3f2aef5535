"""Training-data operators: filtering, deduplication, packing and tokenising of text corpora on Spark."""
