"""Training-data operators: ten methods for filtering, scoring, deduplicating and packing text at scale."""
