"""Open-set re-identification of passages on Spark: protocol, scorers, deduplication gate, measures, inference and streams."""
