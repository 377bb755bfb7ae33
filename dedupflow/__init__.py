"""Concurrent cross-client deduplication on Spark: protected tags, atomic claims, recovery, joins and rounds as DataFrame plans."""
