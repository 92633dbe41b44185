"""Quantile queries over very many sub-populations by mergeable moment summaries, planned as Spark aggregates."""
