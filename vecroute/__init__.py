"""Routed approximate top-k vector search on Spark, with its baselines and measures."""
