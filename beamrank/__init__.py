"""Ranked beams of candidate queries, their rerankers and ablations, on Spark."""
