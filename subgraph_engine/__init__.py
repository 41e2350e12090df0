"""Compute-heavy subgraph search on Spark, and the operators around it."""
