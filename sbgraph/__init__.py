"""Exact balanced-butterfly counting in signed bipartite graphs, on Spark."""
