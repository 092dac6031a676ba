"""Index, assignment, exchange, counting and measures over signed bipartite graphs."""
