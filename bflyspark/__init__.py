"""Butterfly counts of bipartite graphs in time windows, as Spark plans."""
