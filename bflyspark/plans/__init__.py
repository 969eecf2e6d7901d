"""Query registry, SQL surface and relational operators on the graph tables."""
