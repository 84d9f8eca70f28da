"""Models grounded from tables, rewrites of graphs, and the catalogue of queries."""
