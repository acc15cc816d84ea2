"""Subgraph matching on Spark with prefix sets and proactively pruned adjacency lists."""
