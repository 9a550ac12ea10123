"""Subgraph listing on static and dynamic graphs, written as Spark plans."""
