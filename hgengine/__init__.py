"""Hypergraph analytics on Spark: typed hypergraphs, alternating supersteps, placements and their measures."""

__version__ = "0.1.0"
