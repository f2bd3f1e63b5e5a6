"""Overlapping communities of bipartite graphs by biclique percolation, as PySpark DataFrame programs."""

__version__ = "0.1.0"
