"""certgraph: sparse k-connectivity certificates of very large graphs on Spark DataFrames."""

__version__ = "0.1.0"
