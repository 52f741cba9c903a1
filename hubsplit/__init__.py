"""hubsplit: subgraph programs over hub-splitting edge partitions, on Spark DataFrames."""

__version__ = "0.1.0"
