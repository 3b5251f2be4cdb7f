"""redgraph: reduction-style graph programs on Spark DataFrames."""

__version__ = "0.1.0"
