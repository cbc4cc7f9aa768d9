"""edgesplit: edge partitioning of large graphs on Spark DataFrames."""

__version__ = "0.1.0"
