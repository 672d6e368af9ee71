"""idfold: learned id folding for embedding tables, on Spark DataFrames."""

__version__ = "0.1.0"
