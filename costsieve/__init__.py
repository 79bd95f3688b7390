"""Cost-aware approximate membership filters on Spark DataFrames."""

__version__ = "0.1.0"
