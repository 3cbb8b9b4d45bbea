"""basisflow: similarity deduplication of small byte chunks on Spark DataFrames."""

__version__ = "0.1.0"
