"""colpick: representative-column selection on Spark DataFrames."""

__version__ = "0.1.0"
