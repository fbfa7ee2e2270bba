"""curvature_spark: communication-compressed second-order training on Spark DataFrames."""

__version__ = "0.1.0"
