"""zbox: multi-dimensional box queries over bit-interleaved keys, on Spark DataFrames."""

__version__ = "0.1.0"
