"""rarespan: grammar-based discovery of rare stretches in ordered data, on Spark DataFrames."""

__all__ = ["__version__"]
__version__ = "0.1.0"
