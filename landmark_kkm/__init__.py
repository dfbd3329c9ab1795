"""Kernel clustering of large tables on Spark: landmark embeddings, Lloyd loops, baselines and measures."""

__version__ = "0.1.0"
