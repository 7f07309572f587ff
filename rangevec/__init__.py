"""Range-filtered vector search on Spark."""

__version__ = "0.1.0"
