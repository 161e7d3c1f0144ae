"""keyhop: ad-hoc filtering of large fact tables by jumps over one composite key, on Spark."""

__version__ = "0.1.0"
