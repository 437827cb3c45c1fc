"""Learned equi-depth slicing on Spark: sort, rank, join, group and index through one exchange."""

__version__ = "0.1.0"
