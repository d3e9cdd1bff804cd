"""Private node vectors from graphs whose vertices see only their own links, on Spark DataFrames."""

from veilwalk.config import WalkConfig

__all__ = ["WalkConfig"]
