"""Static functions and membership filters over GF(2) band systems, built with Spark."""

__version__ = "0.1.0"
