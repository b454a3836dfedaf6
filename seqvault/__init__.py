"""Compressed, sealed full-text indexes over string collections, built and searched with Spark."""

__version__ = "0.1.0"
