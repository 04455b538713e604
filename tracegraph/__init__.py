"""Spatio-temporal trace graph engine on PySpark."""

__version__ = "0.1.0"
