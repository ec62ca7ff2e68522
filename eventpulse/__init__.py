"""Block-wise event detection on PySpark."""

__version__ = "0.1.0"
