"""trainscape: a PySpark engine for distributed-training trade-off studies."""

__version__ = "0.1.0"
