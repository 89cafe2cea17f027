"""Schema-free answers over printed tables, on Spark."""

__all__ = ["__version__"]
__version__ = "0.1.0"
