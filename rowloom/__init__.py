"""Row reordering for column compression, as Spark DataFrame plans."""

__version__ = "0.1.0"
