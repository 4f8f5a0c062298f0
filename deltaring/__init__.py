"""deltaring: learning statistics over joins, kept under inserts and deletes, on Spark."""

__version__ = "0.1.0"
