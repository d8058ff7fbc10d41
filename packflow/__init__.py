"""packflow: pack unevenly partitioned texts into few, bounded encoder calls on Spark."""

__version__ = "0.1.0"
