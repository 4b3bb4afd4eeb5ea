"""opatlas: operator-to-function knowledge bases on Spark DataFrames."""

__version__ = "0.1.0"
