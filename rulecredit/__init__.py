"""Contribution scores for mined association rules, as Spark DataFrame plans."""

__version__ = "0.1.0"
