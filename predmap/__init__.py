"""Compact immutable key -> value maps on Spark, guided by a model of the values."""
