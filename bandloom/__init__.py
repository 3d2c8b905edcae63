"""Static membership filters and static functions from banded GF(2) systems, on Spark."""
