"""Expressions that several kernels use."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def binary_entropy(p: Column) -> Column:
    """Entropy in bits of a share; zero at and beyond 0 and 1."""
    return F.when((p <= 0) | (p >= 1), F.lit(0.0)).otherwise(-p * F.log2(p) - (1 - p) * F.log2(1 - p))
