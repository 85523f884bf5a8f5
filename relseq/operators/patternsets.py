"""Sets of refinements as tables (skeleton, vector, support): set operations, and what changed between two runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEY = ["skeleton", "vector"]


def union(a: DataFrame, b: DataFrame) -> DataFrame:
    """Refinements of either set; the higher support where both have one."""
    return a.select(*KEY, "support").unionByName(b.select(*KEY, "support")).groupBy(*KEY).agg(F.max("support").alias("support"))


def intersection(a: DataFrame, b: DataFrame) -> DataFrame:
    """Refinements of both sets, with the support of the first."""
    return a.select(*KEY, "support").join(b.select(*KEY), KEY, "left_semi")


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Refinements of the first set that the second lacks."""
    return a.select(*KEY, "support").join(b.select(*KEY), KEY, "left_anti")


def changes(a: DataFrame, b: DataFrame) -> DataFrame:
    """(skeleton, vector, support_a, support_b, change): every refinement of two runs, whether of one corpus under two
    settings or of two corpora; both sides are dealt by skeleton and vector and meet there."""
    both = a.select(*KEY, F.col("support").alias("support_a")).join(b.select(*KEY, F.col("support").alias("support_b")), KEY, "full_outer")
    change = F.when(F.col("support_a").isNull(), "new").when(F.col("support_b").isNull(), "gone").when(F.col("support_a") < F.col("support_b"), "more").when(F.col("support_a") > F.col("support_b"), "less").otherwise("same")
    return both.withColumn("change", change)
