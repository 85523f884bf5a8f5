"""Joins that the library has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, values: list[str], prefix: str = "last_") -> DataFrame:
    """Each left row with the latest right row of its key at or before its time. One exchange by key: both sides are
    laid one after the other and values carried forward."""
    a = left.select("*", F.lit(1).alias("__side"), F.col(left_time).alias("__at"), *[F.lit(None).cast(right.schema[v].dataType).alias(f"{prefix}{v}") for v in values], F.lit(None).cast(right.schema[right_time].dataType).alias(f"{prefix}{right_time}"))
    rest = [F.col(k) for k in keys] + [F.lit(None).cast(f.dataType).alias(f.name) for f in left.schema.fields if f.name not in keys]
    b = right.select(*rest, F.lit(0).alias("__side"), F.col(right_time).alias("__at"), *[F.col(v).alias(f"{prefix}{v}") for v in values], F.col(right_time).alias(f"{prefix}{right_time}"))
    names = [*values, right_time]
    # A struct, so that null values of the latest row are not skipped.
    row = F.when(F.col("__side") == 0, F.struct(*[F.col(f"{prefix}{v}") for v in names]))
    carried = F.last(row, ignorenulls=True).over(Window.partitionBy(*keys).orderBy("__at", "__side").rowsBetween(Window.unboundedPreceding, 0))
    both = a.unionByName(b.select(*a.columns)).withColumn("__row", carried).where("__side = 1")
    return both.select(*left.columns, *[F.col("__row")[f"{prefix}{v}"].alias(f"{prefix}{v}") for v in names])


def within(left: DataFrame, right: DataFrame, keys: list[str], left_at: str, right_at: str, reach: int) -> DataFrame:
    """Pairs of equal key with ``0 < right_at - left_at <= reach``, by buckets of the reach: a hot key is spread over its
    buckets, and each left row goes to two of them."""
    a = left.withColumn("__b", F.explode(F.array(F.floor(F.col(left_at) / reach), F.floor(F.col(left_at) / reach) + 1)))
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("__rb", F.floor(F.col(f"r_{right_at}") / reach))
    on = F.col("__b") == F.col("__rb")
    for k in keys:
        on = on & (F.col(k) == F.col(f"r_{k}"))
    gap = F.col(f"r_{right_at}") - F.col(left_at)
    return a.join(b, on).where((gap > 0) & (gap <= reach)).drop("__b", "__rb")
