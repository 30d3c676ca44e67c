"""Operators around validation: as-of and range joins, reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], on: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the latest right row at or before it, by one sort of both sides together."""
    blank = [F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values]
    extra = [c for c in left.columns if c not in (*by, on)]
    lhs = left.select(*by, on, F.struct(*extra).alias("_l"), *blank, F.lit(1).alias("_side"))
    rhs = right.select(*by, on, F.lit(None).cast(lhs.schema["_l"].dataType).alias("_l"), *values, F.lit(0).alias("_side"))
    w = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    packed = F.last(F.when(F.col("_side") == 0, F.struct(*values)), ignorenulls=True).over(w)
    return lhs.unionByName(rhs).withColumn("_m", packed).where("_side = 1").select(*by, on, "_l.*", *[F.col(f"_m.{v}").alias(v) for v in values])


def range_join(left: DataFrame, right: DataFrame, by: list[str], at: Column, low: Column, high: Column) -> DataFrame:
    """Pairs with equal keys whose ``at`` lies between ``low`` and ``high``: an equi-join with a residual condition."""
    r = right.withColumnsRenamed({c: f"_r_{c}" for c in by})
    keys = [F.col(c) == F.col(f"_r_{c}") for c in by]
    cond = keys[0]
    for k in keys[1:]:
        cond = cond & k
    return left.join(r, cond & at.between(low, high)).drop(*[f"_r_{c}" for c in by])


def quality_report(verdicts: DataFrame, dims: list[str], kind: str = "rollup") -> DataFrame:
    grouped = verdicts.rollup(*dims) if kind == "rollup" else verdicts.cube(*dims)
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.count_if("valid").alias("n_valid"))


def top_invalid(report: DataFrame, k: int) -> DataFrame:
    """The shapes with most invalid entities, as a bounded heap a task."""
    return report.orderBy(F.desc("n_invalid"), "shape").limit(k)
