"""Continuous behaviour: traces of answers and measures over them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def answer_trace(answers: DataFrame, by: list[str], order: list[str]) -> DataFrame:
    """``answer_no`` of each answer of an engine; ``answers`` has a column ``t`` of seconds."""
    return answers.withColumn("answer_no", F.row_number().over(Window.partitionBy(*by).orderBy(*order)).cast("long"))


def dief_at_t(trace: DataFrame, at: Column | float, by: list[str]) -> DataFrame:
    """Area under the curve of answers up to time ``at``: 0 before the first answer, linear between answers, flat after the last.

    Answers at one time count as one step to the largest number.
    """
    at = F.lit(float(at)) if isinstance(at, (int, float)) else at
    steps = trace.where(F.col("t") <= at).groupBy(*by, "t").agg(F.max("answer_no").alias("k"))
    w = Window.partitionBy(*by).orderBy("t")
    nxt, kn = F.lead("t").over(w), F.lead("k").over(w)
    area = F.when(nxt.isNull(), (at - F.col("t")) * F.col("k")).otherwise((nxt - F.col("t")) * (F.col("k") + kn) / 2.0)
    return steps.withColumn("area", area).groupBy(*by).agg(F.sum("area").alias("dief"))


def trace_summary(trace: DataFrame, by: list[str], steps: bool = True) -> DataFrame:
    """Inverse time to the first answer, inverse execution time, completeness (the last answer's number), throughput, and with ``steps`` the rows of the trace."""
    one = F.lit(1.0)
    out = trace.groupBy(*by).agg(F.min("t").alias("first"), F.max("t").alias("et"), F.max("answer_no").alias("comp"), F.count(F.lit(1)).alias("n_steps"))
    out = out.select(
        *by, F.try_divide(one, "first").alias("inv_tfff"), F.try_divide(one, "et").alias("inv_et"), "comp",
        F.try_divide(F.col("comp").cast("double"), F.col("et")).alias("throughput"), "n_steps",
    )
    return out if steps else out.drop("n_steps")


def times(runs: DataFrame, by: list[str]) -> DataFrame:
    """Mean and standard deviation of ``seconds`` over runs."""
    return runs.groupBy(*by).agg(F.avg("seconds").alias("mean_s"), F.stddev_samp("seconds").alias("sd_s"), F.count(F.lit(1)).alias("n_runs"))
