"""A query endpoint that gives at most so many rows an answer, and what that does to verdicts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Endpoint:
    """Answers are sorted by all their columns, as a deterministic endpoint would, and cut after ``max_rows``; None cuts nothing."""

    max_rows: int | None = None

    def answer(self, rows: DataFrame) -> DataFrame:
        return rows if self.max_rows is None else rows.orderBy(*rows.columns).limit(self.max_rows)


def misclassified(exact: DataFrame, capped: DataFrame) -> DataFrame:
    """By shape, from two sets of verdicts: valid entities, those that the capped engine calls invalid, their share; and invalid ones called valid."""
    both = exact.select("shape", "entity", F.col("valid").alias("truth")).join(capped.select("shape", "entity", F.col("valid").alias("said")), ["shape", "entity"], "left")
    said = F.coalesce("said", F.lit(False))
    out = both.groupBy("shape").agg(
        F.count_if("truth").alias("n_valid"), F.count_if(F.col("truth") & ~said).alias("n_missed"), F.count_if(~F.col("truth") & said).alias("n_wrongly_valid"),
    )
    return out.withColumn("share_missed", F.try_divide(F.col("n_missed").cast("double"), F.col("n_valid")))
