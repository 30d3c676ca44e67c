"""Functions for SQL: binomials, diefficiency, and the plan of a schema as a table function."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from shapeplan.runtime import ship


def dief(times: pd.Series, until: float) -> float:
    """Area under the curve of answers at ``times`` up to ``until``."""
    t = np.sort(times[times <= until].to_numpy(float))
    if not len(t):
        return 0.0
    u, k = np.unique(t, return_counts=True)
    k = np.cumsum(k).astype(float)
    return float(np.sum(np.diff(u) * (k[1:] + k[:-1]) / 2) + (until - u[-1]) * k[-1])


class ShapePlan:
    """Rows (pos, shape, deferred) of a schema given as JSON, in the order of a configuration."""

    def eval(self, schema_json: str, config: int):
        from shapeplan.model import schema_from_dict
        from shapeplan.plans.order import plan_validation

        plan = plan_validation(schema_from_dict(json.loads(schema_json)), config)
        for i, s in enumerate(plan.order, 1):
            yield i, s, ",".join(plan.deferrals[s])


def register(spark: SparkSession) -> None:
    """``shape_plan(json, config)``, ``dief(t, until)`` and ``binom(k, n)``."""
    ship(spark)
    spark.udtf.register("shape_plan", F.udtf(ShapePlan, returnType="pos int, shape string, deferred string"))

    @F.pandas_udf("double")
    def dief_udaf(t: pd.Series, until: pd.Series) -> float:
        return dief(t, float(until.iloc[0]))

    spark.udf.register("dief", dief_udaf)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION binom(k BIGINT, n BIGINT) RETURNS DOUBLE RETURN aggregate(sequence(0, greatest(n, 1) - 1), CAST(1 AS DOUBLE), (a, i) -> CASE WHEN i < n THEN a * greatest(k - i, 0) / (i + 1) ELSE a END)")
