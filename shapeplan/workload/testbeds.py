"""Test beds: schemas, scale factors and corruption levels, and a runner for engine comparisons."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapeplan.execute import validate
from shapeplan.measure import trace as tr
from shapeplan.model import ShapeSchema, load_schema
from shapeplan.plans.order import CONFIGS
from shapeplan.sources import class_tables, corrupt
from shapeplan.sources.mapping import default_mapping

#: The eleven engines of the comparison: name, engine, configuration.
ENGINES = [("naive", "naive", 5), ("naive_py", "naive_py", 5), *((f"planned_{k}", "planned", k) for k in CONFIGS)]


@dataclass(frozen=True)
class Testbed:
    __test__ = False
    schema: str
    sf_dir: str
    level: str

    @property
    def name(self) -> str:
        return f"{self.schema}-{self.sf_dir.rstrip('/').rsplit('/', 1)[-1]}-{self.level}"

    def open(self, spark: SparkSession) -> tuple:
        return graph_of(spark, self.sf_dir, self.schema, self.level)


def graph_of(spark: SparkSession, sf_dir: str, schema: str, level: str = "L0") -> tuple:
    s: ShapeSchema = load_schema(schema)
    g = class_tables(spark, sf_dir, default_mapping(s.options.get("line_key", "line")))
    return corrupt(g, level, wide=schema == "C"), s


def testbeds(root: str = "/root/testdata") -> list[Testbed]:
    """Three schemas, three sizes, three corruption levels."""
    return [Testbed(s, f"{root}/{sf}", level) for s in "ABC" for sf in ("sf0.001", "sf0.01", "sf0.1") for level in ("L1", "L2", "L3")]


testbeds.__test__ = False


def run_matrix(spark: SparkSession, beds: list[Testbed], engines=ENGINES, runs: int = 5, warm_up: bool = True) -> Iterator[tuple[str, str, int, float]]:
    """(test bed, engine, run, seconds) for each validation; a warm-up run before them isn't counted."""
    for bed in beds:
        graph, schema = bed.open(spark)
        for name, engine, config in engines:
            for run in range(-warm_up, runs):
                began = time.monotonic()
                validate(graph, schema, engine, config).verdicts.write.format("noop").mode("overwrite").save()
                if run >= 0:
                    yield bed.name, name, run, time.monotonic() - began


def steps(spark: SparkSession, runs: dict) -> DataFrame:
    """Traces of results by engine: ``engine``, ``t`` (seconds), ``answer_no`` (verdicts so far); a row for each delivery, as its verdicts share a time."""
    rows = [(e, t, sum(n for _, _, n in r.trace[: i + 1])) for e, r in runs.items() for i, (_, t, _) in enumerate(r.trace)]
    return spark.createDataFrame(rows, "engine string, t double, answer_no long")


def continuous(spark: SparkSession, sf_dir: str, schema: str, level: str, engines: tuple[str, ...]) -> DataFrame:
    """By engine the measures of continuous behaviour over its own trace, the area up to the time at which the slowest engine ends."""
    graph, s = graph_of(spark, sf_dir, schema, level)
    made = steps(spark, {e: validate(graph, s, e, traced=True) for e in engines})
    until = made.agg(F.max("t")).first()[0]
    return tr.trace_summary(made, ["engine"]).join(tr.dief_at_t(made, until, ["engine"]), "engine").withColumn("until", F.lit(until))


def measured(spark: SparkSession, sf_dir: str, schema: str, level: str, engines: tuple[str, ...]) -> DataFrame:
    """What of ``continuous`` doesn't depend on the clock."""
    out = continuous(spark, sf_dir, schema, level, engines)
    within = (F.col("dief") >= 0) & (F.col("dief") <= F.col("until") * F.col("comp"))
    return out.select("engine", "comp", "n_steps", within.alias("area_within"), (F.col("inv_tfff") >= F.col("inv_et")).alias("first_before_last"))


def times_table(spark: SparkSession, rows) -> DataFrame:
    return spark.createDataFrame(list(rows), "testbed string, engine string, run int, seconds double")
