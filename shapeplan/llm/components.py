"""Connected components over a table of links, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapeplan.runtime import written


def _stars(links: DataFrame, large: bool) -> DataFrame:
    """One contraction of links (u, v) with v < u: every node's neighbours move to its smallest neighbour.

    The large one hangs greater neighbours of a node on the smallest of node and neighbours,
    the small one does so for the node and its smaller neighbours.
    """
    if large:
        both = links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        moved = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = links.groupBy("u").agg(F.min("v").alias("m"))
        hung = links.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        moved = hung.unionByName(least.select("u", F.col("m").alias("v")))
    return moved.where(F.col("u") != F.col("v")).distinct()


def _state(links: DataFrame) -> tuple:
    row = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Nodes of ``links`` with the smallest node that each reaches: columns ``node``, ``label``.

    Links may repeat, point either way or to the node itself (such a node is then left out unless
    something else links it). Every round is written to the shared folder, so lineage stays short;
    the loop ends when a round changes nothing. Only one count and one checksum reach the driver.
    """
    now = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    now = written(now, "links")
    state = _state(now)
    while state[0]:
        now = written(_stars(_stars(now, True), False), "stars")
        after = _state(now)
        if after == state:
            break
        state = after
    top = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("label"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(top)
