"""Mixing sources to target weights by Pareto order sampling, in DataFrame functions alone.

A source's target of words is its weight's share of the whole, at most ``most`` times what it has;
the excess of full sources goes to the others by weight until none is above. The shares follow from the
sources in order of the level at which each fills up.

Within a source every document is due ``target / source_size`` copies. The whole part is allocated to
all. The rest is a sample with unequal inclusion probabilities, proportional to the square root of a document's size (by
powers of two), so that an extra copy goes to longer documents more readily. Where that exceeds one, documents are
certain, and get their copy first; the probabilities of the others are scaled so that the expected words are what is
left. Documents are then ranked by their random odds divided by their inclusion odds, u/(1-u) over p/(1-p), and taken in that
order until the words are reached; the last one taken is the one that brings the sum nearest. The random number is a hash
of the id, so reruns agree.

No source is sorted as a whole: words are summed in fine ranges of the rank, ``RANGES`` of them at each of two levels, to find the range
in which the target falls, and only its documents are ordered. Nor are all sources sorted in one place: sums over sources
run within ranges of them, then over ranges. Rows of sources are broadcast where they are at most ``FEW``, else joined
by source and salt.

Rows: a null or blank text has size 0 and takes 0. A null source is a source of its own, last in
order. Repeated rows share a random number and are told apart by size alone; rows equal in both are
taken or left together up to the order of their text. Columns other than those named are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shapeplan.llm.words import WORD
from shapeplan.runtime import written

#: Ranges in which the words of a source are summed, at each of two levels.
RANGES = 4096

#: Rows of sources that are broadcast, at most; their columns are fixed, but for the name of the source.
FEW = 50_000

#: Parts in which the documents of a source meet its row where sources are many.
SALTS = 32


def size_of(text: str = "text") -> Column:
    """Number of words, without a list of them: white-space runs become one mark each."""
    squeezed = F.regexp_replace(F.coalesce(F.col(text), F.lit("")), WORD, "\x01")
    return F.length(F.regexp_replace(squeezed, "[\x20\x09-\x0D]", "")).cast("long")


def random_number(key: Column) -> Column:
    """A number in (0, 1) from the first 52 bits of a digest of the key."""
    digits = F.substring(F.md5(F.concat(F.lit("mix:"), F.coalesce(key.cast("string"), F.lit("")))), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + 0.5) / F.lit(float(1 << 52))


def _in_order(rows: DataFrame, order: list[Column], sums: tuple[str, ...], name: str) -> DataFrame:
    """``place`` of each row in the given order, from 0, and of each named column the sum over the rows before, ``before_<column>``.

    Rows are sorted by ranges; only one row a range is in one place.
    """
    at = F.shiftright("_at", 33).alias("_part")
    lined = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    lined = written(lined, name).withColumn("_part", at)
    over = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    per = lined.groupBy("_part").agg(F.min("_at").alias("_least"), F.count(F.lit(1)).alias("_n"), *[F.sum(c).alias(f"_s_{c}") for c in sums])
    zero = lambda c: F.coalesce(F.sum(c).over(over), F.lit(0))
    per = per.select("_part", "_least", zero("_n").alias("_n"), *[zero(f"_s_{c}").alias(f"_s_{c}") for c in sums])
    inside = Window.partitionBy("_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
    out = lined.join(F.broadcast(per), "_part")  # a row a partition
    before = [(F.col(f"_s_{c}") + F.coalesce(F.sum(c).over(inside), F.lit(0))).alias(f"before_{c}") for c in sums]
    return out.select(*rows.columns, (F.col("_at") - F.col("_least") + F.col("_n")).alias("place"), *before)


def targets(sizes: DataFrame, *, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """``source``, ``source_size``, ``target``, ``gid`` (its place), from one row a source."""
    by_name = _in_order(sizes, [F.col("source").asc_nulls_last()], (), "sources")
    w = F.array(*[F.lit(float(x)) for x in weights])[(F.col("gid") % len(weights)).cast("int")]
    by = by_name.withColumnRenamed("place", "gid").withColumn("w", w).withColumn("cap", F.col("source_size") * F.lit(most)).withColumn("fills", F.col("cap") / F.col("w"))
    rising = _in_order(by, [F.col("fills").asc(), F.col("source").asc_nulls_last()], ("cap", "w"), "levels")
    whole = rising.agg(F.sum("source_size").alias("n"), F.sum("w").alias("w")).first()
    if whole["n"] is None:
        return sizes.select("source", "source_size", F.lit(0.0).alias("target"), F.lit(0).cast("long").alias("gid"))
    level = (F.lit(float(whole["n"]) * share) - F.col("before_cap")) / (F.lit(whole["w"]) - F.col("before_w"))
    # The first source, by the level at which it fills, that the water doesn't fill sets the level for the rest.
    water = rising.withColumn("level", level).where("level <= fills").agg(F.min_by("level", F.struct("fills", "gid")).alias("x")).first()["x"]
    target = F.col("cap") if water is None else F.least(F.col("cap"), F.lit(water) * F.col("w"))
    return rising.select("source", "source_size", target.alias("target"), "gid")


def size_class(size: str = "size") -> Column:
    """Power of two of a size, null for none."""
    return F.when(F.col(size) > 0, F.floor(F.log2(size)).cast("int"))


def inclusion(kind: Column) -> Column:
    """What the inclusion probability of a size class is proportional to."""
    return F.pow(F.lit(2.0), kind / 2)


def _odds(classes: DataFrame, goal: DataFrame) -> DataFrame:
    """By ``gid``: the largest class that isn't certain, the factor of its and smaller classes' probabilities, the words of certain ones."""
    falling = Window.partitionBy("gid").orderBy(F.desc("kind"))
    rows = classes.join(goal.select("source", "gid", "need"), classes["source"].eqNullSafe(goal["source"])).where("kind is not null").select("gid", "kind", "words", "need")
    f = inclusion(F.col("kind"))
    certain = F.coalesce(F.sum("words").over(falling.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rest = F.sum(f * F.col("words")).over(falling.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    rows = rows.withColumn("certain", certain).withColumn("factor", (F.col("need") - F.col("certain")) / rest)
    fits = rows.where(F.col("factor") * f <= 1)
    return fits.groupBy("gid").agg(F.max_by(F.struct(F.col("kind").alias("upto"), "factor", "certain"), "kind").alias("x")).select("gid", "x.*")


def mix(docs: DataFrame, *, key: tuple[str, ...] = (), **how) -> DataFrame:
    """Per document: ``doc_id``, ``source``, ``size``, ``source_size``, ``target``, ``copies``, ``taken`` and the columns of ``key``."""
    base = written(docs.select("doc_id", "source", size_of().alias("size"), *key), "sizes")  # texts are read once
    classes = written(base.groupBy("source", size_class().alias("kind")).agg(F.sum("size").alias("words")), "classes")
    goal = targets(classes.groupBy("source").agg(F.sum("words").alias("source_size")), **how)
    due = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    goal = goal.withColumn("whole", F.floor(due).cast("long")).withColumn("need", F.col("target") - F.floor(due) * F.col("source_size"))
    odds = _odds(classes, goal)
    goal = written(goal.join(odds, "gid", "left").withColumn("left", F.col("need") - F.coalesce("certain", F.lit(0))), "goal")
    few = goal.count() <= FEW

    def with_source(rows: DataFrame, side: DataFrame, on: str, how: str = "inner") -> DataFrame:
        """Rows with what is known of their source."""
        same = lambda a, b: a[on].eqNullSafe(b[on])
        if few:
            return rows.join(F.broadcast(side), same(rows, side), how).drop(side[on])
        rows = rows.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "size"), F.lit(SALTS)).cast("int"))
        side = side.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        return rows.join(side, same(rows, side) & (rows["_salt"] == side["_salt"]), how).drop(side[on], rows["_salt"], side["_salt"])

    ranked = with_source(base.withColumn("u", random_number(F.col("doc_id"))), goal, "source")
    kind = size_class()
    ranked = ranked.withColumn("sure", F.coalesce(kind > F.col("upto"), F.lit(False)))
    p = F.when(kind.isNull() | F.col("factor").isNull(), F.lit(0.0)).otherwise(F.least(F.lit(1.0), F.col("factor") * inclusion(kind)))
    for_it, against = F.col("u") * (1 - p), (1 - F.col("u")) * p
    # Odds a to b as the share a / (a + b), which has the same order.
    ranked = ranked.withColumn("rank", for_it / (for_it + against))
    fine = lambda c, width: F.least(F.floor(c / F.lit(width)), F.lit(RANGES - 1))
    ranked = ranked.withColumn("r1", fine(F.col("rank"), 1.0 / RANGES))
    ranked = ranked.withColumn("r2", fine(F.col("rank") - F.col("r1") / F.lit(float(RANGES)), 1.0 / RANGES / RANGES))
    before = Window.partitionBy("gid").orderBy("r").rowsBetween(Window.unboundedPreceding, Window.currentRow)

    def edge(rows: DataFrame, r: str, start: Column) -> DataFrame:
        """By source the range in which the need is met, and the words before it."""
        sums = rows.where("not sure").groupBy("gid", F.col(r).alias("r")).agg(F.sum("size").alias("s"), F.first("left").alias("left"), F.first(start).alias("start"))
        sums = sums.withColumn("upto", F.col("start") + F.sum("s").over(before))
        met = sums.where("upto >= left").groupBy("gid").agg(F.min_by(F.struct("r", (F.col("upto") - F.col("s")).alias("done")), "r").alias("x"))
        return written(met.select("gid", F.col("x.r").alias(f"e{r}"), F.col("x.done").alias(f"d{r}")), "edges")

    first = edge(ranked, "r1", F.lit(0).cast("long"))
    within = with_source(ranked, first, "gid").where("r1 = er1")
    second = edge(within, "r2", F.col("dr1"))
    marked = with_source(with_source(ranked, first, "gid", "left"), second, "gid", "left")
    inside = ~F.col("sure") & (F.col("r1") == F.col("er1")) & (F.col("r2") == F.col("er2"))
    ahead = F.col("sure") | F.col("er1").isNull() | (F.col("r1") < F.col("er1")) | ((F.col("r1") == F.col("er1")) & (F.col("r2") < F.col("er2")))
    last = Window.partitionBy("gid").orderBy("rank", "u", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    cols = ["doc_id", "source", "size", "source_size", "target", *key]
    # "upto - size / 2 <= left" takes the document that crosses what is left if that brings the sum nearer.
    crossing = (F.col("left") > 0) & (F.col("upto") - F.col("size") / 2 <= F.col("left"))
    edge_rows = marked.where(inside).withColumn("upto", F.col("dr2") + F.sum("size").over(last)).select(*cols, (F.col("whole") + crossing.cast("long")).alias("copies"))
    others = marked.where(~F.coalesce(inside, F.lit(False))).select(*cols, (F.col("whole") + (ahead & (F.col("sure") | (F.col("left") > 0))).cast("long")).alias("copies"))
    out = edge_rows.unionByName(others)
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), *key)
