"""Readers and writers of triples, edges and verdicts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_TYPE = "http://www.w3.org/1999/02/22-rdf-syntax-ns#type"


def write_triples(triples: DataFrame, path: str) -> None:
    """Parquet, a folder for each predicate, subjects in order within files; scans of a predicate read its folder alone."""
    triples.repartition("p", F.pmod(F.xxhash64("s"), F.lit(64))).sortWithinPartitions("p", "s").write.partitionBy("p").parquet(path)


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def to_ntriples(triples: DataFrame) -> DataFrame:
    """One line a triple in column ``value``, ready for ``write.text``."""
    esc = F.col("o.lex")
    for c, said in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r")):
        esc = F.replace(esc, F.lit(c), F.lit(said))
    lit = F.concat(F.lit('"'), esc, F.lit('"^^<'), F.col("o.dt"), F.lit(">"))
    obj = F.when(F.col("o.kind") == "iri", F.concat(F.lit("<"), F.col("o.iri"), F.lit(">"))).otherwise(lit)
    return triples.select(F.concat(F.lit("<"), "s", F.lit("> <"), F.col("p"), F.lit("> "), obj, F.lit(" .")).alias("value"))


def from_ntriples(lines: DataFrame) -> DataFrame:
    """Triples of N-Triples lines; comments and blank lines are skipped.

    Lines in the form of ``to_ntriples`` are cut at their marks; a pattern reads all others, further blanks at the end for instance.
    """
    # Quotes within a literal are escaped and types hold none, so the last one of a line closes it, however long it is.
    pattern = r'(?s)^<([^>]*)> <([^>]*)> (?:<([^>]*)>|"(.*)"(?:\^\^<([^>]*)>)?) \.\s*$'
    has = lambda name, mark: F.contains(F.col(name), F.lit(mark))
    starts, ends = (lambda name, mark: F.startswith(F.col(name), F.lit(mark))), (lambda name, mark: F.endswith(F.col(name), F.lit(mark)))
    # All marks are single bytes, so cuts are by bytes and no letters need counting.
    after = lambda name, n: F.expr(f"CAST(substring(CAST({name} AS BINARY), {n}) AS STRING)")
    cut = lines.select("value", F.substring_index("value", "> ", 1).alias("a"), F.substring_index("value", "> ", 2).alias("ab"))
    cut = cut.select("value", after("a", "2").alias("s"), after("ab", "octet_length(a) + 3").alias("b"), after("value", "octet_length(ab) + 3").alias("end"))
    cut = cut.withColumns({"p": after("b", "2"), "body": after("end", "2, octet_length(end) - 3"), "typed": F.substring_index("end", '"^^<', -1)})
    cut = cut.withColumns({"iri": after("body", "1, octet_length(body) - 1"), "dt": after("typed", "1, octet_length(typed) - 3"), "lex": after("body", "1, octet_length(body) - octet_length(typed) - 2")})
    cut = cut.withColumn("framed", starts("value", "<") & starts("b", "<") & ~has("s", ">") & ~has("p", ">") & ends("end", " ."))
    form = F.when(F.col("framed") & starts("end", "<") & ends("body", ">") & ~has("iri", ">"), "iri")
    form = form.when(F.col("framed") & starts("end", '"') & ends("body", ">") & has("body", '"^^<') & ~has("dt", ">"), "typed")
    form = form.when(F.col("value").rlike(pattern), "other")
    part = lambda i: F.regexp_extract("value", pattern, i)
    other = F.col("form") == "other"
    is_lit = F.when(other, F.col("value").rlike(r'^<[^>]*> <[^>]*> "')).otherwise(F.col("form") == "typed")
    raw = F.when(other, part(4)).otherwise(F.col("lex"))
    # A backslash pair is set aside first, so that "\\n" stays a backslash and an n.
    plain = raw
    for said, c in ((r"\\", "\x00"), (r"\n", "\n"), (r"\r", "\r"), (r"\"", '"'), ("\x00", "\\")):
        plain = F.replace(plain, F.lit(said), F.lit(c))
    dt = F.when(other, part(5)).otherwise(F.col("dt"))
    o = F.struct(
        F.when(F.col("is_lit"), "literal").otherwise("iri").alias("kind"), F.when(~F.col("is_lit"), F.when(other, part(3)).otherwise(F.col("iri"))).alias("iri"),
        F.when(F.col("is_lit"), F.when(F.contains(raw, F.lit("\\")), plain).otherwise(raw)).alias("lex"), F.when(F.col("is_lit") & (dt != ""), dt).alias("dt"),
    )
    named = F.when(other, part(2)).otherwise(F.col("p"))
    p = F.when(named == _TYPE, "type").otherwise(named)
    read = cut.withColumn("form", form).withColumn("is_lit", is_lit)
    # Not a filter: that would be moved below, and all of this be done twice.
    return read.select(F.inline(F.when(F.col("form").isNotNull(), F.array(F.struct(F.when(other, part(1)).otherwise(F.col("s")).alias("s"), p.alias("p"), o.alias("o"))))))


def read_edges_csv(spark: SparkSession, path: str) -> DataFrame:
    """An edge list ``s,p,o`` of identifiers, as triples."""
    rows = spark.read.csv(path, header=True, schema="s string, p string, o string")
    none = F.lit(None).cast("string")
    return rows.select("s", "p", F.struct(F.lit("iri").alias("kind"), F.col("o").alias("iri"), none.alias("lex"), none.alias("dt")).alias("o")).dropDuplicates()


def write_verdicts(verdicts: DataFrame, path: str, mode: str = "overwrite") -> None:
    """One folder a shape; with dynamic overwrite a rerun replaces only the shapes it decided."""
    verdicts.write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("shape").parquet(path)


def write_report(report: DataFrame, path: str, kind: str = "json") -> None:
    getattr(report.coalesce(1).write.mode("overwrite"), kind)(path)
