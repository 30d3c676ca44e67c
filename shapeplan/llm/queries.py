"""Queries over the given tables that apply each operator with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapeplan.llm import chroma, compaction, curve_search, language, minhash, mixing, packing, plane_file, substring_dedup, suffix_tree_lm
from shapeplan.runtime import scratch_path, table


def op1_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), n=2)


def op2_chroma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bytes of every document's text stand in for 8-bit samples; no table holds audio."""
    return chroma.matched(table(spark, sf_dir, "documents").select("doc_id", F.col("text").alias("media")))


def op3_suffix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_tree_lm.lm_scores(table(spark, sf_dir, "documents"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents"))


def op5_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.deduplicated(table(spark, sf_dir, "documents")).withColumnRenamed("kept", "kept_sha256")


def op6_bit_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plane_file.round_trip(table(spark, sf_dir, "documents"))


def op7_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op8_compaction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten arrivals of documents, half of all in the first, a quarter in the second, an equal share in each other."""
    docs = table(spark, sf_dir, "documents")
    part = F.pmod("doc_id", F.lit(32))
    arrival = F.coalesce(F.when(part < 16, 0).when(part < 24, 1).otherwise(part - 22), F.lit(0)).cast("int")
    held = compaction.ShardedTable(spark, scratch_path(spark, "shards"), base_bytes=1 << 16)
    held.append_all(docs.withColumn("arrival", arrival), "arrival")
    held.vacuum(grace_s=0)  # nobody else writes to it
    rows = held.read(schema=docs.schema)
    return rows.select("doc_id", "lang", "source", "n_chars", F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


def op9_bin_slack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"))


def op10_curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curve_search.neighbours(table(spark, sf_dir, "embeddings"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (op1_minhash, op2_chroma, op3_suffix_tree, op4_language, op5_substring, op6_bit_planes, op7_pareto_mix, op8_compaction, op9_bin_slack, op10_curves)
    return {f.__name__: f for f in named}


_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP1_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format(_LOWER)} AS ws FROM documents),
sh AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) >= 2 THEN list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) WHEN len(ws) = 1 THEN [ws[1]] ELSE [] END) AS s
  FROM w),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
link AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id
  JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, na.n, nb.n HAVING 100 * count(*) >= 80 * (na.n + nb.n - count(*))),
sym AS (SELECT a, b FROM link UNION SELECT b, a FROM link),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.b FROM reach r JOIN sym e ON r.b = e.a),
least AS (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, l.component_id, d.doc_id = l.component_id AS kept
FROM documents d LEFT JOIN n USING (doc_id) JOIN least l USING (doc_id)
"""

OP5_SQL = f"""
WITH w AS (SELECT doc_id, {_WORDS.format("coalesce(text, '')")} AS ws FROM documents),
win AS (SELECT doc_id, i, sha256(array_to_string(ws[i:i + 49], ' ')) AS h FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM w WHERE len(ws) >= 50)),
first AS (SELECT h, min(doc_id) AS f FROM win GROUP BY h),
hit AS (SELECT doc_id, i FROM win JOIN first USING (h) WHERE f < doc_id),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS k FROM hit),
word AS (SELECT doc_id, unnest(ws) AS x, unnest(range(1, len(ws) + 1)) AS k FROM w),
kept AS (SELECT word.doc_id, string_agg(x, ' ' ORDER BY word.k) AS t FROM word LEFT JOIN gone ON gone.doc_id = word.doc_id AND gone.k = word.k WHERE gone.k IS NULL GROUP BY word.doc_id),
n AS (SELECT doc_id, count(*) AS c FROM gone GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(c, 0)::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN kept USING (doc_id)
"""

OP8_SQL = "SELECT doc_id, lang, source, n_chars, sha256(text) AS text_sha256 FROM documents"


def oracle_sql() -> dict[str, str]:
    return {"op1_minhash": OP1_SQL, "op5_substring": OP5_SQL, "op8_compaction": OP8_SQL}
