"""The stages of the training-data pipeline: each takes and returns documents, the last returns pieces.

All stages take an empty table and give an empty one, look at whole texts of any length, and carry further columns along, whatever their
names (but for ``_row``). What they do with nulls, repeated rows and ties is said at each.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapeplan.llm import language, minhash, mixing, packing, substring_dedup
from shapeplan.runtime import written

#: The column that tells rows apart within a stage, as ids may be null or repeat.
ROW = "_row"


def _keyed(docs: DataFrame) -> DataFrame:
    return written(docs.withColumn(ROW, F.monotonically_increasing_id()), "keyed")


def keep_identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language is found; those without a letter go, null texts with them.

    Rows repeating an id are judged one by one. If no row has a language all documents without one go, as nothing was learned.
    """
    labels, logp = language.fit(docs)
    kept = language.predict(docs.select(F.struct("*").alias("row"), "doc_id", "text"), labels, logp, whole=True).where("lang_pred <> 'und'")
    return kept.select("row.*")


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five words, 0.8), the one of least id.

    Rows that share an id go or stay each by its own text. Rows without an id are near copies of nothing and stay.
    Of rows equal in id and text, null ids too, one stays.
    """
    # Rows are told apart by id and a hash of the text, so no copy of the texts is written for it.
    keyed = docs.withColumn(ROW, F.xxhash64("text"))
    gone = minhash.near_duplicates(keyed, key=(ROW,)).where("not kept").select("doc_id", ROW).distinct()
    kept = keyed.join(gone, ["doc_id", ROW], "left_anti").select(*docs.columns)
    return kept.dropDuplicates(["doc_id", "text"])


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 words or more that an earlier document has are cut out; documents left empty by that go.

    Rows without an id lose nothing, nor does another row lose to them. Rows that share an id count as one document, so none loses to
    another. Null texts stay.
    """
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    out = substring_dedup.deduplicated(docs, keep=rest, text=True).where("n_removed < n_words or n_removed = 0")
    out = out.withColumnRenamed("kept", "text")
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as the mix takes each, also those that share an id or have none.

    Rows without words are due copies like others, of no words. Of rows that tie in id and size, those that are taken are any.
    """
    keyed = _keyed(docs)
    taken = mixing.mix(keyed, key=(ROW,)).where("copies > 0").select(ROW, "copies")
    return keyed.join(taken, ROW).withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of 2,048 ids; a null text is its end id alone, rows repeating an id are packed one by one."""
    return packing.packed(docs)
