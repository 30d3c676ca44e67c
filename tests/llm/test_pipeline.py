"""The pipeline: each stage's decisions on its input, and the whole."""

from collections import Counter

import __spark_entry__
import corpus_pipeline
from shapeplan.llm import mixing, stages
from tests.conftest import SMALL
from tests.llm.test_operators import brute_components


def test_stages_keep_columns_and_clean_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SMALL)
        assert out.columns == docs.columns, name
        assert stage(spark, docs.limit(0), SMALL).count() == 0
    assert stages.keep_identified(spark, docs, SMALL).count() == docs.where("text rlike '[a-zA-Z]'").count()


def test_one_of_each_group_stays(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    kept = {r.doc_id for r in stages.keep_one_of_near_copies(spark, docs.unionByName(docs.limit(2)), SMALL).collect()}
    assert kept == {c for _, c in brute_components(rows, 5).values()}


def test_pack_stage_takes_nothing(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    assert stages.pack_sequences(spark, docs, SMALL).count() == 0


def test_run(spark):
    out = corpus_pipeline.run(spark, SMALL)
    assert {"doc_id", "start", "length", "sequence_id", "offset"} <= set(out.columns) and out.count() > 0
    assert "pipeline" in __spark_entry__.queries() and corpus_pipeline.ORACLE_SQL is None


def test_rows_without_or_sharing_an_id_follow_their_own_decision(spark):
    words = [[f"w{k}x{i}" for i in range(40)] for k in range(4)]
    near = [*words[0][:-1], "other"]
    rows = [(1, words[0]), (7, near), (7, words[1]), (None, words[2]), (None, words[3]), (None, near)]
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in rows], "doc_id long, text string")
    kept = [tuple(r) for r in stages.keep_one_of_near_copies(spark, docs, SMALL).collect()]
    assert Counter(kept) == Counter((i, " ".join(w)) for i, w in rows if (i, w) != (7, near))


def test_mix_takes_each_row_as_often_as_it_is_due(spark):
    rows = [(i if i % 3 else None if i % 2 else 90, " ".join([f"t{i}"] * (i + 1)), f"s{i % 2}") for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    due = {r.size: r.copies for r in mixing.mix(docs).collect()}  # every row has a size of its own
    got = Counter(len(r.text.split()) for r in stages.mix_sources(spark, docs, SMALL).collect())
    assert got == Counter(due) - Counter() and any(due[i + 1] for i in range(30) if rows[i][0] is None)
