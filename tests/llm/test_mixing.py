"""Which documents the Pareto sample takes, against a plain version; sums over ordered rows."""

import hashlib
import math
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from shapeplan.llm import mixing
from tests.conftest import SMALL
from tests.llm.test_operators import frame, some_docs


def number(doc_id):
    return (int(hashlib.md5(f"mix:{'' if doc_id is None else doc_id}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)


def brute_copies(own, target):
    """Copies of (doc_id, size) of one source: whole ones, certain ones, then by rank until the words are reached; ids are distinct."""
    total = sum(n for _, n in own)
    whole = math.floor(target / total)
    need = target - whole * total
    kind = {i: math.floor(math.log2(n)) for i, n in own if n}
    for top in sorted(set(kind.values()), reverse=True):
        certain = sum(n for i, n in own if n and kind[i] > top)
        factor = (need - certain) / sum(2 ** (kind[i] / 2) * n for i, n in own if n and kind[i] <= top)
        if factor * 2 ** (top / 2) <= 1:
            break
    copies = {i: whole + bool(n and kind[i] > top) for i, n in own}
    p = {i: min(1.0, factor * 2 ** (kind[i] / 2)) for i, n in own if n and kind[i] <= top}
    odds = {i: (number(i) / (1 - number(i))) / (x / (1 - x)) if 0 < x < 1 else math.inf for i, x in p.items()}
    left, done = need - certain, 0
    for i, n in sorted(((i, n) for i, n in own if i in p), key=lambda x: odds[x[0]]):
        if done + n / 2 > left or left <= 0:
            break
        copies[i] += 1
        done += n
    return copies, p


@pytest.mark.parametrize("few", [mixing.FEW, 1])
def test_documents_of_least_rank_are_taken(spark, monkeypatch, few):
    monkeypatch.setattr(mixing, "FEW", few)
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text", "source")
    by = defaultdict(list)
    for r in mixing.mix(docs).collect():
        by[r.source].append(r)
    partial = 0
    for rows in by.values():
        want, p = brute_copies([(r.doc_id, r.size) for r in rows], rows[0].target)
        assert {r.doc_id: r.copies for r in rows if r.size} == {r.doc_id: want[r.doc_id] for r in rows if r.size}
        partial += len({round(x, 9) for x in p.values() if 0 < x < 1}) > 1
    assert partial  # inclusion odds differ within a source


def test_longer_documents_are_taken_more_readily(spark):
    rows = [(i, " ".join(["w"] * (4 if i % 2 else 64)), "en", "a") for i in range(4000)] + [(9000, "x " * 90_000, "en", "b")]
    got = [r for r in mixing.mix(frame(spark, rows), share=0.5, weights=(1, 1)).collect() if r.source == "a"]
    short, long = ([r.copies for r in got if r.size == n] for n in (4, 64))
    p = sum(long) / len(long)
    assert p < 1 and 3 < p / (sum(short) / len(short)) < 5  # the square root of 16
    assert abs(sum(r.taken for r in got) - got[0].target) <= 32


def test_rows_of_all_kinds(spark):
    rows = [(1, "a b", "en", "s"), (1, "a b", "en", "s"), (1, "c", "en", "s"), (None, "d e f", "en", None), (2, None, None, None), (3, " ", "x", "")]
    got = mixing.mix(frame(spark, [*rows, *some_docs(10)])).collect()
    assert len(got) == 6 + len(some_docs(10)) and all(0 <= r.taken <= 2 * r.size for r in got)
    assert mixing.mix(frame(spark, [])).count() == 0
    assert {r.taken for r in mixing.mix(frame(spark, [(1, None, None, None), (2, " ", None, "a")])).collect()} == {0}


def test_sums_in_order(spark):
    rows = spark.range(500).select((F.col("id") * 7919 % 500).alias("k"), (F.col("id") % 5).alias("v"))
    got = sorted((r.place, r.k, r.before_v) for r in mixing._in_order(rows, [F.col("k").desc()], ("v",), "t").collect())
    v = {r.k: r.v for r in rows.collect()}
    assert [(p, k) for p, k, _ in got] == [(i, 499 - i) for i in range(500)]
    assert all(b == sum(v[x] for x in range(k + 1, 500)) for _, k, b in got)
