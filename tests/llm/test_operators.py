"""Operators against brute force on small inputs, with nulls, empty and repeated rows."""

import hashlib
import itertools
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from shapeplan.llm import chroma, compaction, curve_search, language, minhash, mixing, packing, plane_file, queries, substring_dedup, suffix_tree_lm
from shapeplan.llm.fm_index import FMIndex
from shapeplan.llm.tokens import Encoder, default_vocabulary, tokenizer
from shapeplan.runtime import scratch_path
from tests.conftest import SMALL

COLS = "doc_id long, text string, lang string, source string, n_chars long, node string, bucket int"


def frame(spark, rows):
    """Documents with further columns whose names clash with those used inside."""
    return spark.createDataFrame([(i, t, lang, src, len(t or ""), "x", 1) for i, t, lang, src in rows], COLS)


def some_docs(n=60, seed=1):
    r = random.Random(seed)
    vocab = [f"w{i}" for i in range(400)]
    base = [[r.choice(vocab) for _ in range(r.choice([1, 2, 5, 30, 120, 300]))] for _ in range(n // 3)]
    passage = [r.choice(vocab) for _ in range(70)]
    out = []
    for i in range(n):
        ws = list(r.choice(base))
        for _ in range(r.choice([0, 1, 1, 3, 12])):
            ws[r.randrange(len(ws))] = r.choice(vocab)
        if r.random() < 0.3:
            ws = ws[:40] + passage + ws[40:]
        out.append((i, " ".join(ws), "en", r.choice(["a", "b", None])))
    return out + [(900, None, None, None), (901, "", "en", "a"), (902, " \t ", None, "b"), (903, "A", "de", "a"), (904, "a", "de", "a"), (905, "x\ny  z", None, None)]


def grams(text, n):
    ws = (text or "").encode().lower().split()
    return {tuple(ws[i : i + n]) for i in range(len(ws) - n + 1)} if len(ws) >= n else ({tuple(ws)} if ws else set())


def brute_components(rows, n):
    sets = {i: grams(t, n) for i, t, *_ in rows}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= 80 * len(x | y):
            lo, hi = sorted((find(a), find(b)))
            up[hi] = lo
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize("n", [2, 5])
def test_near_duplicates(spark, n):
    rows = some_docs(90)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(frame(spark, rows), n=n).collect()}
    assert got == brute_components(rows, n)


def test_near_duplicates_chain_and_repeats(spark):
    ws = [f"v{i}" for i in range(100)]
    rows = []
    for i in range(40):  # each differs from the next in two words, ends are far apart
        own = ws[2 * i :] + [f"n{k}" for k in range(2 * i)]
        rows.append((i, " ".join(own[:100]), "en", "a"))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(frame(spark, rows), n=2).collect()}
    assert got == brute_components(rows, 2)
    twice = minhash.near_duplicates(frame(spark, [(1, "a b c", "en", "a")] * 3 + [(None, "a b c", "en", "a")]), n=2).collect()
    assert len(twice) == 4 and all(r.component_id == 1 for r in twice if r.doc_id is not None)


def test_signature_estimates():
    r = np.random.default_rng(0)
    x = r.integers(0, 2**63, 900).astype(np.uint64)
    a, b = minhash.signature(np.unique(x[:800]), 128), minhash.signature(np.unique(x[100:]), 128)
    assert abs((a == b).mean() - 700 / 900) < 0.15


@pytest.mark.parametrize("hot", [8192, 1])
def test_substring_dedup(spark, hot):
    rows = some_docs(80, 2)
    first, expected = {}, {}
    for i, t, *_ in sorted(rows):
        ws = (t or "").encode().split()
        keep, keys = [True] * len(ws), [tuple(ws[k : k + 50]) for k in range(len(ws) - 49)]
        for k, x in enumerate(keys):
            if first.get(x, i) < i:
                keep[k : k + 50] = [False] * 50
        for x in keys:
            first.setdefault(x, i)
        kept = [w for w, k in zip(ws, keep) if k]
        expected[i] = (len(ws), len(ws) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest())
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in substring_dedup.deduplicated(frame(spark, rows), hot=hot).collect()}
    assert got == expected and any(x[1] for x in expected.values())


def test_fm_index():
    r = np.random.default_rng(3)
    seqs = [r.integers(1, 6, n) for n in (30, 1, 44, 7)]
    index = FMIndex(seqs, 6)
    for n in (1, 2, 4, 6):
        for _ in range(30):
            p = r.integers(1, 6, n)
            assert index.count(p) == sum((s[i : i + n] == p).all() for s in seqs for i in range(len(s) - n + 1))
    # A stream that isn't part of the index.
    stream = np.concatenate([seqs[0][3:15], [9], seqs[2][:20], r.integers(1, 6, 25)])
    known = {tuple(s[i : i + 6]) for s in seqs for i in range(len(s) - 5)}
    got = index.matched_groups([stream])[0]
    assert [g >= 0 for g in got[: len(stream) - 5]] == [tuple(stream[i : i + 6]) in known for i in range(len(stream) - 5)]


def test_language(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    got = language.identify(docs.unionByName(frame(
        spark, [(9001, None, "en", "a"), (9002, "12 !", None, "a")],
    ).select(docs.columns))).join(docs.select("doc_id", "lang"), "doc_id", "left").collect()
    held = [r for r in got if r.held_out and r.doc_id < 9000]
    assert sum(r.lang == r.lang_pred for r in held) >= 0.98 * len(held)
    assert {r.doc_id: r.lang_pred for r in got if r.doc_id > 9000} == {9001: "und", 9002: "und"}
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in got)
    assert {r.lang_pred for r in language.identify(docs.limit(0).unionByName(docs.limit(3).withColumn("lang", F.lit(None).cast("string")))).collect()} == {"und"}


def test_forward_sums_all_segmentations():
    pieces = ["a", "b", "ab", "ba", "aba"]
    p = np.log(np.array([[0.2], [0.1], [0.3], [0.15], [0.05], [0.01]]))
    lattice = language.Lattice(pieces, p)

    def brute(w):
        return 1.0 if not w else sum(math.exp(p[k, 0]) * brute(w[len(x) :]) for k, x in enumerate(pieces) if w.startswith(x)) + (0.01 * brute(w[1:]) if w[0] not in "ab" else 0)

    words = ["a", "ab", "abab", "abcba", "aabbaab"]
    assert np.allclose(lattice.log_probability(words)[:, 0], [math.log(brute(w)) for w in words])
    e = lattice.expected(["abab"], np.ones((1, 1)))[:, 0]
    assert math.isclose(sum(n * k for n, k in zip(e, (1, 1, 2, 2, 3, 1))), 4.0)


def test_long_words_sum_all_segmentations_too():
    """Against an exact sum in whole numbers, beyond the length up to which words go together."""
    pieces, share = ["a", "b", "ab", "ba", "aba"], [20, 10, 30, 15, 5, 1]
    lattice = language.Lattice(pieces, np.log(np.array(share)[:, None] / 100))
    r = random.Random(9)
    for n in (60, 64, 65, 200, 3000):
        word = "".join(r.choice("aabbc") for _ in range(n))
        ways = [1] + [0] * n  # sums of products, times 100 for each character
        for j in range(1, n + 1):
            for k, x in enumerate(pieces):
                if word[:j].endswith(x):
                    ways[j] += ways[j - len(x)] * share[k] * 100 ** (len(x) - 1)
            if word[j - 1] == "c":
                ways[j] += ways[j - 1]
        exact = math.log(ways[n] >> max(0, ways[n].bit_length() - 60)) + max(0, ways[n].bit_length() - 60) * math.log(2) - n * math.log(100)
        assert math.isclose(lattice.log_probability([word])[0, 0], exact, rel_tol=1e-9)
        e = lattice.expected([word], np.ones((1, 1)))[:, 0]
        assert math.isclose(sum(m * k for m, k in zip(e, (1, 1, 2, 2, 3, 1))), n, rel_tol=1e-9)


def test_language_of_long_words_repeated_ids_and_nothing(spark):
    rows = [(i, "".join("abcd"[(i + k) % 3 + (i % 2)] for k in range(300)), "xy"[i % 2], "s") for i in range(40)]
    got = language.identify(frame(spark, [*rows, (1, rows[1][1], None, None), (1, None, None, None)])).collect()
    assert len(got) == 42 and all(r.lang_pred == "xy"[r.doc_id % 2] for r in got if r.score > 0)
    assert language.identify(frame(spark, [])).count() == 0


def test_lm_base_and_held_out(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    rows = [(r.doc_id, ((r.text or "").encode().lower().split()) + [b"\x00end"]) for r in docs.collect()] + [(9001, [b"\x00end"])]
    train = Counter(w for i, ws in rows if zlib.crc32(str(i).encode()) % 7 != 2 for w in ws)
    n, v = sum(train.values()), len(train)
    got = {r.doc_id: r for r in suffix_tree_lm.lm_scores(docs.unionByName(spark.createDataFrame([(9001, None)], "doc_id long, text string"))).collect()}
    for i, ws in rows:
        base = sum(math.log10((train[w] + 1) / (n + v + 1)) for w in ws)
        r = got[i]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(ws), sum(train[w] > 0 for w in ws), n) and math.isclose(r.base_score, base, rel_tol=1e-9)
    held = [r for r in got.values() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


TEXTS = ["", " ", "a\nb c", "a  b\n\nc", "it's\nthe 'll", "É été, für!! straße?: ok", "日本語 テスト。 x", "\n", "a \nb", "x" * 3000, "<|endoftext|> a", "a\x1cb c\x1d", "tail. "]


def test_encoder_equals_tokenizer():
    e, t = Encoder(), tokenizer(default_vocabulary())
    for x in TEXTS + [r[1] or "" for r in some_docs(20)]:
        assert np.frombuffer(e.encode(x), "<u4").tolist() == t.encode(x, add_special_tokens=False).ids


@pytest.mark.parametrize("kind", ["bit", "byte"])
def test_plane_files(spark, kind):
    rows = [(7 * i % 23, x, "en", "a") for i, x in enumerate(TEXTS)] + [(50, None, None, None)]
    path = scratch_path(spark, "planes")
    plane_file.write_ids(frame(spark, rows), path, page_ids=64, kind=kind)
    t, start = tokenizer(default_vocabulary()), 0
    got = {r.doc_id: r for r in plane_file.read_index(spark, path).collect()}
    full = {r.doc_id: r.ids for r in plane_file.read_ids(spark, path).collect()}
    for i, x, *_ in sorted(rows):
        ids = t.encode(x or "", add_special_tokens=False).ids + [0]
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())) and full[i] == ids
        start += len(ids)
    assert plane_file.round_trip(frame(spark, [])).count() == 0


def test_fill_is_best():
    r = random.Random(5)
    for _ in range(60):
        items = Counter(r.randrange(1, 30) for _ in range(8))
        room = r.randrange(1, 60)
        use = packing.fill(dict(items), room)
        sums = {0}
        for n in items.elements():
            sums |= {s + n for s in sums if s + n <= room}
        assert sum(n * k for n, k in use.items()) == max(sums) and all(k <= items[n] for n, k in use.items())


def test_packing(spark):
    rows = [(r[0], (r[1] or "") * 9, *r[2:]) for r in some_docs(40)] + [(1, None, "en", "a")]
    out = packing.packed(frame(spark, rows), capacity=512).collect()
    per = {}
    for r in out:
        per.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in per.values():
        parts.sort()
        assert parts[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(parts, parts[1:])) and sum(n for _, n in parts) <= 512
    t = tokenizer(default_vocabulary())
    total = sum(len(t.encode(x or "", add_special_tokens=False).ids) + 1 for _, x, *_ in rows)
    assert sum(r.length for r in out) == total and len(per) * 512 - total < 0.03 * total + 1024


def test_pieces_are_whole_gapless_and_spread(spark):
    long = " ".join(f"word{i}" for i in range(9000))
    rows = [(i, x, "en", "a") for i, x in enumerate(TEXTS)] + [(50, None, None, None), (51, long, "en", "a")] + [(7, "same text", "en", "a")] * 9000
    out = packing.packed(frame(spark, rows), capacity=256).collect()
    t, per = tokenizer(default_vocabulary()), {}
    for r in out:
        per.setdefault((r.doc_id, r.doc_tokens), []).append(r)
    for i, x, *_ in rows[: len(TEXTS) + 2]:
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4")
        own = sorted(per[i, len(ids)], key=lambda r: r.start)
        assert [r.start for r in own] == list(range(0, len(ids), 256)) and sum(r.length for r in own) == len(ids)
        assert all(r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes()) for r in own)
    copies = [r.sequence_id for r in out if r.doc_id == 7 and r.doc_tokens == 3]
    assert len(copies) == 9000 and len({s >> 33 for s in copies}) > 1  # copies of one row are in several groups
    assert packing.packed(frame(spark, [])).count() == 0


def test_mixing(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text", "source").unionByName(spark.createDataFrame(
        [(9001, "a b", None), (9002, None, "src3"), (9003, " ", None)], "doc_id long, text string, source string",
    ))
    rows = mixing.mix(docs).collect()
    sizes = Counter()
    for r in docs.collect():
        sizes[r.source] += len((r.text or "").encode().split())
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(order)}
    target, full = {}, set()
    while True:
        left = 1.5 * sum(sizes.values()) - sum(2 * sizes[s] for s in full)
        free = [s for s in order if s not in full]
        target = {s: 2 * sizes[s] if s in full else left * weight[s] / sum(weight[x] for x in free) for s in order}
        if not (over := {s for s in free if target[s] > 2 * sizes[s]}):
            break
        full |= over
    for s in order:
        own = [r for r in rows if r.source == s]
        assert all(math.isclose(r.target, target[s]) and r.source_size == sizes[s] and r.taken <= 2 * r.size for r in own)
        assert abs(sum(r.taken for r in own) - target[s]) <= max(r.size for r in own)
    assert sorted(map(tuple, mixing.mix(docs).collect()), key=str) == sorted(map(tuple, rows), key=str)
    assert mixing.mix(docs.limit(0)).count() == 0


def test_compaction(spark):
    root = scratch_path(spark, "shards")
    held = compaction.ShardedTable(spark, root, fanout=3, base_bytes=1 << 10, target_bytes=1 << 20)
    rows = frame(spark, some_docs(20))
    for _ in range(7):
        held.append(rows)
        held.compact()
    held.append(rows.limit(0))
    assert held.read().count() == 7 * rows.count()
    assert len(held.manifest()["shards"]) < 7
    old = held.versions()[0]
    assert held.read(old).count() == rows.count()
    assert not held._publish(held.versions()[-1], [])  # a version that is taken
    held.vacuum()
    assert held.read().count() == 7 * rows.count() and len(held.versions()) == 1


def test_vacuum_leaves_what_a_writer_has_not_committed(spark):
    root = scratch_path(spark, "shards")
    held = compaction.ShardedTable(spark, root, base_bytes=1 << 10)
    rows = frame(spark, some_docs(5))
    held.append(rows)
    rows.write.parquet(f"{root}/data/pending")
    held.vacuum()
    entry = held.describe(f"{root}/data/pending", 0)
    held.commit([entry])
    assert held.read().count() == 2 * rows.count()
    rows.write.parquet(f"{root}/data/crashed")
    held.vacuum(grace_s=0)
    assert "crashed" not in held._list(f"{root}/data") and held.read().count() == 2 * rows.count()


def test_empty_arrivals_commit_nothing(spark):
    held = compaction.ShardedTable(spark, scratch_path(spark, "shards"), fanout=2)
    rows = frame(spark, some_docs(5))
    for _ in range(3):
        assert held.append(rows.limit(0)) == 0 and not held.versions()
    assert held.append_all(rows.limit(0).withColumn("a", F.lit(1)), "a") == [] and held.compact() == 0
    assert held.read() is None and held.read(schema=rows.schema).count() == 0


def test_arrivals_of_many_files_are_compacted_whatever_their_size(spark):
    rows = frame(spark, some_docs(60)).repartition(24)
    for target, merged in ((1 << 30, True), (1 << 14, True), (1 << 10, False)):  # more than the arrival, less, and less than each of its files
        held = compaction.ShardedTable(spark, scratch_path(spark, "shards"), fanout=2, base_bytes=1 << 10, target_bytes=target)
        held.append(rows)
        [before] = held.manifest()["shards"]
        assert held.compact() == merged and held.compact() == 0
        [after] = held.manifest()["shards"]
        assert before["files"] > 12 and after["files"] <= (held.needed(before["bytes"]) if merged else 24)
        assert after["rows"] == rows.count() and held.read().exceptAll(rows).isEmpty()


def test_no_arrival_of_the_query_stays_in_many_files(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    docs.repartition(32).write.parquet(str(tmp_path / "documents.parquet"))
    got = queries.op8_compaction(spark, str(tmp_path))
    assert got.count() == docs.count() and len(got.inputFiles()) <= 10
    assert got.exceptAll(queries.op8_compaction(spark, SMALL)).isEmpty()


def test_hilbert_is_a_curve():
    pts = np.array(list(itertools.product(range(8), repeat=2)))
    key = curve_search.hilbert(pts, 3)
    line = pts[np.argsort(key)]
    assert sorted(key.tolist()) == list(range(64)) and (np.abs(np.diff(line, axis=0)).sum(axis=1) == 1).all()


def test_neighbours(spark):
    r = np.random.default_rng(6)
    x = r.standard_normal((600, 16)).astype(np.float32)
    x[200:320] = x[20]  # a vector that many rows share
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(1000, None), (1020, [0.0] * 16), (1040, [float("nan")] * 16), (1060, [None] * 16), (1080, [float("inf")] * 16)]
    got = {}
    for q in curve_search.neighbours(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), k=10).orderBy("query_id", "rank").collect():
        got.setdefault(q.query_id, []).append(q.vec_id)
    hits = 0
    for i in range(0, 600, 20):
        s = x.astype(float) @ x[i].astype(float)
        best = [j for j in sorted(range(600), key=lambda j: (-s[j], j)) if j != i][:10]
        hits += len({*best} & {*got[i]})
        assert len(got[i]) == 10
    assert set(got) == set(range(0, 600, 20)) and hits >= 0.9 * 300
    assert got[220] == [20, *range(200, 209)]


def exact_neighbours(vectors, k, every):
    """By brute force, with zeros after the end of shorter vectors."""
    dim = max(len(v) for _, v in vectors)
    ids = np.array([i for i, _ in vectors])
    x = np.array([[*v, *[0.0] * (dim - len(v))] for _, v in vectors])
    out = {}
    for i, v in zip(ids, x):
        if i % every == 0:
            s = x @ v
            out[int(i)] = [(int(ids[j]), float(s[j])) for j in sorted(range(len(ids)), key=lambda j: (-s[j], ids[j])) if ids[j] != i][:k]
    return out


def found_neighbours(spark, vectors, **how):
    rows = spark.createDataFrame(vectors, "vec_id long, embedding array<double>").withColumn("point", F.lit("x")).withColumn("rank", F.lit(0))
    got = {}
    for q in curve_search.neighbours(rows, **how).orderBy("query_id", "rank").collect():
        got.setdefault(q.query_id, []).append((q.vec_id, q.score))
    return got


def test_neighbours_that_tie_come_by_id(spark):
    r = np.random.default_rng(8)
    few = [(int(i), np.eye(6)[r.integers(0, 6)].tolist()) for i in r.permutation(150)]  # one-hot: many equal ones
    signs = [(int(i), (r.integers(0, 2, 10) * 2.0 - 1).tolist()) for i in r.permutation(200)]  # nearly all different, few scores
    for vectors in (few, signs):
        assert found_neighbours(spark, vectors, k=7) == exact_neighbours(vectors, 7, 20)


def test_neighbours_groups_hold_bounded_numbers_of_queries(spark, monkeypatch):
    window = curve_search._window

    def bounded(group, k):
        n = sum(group.column("asks").to_pylist())
        if n > 2 * 128 or group.num_rows - n > 128:
            raise ValueError(f"{n} queries, {group.num_rows - n} vectors in a group")
        return window(group, k)

    monkeypatch.setattr(curve_search, "CHUNK", 128)
    monkeypatch.setattr(curve_search, "_window", bounded)
    vectors = [(i, list(map(float, v))) for i, v in enumerate(np.random.default_rng(3).standard_normal((1200, 8)))]
    got, want = found_neighbours(spark, vectors, k=5, every=1), exact_neighbours(vectors, 5, 1)
    assert got.keys() == want.keys()
    assert sum(len({v for v, *_ in got[q]} & {v for v, *_ in want[q]}) for q in want) >= 0.9 * 5 * len(want)


def test_neighbours_of_different_lengths_and_none(spark):
    r = np.random.default_rng(9)
    vectors = [(i, r.standard_normal(int(r.choice([4, 4, 4, 7, 2]))).tolist()) for i in range(120)]
    got, want = found_neighbours(spark, vectors, k=5), exact_neighbours(vectors, 5, 20)
    assert {q: [i for i, _ in v] for q, v in got.items()} == {q: [i for i, _ in v] for q, v in want.items()}
    assert found_neighbours(spark, []) == {} and found_neighbours(spark, [(20, [1.0])]) == {}


def test_chroma(spark):
    t = np.arange(40_000) / chroma.RATE
    notes = np.repeat(np.random.default_rng(7).integers(48, 72, 40), 1000)
    wave = np.sin(2 * np.pi * 440 * 2 ** ((notes - 69) / 12) * t)
    media = bytes(((wave * 0.9 + 1) * 127.5).astype(np.uint8))
    shifted = media[64 * 100 :]
    assert chroma.align(chroma.fingerprint(media), chroma.fingerprint(shifted))[0] == 100
    rows = [(1, bytearray(media)), (2, bytearray(shifted)), (3, None), (4, bytearray(b"\x80" * 5000)), (5, bytearray(b""))]
    got = {r.doc_id: r for r in chroma.matched(spark.createDataFrame(rows, "doc_id long, media binary")).collect()}
    assert got[2].match_id == 1 and got[2].match_offset == 100 and got[2].bit_error < 0.05
    assert got[3].n_codes == 0 and got[3].match_id is None and got[5].match_id is None
    assert len(chroma.filters()) == 16


def best_of_all_pairs(rows):
    """By brute force: id and codes of each row to its best match of smaller id."""
    out = {}
    for own, b in rows:
        found = [(e, other, o) for other, a in rows if other < own for o, e in [chroma.align(a, b)] if e is not None and e <= chroma.SAME]
        out[own] = min(found, default=(None, None, None))
    return out


def test_chroma_finds_the_best_of_all_pairs(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", F.col("text").cast("binary").alias("media"))
    got = {r.doc_id: (r.bit_error, r.match_id, r.match_offset) for r in chroma.matched(docs).collect()}
    assert got == best_of_all_pairs([(r.doc_id, chroma.fingerprint(r.media)) for r in docs.collect()])


def test_chroma_bundles_are_small_and_whole(spark):
    texts = [r.text for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("text").collect()]
    codes = [c for c in (chroma.fingerprint((t or "").encode()) for t in texts) if len(c)] + [np.array([7], "<u4")]
    ids, nodes = np.arange(len(codes)) * 1000 - 5, [bytes([k % 256, *[0] * 15]) for k in range(len(codes))]
    data = chroma.bundle(ids, nodes, codes)
    got = chroma.unbundle(data)
    assert got[0].tolist() == ids.tolist() and got[1] == nodes and all(np.array_equal(a, b) for a, b in zip(got[2], codes, strict=True))
    assert len(data) < 2 * sum(map(len, codes))


@pytest.mark.parametrize("at_once", [1 << 21, 50, 1])
def test_chroma_cells_equal_align(monkeypatch, at_once):
    monkeypatch.setattr(chroma, "AT_ONCE", at_once)
    rng = np.random.default_rng(3)
    codes = [rng.integers(0, 6, int(k)).astype("<u4") for k in rng.integers(1, 40, 60)] + [np.full(60, 3, "<u4"), np.full(50, 3, "<u4")]
    ids = rng.permutation(len(codes))
    want = best_of_all_pairs([*zip(ids.tolist(), codes)])
    half = len(codes) // 2
    found = []
    for left, right in ((range(half), range(half)), (range(half), range(half, len(codes))), (range(half, len(codes)), range(half, len(codes)))):
        found += zip(*(c.tolist() for c in chroma.best_in_cell(ids, codes, np.array(left), np.array(right), chroma.SAME)))
    got = {int(i): (None, None, None) for i in ids}
    for k in {f[0] for f in found}:
        got[int(ids[k])] = min((e, other, o) for own, e, other, o in found if own == k)
    assert got == want


def test_chroma_of_repeating_sound_does_not_follow_rounding():
    media = bytes(np.random.default_rng(1).integers(0, 256, chroma.HOP, dtype=np.uint8)) * 100
    assert len(set(chroma.fingerprint(media).tolist())) == 1
    some = [media, None, media[:5000], b"a", media[:1990], bytes(range(256)) * 90]
    assert all(np.array_equal(a, chroma.fingerprint(m)) for a, m in zip(chroma.fingerprinted(some), some, strict=True))


def test_chroma_compares_no_more_bits_than_decide(monkeypatch):
    rng = np.random.default_rng(5)
    codes = [np.array([7], np.uint32)] + [rng.integers(8, 1 << 32, 200, dtype=np.uint32) for _ in range(40)]
    for own in codes:
        own[0] = 7  # all pairs have an equal integer, and all others of the first recording agree with it wholly
    count, compared = np.bitwise_count, []
    monkeypatch.setattr(np, "bitwise_count", lambda x: compared.append(x.size) or count(x))
    places = np.arange(len(codes))
    own, error, other, offset = chroma.best_in_cell(places, codes, places, places, chroma.SAME)
    assert sorted(own.tolist()) == list(range(1, 41)) and not error.any() and not other.any() and not offset.any()
    assert sum(compared) <= 4 * 41 * 40 // 2


@pytest.mark.parametrize("at_once", [1 << 21, 30, 1])
def test_chroma_cells_with_repeated_ids_equal_align(monkeypatch, at_once):
    monkeypatch.setattr(chroma, "AT_ONCE", at_once)
    rng = np.random.default_rng(8)
    codes = [rng.integers(0, 5, int(k)).astype("<u4") for k in rng.integers(1, 7, 80)]
    ids, places = rng.integers(0, 25, len(codes)), np.arange(len(codes))
    want = {}
    for own in places.tolist():
        pairs = [(ids[x], *chroma.align(codes[x], codes[own])) for x in places.tolist() if ids[x] < ids[own]]
        found = [(e, int(other), o) for other, o, e in pairs if e is not None and e <= chroma.SAME]
        want |= {own: min(found)} if found else {}
    assert {k: tuple(m) for k, *m in zip(*(c.tolist() for c in chroma.best_in_cell(ids, codes, places, places, chroma.SAME)))} == want


def test_chroma_of_nothing_and_of_copies_alone(spark):
    form = "doc_id long, media binary"
    assert chroma.matched(spark.createDataFrame([], form)).collect() == []
    none = chroma.matched(spark.createDataFrame([(1, None), (2, bytearray(b"short"))], form)).collect()
    assert sorted((r.doc_id, r.n_codes, r.match_id) for r in none) == [(1, 0, None), (2, 0, None)]
    media = bytearray(np.random.default_rng(4).integers(0, 256, 5000, dtype=np.uint8))
    copies = chroma.matched(spark.createDataFrame([(k, media) for k in (7, 3, 9)], form)).collect()
    assert sorted((r.doc_id, r.match_id, r.match_offset, r.bit_error) for r in copies if r.match_id) == [(7, 3, 0, 0.0), (9, 3, 0, 0.0)] and len(copies) == 3


@pytest.mark.parametrize("per_group", [1 << 24, 40])
def test_chroma_groups_of_many_pieces_find_the_best_of_all_pairs(spark, monkeypatch, per_group):
    monkeypatch.setattr(chroma, "PER_PIECE", 20)
    monkeypatch.setattr(chroma, "PER_GROUP", per_group)
    monkeypatch.setattr(chroma, "GROUPS", 2)
    rows = [(k, bytearray(np.random.default_rng(k % 9).integers(32, 127, 1984 + 64 * (k % 5), dtype=np.uint8))) for k in range(40)] + [(None, bytearray(5000)), (50, None)]
    docs = spark.createDataFrame(rows, "doc_id long, media binary")
    got = {r.doc_id: (r.bit_error, r.match_id, r.match_offset) for r in chroma.matched(docs).collect()}
    want = best_of_all_pairs([(k, chroma.fingerprint(m)) for k, m in rows if k is not None])
    assert got == want | {None: (None, None, None)}
