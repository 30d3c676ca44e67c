"""The suffix tree against dictionaries, one position at a time: probabilities, sums to one, whole queries."""

import math
import random
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from shapeplan.llm import suffix_tree_lm as lm
from tests.llm.test_operators import frame, some_docs

START, END = "<start>", "<end>"


class BruteTree:
    def __init__(self, docs, depth, least, penalty):
        self.depth, self.table, self.count, self.states = depth, {}, Counter(), {()}
        for words in docs:
            self.count.update([*words, END])
            for h, w in self.positions(words):
                for d in range(1, depth + 1):
                    self.table.setdefault(h[:d], Counter())[w] += 1
        self.norm = sum(self.count.values()) + len(self.count) + 1
        for d in range(1, depth + 1):
            for s, c in self.table.items():
                if len(s) != d or s[:-1] not in self.states or (d > 1 and s[-2] == START) or sum(c.values()) < least:
                    continue
                n = sum(c.values())
                if sum(k * (math.log(k / n) - math.log(self.p(s[:-1], w))) for w, k in c.items()) > penalty * len(c):
                    self.states.add(s)

    def positions(self, words):
        line = [START] * self.depth + list(words) + [END]
        for i in range(self.depth, len(line)):
            yield tuple(line[i - k] for k in range(1, self.depth + 1)), line[i]

    def p(self, state, w):
        if not state:
            return (self.count[w] + 1) / self.norm
        c = self.table[state]
        n = sum(c.values())
        return max(c[w] - lm.DISCOUNT, 0) / n + lm.DISCOUNT * len(c) / n * self.p(state[:-1], w)

    def state(self, h):
        return max((h[:d] for d in range(self.depth + 1) if all(h[:e] in self.states for e in range(d + 1))), key=len)

    def score(self, words):
        return sum(math.log10(self.p(self.state(h), w)) for h, w in self.positions(words))


def corpus(seed=3, n=70):
    """Words that depend on the two before, one of which is very frequent."""
    r = random.Random(seed)
    rows = []
    for i in range(n):
        ws = ["a", "b"]
        for _ in range(r.randrange(60)):
            ws.append("the" if r.random() < 0.4 else f"{ws[-1][0]}{ws[-2][0]}" if r.random() < 0.7 else f"w{r.randrange(9)}")
        rows.append((i, " ".join(ws), "en", "a"))
    return rows + some_docs(30, 8) + [(3, "a b the the", "en", "a"), (None, "the b", None, None)]


def split(rows):
    out = [(i, (t or "").lower().split(), zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2) for i, t, *_ in rows]
    return out, [ws for _, ws, held in out if not held]


@pytest.mark.parametrize(("depth", "hot", "buckets", "penalty"), [(2, 10**9, 1, 1.5), (2, 20, 5, 1.5), (3, 60, 3, 0.05), (1, 20, 2, 1.5)])
def test_scores_equal_brute_force(spark, depth, hot, buckets, penalty):
    rows = corpus()
    docs, train = split(rows)
    tree = BruteTree(train, depth, 8, penalty)
    assert any(len(s) == depth for s in tree.states)
    want = Counter((
        i, held, len(ws) + 1, sum(tree.count[w] > 0 for w in [*ws, END]), round(sum(math.log10(tree.p((), w)) for w in [*ws, END]), 6),
        round(tree.score(ws), 2),
    ) for i, ws, held in docs)
    got = lm.lm_scores(frame(spark, rows), depth=depth, hot=hot, buckets=buckets, penalty=penalty).collect()
    assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, round(r.base_score, 6), round(r.score, 2)) for r in got) == want
    assert {r.train_tokens for r in got} == {sum(tree.count.values())}
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_distributions_sum_to_one():
    docs, train = split(corpus())
    tree = BruteTree(train, 2, 8, 1.5)
    for s in tree.states:
        unknown = tree.p(s, "never seen")
        assert math.isclose(sum(tree.p(s, w) for w in tree.count) + unknown, 1.0, rel_tol=1e-9)


def test_tree_probabilities_of_positions_and_of_distinct_ones():
    r = np.random.default_rng(4)
    stream = r.integers(0, 5, 900)
    stream[2:] = np.where(r.random(898) < 0.6, (stream[:-2] + 1) % 5, stream[2:])
    symbols, root = [stream[2:], stream[1:-1], stream[:-2]], np.full(5, 0.2)
    single = lm.tree_probabilities(symbols, np.ones(898, int), root, 8, 1.5)
    first, kind = lm._types([symbols[1], symbols[2], symbols[0]], 5)
    many = lm.tree_probabilities([s[first] for s in symbols], np.bincount(kind), root, 8, 1.5)
    assert np.allclose(single, many[kind])
    for c in {(a, b) for a, b in zip(symbols[1], symbols[2])}:
        at = {int(symbols[0][i]): single[i] for i in range(898) if (symbols[1][i], symbols[2][i]) == c}
        assert len(at) < 5 or math.isclose(sum(at.values()), 1.0)


def bucket_rows(slices=6, n=150_000, words=1500):
    """What slices send to a bucket: histories that mostly end in one word."""
    r, rows = np.random.default_rng(5), []
    for k in range(slices):
        before, last = np.minimum(r.integers(0, words, n), r.integers(0, words, n)), np.where(r.random(n) < 0.9, 7, r.integers(0, 50, n))
        word = np.where(r.random(n) < 0.4, (before * 31 + last) % words, r.integers(0, words, n))
        first, kind = lm._types([last, before, word], words)
        data = lm._pack(
            lm._steps(np.arange(words)), lm._steps(np.arange(words) + 5), np.zeros(1, np.int64), lm._small(np.bincount(kind)), *(lm._small(x[first]) for x in (word, last, before)),
        )
        rows.append(pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([0], pa.int64()), pa.array([data], pa.binary())], schema=lm.FORM))
    return rows


def test_a_bucket_scored_in_parts_equals_the_whole(monkeypatch):
    rows = bucket_rows(3, 20_000, 300)
    scored = lambda: [lm._unpack(o["data"][0].as_py())[0] for o in lm._score(iter(rows), 2, 8, 0.2, 1e5)]
    whole = scored()
    monkeypatch.setattr(lm, "CHUNK", 500)
    for a, b in zip(whole, scored(), strict=True):
        assert np.allclose(a, b, atol=1e-6)
    own = lm._Bucket([lm._unpack(o["data"][0].as_py()) for o in rows], 2)
    ranges = list(own.chunks(None, np.full(300, 0.01)))
    assert max(b - a for a, b, _ in ranges) <= 500 and [a for a, _, _ in ranges] == [0, *(b for _, b, _ in ranges[:-1])] and ranges[-1][1] == len(own.learned)
    assert len({*whole[0].round(3)}) > 100


def test_memory_of_a_bucket_follows_its_histories(monkeypatch):
    monkeypatch.setattr(lm, "CHUNK", 50_000)
    rows = bucket_rows()
    n = sum(len(lm._unpack(o["data"][0].as_py())[3]) for o in rows)
    tracemalloc.start()
    for _ in lm._score(iter(rows), 2, 8, 1.5, 1e7):
        pass
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 90 * n


def test_rows_of_all_kinds(spark):
    assert lm.lm_scores(frame(spark, [])).count() == 0
    long = " ".join(f"w{i % 700}" for i in range(200_000))
    rows = [(1, long, "en", "a"), (1, long, "en", "a"), (2, None, None, None), (2, "", None, None), (None, " \t", None, None)]
    got = lm.lm_scores(frame(spark, rows)).collect()
    assert sorted(r.n_tokens for r in got) == [1, 1, 1, 200_001, 200_001]
    assert all(math.isfinite(r.score) and r.score < 0 for r in got)
    only_held = [(i, "a b c", "en", "a") for i in range(200) if zlib.crc32(str(i).encode()) % 7 == 2]
    assert all(r.train_tokens == 0 and r.score == pytest.approx(0.0) for r in lm.lm_scores(frame(spark, only_held)).collect())
