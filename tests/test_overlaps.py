"""The k greatest products with later rows: equal to brute force over ranges and numberings, and no slab is sent to all others."""

import random

import pytest

from semigrid.matrix import SparseMatrix
from semigrid.plans import overlaps
from semigrid.workloads import graph_queries
from semigrid.workloads import graphs as W


def _brute(entries, k):
    rows = {}
    for i, j, v in entries:
        rows.setdefault(i, {})[j] = v
    out = []
    for i, x in rows.items():
        dots = [(-sum(v * y.get(j, 0) for j, v in x.items()), other) for other, y in rows.items() if other > i]
        out += [(i, j, -d, r + 1) for r, (d, j) in enumerate(sorted(p for p in dots if p[0])[:k])]
    return sorted(out)


def _entries(seed, values):
    """Rows of 0 to 60 words, a few common words in most of them, copies and rows alone."""
    rng, out = random.Random(seed), []
    for i in range(150):
        words = {f"c{x}" for x in range(9) if rng.random() < 0.7} | {f"w{int(rng.paretovariate(0.7))}" for _ in range(rng.randrange(50))}
        words = {f"only{i}"} if i % 29 == 0 else words
        if i % 10 == 3 and out:
            words = {j for n, j, _ in out if n == out[-1][0]}
        out += [(i * 7 - 300, w, rng.choice(values)) for w in sorted(words)]
    return out


@pytest.mark.parametrize("values", [(1,), (1, 3, 70_000)])
@pytest.mark.parametrize("listed", [8_000_000, 0])
@pytest.mark.parametrize("bits", [64, 1024])
def test_as_brute_force(spark, monkeypatch, values, listed, bits):
    for limit, value in (("HELD_ENTRIES", 700), ("WEIGHT", 8), ("LISTED_IDS", listed), ("BITS", bits), ("TRIED", 2), ("_BATCH", 13)):
        monkeypatch.setattr(overlaps, limit, value)
    entries = _entries(len(values), values)
    m = SparseMatrix(spark.createDataFrame([*entries, (None, "c1", 1), (5, None, 1)], "i long, j string, v long").repartition(5), 1 << 40, 1 << 40)
    assert sorted(map(tuple, W.topk_overlap(m, 3).collect())) == _brute(entries, 3)


def test_steps_of_two_bytes():
    import numpy as np

    for codes in ([0], [7, 8, 65_535, 65_536, 131_071, 1_000_000], [65_534, 131_069, 131_069 + 2 * 65_535], []):
        codes = np.array(codes, np.int64)
        assert (overlaps._unpacked(overlaps._packed(codes, True), True) == codes).all()


def test_what_is_sent_does_not_grow_with_slabs_times_slabs(spark, monkeypatch):
    """A row goes to the ranges from its own on, once each, in two bytes an entry; before, each slab went to all groups of slabs, in 20 bytes."""
    monkeypatch.setattr(overlaps, "HELD_ENTRIES", 1000)
    sent = []
    kept = overlaps.materialize
    monkeypatch.setattr(overlaps, "materialize", lambda df, tag, **x: sent.append((tag, kept(df, tag, **x))) or sent[-1][1])
    entries = _entries(1, (1,))
    W.topk_overlap(SparseMatrix(spark.createDataFrame(entries, "i long, j string, v long"), 1 << 40, 1 << 40), 3)
    pieces = dict(sent)["pieces"].selectExpr("sum(n)", "sum(length(codes))", "count(vals)").first()
    assert pieces[1] <= 2 * pieces[0] and pieces[2] == 0


def test_repeated_documents(spark, tmp_path):
    docs = [(1, "a b A"), (1, "b c"), (2, "a  b c"), (None, "a"), (None, "a"), (3, None), (4, "")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = graph_queries._doc_words(spark, str(tmp_path)).df.collect()
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, [(1, "a", 1), (1, "b", 1), (1, "c", 1), (2, "a", 1), (2, "b", 1), (2, "c", 1), (None, "a", 1)]))
