"""Factors of copied passages: their sources, their growth, and their check."""

import random

import numpy as np
import pytest

dedup = pytest.importorskip("bundlery.llm.substring_dedup")


def words(seed, n):
    r = random.Random(seed)
    return [f"w{r.randrange(10**9)}" for _ in range(n)]


def plain(docs, width=50):
    """Words under windows that start in a smaller doc_id, kept by row."""
    first = {}
    for d, t in sorted((x for x in docs if x[0] is not None), key=lambda x: x[0]):
        w = (t or "").split()
        for i in range(len(w) - width + 1):
            first.setdefault(tuple(w[i : i + width]), d)
    out = []
    for d, t in docs:
        w, gone = (t or "").split(), set()
        for i in range(len(w) - width + 1 if d is not None else 0):
            if first[tuple(w[i : i + width])] < d:
                gone.update(range(i, i + width))
        out.append((d, len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone)))
    return sorted(out, key=repr)


A, B, C = words(1, 300), words(2, 300), words(3, 5000)
DOCS = [
    (1, A + words(11, 90)),
    (2, words(12, 60) + A[40:200] + words(13, 20) + B),
    (3, B[100:260] + A[:120] + words(14, 10)),
    (4, A[10:59] + words(15, 5) + A[60:110] + A[60:110]),
    # one id with two texts, and a row twice
    (5, C[:400]),
    (5, words(16, 30) + A[100:180]),
    (6, C),
    (6, C),
    (7, C[1000:3000] + C[200:260]),
    (None, A),
    (8, None),
    (9, []),
    (10, ["a"] * 400),
    (11, ["a"] * 120 + ["b"] + ["a"] * 60),
]
ROWS = [(d, " ".join(w) if w is not None else None) for d, w in DOCS]


@pytest.fixture(scope="module")
def table(spark):
    return spark.createDataFrame(ROWS, "doc_id long, text string").repartition(4)


def test_kept_words_are_those_of_plain_windows(table):
    got = [(r["doc_id"], r["n_words"], r["n_removed"], r["kept"]) for r in dedup.dedup_substrings(table).collect()]
    assert sorted(got, key=repr) == plain(ROWS)


def test_factors_stand_at_their_sources_and_are_whole(table):
    texts = {}
    for d, t in ROWS:
        texts.setdefault(d, []).append((t or "").split())
    found = dedup.duplicate_factors(table).collect()
    for r in found:
        n = r["length"]
        assert n >= 50 and r["source_id"] < r["doc_id"]
        sources = [w[r["source_start"] : r["source_start"] + n] for w in texts[r["source_id"]]]
        assert any(w[r["start"] : r["start"] + n] in sources for w in texts[r["doc_id"]])
    # a long copy is one factor over all blocks
    assert max(r["length"] for r in found if r["doc_id"] == 7) == 2000
    assert {(r["start"], r["length"], r["source_id"], r["source_start"]) for r in found if r["doc_id"] == 2} == {(60, 160, 1, 40)}


def test_a_factor_keeps_to_its_source():
    # windows 0..9 of document 9 stand in document 5, windows 4..6 also in document 1
    h = np.concatenate([np.arange(10), np.arange(10), np.arange(4, 7)]).astype(np.uint64) + np.uint64(77)
    doc = np.repeat([9, 5, 1], [10, 10, 3]).astype(np.int64)
    start = np.concatenate([np.arange(10), np.arange(100, 110), np.arange(3)])
    first = dedup._first_entries(h, doc)
    got = dedup._factors(h, doc, np.zeros_like(doc), start, first, doc > doc[first], 50)
    mine = [tuple(x) for x in got[got["doc"] == 9].tolist()]
    assert mine == [(9, 0, 0, 59, 5, 0, 100)]


def test_a_collision_of_hashes_removes_nothing(spark, table):
    false = [(2, 60, 160, 1, 41), (2, 60, 160, 1, 40)]
    keys = {r["doc_id"]: r["text_key"] for r in dedup._keyed(table).collect()}
    rows = [(d, keys[d], s, n, x, keys[x], at) for d, s, n, x, at in false]
    for given, gone in ((rows[:1], 0), (rows, 160)):
        got = dedup.strip_factors(table, spark.createDataFrame(given, dedup.FACTORS)).where("doc_id = 2").first()
        assert got["n_removed"] == gone


def test_fragments_of_one_source_are_joined():
    rows = [(0, 60, 1, 0, 10), (11, 60, 1, 0, 21), (40, 50, 1, 0, 51), (71, 50, 1, 0, 81), (200, 50, 1, 0, 300)]
    assert dedup.join_fragments(rows) == [(0, 121, 1, 0, 10), (40, 50, 1, 0, 51), (200, 50, 1, 0, 300)]
