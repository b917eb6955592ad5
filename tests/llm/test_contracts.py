"""Registered text queries against brute force on the smallest tables."""

import hashlib
import re
import zlib
from collections import defaultdict

import pyarrow.parquet as pq
import pytest

queries = pytest.importorskip("bundlery.llm.queries")
SF = "/root/testdata/sf0.001"
DOCS = {r["doc_id"]: r["text"] or "" for r in pq.read_table(f"{SF}/documents.parquet").to_pylist()}
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def run(spark, prefix):
    name = next(k for k in queries.QUERIES if k.startswith(prefix + "_"))
    return [r.asDict() for r in queries.QUERIES[name](spark, SF).collect()]


def lower(text):
    return text.translate({c: c + 32 for c in range(65, 91)})


def test_components_of_near_copies(spark):
    sets = {}
    for d, t in DOCS.items():
        w = WORD.findall(lower(t))
        sets[d] = {tuple(w[i : i + 3]) for i in range(max(1, len(w) - 2))} if w else set()
    root = {d: d for d in sets}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            n = len(sets[a] & sets[b])
            if n and 100 * n >= 90 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in run(spark, "op1")}
    assert got == {d: (len(sets[d]), find(d)) for d in sets}


def test_windows_that_start_in_an_earlier_document_go(spark):
    words = {d: WORD.findall(t) for d, t in DOCS.items()}
    first = {}
    for d in sorted(words):
        for i in range(len(words[d]) - 49):
            first.setdefault(tuple(words[d][i : i + 50]), d)
    want = {}
    for d, w in words.items():
        gone = set()
        for i in range(len(w) - 49):
            if first[tuple(w[i : i + 50])] < d:
                gone.update(range(i, i + 50))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        want[d] = (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest())
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in run(spark, "op6")} == want


def test_token_counts_are_the_library_s(spark):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(queries.vocabulary("byte_bpe_50k.json"))
    tok.no_truncation()
    want = {d: len(tok.encode(t, add_special_tokens=False).ids) for d, t in DOCS.items()}
    got = run(spark, "op3")
    assert {r["doc_id"]: r["n_tokens"] for r in got} == want
    assert all(r["n_bytes"] == len(DOCS[r["doc_id"]].encode()) and r["over_limit"] == (r["n_tokens"] > 1024) for r in got)


def test_packing_holds_every_token_once_and_has_no_gaps(spark):
    import numpy as np
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(queries.vocabulary("word_bpe_49k.json"))
    tok.no_truncation()
    got, bins, pieces = run(spark, "op7"), defaultdict(list), defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]].append(r)
    for d, t in DOCS.items():
        ids = np.array([*tok.encode(t, add_special_tokens=False).ids, 0], "<u4")
        mine = sorted(pieces[d], key=lambda r: r["piece"])
        assert [r["start"] for r in mine] == list(range(0, len(ids), 2048)) and sum(r["length"] for r in mine) == len(ids)
        assert all(r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes()) for r in mine)
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    total = sum(r["length"] for r in got)
    assert len(bins) <= 1.05 * -(-total // 2048) + 1


def test_media_reads_back_what_was_stored(spark):
    for r in run(spark, "op9"):
        raw = DOCS[r["doc_id"]].encode()
        padded = raw + bytes((-len(raw)) % 64 or (64 if not raw else 0))
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"]) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest())
        assert r["tail_crc32"] == zlib.crc32(padded[-64:])


def test_held_out_languages(spark):
    lang = {r["doc_id"]: r["lang"] for r in pq.read_table(f"{SF}/documents.parquet", columns=["doc_id", "lang"]).to_pylist()}
    got = run(spark, "op2")
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for r in got)
    held = [r["lang_pred"] == lang[r["doc_id"]] for r in got if r["held_out"] and r["lang_pred"] != "und" and lang[r["doc_id"]]]
    assert sum(held) >= 0.85 * len(held)


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_sql(spark, name):
    import os

    import duckdb

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f[:-8]} AS SELECT * FROM read_parquet('{SF}/{f}')")
    df = queries.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    rel = con.execute(queries.ORACLE_SQL[name])
    at = [[d[0] for d in rel.description].index(c) for c in cols]
    assert sorted(map(repr, ([r[c] for c in cols] for r in df.collect()))) == sorted(map(repr, ([r[i] for i in at] for r in rel.fetchall())))
