"""Personal data, leaks and the pipeline's stages against brute force."""

import hashlib
import re
from collections import Counter

import pyarrow.parquet as pq
import pytest

queries = pytest.importorskip("bundlery.llm.queries")
pipeline = pytest.importorskip("corpus_pipeline")
regex = pytest.importorskip("regex")

SF = "/root/testdata/sf0.001"
DOCS = {r["doc_id"]: r["text"] or "" for r in pq.read_table(f"{SF}/documents.parquet").to_pylist()}
ITEMS = {r["item_id"]: r["text"] or "" for r in pq.read_table(f"{SF}/benchmark.parquet").to_pylist()}
KINDS = ("email", "ip", "card", "phone")
# fixed values: the patterns of the contract
PATTERNS = (
    r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    r"[0-9]([\x20-]?[0-9])+",
    r"\+[0-9][\x20().0-9-]+[0-9]",
)


def luhn(number):
    total = 0
    for i, c in enumerate(reversed(number)):
        x = int(c) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def valid(kind, text):
    digits = re.sub(r"[^0-9]", "", text)
    if kind == 1:
        return all(int(p) <= 255 for p in text.split("."))
    if kind == 2:
        return 12 <= len(digits) <= 19 and luhn(digits)
    return kind == 0 or 9 <= len(digits) <= 15


def plain_spans(text):
    return sorted((m.start(), k, m.end()) for k, p in enumerate(PATTERNS) for m in re.finditer(p, text) if valid(k, m[0]))


def shingles(text, width=5):
    w = text.split()
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def normal(text):
    return regex.sub(r"[^\p{L}\p{N}]+", " ", text).lower()


def leaks(docs):
    sets = {i: shingles(normal(t)) for i, t in ITEMS.items()}
    out = {}
    for d, t in docs.items():
        own = shingles(normal(t))
        for i, s in sets.items():
            if s and len(s & own) >= 0.8 * len(s) - 1e-9:
                out[d, i] = (len(s & own), len(s))
    return out


def test_base_spans_of_all_texts(spark):
    for r in queries.QUERIES["op4_personal_data"](spark, SF).collect():
        want = plain_spans(DOCS[r["doc_id"]])
        listed = [f"{KINDS[k]}:{s}:{e}" for s, k, e in want]
        count = Counter(k for _, k, _ in want)
        assert [r[f"n_{k}"] for k in KINDS] == [count[i] for i in range(4)]
        assert r["base_sha256"] == hashlib.sha256(",".join(listed).encode()).hexdigest()
        assert [x for x in r["spans"].split(",") if x and not x.startswith("term")] == listed


@pytest.mark.parametrize("text", ["!@a.b@c.d", "a@b.c@d.e", "1.2.3.4.5.6.7.8 256.1.1.1", "4111 1111-1111 1111", "+1 (2) 3.4-5 6789012)", "@@a@b", "a@b..c", "1" * 40, "+49 30 123 456 789 0 12", "0.0.0.00000255", "x+1@y.z+123456789"])
def test_base_spans_of_crafted_texts(text):
    from bundlery.llm.personal_data import base_spans

    assert base_spans(text) == [(s, KINDS[k], e) for s, k, e in plain_spans(text)]


def test_leaks_are_those_of_exact_containment(spark):
    got = {(r["doc_id"], r["item_id"]): (r["n_shared"], r["n_item"]) for r in queries.QUERIES["op8_benchmark_decontamination"](spark, SF).collect()}
    assert got == leaks(DOCS) and got


def test_stages_one_after_another(spark):
    texts = dict(DOCS)
    docs = queries.table(spark, SF, "documents")
    columns = docs.columns
    for name, stage in pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.columns == columns
        rows = docs.collect()
        after = {r["doc_id"]: r["text"] for r in rows}
        assert len(after) == len(rows)
        if name == "language_id":
            assert all(re.search(r"[^\W\d_]", t or "") for t in after.values())
        if name == "ngram_jaccard_join":
            # the smallest id of each component of links stays
            sets = {d: shingles(re.sub(r"[A-Z]", lambda m: m[0].lower(), texts[d])) for d in texts}
            up = {d: d for d in sets}

            def find(d):
                while up[d] != d:
                    d = up[d]
                return d

            ids = sorted(sets)
            for i, a in enumerate(ids):
                for b in ids[i + 1 :]:
                    n = len(sets[a] & sets[b])
                    if n and 100 * n >= 80 * len(sets[a] | sets[b]):
                        x, y = find(a), find(b)
                        up[max(x, y)] = min(x, y)
            assert set(after) == {d for d in ids if find(d) == d}
        if name == "benchmark_decontamination":
            assert set(texts) - set(after) == {d for d, _ in leaks(texts)}
        if name == "personal_data":
            assert set(after) == set(texts)
            for d, t in texts.items():
                assert (after[d] == t) or "[" in after[d]
                assert not any(t[s:e] in after[d] for s, k, e in plain_spans(t) if k == 0)
        texts = after
    total = Counter()
    for r in pipeline.STAGES[-1][1](spark, docs, SF).collect():
        total[r["sequence_id"]] += r["length"]
    assert total and max(total.values()) <= 2048
