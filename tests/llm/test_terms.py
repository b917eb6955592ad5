"""Disclosing terms against their mutual information counted by hand."""

import math
import re

import pytest

personal = pytest.importorskip("bundlery.llm.personal_data")

FILL = ("people walk along", "people talk about", "people write down", "people look after")


def texts():
    near = [f"{FILL[i]} zanzibar at me@ex.org {'abcd'[i] * 5}" for i in range(4)]
    far = [f"{FILL[i % 4]} other things {i}" for i in range(26)]
    # a passage in four copies is one context only
    copies = ["people call kilimanjaro at you@ex.org today"] * 4
    return near + far + copies


def test_terms_that_stand_nowhere_else_are_found(spark):
    all_texts = texts()
    words = [set(re.findall(r"[^\W\d_]{4,}", t)) for t in all_texts]
    own = {i for i, t in enumerate(all_texts) if "me@ex.org" in t}
    want = set()
    for term in set().union(*words):
        has = {i for i, w in enumerate(words) if term in w}
        both = has & own
        if len(both) >= 3:
            mutual = math.log2(len(all_texts) * len(both) / (len(has) * len(own)))
            if mutual >= 0.9 * math.log2(len(all_texts) / len(own)):
                want |= {(i, m.start(), m.end()) for i in both for m in re.finditer(rf"\b{term}\b", all_texts[i])}
    docs = spark.createDataFrame(list(enumerate(all_texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["start"], r["end"]) for r in personal.disclosing_terms(docs).collect()}
    assert got == want and {all_texts[i][s:e] for i, s, e in got} == {"zanzibar"}
    clean = {r["doc_id"]: r["text"] for r in personal.sanitise(docs).collect()}
    assert clean[0] == "people walk along [TERM] at [EMAIL] aaaaa"
    assert clean[30] == "people call kilimanjaro at [EMAIL] today" and clean[5] == all_texts[5]


def test_identifiers_of_one_document_are_judged_over_the_whole_text(spark):
    # the term stands far from the identifier, and both in one document only
    far = f"{'people walk along ' * 20}zanzibar {'people talk about ' * 20}me@ex.org and people write zanzibar@ex.org"
    all_texts = [far] + [f"{FILL[i % 4]} and other things" for i in range(199)]
    docs = spark.createDataFrame(list(enumerate(all_texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["start"], r["end"]) for r in personal.disclosing_terms(docs).collect()}
    at = far.index("zanzibar")
    assert got == {(0, at, at + 8)}


def test_terms_of_other_documents_disclose_nothing(spark):
    # the estimate of each pair by hand: smoothed by half a document, copies of a passage once
    all_texts = [f"{FILL[i % 4]} and other things" for i in range(196)]
    all_texts += ["people call sansibar mombasa at me@ex.org today", "sansibar people write down", "mombasa nairobi", "nairobi at +49 30 1234567"]
    n, want = len(all_texts), set()
    for e in ("me@ex.org", "+49 30 1234567"):
        own = {i for i, t in enumerate(all_texts) if e in t}
        for term in set(re.findall(r"[^\W\d_]{4,}", " ".join(all_texts[i] for i in own))):
            has = {i for i, t in enumerate(all_texts) if re.search(rf"\b{term}\b", t)}
            both, p = len(has & own), len(own) / n
            if math.log2((both + 0.5 * p) / (len(has) + 0.5) / p) >= 0.9 * -math.log2(p):
                want |= {(i, m.start(), m.end()) for i in has & own for m in re.finditer(rf"\b{term}\b", all_texts[i])}
    docs = spark.createDataFrame(list(enumerate(all_texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["start"], r["end"]) for r in personal.disclosing_terms(docs).collect()}
    assert got == want and {all_texts[i][s:e] for i, s, e in got} == {"call", "today"}
