"""Odd tables: nulls, blanks, very long texts, repeated rows, clashing names, no rows."""

import pytest

queries = pytest.importorskip("bundlery.llm.queries")

from bundlery.llm.benchmark_leaks import drop_leaks, find_leaks  # noqa: E402
from bundlery.llm.bin_packing import pack_documents  # noqa: E402
from bundlery.llm.language_id import identify_languages, keep_identified  # noqa: E402
from bundlery.llm.licence_scan import scan_licences  # noqa: E402
from bundlery.llm.media_columns import media_columns  # noqa: E402
from bundlery.llm.personal_data import find_personal_data, sanitise  # noqa: E402
from bundlery.llm.reply_trees import format_conversations  # noqa: E402
from bundlery.llm.signature_join import drop_near_duplicates, jaccard_components  # noqa: E402
from bundlery.llm.substring_dedup import dedup_substrings  # noqa: E402
from bundlery.llm.token_counts import count_tokens  # noqa: E402

WORDS = " ".join(f"word{i % 997}x{i % 13}" for i in range(60_000))
TEXTS = [None, "", " \t\n", "one", "one two", "mail a.b@c.de or +49 (0)30 12345678 now", WORDS, WORDS, "日本語 текст über", "x" * 200_000, "one two three four five six seven"]
#: Columns beside those of ``documents``, named like the operators' own.
CLASH = ("key", "part", "term", "bucket", "base", "start", "room", "_id")
EXTRA = ", ".join(f"{c} string" for c in CLASH)
SCHEMA = f"doc_id long, text string, lang string, source string, n_chars long, {EXTRA}"
ITEMS = "item_id long, text string, key string, doc_id long"

DOC_OPS = {
    "jaccard": lambda d: jaccard_components(d),
    "languages": lambda d: identify_languages(d),
    "tokens": lambda d: count_tokens(d, queries.vocabulary("byte_bpe_50k.json"), limit=1024),
    "personal": lambda d: find_personal_data(d),
    "substrings": lambda d: dedup_substrings(d, width=50),
    "media": lambda d: media_columns(d),
}
STAGES = {
    "identified": lambda d, i: keep_identified(d),
    "distinct": lambda d, i: drop_near_duplicates(d),
    "clean": lambda d, i: drop_leaks(d, i),
    "sanitised": lambda d, i: sanitise(d),
}


def rows(ids=True):
    lang = ["en", "de", None, "fr", "en"]
    return [(i if ids else None, t, lang[i % 5], None, None, *["z"] * len(CLASH)) for i, t in enumerate(TEXTS)]


@pytest.fixture(scope="module")
def odd(spark):
    # the row of index 5 twice, and one row without an id
    table = rows()
    return spark.createDataFrame(table + [table[5], (None, *table[10][1:])], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, "one two three four five six seven", "k", 3), (2, None, None, None), (3, " ", None, None), (None, "never seen in any text at all", None, 1)], ITEMS)


@pytest.mark.parametrize("name", DOC_OPS)
def test_each_row_gets_a_result(odd, name):
    got = DOC_OPS[name](odd).collect()
    ids = sorted((r["doc_id"] for r in got), key=repr)
    assert ids == sorted((r["doc_id"] for r in odd.select("doc_id").collect()), key=repr)


@pytest.mark.parametrize("name", DOC_OPS)
def test_no_rows_give_no_rows(odd, name):
    assert DOC_OPS[name](odd.limit(0)).collect() == []


@pytest.mark.parametrize("name", STAGES)
def test_stages_keep_columns(odd, items, name):
    got = STAGES[name](odd, items)
    assert got.columns == odd.columns and got.count() <= odd.count()
    assert STAGES[name](odd.limit(0), items.limit(0)).collect() == []


def test_one_of_each_group_of_copies_stays_and_rows_without_id_too(odd):
    kept = [r["doc_id"] for r in drop_near_duplicates(odd).collect()]
    assert kept.count(None) == 1
    assert sorted(k for k in kept if k is not None) == [0, 1, 2, 3, 4, 5, 6, 8, 9, 10]


def test_leaks_of_odd_rows(odd, items):
    got = sorted(((r["doc_id"], r["item_id"]) for r in find_leaks(odd, items).collect()), key=repr)
    assert got == [(10, 1), (None, 1)]
    kept = [r["doc_id"] for r in drop_leaks(odd, items).collect()]
    assert 10 not in kept and None not in kept and len(kept) == odd.count() - 2
    assert find_leaks(odd, items.limit(0)).collect() == [] and find_leaks(odd.limit(0), items).collect() == []


def test_licences_of_odd_rows(odd):
    assert {r["doc_id"] for r in scan_licences(odd).collect()} <= {*range(len(TEXTS)), None}
    assert scan_licences(odd.limit(0)).collect() == []


def test_identifiers_are_replaced(odd):
    texts = {r["text"] for r in sanitise(odd).collect()}
    assert "mail [EMAIL] or [PHONE] now" in texts and None in texts and WORDS in texts


def test_packing_of_odd_rows(odd):
    got = pack_documents(odd, queries.vocabulary("word_bpe_49k.json"), capacity=2048)
    assert {r["doc_id"] for r in got.collect()} == {*range(len(TEXTS)), None}
    places = sorted((r["sequence_id"], r["offset"], r["length"]) for r in got.collect())
    for a, b in zip(places, places[1:]):
        assert b[1] == (a[1] + a[2] if a[0] == b[0] else 0)
    assert pack_documents(odd.limit(0), queries.vocabulary("word_bpe_49k.json"), capacity=2048).collect() == []


def test_conversations_with_gaps(spark):
    schema = "conv_id long, turn long, role string, text string, path string, score double"
    table = spark.createDataFrame([(1, 0, "user", None, "p", None), (1, 1, None, "x", None, None), (2, 5, "assistant", "", None, 1.0), (None, 0, "user", "a", None, None)], schema)
    got = {r["conv_id"] for r in format_conversations(table).collect()}
    assert got >= {1, 2}
    assert format_conversations(table.limit(0)).collect() == []


def test_words_in_use_outlive_a_turnover_of_what_is_remembered(monkeypatch):
    from public_tokenizers import path

    from bundlery.llm import bin_packing as b

    monkeypatch.setattr(b, "REMEMBERED", 40)
    monkeypatch.setattr(b, "REMEMBERED_WORDS", 40)
    with open(path("word_bpe_49k.json"), encoding="utf-8") as f:
        w = b.WordIds(f.read())
    asked, tokenize = [], w.tokenizer.model.tokenize
    w.tokenize = lambda s: asked.append(s) or tokenize(s)
    texts = [f"The same {'abcdefghij'[i % 10] * (i % 30 + 3)}{'xyzuvw'[i % 6] * (i % 13)}." for i in range(300)]
    assert [w.ids(t) for t in texts] == [w.encoded(t) for t in texts]
    assert asked.count("the") == 1 and asked.count("same") == 1 and len(set(asked)) > 200
