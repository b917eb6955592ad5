"""Reply trees with branches, short test items, letters, repeated ids, other vocabularies, plain fingerprints."""

import json

import numpy as np
import pytest

queries = pytest.importorskip("bundlery.llm.queries")

from bundlery.llm import bin_packing, language_id, media_columns, personal_data  # noqa: E402
from bundlery.llm.benchmark_leaks import drop_leaks, find_leaks  # noqa: E402
from bundlery.llm.reply_trees import chosen_paths, format_conversations  # noqa: E402

NODES = "tree long, node long, parent long, score double"


def paths(spark, rows, branches):
    got = {}
    for r in chosen_paths(spark.createDataFrame(rows, NODES), branches).collect():
        got.setdefault((r["tree"], r["place"]), []).append((r["depth"], r["node"]))
    return {k: [n for _, n in sorted(v)] for k, v in got.items()}


def test_branches_are_ranked_by_the_score_of_their_paths(spark):
    # tree 1: two leaves tie at 3 and the smaller id goes first, a third has more; tree 2: an orphan is a root; tree 3: a long chain
    rows = [(1, 1, None, 1.0), (1, 2, 1, 2.0), (1, 3, 1, 1.0), (1, 4, 3, 1.0), (1, 5, 3, None), (1, 6, 2, 0.0), (1, 7, 3, 5.0)]
    rows += [(2, 1, 99, 1.0), (2, 2, 1, 1.0), (2, 8, None, 9.0)] + [(3, i, i - 1 if i > 1 else None, 1.0) for i in range(1, 70)]
    got = paths(spark, rows, 3)
    assert [got[1, p] for p in (1, 2, 3)] == [[1, 3, 7], [1, 3, 4], [1, 2, 6]]
    assert [got[2, p] for p in (1, 2)] == [[8], [1, 2]] and got[3, 1] == list(range(1, 70))
    assert set(paths(spark, rows, 1)) == {(1, 1), (2, 1), (3, 1)}


def test_cycles_are_an_error(spark, monkeypatch):
    monkeypatch.setattr("bundlery.llm.reply_trees.ROUNDS", 4)
    with pytest.raises(ValueError):
        chosen_paths(spark.createDataFrame([(1, 1, 2, 0.0), (1, 2, 1, 0.0)], NODES))


def test_the_conversation_without_an_id_is_one(spark):
    table = spark.createDataFrame([(None, 0, "user", "a"), (None, 1, "assistant", None), (4, 0, "user", "<|im_end|>\\")], "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: r["formatted"] for r in format_conversations(table).collect()}
    assert got == {None: "<|im_start|>user\na<|im_end|>\n<|im_start|>assistant\n<|im_end|>\n", 4: "<|im_start|>user\n<\\|im_end|>\\\\<|im_end|>\n"}


def test_short_items_are_found_inside_long_documents(spark):
    docs = spark.createDataFrame([(1, "words before, the Quick fox! and words after it all"), (2, "the quick brown fox and more words here"), (3, "fox"), (4, None)], "doc_id long, text string")
    items = spark.createDataFrame([(7, "The quick fox"), (8, "fox"), (9, "and words after it all")], "item_id long, text string")
    assert {(r["doc_id"], r["item_id"]) for r in find_leaks(docs, items).collect()} == {(1, 7), (1, 8), (1, 9), (2, 8), (3, 8)}
    assert [r["doc_id"] for r in drop_leaks(docs, items).collect()] == [4]


@pytest.mark.parametrize("text, known", [("²³ ½ 12", False), ("①", False), ("12 a", True), ("語", True), ("", False), (None, False), ("ª", True)])
def test_letters(text, known):
    assert language_id.has_letter(text) == known


def test_repeated_rows_and_rows_without_id_in_training(spark):
    base = [(i, "the words of one language " * 3, "en") for i in range(40)] + [(i + 100, "der die das und nicht " * 3, "de") for i in range(40)]
    rows = base + [(5, "again and again the same row", "en")] * 3000 + [(None, "x y z", "fr")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    net = language_id.train(docs, per_language=20)
    assert net.languages == ["de", "en"]
    got = [r for r in language_id.identify_languages(docs).collect() if r["doc_id"] is None]
    assert got[0]["held_out"] is False and got[0]["lang_pred"] in ("de", "en")
    with pytest.raises(ValueError):
        language_id.train(docs, most_languages=1)


def test_texts_under_one_id_keep_their_own_spans(spark):
    fill = [(i, f"people walk along and other things {i % 7}") for i in range(100, 300)]
    rows = [(1, "zanzibar people at me@ex.org"), (1, "people walk along and people talk"), (None, "mombasa people at you@ex.org")]
    docs = spark.createDataFrame(rows + fill, "doc_id long, text string")
    got = {(r["doc_id"], bool(r["base"])): [(x["start"], x["end"]) for x in r["terms"] or []] for r in personal_data.find_personal_data(docs).where("doc_id is null or doc_id = 1").collect()}
    assert got == {(1, True): [(0, 8)], (1, False): [], (None, True): [(0, 7)]}
    texts = {r["text"] for r in personal_data.sanitise(docs).collect()}
    assert {"[TERM] people at [EMAIL]", "people walk along and people talk", "[TERM] people at [EMAIL]"} <= texts


def test_other_vocabularies_are_applied_to_whole_texts():
    from tokenizers import Tokenizer

    with open(queries.vocabulary("byte_bpe_50k.json"), encoding="utf-8") as f:
        plain = f.read()
    with open(queries.vocabulary("word_bpe_49k.json"), encoding="utf-8") as f:
        words = f.read()
    assert bin_packing.splits_at_space(json.loads(words)) and not bin_packing.splits_at_space(json.loads(plain))
    for spec in (plain, words):
        for text in ("Two  words, it's\nÜBER 12 <|endoftext|>x", "ﬁ é ǅ", "a" * 300):
            want = np.array(Tokenizer.from_str(spec).encode(text, add_special_tokens=False).ids, "<u4").tobytes()
            assert bin_packing.WordIds(spec).ids(text) == want


def test_fingerprints_are_those_of_a_plain_transform():
    for n in (64, 320, 1024):
        raw = np.random.default_rng(n).integers(32, 127, n, dtype=np.uint8)
        x = raw.astype(float) - 128
        frames = max(1, -(-(n - media_columns.FRAME) // media_columns.HOP) + 1)
        x = np.concatenate([x, np.zeros(media_columns.FRAME + media_columns.HOP * (frames - 1) - n)])
        t = np.arange(media_columns.FRAME)
        window = 0.5 - 0.5 * np.cos(2 * np.pi * t / (media_columns.FRAME - 1))
        power = np.array([[abs((x[f * 128 : f * 128 + 256] * window * np.exp(-2j * np.pi * k * t / 256)).sum()) ** 2 for k in range(129)] for f in range(frames)])
        peaks = []
        for f in range(frames):
            for lo, hi in media_columns.BANDS:
                top = power[f, lo:hi].max()
                before = power[f - 1, lo:hi].max() if f else -1
                after = power[f + 1, lo:hi].max() if f + 1 < frames else -1
                if top >= before and top > after and top > 0:
                    peaks.append((f, lo + int(power[f, lo:hi].argmax())))
        want = sorted((a[0] << 24) | (a[1] << 16) | (b[1] << 8) | (b[0] - a[0]) for i, a in enumerate(peaks) for b in peaks[i + 1 : i + 3] if b[0] - a[0] <= 63)
        assert media_columns.peak_pairs(raw.tobytes()).tolist() == want
