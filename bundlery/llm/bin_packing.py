"""Packing of tokenised documents into sequences by minimum bin slack.

Tokenising yields one row per piece with its length only.  The histogram of
lengths has at most ``capacity`` rows, whatever the corpus, so the packing is
planned on the driver over lengths: each bin takes the longest piece left, and a
subset-sum dynamic programme over a bitset of reachable fillings finds the
fullest combination of available lengths beside it, which is then removed - as
often as the histogram allows, in one step.  The plan says, for a range of
ranks within a length, which sequence and which offset they get.  Pieces learn
their rank from two-level numbering (within salted parts of a length, then
part offsets), so a length that very many pieces share is no single task.
"""

from __future__ import annotations

import json
import sys
import zlib
from array import array

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .lineage import settle
from .textbits import slices

CAPACITY = 2048
#: Chunks and words that one worker remembers, half of them from before its last turnover.
REMEMBERED, REMEMBERED_WORDS = 400_000, 300_000
#: Signs that may follow a word in a chunk (fixed value).
TAIL = ".,;:!?*#$%&|"
_SEPARATORS = "\x1c\x1d\x1e\x1f"


def fullest_bin(left: dict[int, int], lengths: list[int], capacity: int) -> dict[int, int]:
    """The longest length with the combination that leaves the least slack.

    ``left`` counts the pieces of each length, ``lengths`` lists those with any,
    longest first.
    """
    first = lengths[0]
    room = capacity - first
    used = {first: 1}
    if not room:
        return used
    mask, reach, trail = (1 << room + 1) - 1, 1, []
    for n in lengths:
        copies = min(left[n] - (n == first), room // n)
        step = 1
        while copies > 0:
            take = min(step, copies)
            grown = (reach | reach << take * n) & mask
            if grown != reach:
                trail.append((n, take, reach))
                reach = grown
            copies -= take
            step *= 2
        if reach >> room & 1:
            break
    at = reach.bit_length() - 1
    for n, take, before in reversed(trail):
        if not before >> at & 1:
            used[n] = used.get(n, 0) + take
            at -= take * n
    return used


def plan_bins(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Rows ``length, lo, hi, sequence, each, offset``.

    Ranks ``lo <= r < hi`` of a length fill sequences from ``sequence`` on,
    ``each`` pieces to one, from ``offset`` on.
    """
    left = {n: c for n, c in histogram.items() if c > 0 and n > 0}
    if any(n > capacity for n in left):
        raise ValueError("a piece is longer than a sequence")
    lengths = sorted(left, reverse=True)
    rank, rows, sequence = dict.fromkeys(left, 0), [], 0
    while lengths:
        used = fullest_bin(left, lengths, capacity)
        times = min(left[n] // c for n, c in used.items())
        offset = 0
        for n, c in used.items():
            rows.append((n, rank[n], rank[n] + times * c, sequence, c, offset))
            rank[n] += times * c
            left[n] -= times * c
            offset += n * c
        sequence += times
        lengths = [n for n in lengths if left[n]]
    return rows


#: The steps for which chunks between white space are independent, and words of
#: composed Latin letters may skip normalisation (fixed values of the vocabulary format).
NORMALISED = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
WORD_RULE = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


def splits_at_space(spec: dict) -> bool:
    """Whether a vocabulary file has the steps that ``WordIds`` shortens."""
    normal, pre = spec.get("normalizer") or {}, (spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}, {}]
    first, last = pre[0], pre[-1]
    return (
        normal.get("normalizers") == NORMALISED
        and len(pre) == 2
        and (first.get("type"), first.get("pattern"), first.get("behavior"), first.get("invert")) == ("Split", {"Regex": WORD_RULE}, "Removed", True)
        and (last.get("type"), last.get("add_prefix_space"), last.get("use_regex")) == ("ByteLevel", False, False)
        and spec["model"]["type"] == "BPE"
        and not spec["model"].get("dropout")
        and not any(x["lstrip"] or x["rstrip"] or x["single_word"] or x["normalized"] for x in spec["added_tokens"])
    )


class WordIds(dict):
    """White-space-free chunk -> its ids as little-endian 32-bit bytes.

    ``spec`` is the text of a vocabulary file.  Files with other steps than the
    known ones are applied to whole texts.
    """

    def __init__(self, spec: str):
        super().__init__()
        from tokenizers import Tokenizer

        if sys.byteorder != "little" or array("I").itemsize != 4:
            raise RuntimeError("ids are kept as little-endian 32-bit numbers")
        self.tokenizer = Tokenizer.from_str(spec)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.tokenize = self.tokenizer.model.tokenize
        self.known = splits_at_space(json.loads(spec))
        self.special = [x.content for x in self.tokenizer.get_added_tokens_decoder().values()]
        self.words: dict[str, bytes] = {}
        # what was in use before the last turnover: words that come again come back from here
        self.old: dict[str, bytes] = {}
        self.old_words: dict[str, bytes] = {}
        printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
        spare = iter(range(0x100, 0x200))
        self.byte_symbol = {b: b if b in printable else next(spare) for b in range(256)}

    def encoded(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _word(self, word: str) -> bytes:
        """Ids of one lower-case pre-token, past the steps that cannot change it."""
        out = self.words.get(word)
        if out is None:
            if len(self.words) >= REMEMBERED_WORDS // 2:
                self.old_words, self.words = self.words, {}
            out = self.old_words.get(word)
            if out is None:
                symbols = word if word.isascii() else word.encode().decode("latin-1").translate(self.byte_symbol)
                out = array("I", [t.id for t in self.tokenize(symbols)]).tobytes()
            self.words[word] = out
        return out

    def __missing__(self, chunk: str) -> bytes:
        out = self.old.get(chunk)
        if out is None:
            out = self._chunk(chunk)
        if len(chunk) <= 48:
            if len(self) >= REMEMBERED // 2:
                self.old = dict(self)
                self.clear()
            self[chunk] = out
        return out

    def _chunk(self, chunk: str) -> bytes:
        """Ids of a chunk that is not remembered."""
        word = chunk.rstrip(TAIL)
        low = word.lower()
        # composed Latin letters only: normalisation keeps them and case folds one to one
        if word.isalpha() and (word.isascii() or (max(word) < "\u0180" and len(low) == len(word))):
            out = self._word(low)
            if len(word) < len(chunk):
                out += self._word(chunk[len(word) :])
        else:
            out = self.encoded(chunk)
        return out

    def ids(self, text: str) -> bytes:
        """Ids of a text: no pre-token crosses white space, so chunks are independent."""
        if not self.known or any(s in text for s in self.special) or any(c in text for c in _SEPARATORS):
            return self.encoded(text)
        return b"".join(map(self.__getitem__, text.split()))


_words: dict[int, WordIds] = {}


def token_pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32``: each document's ids, then ``end_id``.

    Only documents of more than ``capacity`` ids are cut.  A null or empty text
    is the end id alone.  The driver reads the file ``vocabulary`` and broadcasts
    its text, whose size the vocabulary bounds.
    """
    with open(vocabulary, encoding="utf-8") as f:
        held = docs.sparkSession.sparkContext.broadcast(f.read())
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def run(batches):
        own = hash(held.value)
        if own not in _words:
            _words.clear()
            _words[own] = WordIds(held.value)
        ids, end = _words[own].ids, end_id.to_bytes(4, "little")
        for batch in slices(batches):
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                raw = (ids(text) if text else b"") + end
                for piece, at in enumerate(range(0, len(raw), 4 * capacity)):
                    part = raw[at : at + 4 * capacity]
                    rows.append((doc, piece, at // 4, len(part) // 4, zlib.crc32(part)))
            if rows:
                d, p, s, n, c = zip(*rows)
                yield pa.RecordBatch.from_arrays([pa.array(d, pa.int64()), pa.array(p, pa.int32()), pa.array(s, pa.int64()), pa.array(n, pa.int64()), pa.array(c, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return source.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


#: Pieces of one length that a task ranks.
RANKED = 1 << 20


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY, ranked: int = RANKED) -> DataFrame:
    """``pieces`` with ``sequence_id`` and ``offset``; ``pieces`` must be settled.

    The histogram (at most ``capacity`` rows) is the only thing the driver sees.
    The most frequent length decides into how many parts lengths are dealt, so
    that about ``ranked`` pieces of a length are ranked together.
    """
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    parts = max(64, -(-max(histogram.values(), default=0) // ranked))
    rows = plan_bins(histogram, capacity)
    plan = spark.createDataFrame(rows, "length long, lo long, hi long, first long, each long, at long")
    part = pieces.withColumn("part", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(parts)).cast("int"))
    own = W.partitionBy("length", "part").orderBy("doc_id", "piece", "start", "ids_crc32")
    below = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    base = part.groupBy("length", "part").agg(F.count("*").alias("n")).select("length", "part", F.coalesce(F.sum("n").over(below), F.lit(0)).alias("base"))
    ranked = part.withColumn("r", F.row_number().over(own) - 1).join(base, ["length", "part"]).withColumn("rank", F.col("r") + F.col("base"))
    # a few thousand rows at most: every planned bin uses up a length
    placed = ranked.join(F.broadcast(plan), "length").where("rank >= lo and rank < hi")
    slot = F.col("rank") - F.col("lo")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("first") + F.floor(slot / F.col("each"))).cast("long").alias("sequence_id"), (F.col("at") + slot % F.col("each") * F.col("length")).cast("long").alias("offset"))


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY) -> DataFrame:
    """Pieces of all documents with the sequence and the place they are packed to."""
    return pack_pieces(settle(token_pieces(docs, vocabulary, capacity)), capacity)
