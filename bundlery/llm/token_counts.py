"""Token counts by heap-and-linked-list byte-pair merging.

A text is cut into pre-tokens; each pre-token starts as a doubly linked list of
byte symbols, and a heap holds its adjacent pairs by merge rank.  Popping the
lowest pair unlinks one node, until no pair has a rank; the number of tokens is
the number of symbols less the number of merges, so no identifier is built.
The work for one pre-token is O(n log n) whatever its length, and the result
for a short pre-token is remembered within bounds.
"""

from __future__ import annotations

import heapq
import json

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textbits import slices, text_view

#: Pre-token pattern of the byte-level scheme (fixed value).
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Pre-tokens remembered by one worker, and the longest of them in characters.
REMEMBERED, LONGEST = 400_000, 48


def _byte_symbols() -> list[str]:
    """The printable character that stands for each byte in the vocabulary file."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


class PairMerger(dict):
    """Pre-token -> number of tokens; missing entries are merged on demand."""

    def __init__(self, file_text: str):
        super().__init__()
        spec = json.loads(file_text)
        model = spec["model"]
        pre = spec["pre_tokenizer"] or {}
        odd = [x["content"] for x in spec["added_tokens"] if x["lstrip"] or x["rstrip"] or x["single_word"]]
        if model["type"] != "BPE" or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or spec["normalizer"] or model.get("ignore_merges") or odd:
            raise ValueError("only plain byte-level pair vocabularies are supported")
        vocab = model["vocab"]
        self.start = [vocab[c] for c in _byte_symbols()]
        self.rank: dict[tuple[int, int], tuple[int, int]] = {}
        for r, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.rank.setdefault((vocab[a], vocab[b]), (r, vocab[a + b]))
        self.cut = regex.compile(PRE_TOKEN)
        special = sorted((x["content"] for x in spec["added_tokens"]), key=len, reverse=True)
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.marks = special

    def merged(self, piece: bytes) -> int:
        """Tokens of one pre-token."""
        rank, symbol = self.rank, [self.start[b] for b in piece]
        n = len(symbol)
        if n < 2:
            return n
        right, left = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            if (hit := rank.get((symbol[i], symbol[i + 1]))) is not None:
                heap.append((hit[0], i, symbol[i], symbol[i + 1]))
        heapq.heapify(heap)
        merges = 0
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = right[i]
            if symbol[i] != a or j >= n or symbol[j] != b:
                continue  # one of the two was merged meanwhile
            symbol[i] = made = rank[a, b][1]
            symbol[j] = -1
            k = right[i] = right[j]
            merges += 1
            if k < n:
                left[k] = i
                if (hit := rank.get((made, symbol[k]))) is not None:
                    heapq.heappush(heap, (hit[0], i, made, symbol[k]))
            h = left[i]
            if h >= 0 and (hit := rank.get((symbol[h], made))) is not None:
                heapq.heappush(heap, (hit[0], h, symbol[h], made))
        return n - merges

    def __missing__(self, piece: str) -> int:
        count = self.merged(piece.encode())
        if len(piece) <= LONGEST:
            if len(self) >= REMEMBERED:
                self.clear()
            self[piece] = count
        return count

    def count(self, text: str) -> int:
        """Tokens of a text; special strings inside it count one each."""
        if not text:
            return 0
        look = self.__getitem__
        if self.special is not None and any(m in text for m in self.marks):
            parts = self.special.split(text)
            return len(parts) - 1 + sum(sum(map(look, self.cut.findall(p))) for p in parts)
        return sum(map(look, self.cut.findall(text)))


_mergers: dict[int, PairMerger] = {}


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 1024) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` of each row's whole text.

    ``vocabulary`` is the path of a byte-level pair vocabulary; the driver reads
    it and broadcasts its text, whose size the vocabulary bounds.  Null and empty
    texts have no bytes and no tokens.  Repeated rows give repeated results.
    """
    with open(vocabulary, encoding="utf-8") as f:
        held = docs.sparkSession.sparkContext.broadcast(f.read())
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def run(batches):
        own = hash(held.value)
        if own not in _mergers:
            _mergers.clear()
            _mergers[own] = PairMerger(held.value)
        count = _mergers[own].count
        for batch in slices(batches):
            _, off = text_view(batch.column(1))
            tokens = [count(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(off[1:] - off[:-1]), pa.array(tokens, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    return source.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
