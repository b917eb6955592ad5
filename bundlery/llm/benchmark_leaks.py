"""Benchmark decontamination by size-partitioned MinHash containment search.

Test items are put into partitions by the size of their shingle set.  Within
one partition every item is sketched by its ``k`` smallest hashes (a bottom-k
MinHash), where ``k = floor((1 - t) * upper size) + 1``.  A document that
contains a share ``t`` of an item's shingles misses at most ``k - 1`` of them,
so it holds at least one sketched hash: the search loses nothing, however long
the document is.  Candidates are verified by exact containment of the item's
whole shingle set in the document's.

The items of one block are broadcast (``block_shingles`` bounds the block);
more items mean more blocks, each one pass over the documents, so nothing that
is broadcast grows with either table.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textbits import shingle_rows, slices, spare_name, text_view

#: Shingles of a broadcast block of items: 8 bytes each in three arrays.
BLOCK_SHINGLES = 1 << 20


class ItemIndex:
    """Sketches and whole shingle sets of one block of items."""

    def __init__(self, ids: list[int | None], sets: list[np.ndarray], share: float, short: list[int] = ()):
        self.ids, self.share = ids, share
        self.sizes = np.asarray([len(s) for s in sets], np.int64)
        # partitions double in size; the sketch length follows the upper bound
        upper = 1 << np.ceil(np.log2(np.maximum(self.sizes, 1))).astype(np.int64)
        keep = np.minimum(np.floor((1 - share) * upper + 1e-9).astype(np.int64) + 1, self.sizes)
        sketch = [s[:k] for s, k in zip(sets, keep)]
        self.keys = np.unique(np.concatenate(sketch)) if sketch else np.zeros(0, np.uint64)
        flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        owner = np.repeat(np.arange(len(sets)), self.sizes)
        order = np.argsort(flat, kind="stable")
        self.flat, self.owner = flat[order], owner[order]
        #: Numbers of words of the items that are shorter than a shingle.
        self.short = tuple(sorted(set(short)))
        # a first look by 16 bits of the hash spares most of the binary searches
        self.seen = np.zeros(1 << 16, bool)
        self.seen[(self.keys >> np.uint64(48)).astype(np.int64)] = True

    def hits(self, shingles: np.ndarray) -> list[tuple[int | None, int, int]]:
        """(item id, shared shingles, item shingles) of all contained items."""
        if not len(self.keys) or not len(shingles):
            return []
        near = shingles[self.seen[(shingles >> np.uint64(48)).astype(np.int64)]]
        if not len(near):
            return []
        at = np.minimum(np.searchsorted(self.keys, near), len(self.keys) - 1)
        if not (self.keys[at] == near).any():
            return []
        # verification: exact overlap with every item that shares a shingle
        here = np.isin(self.flat, shingles)
        shared = np.bincount(self.owner[here], minlength=len(self.ids))
        good = np.flatnonzero((self.sizes > 0) & (shared >= np.ceil(self.share * self.sizes - 1e-9)))
        return [(self.ids[i], int(shared[i]), int(self.sizes[i])) for i in good]


def _normal(col):
    """Lower case, everything but letters and digits as one space."""
    return F.lower(F.regexp_replace(F.coalesce(col, F.lit("")), r"[^\p{L}\p{N}]+", " "))


def _blocks(items: DataFrame, share: float, width: int, block_shingles: int):
    """Indexes of the items, one block after another; at least one, perhaps empty."""
    lines = items.select(F.col("item_id").cast("long").alias("item_id"), _normal(F.col("text")).alias("t"))
    ids, sets, short, total = [], [], [], 0
    for row in lines.toLocalIterator():
        s = next(shingle_rows(*text_view(pa.array([row["t"]])), width))
        if len(s):
            ids.append(row["item_id"])
            sets.append(s)
            total += len(s)
            words = len(row["t"].split())
            short += [words] if words < width else []
        if total >= block_shingles:
            yield ItemIndex(ids, sets, share, short)
            ids, sets, short, total = [], [], [], 0
    yield ItemIndex(ids, sets, share, short)


def find_leaks(docs: DataFrame, items: DataFrame, share: float = 0.8, width: int = 5, block_shingles: int = BLOCK_SHINGLES) -> DataFrame:
    """Pairs of a document and a test item whose shingles it contains.

    Returns ``doc_id, item_id, n_shared, n_item, containment`` with
    ``containment = n_shared / n_item >= share``, one row for each document row
    and item.  Texts are compared as lower-case runs of letters and digits.  An item of
    fewer than ``width`` words is one shingle of all its words, looked up among
    the documents' runs of that many words; items without words and null texts
    match nothing.  Repeated document rows give repeated results;
    items with the same id are separate, and ids may be null.  Extra columns are
    ignored.
    """
    spark = docs.sparkSession
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _normal(F.col("text")).alias("t"))
    schema = "doc_id long, item_id long, n_shared long, n_item long, containment double"

    found = None
    for index in _blocks(items, share, width, block_shingles):
        held = spark.sparkContext.broadcast(index)

        def search(batches, held=held):
            own = held.value
            for batch in slices(batches):
                ids = batch.column(0).to_pylist()
                rows = [(d, *h) for d, s in zip(ids, shingle_rows(*text_view(batch.column(1)), width, also=own.short)) for h in own.hits(s)]
                if rows:
                    d, i, n, m = map(list, zip(*rows))
                    yield pa.RecordBatch.from_arrays([pa.array(d, pa.int64()), pa.array(i, pa.int64()), pa.array(n, pa.int64()), pa.array(m, pa.int64()), pa.array([a / b for a, b in zip(n, m)], pa.float64())], ["doc_id", "item_id", "n_shared", "n_item", "containment"])

        part = source.mapInArrow(search, schema)
        found = part if found is None else found.unionAll(part)
    return found


def drop_leaks(docs: DataFrame, items: DataFrame, share: float = 0.8, width: int = 5, block_shingles: int = BLOCK_SHINGLES) -> DataFrame:
    """The documents that contain no test item, with their own columns.

    Rows are judged where they are read, one block of items after another, so
    nothing is joined or shuffled, and rows without an id are judged alike.
    """
    spark = docs.sparkSession
    extra = spare_name(docs.columns, "_normal")
    marked = docs.withColumn(extra, _normal(F.col("text").cast("string")))
    kept = marked
    for index in _blocks(items, share, width, block_shingles):
        held = spark.sparkContext.broadcast(index)

        def judge(batches, held=held):
            own = held.value
            for batch in slices(batches):
                text = batch.column(batch.schema.names.index(extra))
                yield batch.filter(pa.array([not own.hits(s) for s in shingle_rows(*text_view(text), width, also=own.short)], pa.bool_()))

        kept = kept.mapInArrow(judge, marked.schema)
    return kept.select(docs.columns)
