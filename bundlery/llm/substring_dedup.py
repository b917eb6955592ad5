"""Removal of passages that occur in an earlier document.

Relative Lempel-Ziv parsing over a distributed reference.  The reference (all
windows of ``width`` words of all documents) is cut into blocks by a
content-defined anchor: the anchor of a window is its smallest hash of
``gram`` consecutive words, so equal windows have the same anchor and always
meet in the same block, while neighbouring windows mostly share theirs and
travel together as one run.  A block indexes each window to the documents and
places it starts at.

1.  A document is factored greedily against every block.  A factor starts at a
    window with an earlier document as its source and remembers the place there;
    it grows word by word as long as the block has the next window at the next
    place of the same source, and only then another source is looked for.
2.  Where a run ends at a block's border, the next block answers for the next
    window.  Factors of one document that continue each other in the same source
    are joined over these borders, so a passage is one factor however many blocks
    its windows are in.
3.  The words of each factor, first to last, are compared with the words at its
    source by a 128-bit digest of the text itself, since windows met by a 64-bit
    hash only.  A factor that differs is not a copy and removes nothing.

Words outside all factors are kept.  A map task sends each distinct window once,
for the smallest document of the task; later copies inside the task are factored
on the spot.  A passage that a third of all documents share costs one entry per
task, and one digest.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lineage import PACKED, bucket_count, packed_batches, settle
from .textbits import mix64, row_chunks, run_hashes, slices, text_view, word_hashes, word_table

WIDTH, GRAM = 50, 16
#: Words that a map task gathers before it settles and sends them.
TASK_WORDS = 800_000
_U = np.uint64
_RUN = np.dtype([("doc", "<i8"), ("key", "<i8"), ("start", "<u4"), ("n", "<u4")])
_FACTOR = np.dtype([("doc", "<i8"), ("key", "<i8"), ("start", "<i8"), ("n", "<i8"), ("sdoc", "<i8"), ("skey", "<i8"), ("sstart", "<i8")])


def _anchors(grams: np.ndarray, windows: int, span: int) -> np.ndarray:
    """Smallest gram hash of each window, by doubling minima."""
    low, size = grams, 1
    while size * 2 <= span:
        low = np.minimum(low[:-size], low[size:])
        size *= 2
    if size < span:
        low = np.minimum(low[: windows], low[span - size : span - size + windows])
    return low[:windows]


def _windows(data: np.ndarray, off: np.ndarray, width: int, gram: int):
    """Hash, anchor, row and start of each window of a batch."""
    for lo, hi in row_chunks(off):
        base = off[lo]
        starts, ends, first = word_table(data[base : off[hi]], off[lo : hi + 1] - base)
        words = word_hashes(data[base : off[hi]], starts, ends, False)
        if len(words) < width:
            continue
        whole = run_hashes(words, width)
        anchor = _anchors(run_hashes(words, gram), len(whole), width - gram + 1)
        counts = np.maximum(0, first[1:] - first[:-1] - width + 1)
        row = np.repeat(np.arange(hi - lo), counts)
        start = np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)
        at = first[row] + start
        yield whole[at], anchor[at], lo + row, start


def _runs(doc: np.ndarray, key: np.ndarray, start: np.ndarray, mark: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Heads and lengths of runs of consecutive starts in one document with one mark."""
    new = (doc[1:] != doc[:-1]) | (key[1:] != key[:-1]) | (start[1:] != start[:-1] + 1) | (mark[1:] != mark[:-1])
    heads = np.flatnonzero(np.concatenate([[True], new]))
    return heads, np.diff(np.append(heads, len(doc)))


def _first_entries(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """For each window, the position of an equal one of the smallest document."""
    order = np.lexsort((doc, h))
    same = h[order]
    head = np.concatenate([[True], same[1:] != same[:-1]])
    first = order[np.flatnonzero(head)]
    out = np.empty(len(h), np.int64)
    out[order] = first[np.cumsum(head) - 1]
    return out


def _entry(h, doc, key, start):
    """A hash of one index entry: a window at its place."""
    with np.errstate(over="ignore"):
        place = doc.view(_U) * _U(0x9E3779B97F4A7C15) + key.view(_U) * _U(0xC2B2AE3D27D4EB4F) + start.astype(np.int64).view(_U)
        return mix64(h ^ mix64(place))


def _factors(h, doc, key, start, first, later, width: int) -> np.ndarray:
    """Greedy factors over the windows that have an earlier source.

    ``first`` is the entry that a new factor takes as its source.  A factor goes
    on where the index has the next window at the next place of that source.
    """
    at = np.flatnonzero(later)
    at = at[np.lexsort((start[at], key[at], doc[at]))]
    d, k, s, src = doc[at], key[at], start[at].astype(np.int64), first[at]
    sd, sk, ss = doc[src], key[src], start[src].astype(np.int64)
    joined = (d[1:] == d[:-1]) & (k[1:] == k[:-1]) & (s[1:] == s[:-1] + 1)
    along = joined & (sd[1:] == sd[:-1]) & (sk[1:] == sk[:-1]) & (ss[1:] == ss[:-1] + 1)
    heads = np.flatnonzero(np.concatenate([[True], ~along]))
    ends = np.append(heads[1:], len(at))
    if (joined & ~along).any():
        # a source may go on where another, smaller one begins: keep to it
        index = np.sort(_entry(h, doc, key, start))
        new_heads, new_ends, i = [], [], 0
        lo, end = int(heads[0]), int(ends[0])
        while True:
            i += 1
            if i < len(heads) and joined[heads[i] - 1]:
                a, b = max(int(heads[i]), end), int(ends[i])
                while a < b:
                    step = np.arange(a, b)
                    wanted = _entry(h[at[a:b]], np.full(b - a, sd[lo]), np.full(b - a, sk[lo]), ss[lo] + (step - lo))
                    there = index[np.minimum(np.searchsorted(index, wanted), len(index) - 1)] == wanted
                    grown = int(there.argmin()) if not there.all() else b - a
                    end = a + grown
                    if grown == b - a:
                        break
                    new_heads.append(lo)
                    new_ends.append(end)
                    # what is left of the run is a factor of its own source
                    lo, end = end, b
                    break
                continue
            new_heads.append(lo)
            new_ends.append(end)
            if i == len(heads):
                break
            lo, end = int(heads[i]), int(ends[i])
        heads, ends = np.asarray(new_heads), np.asarray(new_ends)
    out = np.empty(len(heads), _FACTOR)
    out["doc"], out["key"], out["start"], out["n"] = d[heads], k[heads], s[heads], ends - heads + width - 1
    out["sdoc"], out["skey"], out["sstart"] = sd[heads], sk[heads], ss[heads]
    return out


def _block_batches(bucket, h, doc, key, start, buckets):
    """One binary value per block: its runs of neighbouring windows, then their hashes."""
    order = np.argsort(bucket, kind="stable")
    bucket, h, doc, key, start = bucket[order], h[order], doc[order], key[order], start[order]
    edge = np.searchsorted(bucket, np.arange(buckets + 1))
    heads, n = _runs(doc, key, start, bucket)
    runs = np.empty(len(heads), _RUN)
    runs["doc"], runs["key"], runs["start"], runs["n"] = doc[heads], key[heads], start[heads], n
    of = np.searchsorted(heads, edge)
    full = np.flatnonzero(edge[1:] > edge[:-1])
    for part in np.array_split(full, 1 + (len(h) * 10 >> 24)):
        if len(part):
            bodies = [np.int64(of[b + 1] - of[b]).tobytes() + runs[of[b] : of[b + 1]].tobytes() + h[edge[b] : edge[b + 1]].tobytes() for b in part]
            yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), pa.array(bodies, pa.binary())], ["bucket", "body"])


def _open_block(body) -> tuple[np.ndarray, ...]:
    """Hash, document, text and start of the windows of one binary value."""
    n = int(np.frombuffer(body, "<i8", 1)[0])
    runs = np.frombuffer(body, _RUN, n, 8)
    h = np.frombuffer(body, "<u8", -1, 8 + n * _RUN.itemsize)
    count = runs["n"].astype(np.int64)
    step = np.arange(len(h)) - np.repeat(np.cumsum(count) - count, count)
    return h, np.repeat(runs["doc"], count), np.repeat(runs["key"], count), np.repeat(runs["start"].astype(np.int64), count) + step


FACTORS = "doc_id long, text_key long, start long, length long, source_id long, source_key long, source_start long"
_NAMES = [c.split()[0] for c in FACTORS.split(", ")]


def _factor_batch(x: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x[f])) for f in _FACTOR.names], _NAMES)


def _keyed(docs: DataFrame) -> DataFrame:
    """``doc_id, text_key, text``; the key tells texts under one doc_id apart."""
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), text.alias("text"))


def _fragments(docs: DataFrame, width: int, gram: int, task_words: int) -> DataFrame:
    """Factors as the blocks find them, cut where a document goes on in another block."""
    buckets = bucket_count(docs.sparkSession)

    def flush(held, ids, keys):
        h, anchor, row, start = (np.concatenate(x) for x in zip(*held))
        doc, key = np.asarray(ids, np.int64)[row], np.asarray(keys, np.int64)[row]
        first = _first_entries(h, doc)
        later = doc > doc[first]
        if later.any():
            # settled here; negative buckets carry finished factors
            done = _factors(h, doc, key, start, first, later, width)
            for batch in packed_batches((mix64(done["doc"].astype(np.int64).view(_U)) % _U(buckets)).astype(np.int64), done, buckets):
                yield pa.RecordBatch.from_arrays([pa.array(-1 - batch.column(0).to_numpy()), batch.column(1)], ["bucket", "body"])
        keep = ~later
        bucket = (mix64(anchor[keep] ^ _U(0xA5A5)) % _U(buckets)).astype(np.int64)
        yield from _block_batches(bucket, h[keep], doc[keep], key[keep], start[keep], buckets)

    def send(batches):
        held, ids, keys, words = [], [], [], 0
        for batch in slices(batches):
            own, text_keys = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for h, anchor, row, start in _windows(*text_view(batch.column(2)), width, gram):
                # rows are numbered anew among those that are held
                seen, row = np.unique(row, return_inverse=True)
                held.append((h, anchor, (row + len(ids)).astype(np.int32), start.astype(np.int32)))
                ids += [own[i] for i in seen]
                keys += [text_keys[i] for i in seen]
                words += len(h)
                if words >= task_words:
                    yield from flush(held, ids, keys)
                    held, ids, keys, words = [], [], [], 0
        if words:
            yield from flush(held, ids, keys)

    def parse(batches):
        def block(parts):
            h, doc, key, start = (np.concatenate(x) for x in zip(*parts))
            first = _first_entries(h, doc)
            later = doc > doc[first]
            if later.any():
                yield _factor_batch(_factors(h, doc, key, start, first, later, width))

        at, parts = None, []
        for batch in batches:
            for b, body in zip(batch.column(0).to_pylist(), batch.column(1)):
                if b < 0:
                    yield _factor_batch(np.frombuffer(body.as_buffer(), _FACTOR))
                    continue
                if b != at and parts:
                    yield from block(parts)
                    parts = []
                at = b
                parts.append(_open_block(body.as_buffer()))
        if parts:
            yield from block(parts)

    sent = _keyed(docs).where("doc_id is not null").mapInArrow(send, PACKED)
    return sent.repartition(buckets // 4, "bucket").sortWithinPartitions("bucket").mapInArrow(parse, FACTORS)


def join_fragments(rows: list[tuple[int, int, int, int, int]]) -> list[tuple[int, int, int, int, int]]:
    """``start, length, source_id, source_key, source_start`` with those that continue each other joined."""
    out: dict[tuple, list[int]] = {}
    done = []
    for start, n, sdoc, skey, sstart in sorted(set(rows)):
        line = (sdoc, skey, sstart - start)
        held = out.get(line)
        if held and start <= held[0] + held[1]:
            held[1] = max(held[1], start + n - held[0])
            continue
        if held:
            done.append((line, *held))
        out[line] = [start, n]
    done += [(line, *held) for line, held in out.items()]
    return sorted((start, n, sdoc, skey, start + shift) for (sdoc, skey, shift), start, n in done)


def duplicate_factors(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, task_words: int = TASK_WORDS) -> DataFrame:
    """Factors ``doc_id, text_key, start, length, source_id, source_key, source_start`` (in words).

    A factor is a run of words that also stands at ``source_start`` of an earlier
    document.  The union of a document's factors is exactly the words under
    windows that also start in a document with a smaller id.  Factors of one
    document may touch or overlap; none is shorter than ``width``.  Null texts and
    rows without an id have no factors and are no source.  Repeated rows of one
    doc_id count as one source and never remove each other.
    """
    item = F.struct("start", "length", "source_id", "source_key", "source_start")
    per = _fragments(docs, width, gram, task_words).groupBy("doc_id", "text_key").agg(F.collect_list(item).alias("parts"))

    def join(batches):
        for batch in batches:
            rows = []
            for doc, key, parts in zip(*(c.to_pylist() for c in batch.columns)):
                rows += [(doc, key, *x) for x in join_fragments([tuple(p.values()) for p in parts])]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], _NAMES)

    return per.mapInArrow(join, FACTORS)


def _digest(words: list[bytes], start: int, n: int) -> bytes:
    return xxhash.xxh3_128_digest(b" ".join(words[start : start + n]))


def _source_digests(source: DataFrame, factors: DataFrame) -> DataFrame:
    """A digest of the words of each distinct place that factors were taken from."""
    places = factors.select(F.col("source_id").alias("id"), F.col("source_key").alias("key"), F.col("source_start").alias("at"), F.col("length").alias("n")).distinct()
    per = places.groupBy("id", "key").agg(F.collect_set(F.struct("at", "n")).alias("places"))

    def digest(batches):
        for batch in slices(batches):
            rows = []
            for doc, key, text, places in zip(*(c.to_pylist() for c in batch.columns)):
                if places:
                    words = text.encode().split()
                    rows += [(doc, key, p["at"], p["n"], _digest(words, p["at"], p["n"])) for p in places]
            if rows:
                d, k, a, n, x = zip(*rows)
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in (d, k, a, n)), pa.array(x, pa.binary())], ["source_id", "source_key", "source_start", "length", "digest"])

    # a left join like the one that strips, so that the texts are dealt out once for both
    own = (F.col("doc_id") == F.col("id")) & (F.col("text_key") == F.col("key"))
    found = source.join(per.hint("shuffle_hash"), own, "left").select("doc_id", "text_key", "text", "places")
    return found.mapInArrow(digest, "source_id long, source_key long, source_start long, length long, digest binary").dropDuplicates(["source_id", "source_key", "source_start", "length"])


def strip_factors(docs: DataFrame, factors: DataFrame) -> DataFrame:
    """``doc_id, n_words, n_removed, kept`` for each row of ``docs``.

    ``kept`` is the words outside all factors, joined by one space.  A factor whose
    words differ from those at its source removes nothing.  ``factors`` must be
    settled.
    """
    source = _keyed(docs)
    known = factors.join(_source_digests(source, factors), ["source_id", "source_key", "source_start", "length"])
    per = known.groupBy(F.col("doc_id").alias("id"), F.col("text_key").alias("key")).agg(F.collect_list(F.struct("start", "length", "digest")).alias("factors"))

    def strip(batches):
        for batch in slices(batches):
            n_words, n_gone, kept = [], [], []
            for text, factors in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                words = (text or "").encode().split()
                total = len(words)
                if factors:
                    out, at = [], 0
                    for s, n in sorted((x["start"], x["length"]) for x in factors if _digest(words, x["start"], x["length"]) == x["digest"]):
                        out += words[at:s]
                        at = max(at, s + n)
                    words = out + words[at:]
                n_words.append(total)
                n_gone.append(total - len(words))
                kept.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_words, pa.int64()), pa.array(n_gone, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())], ["doc_id", "n_words", "n_removed", "kept"])

    own = (F.col("doc_id") == F.col("id")) & (F.col("text_key") == F.col("key"))
    return source.join(per.hint("shuffle_hash"), own, "left").select("doc_id", "text", "factors").mapInArrow(strip, "doc_id long, n_words long, n_removed long, kept string")


def dedup_substrings(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """Each document without the passages that an earlier one has.

    Windows are judged on the input texts, not on what other removals leave.
    """
    return strip_factors(docs, settle(duplicate_factors(docs, width)))
