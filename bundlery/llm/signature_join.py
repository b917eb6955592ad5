"""Jaccard self-join of word-shingle sets by signature trees.

1.  Documents with the same shingle set become one class (a grouped minimum, so
    a set that a third of all rows share is one row per map task).
2.  Classes are brought together by MinHash bands.  ``bands`` and ``rows`` are
    such that a pair at the threshold is missed by every band with probability
    below 1e-7; sharing a band only decides who meets, never who links.
    Connected classes form a neighbourhood.
3.  In each neighbourhood a signature tree is built: a leaf holds the exact
    bitmap of a class over the neighbourhood's tokens, an inner node the OR of
    its children with their size range.  A dual traversal from the root pair
    downward drops node pairs whose sizes cannot reach the threshold, whose
    bitmaps cannot overlap enough, or which already lie in one component;
    what is left at the leaves is counted exactly on the bitmaps.
4.  Neighbourhoods over ``block`` classes are split into blocks.  After a round
    inside the blocks and one among the blocks' main components, only classes
    outside the neighbourhood's main component visit the other blocks: a pair
    inside one component needs no check, every other pair gets one.

Components of the links come from ``connected_components``.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import connected_components, contract
from .lineage import PACKED, bucket_count, bucket_stream, packed_batches, settle
from .textbits import mix64, shingle_rows, slices, spare_name, text_view

BLOCK = 1024
_FAN = 16
_BITS = 1 << 17
_BAND = np.dtype([("sig", "<u8"), ("key", "<i8")])
_U = np.uint64


def band_plan(threshold: float, miss: float = 1e-7, most: int = 340) -> tuple[int, int]:
    """Rows and bands: the most selective plan within ``most`` hashes and ``miss``."""
    best = (1, math.ceil(math.log(miss) / math.log(1 - min(threshold, 1 - 1e-12))))
    for rows in range(2, 13):
        bands = math.ceil(math.log(miss) / math.log(1 - threshold**rows)) if threshold < 1 else 1
        if rows * bands <= most:
            best = (rows, bands)
    return best


def set_key(shingles: np.ndarray) -> int:
    """A signed 64-bit key of a whole set."""
    with np.errstate(over="ignore"):
        return int(mix64(np.asarray([np.add.reduce(mix64(shingles ^ _U(0x5BD1E995)))]) + _U(len(shingles))).view(np.int64)[0])


class Bands:
    """MinHash band signatures of one set; parameters are fixed by a seed."""

    def __init__(self, rows: int, bands: int):
        rng = np.random.default_rng(7)
        self.rows, self.bands = rows, bands
        self.mul = (rng.integers(0, 1 << 31, rows * bands, dtype=np.uint64) * _U(2) + _U(1)).astype(np.uint32)
        self.add = rng.integers(0, 1 << 32, rows * bands, dtype=np.uint64).astype(np.uint32)
        self.keys = rng.integers(1, 1 << 63, rows, dtype=np.uint64) * _U(2) + _U(1)
        self.tag = mix64(np.arange(1, bands + 1, dtype=np.uint64))

    def __call__(self, shingles: np.ndarray) -> np.ndarray:
        x = (shingles >> _U(32)).astype(np.uint32)
        low = np.full(len(self.mul), 0xFFFFFFFF, np.uint32)
        with np.errstate(over="ignore"):
            for at in range(0, len(x), 4096):
                part = x[at : at + 4096]
                # multiply, then fold the high half down: the low bits alone are no fair order
                y = self.mul[:, None] * (part ^ (part >> np.uint32(15)))[None, :]
                y ^= self.add[:, None]
                y *= np.uint32(0x9E3779B1)
                np.minimum(low, y.min(axis=1), out=low)
            return mix64((low.reshape(self.bands, self.rows).astype(np.uint64) * self.keys).sum(axis=1) ^ self.tag)


class _Forest:
    """Union-find over the members of one block."""

    def __init__(self, groups: np.ndarray):
        first: dict[int, int] = {}
        self.up = np.asarray([first.setdefault(int(g), i) for i, g in enumerate(groups)], np.int64)

    def roots(self) -> np.ndarray:
        while True:
            up = self.up[self.up]
            if (up == self.up).all():
                return up
            self.up = up

    def join(self, i: np.ndarray, j: np.ndarray) -> None:
        for a, b in zip(i.tolist(), j.tolist()):
            while self.up[a] != a:
                a = int(self.up[a])
            while self.up[b] != b:
                b = int(self.up[b])
            self.up[max(a, b)] = min(a, b)


def _count(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x).sum(axis=-1, dtype=np.int64)


def tree_links(sets: list[np.ndarray], groups: np.ndarray, visitor: np.ndarray, num: int, den: int) -> list[tuple[int, int]]:
    """Links that join the components of a block, found by a signature tree.

    ``groups`` are components known before; where any ``visitor`` is set, only
    pairs of a visitor and another member are looked at.  A pair links when
    ``den * |x & y| >= num * |x | y|``.  Links inside one component are left
    out once it is connected.
    """
    n = len(sets)
    if n < 2:
        return []
    size = np.asarray([len(s) for s in sets], np.int64)
    flat = np.concatenate(sets)
    token, inverse, freq = np.unique(flat, return_inverse=True, return_counts=True)
    shared = freq > 1
    slot = np.cumsum(shared) - 1
    width = int(shared.sum())
    if not width:
        return []
    exact = width <= _BITS
    bits = min(width, _BITS)
    owner = np.repeat(np.arange(n), size)
    live = shared[inverse]
    place = slot[inverse[live]] % bits
    # neighbours in the tree should be alike: order by size class, then by smallest shared token
    low = np.full(n, len(token))
    np.minimum.at(low, owner[live], inverse[live])
    order = np.lexsort((size, low, np.floor(np.log2(np.maximum(size, 1)) * 2)))
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    dense = np.zeros((n, (bits + 63) // 64 * 8), np.uint8)
    cell = (rank[owner[live]] * dense.shape[1] + place // 8, 1 << (place % 8))
    np.bitwise_or.at(dense.reshape(-1), cell[0], cell[1].astype(np.uint8))
    leaf = dense.view(np.uint64)
    size, groups, visitor = size[order], groups[order], visitor[order]
    forest = _Forest(groups)
    only_visits = bool(visitor.any())
    levels = [(leaf, size, size)]
    while len(levels[-1][0]) > _FAN:
        bitmap, lo, hi = levels[-1]
        cut = np.arange(0, len(bitmap), _FAN)
        levels.append((np.bitwise_or.reduceat(bitmap, cut), np.minimum.reduceat(lo, cut), np.maximum.reduceat(hi, cut)))
    # folded bitmaps count a shared bit once for several tokens: allow for the difference
    slack = 0 if exact else int((size - _count(leaf)).max())
    found: list[tuple[int, int]] = []

    def reach(overlap, lo_sum):
        # den*o >= num*(a+b-o)  <=>  (num+den)*o >= num*(a+b)
        return (num + den) * overlap >= num * lo_sum

    def survivors(level, i, j):
        bitmap, lo, hi = levels[level]
        ok = (den * hi[i] >= num * lo[j]) & (den * hi[j] >= num * lo[i])
        i, j = i[ok], j[ok]
        keep = np.empty(len(i), bool)
        step = max(1, (1 << 20) // bitmap.shape[1])
        for at in range(0, len(i), step):
            a, b = i[at : at + step], j[at : at + step]
            o = np.minimum(_count(bitmap[a] & bitmap[b]) + slack, np.minimum(hi[a], hi[b]))
            keep[at : at + step] = reach(o, lo[a] + lo[b]) | ((a == b) & (level > 0))
        return i[keep], j[keep]

    def verify(i, j):
        if exact:
            step = max(1, (1 << 20) // leaf.shape[1])
            overlap = np.concatenate([_count(leaf[i[at : at + step]] & leaf[j[at : at + step]]) for at in range(0, len(i), step)])
        else:
            overlap = np.asarray([len(np.intersect1d(sets[order[a]], sets[order[b]], assume_unique=True)) for a, b in zip(i, j)], np.int64)
        return reach(overlap, size[i] + size[j])

    def leaves(i, j):
        # one open pair of each member a pass: later passes skip what has become
        # connected; when a pass links nothing, all that is left is counted at once
        alone = False
        while len(i):
            root = forest.roots()
            open_ = root[i] != root[j]
            i, j = i[open_], j[open_]
            if not len(i):
                break
            take = np.arange(len(i)) if alone else np.unique(i, return_index=True)[1]
            good = verify(i[take], j[take])
            forest.join(i[take][good], j[take][good])
            found.extend(zip(order[i[take][good]].tolist(), order[j[take][good]].tolist()))
            rest = np.ones(len(i), bool)
            rest[take] = False
            i, j, alone = i[rest], j[rest], not good.any()

    def walk(level, i, j):
        if level == 0:
            keep = i < j
            if only_visits:
                keep &= visitor[i] | visitor[j]
            i, j = i[keep], j[keep]
            root = forest.roots()
            keep = root[i] != root[j]
            i, j = survivors(0, i[keep], j[keep])
            leaves(i, j)
            return
        i, j = survivors(level, i, j)
        below = len(levels[level - 1][0])
        step = np.arange(_FAN)
        # a bounded number of node pairs is opened at a time, children of equal nodes first
        first = np.argsort(i != j, kind="stable")
        for at in range(0, len(i), 512):
            a, b = i[first[at : at + 512]], j[first[at : at + 512]]
            x = (a[:, None, None] * _FAN + step[None, :, None] + 0 * step[None, None, :]).ravel()
            y = (b[:, None, None] * _FAN + step[None, None, :] + 0 * step[None, :, None]).ravel()
            ok = (x < below) & (y < below) & (x <= y)
            walk(level - 1, x[ok], y[ok])

    top = len(levels) - 1
    k = np.arange(len(levels[top][0]))
    i, j = np.meshgrid(k, k, indexing="ij")
    ok = i <= j
    walk(top, i[ok], j[ok])
    return found


def _round_tasks(spark: SparkSession) -> int:
    return 2 * max(12, int(spark.conf.get("spark.sql.shuffle.partitions")))


def _tree_round(members: DataFrame, num: int, den: int) -> DataFrame:
    """Links ``a, b`` inside each ``room`` of ``room, key, comp, visitor, body``."""

    def join(batches):
        def room(rows):
            found = tree_links([np.frombuffer(r[4], "<u8") for r in rows], np.asarray([r[2] for r in rows], np.int64), np.asarray([r[3] for r in rows], bool), num, den)
            if found:
                yield pa.RecordBatch.from_arrays([pa.array([rows[i][1] for i, _ in found], pa.int64()), pa.array([rows[j][1] for _, j in found], pa.int64())], ["a", "b"])

        at, rows = None, []
        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in range(4)]
            for r, key, comp, visit, body in zip(*cols, batch.column(4)):
                if r != at and rows:
                    yield from room(rows)
                    rows = []
                at = r
                rows.append((r, key, comp, visit, body.as_py()))
        if rows:
            yield from room(rows)

    return members.select("room", "key", "comp", "visitor", "body").repartition(_round_tasks(members.sparkSession), "room").sortWithinPartitions("room").mapInArrow(join, "a long, b long")


def shingle_classes(docs: DataFrame, width: int) -> DataFrame:
    """``doc_id, n_shingles, key``: the size and the key of each document's set."""

    def measure(batches):
        for batch in slices(batches):
            sizes, keys = [], []
            for s in shingle_rows(*text_view(batch.column(1)), width):
                sizes.append(len(s))
                keys.append(set_key(s) if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(keys, pa.int64())], ["doc_id", "n_shingles", "key"])

    return docs.mapInArrow(measure, "doc_id long, n_shingles long, key long")


def _band_edges(docs: DataFrame, width: int, threshold: float) -> DataFrame:
    """Edges ``a, b`` from each class towards the smallest class of its bands, contracted in each task."""
    rows, bands = band_plan(threshold)
    buckets = bucket_count(docs.sparkSession)

    def send(batches):
        make, seen = Bands(rows, bands), set()
        for batch in slices(batches):
            out, keys = [], []
            for s in shingle_rows(*text_view(batch.column(1)), width):
                if not len(s):
                    continue
                key = set_key(s)
                if key in seen:  # copies inside the task are sent once
                    continue
                if len(seen) < 200_000:
                    seen.add(key)
                out.append(make(s))
                keys.append(key)
            if out:
                record = np.empty(len(keys) * bands, _BAND)
                record["sig"] = np.concatenate(out)
                record["key"] = np.repeat(np.asarray(keys, np.int64), bands)
                yield from packed_batches((record["sig"] % _U(buckets)).astype(np.int64), record, buckets)

    def meet(batches):
        for _, x in bucket_stream(batches, _BAND):
            x = x[np.lexsort((x["key"], x["sig"]))]
            head = np.flatnonzero(np.concatenate([[True], x["sig"][1:] != x["sig"][:-1]]))
            low = np.repeat(x["key"][head], np.diff(np.append(head, len(x))))
            pairs = np.column_stack([x["key"], low])[x["key"] != low]
            if len(pairs):
                pairs = np.unique(pairs, axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["a", "b"])

    def stars(batches):
        # in the same worker: a second one would double the memory of a task
        for batch in contract(meet(batches)):
            yield batch.rename_columns(["a", "b"])

    sent = docs.mapInArrow(send, PACKED)
    return sent.repartition(buckets // 4, "bucket").sortWithinPartitions("bucket").mapInArrow(stars, "a long, b long")


def _class_sets(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """``key, hood, body``: the shingle sets of the classes that have neighbours."""

    def build(batches):
        for batch in slices(batches):
            sets = [(i, s.tobytes()) for i, s in enumerate(shingle_rows(*text_view(batch.column(2)), width)) if len(s) and set_key(s) == batch.column(0)[i].as_py()]
            at = pa.array([i for i, _ in sets], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array([b for _, b in sets], pa.binary())], ["key", "hood", "body"])

    return docs.join(wanted.hint("shuffle_hash"), "doc_id").select("key", "hood", "text").mapInArrow(build, "key long, hood long, body binary")


def jaccard_components(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100, block: int = BLOCK) -> DataFrame:
    """``doc_id, n_shingles, component_id`` of each row of ``docs``.

    Two documents link when ``den * |x & y| >= num * |x | y|`` over their
    ``width``-word shingles.  ``component_id`` is the smallest doc_id reachable.
    Null, empty and blank texts have no shingles and stay alone.  Repeated rows
    give repeated results; documents that share a doc_id are kept apart by their
    texts and share only the id.
    """
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sizes = settle(shingle_classes(source, width))
    classes = sizes.where("key is not null").groupBy("key").agg(F.min("doc_id").alias("doc_id"))
    hoods = settle(connected_components(_band_edges(source, width, num / den), contracted=True).select(F.col("node").alias("key"), F.col("component").alias("hood")))
    wanted = classes.join(hoods, "key").select("doc_id", "key", "hood")
    members = settle(_class_sets(source, wanted, width))
    counts = hoods.groupBy("hood").agg(F.count("*").alias("n")).where(F.col("n") > block).withColumn("blocks", F.ceil(F.col("n") / block).cast("int"))
    wide = settle(counts)
    placed = members.join(wide.select("hood", "blocks"), "hood", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))).withColumn("part", F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int"))
    room = F.struct("hood", "part")
    links = settle(_tree_round(placed.select(F.xxhash64("hood", "part").alias("room"), "key", F.col("key").alias("comp"), F.lit(False).alias("visitor"), "body"), num, den))
    if not wide.isEmpty():
        links = _across_blocks(placed.where("blocks > 1"), links, num, den)
    comps = connected_components(_few(links)).select(F.col("node").alias("key"), F.col("component").alias("comp"))
    named = classes.join(comps, "key", "left").withColumn("comp", F.coalesce("comp", "key"))
    low = named.groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    final = named.join(low, "comp").select("key", "component_id")
    return sizes.join(final, "key", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def _few(links: DataFrame) -> DataFrame:
    """Settled links in an eighth of the rounds' tasks: they are far fewer bytes than the sets, and each round would add its tasks."""
    return links.coalesce(max(1, _round_tasks(links.sparkSession) // 8))


def _across_blocks(placed: DataFrame, links: DataFrame, num: int, den: int) -> DataFrame:
    """Links between the blocks of wide neighbourhoods, added to ``links``."""

    def labelled(links):
        comps = connected_components(_few(links)).select(F.col("node").alias("key"), F.col("component").alias("comp"))
        return settle(placed.select("key", "hood", "part", "blocks").join(comps, "key", "left").withColumn("comp", F.coalesce("comp", "key")))

    now = labelled(links)
    # the main component of each block sends one class to a room of its neighbourhood
    parts = now.groupBy("hood", "part", "comp").agg(F.count("*").alias("n"), F.min("key").alias("key"))
    heads = parts.groupBy("hood", "part").agg(F.max_by("key", "n").alias("key"), F.max_by("comp", "n").alias("comp"))
    bodies = placed.select("key", "body")
    among = heads.join(bodies, "key").select(F.xxhash64("hood", F.lit(-1)).alias("room"), "key", "comp", F.lit(False).alias("visitor"), "body")
    links = settle(_few(links).unionAll(_tree_round(among, num, den)))
    # whatever lies outside the main component visits all blocks
    now = labelled(links)
    most = now.groupBy("hood", "comp").agg(F.count("*").alias("n")).groupBy("hood").agg(F.max_by("comp", "n").alias("main"))
    now = now.join(most, "hood").join(bodies, "key")
    home = now.select(F.xxhash64("hood", "part").alias("room"), "key", "comp", (F.col("comp") != F.col("main")).alias("visitor"), "body")
    visits = now.where("comp != main").select("hood", "part", "blocks", "key", "comp", "body").withColumn("to", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).where("to != part")
    away = visits.select(F.xxhash64("hood", F.col("to")).alias("room"), "key", "comp", F.lit(True).alias("visitor"), "body")
    return settle(_few(links).unionAll(_tree_round(home.unionAll(away), num, den)))


def drop_near_duplicates(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The document with the smallest id of each component, columns unchanged.

    Of repeated rows with that id one stays; different texts under one id all
    stay.  Rows without an id stand for no component and stay.
    """
    name, copies = spare_name(docs.columns, "_keep"), spare_name(docs.columns, "_copies")
    keep = jaccard_components(docs, width, num, den).where("doc_id = component_id").groupBy(F.col("doc_id").alias(name)).agg(F.count("*").alias(copies))
    own = docs["doc_id"].cast("long") == F.col(name)
    once = docs.join(keep.where(F.col(copies) == 1).hint("shuffle_hash"), own, "left_semi")
    again = docs.join(keep.where(F.col(copies) > 1).hint("shuffle_hash"), own, "left_semi").dropDuplicates(["doc_id", "text"])
    return once.unionByName(again).unionByName(docs.where("doc_id is null"))
