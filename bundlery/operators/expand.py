"""Walking from chosen groups to their neighbours, and from groups to rows."""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Boxes that the driver holds at once; of larger layers it holds those that are reached.
DRIVER_BOXES = 100_000
#: Boxes that a wave may bring beyond the neighbours it was asked for, and the widths, in
#: usual boxes, by which it looks further to find them (fixed values).
WAVE_BOXES, WAVE_WIDTHS = 10_000, (1.0, 4.0, 16.0, 64.0)


class BoxIndex:
    """A static tree over boxes: halves by their centres, each node with the hull of its boxes."""

    LEAF = 32

    def __init__(self, lo: np.ndarray, hi: np.ndarray):
        n, self.lo, self.hi = len(lo), lo, hi
        self.order = np.arange(n)
        self.nodes: list[tuple[int, int, np.ndarray, np.ndarray, int]] = []
        if n:
            with np.errstate(invalid="ignore"):
                span = np.where(np.isfinite(lo), lo, hi) + np.where(np.isfinite(hi), hi, lo)
            self._build(np.where(np.isfinite(span), span, 0.0), 0, n)

    def _build(self, centre: np.ndarray, a: int, b: int) -> None:
        # nodes in order of a walk; the last entry of one is where its subtree ends
        at, own = len(self.nodes), self.order[a:b]
        self.nodes.append((a, b, self.lo[own].min(axis=0), self.hi[own].max(axis=0), 0))
        if b - a > self.LEAF:
            c = centre[own]
            j = int(np.argmax(c.max(axis=0) - c.min(axis=0)))
            mid = (b - a) // 2
            self.order[a:b] = own[np.argpartition(c[:, j], mid)]
            self._build(centre, a, a + mid)
            self._build(centre, a + mid, b)
        self.nodes[at] = (*self.nodes[at][:4], len(self.nodes))

    def meeting(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Positions of the boxes with ``box.lo <= hi`` and ``box.hi >= lo``, in order."""
        out, at = [], 0
        while at < len(self.nodes):
            a, b, low, high, end = self.nodes[at]
            if not ((low <= hi).all() and (high >= lo).all()):
                at = end
                continue
            if end == at + 1:
                own = self.order[a:b]
                out.append(own[((self.lo[own] <= hi) & (self.hi[own] >= lo)).all(axis=1)])
            at += 1
        return np.sort(np.concatenate(out)) if out else np.zeros(0, np.int64)


@dataclass
class BoxTable:
    """Half-open boxes of one layer's groups, in order of gid.

    ``whole`` says whether all groups of the layer are held; if not, ``known``
    lists the gids whose neighbours are.
    """

    gid: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    cnt: np.ndarray
    obj: np.ndarray
    whole: bool = True
    known: set = field(default_factory=set)

    @cached_property
    def index(self) -> BoxIndex:
        return BoxIndex(self.lo, self.hi)

    @classmethod
    def of(cls, t, whole: bool = True, known: set | None = None) -> "BoxTable":
        """From a pandas table of ``gid, lo, hi, cnt, obj``."""
        t = t.drop_duplicates("gid").sort_values("gid", kind="stable")
        k = len(t["lo"].iloc[0]) if len(t) else 0
        return cls(t["gid"].to_numpy(np.int64), np.stack(t["lo"].to_numpy()) if k else np.zeros((0, 0)), np.stack(t["hi"].to_numpy()) if k else np.zeros((0, 0)), t["cnt"].to_numpy(np.int64), t["obj"].to_numpy(float), whole, known or set())

    @classmethod
    def load(cls, groups: DataFrame, objective, gids: np.ndarray, limit: int = DRIVER_BOXES) -> "BoxTable":
        """All boxes of a layer of at most ``limit`` groups, else those of ``gids``."""
        rows = groups.select("gid", "lo", "hi", "cnt", objective.alias("obj"))
        # counted first: a layer that is too large must not come here to be found so
        if groups.count() <= limit:
            return cls.of(rows.toPandas())
        ids = groups.sparkSession.createDataFrame([(int(g),) for g in gids], "gid long")
        return cls.of(rows.join(F.broadcast(ids), "gid", "left_semi").toPandas(), whole=False)

    def with_neighbours(self, groups: DataFrame, objective, gids: list[int], eps: float = 0.0, most: int = WAVE_BOXES) -> "BoxTable":
        """This table and all boxes that meet those of ``gids``, or ``eps`` below them, found on the executors.

        The same wave looks a few boxes further where that brings at most ``most``
        boxes, and knows all neighbours of what lies whole inside the searched ranges.
        """
        import pandas as pd

        at = self.place(gids)
        size = self.hi[at] - self.lo[at]
        width = np.asarray([np.median(c[np.isfinite(c)]) if np.isfinite(c).any() else 0.0 for c in size.T])
        ranges = [(self.lo[at] - eps - r * width, self.hi[at] + r * width) for r in (0.0, *WAVE_WIDTHS)]
        near = boxes_meeting(groups.select("gid", "lo", "hi", "cnt", objective.alias("obj")), ranges)
        found = np.zeros(len(ranges), np.int64)
        for r in near.groupBy("level").agg(F.count("*").alias("n")).collect():
            found[r["level"]] = r["n"]
        found = np.cumsum(found)
        level = max(0, int(np.searchsorted(found, most, side="right")) - 1)
        mine = pd.DataFrame({"gid": self.gid, "lo": list(self.lo), "hi": list(self.hi), "cnt": self.cnt, "obj": self.obj})
        out = BoxTable.of(pd.concat([mine, near.where(F.col("level") <= level).drop("level").toPandas()], ignore_index=True), False)
        out.known = self.known | set(gids)
        for lo, hi in zip(*ranges[level]):
            inside = out.index.meeting(lo, hi)
            out.known.update(out.gid[inside[((out.lo[inside] - eps >= lo) & (out.hi[inside] <= hi)).all(axis=1)]].tolist())
        return out

    def place(self, gids) -> np.ndarray:
        """Positions of groups that are held."""
        return np.searchsorted(self.gid, gids)

    def group_of_point(self, point: np.ndarray) -> int:
        """Position of the box that holds a point; -1 if none does."""
        near = self.index.meeting(point, point)
        inside = near[((self.lo[near] <= point) & (point < self.hi[near])).all(axis=1)]
        return int(inside[0]) if len(inside) else -1

    def neighbours(self, g: int, eps: float, probes: str = "grid") -> list[int]:
        """Boxes that hold the probe points just outside, or level with, box ``g``.

        ``grid`` probes all combinations of below, middle and above (3^k);
        ``faces`` moves along one attribute at a time (2k), for many attributes.
        """
        lo, hi = self.lo[g], self.hi[g]
        near = self.index.meeting(lo - eps, hi)
        a, b = self.lo[near], self.hi[near]
        below = np.where(np.isfinite(lo), np.minimum(lo - eps, np.nextafter(lo, -np.inf)), np.nan)
        above = np.where(np.isfinite(hi), hi, np.nan)
        # an open side has no edge to measure from: stay one step inside the closed one
        with np.errstate(invalid="ignore"):
            centre = (lo + hi) / 2
        middle = np.where(np.isfinite(lo) & np.isfinite(hi), centre, np.where(np.isfinite(lo), lo, np.where(np.isfinite(hi), np.nextafter(hi, -np.inf), 0.0)))
        steps = [[x for x in (p, m, q) if not np.isnan(x)] for p, m, q in zip(below, middle, above)]
        if probes == "grid":
            points = np.asarray(list(itertools.product(*steps)))
        else:
            points = np.asarray([[x if i == j else middle[i] for i in range(len(lo))] for j, s in enumerate(steps) for x in s])
        found: dict[int, None] = {}
        for at in range(0, len(points), 256):
            p = points[at : at + 256]
            hit = ((a[None] <= p[:, None]) & (p[:, None] < b[None])).all(axis=2)
            for i in near[hit.any(axis=0)].tolist():
                found[i] = None
        found.pop(g, None)
        return list(found)


def neighbour_queue(boxes: BoxTable, seeds: np.ndarray, alpha: int, eps: float, sense: str, probes: str = "grid", fetch: Callable[[BoxTable, list[int]], BoxTable] | None = None) -> np.ndarray:
    """Gids of the seed groups and of neighbours, best first, until their rows reach ``alpha``.

    Where not all boxes are held, ``fetch`` adds the neighbours of all groups that
    wait in the queue, one Spark job a wave; the result is the same.
    """
    sign = -1.0 if sense == "max" else 1.0
    seen = dict.fromkeys(int(s) for s in seeds)
    at = boxes.place(list(seen))
    heap = [(sign * float(boxes.obj[i]), g) for g, i in zip(seen, at)]
    heapq.heapify(heap)
    rows = int(boxes.cnt[at].sum()) if seen else 0
    while heap and rows < alpha:
        if not boxes.whole and heap[0][1] not in boxes.known:
            boxes = fetch(boxes, [g for _, g in heap if g not in boxes.known])
        _, g = heapq.heappop(heap)
        for i in boxes.neighbours(int(boxes.place(g)), eps, probes):
            other = int(boxes.gid[i])
            if other not in seen:
                seen[other] = None
                heapq.heappush(heap, (sign * float(boxes.obj[i]), other))
                rows += int(boxes.cnt[i])
    return np.fromiter(seen, np.int64, len(seen))


def rows_of_groups(layer: DataFrame, gids: np.ndarray, predicate: str | None = None) -> DataFrame:
    """Rows of a layer that belong to groups; there are no more ids than candidate rows."""
    ids = layer.sparkSession.createDataFrame([(int(g),) for g in gids], "gid_up long")
    base = layer.where(predicate) if predicate else layer
    return base.join(F.broadcast(ids), "gid_up", "left_semi")


def layer_epsilon(layer: DataFrame, attrs: list[str]) -> float:
    """Smallest positive difference of two rows on any single attribute.

    The distinct values of all attributes are range-partitioned in one shuffle and
    compared inside the parts; the borders (two values a part and attribute) are
    compared afterwards, so no task sees all values.
    """
    value = F.explode(F.array(*[F.struct(F.lit(i).alias("a"), F.col(x).cast("double").alias("v")) for i, x in enumerate(attrs)])).alias("x")
    values = layer.select(value).select("x.a", "x.v").where("v is not null").repartitionByRange("a", "v")

    def gaps(batches):
        held: dict[int, list] = {}
        for batch in batches:
            a, v = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for i in np.unique(a).tolist():
                held.setdefault(i, []).append(np.unique(v[a == i]))
        for i, parts in held.items():
            v = np.unique(np.concatenate(parts))
            step = np.diff(v)
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([v[0]]), pa.array([v[-1]]), pa.array([step.min() if len(step) else None], pa.float64())], ["a", "lo", "hi", "d"])

    # two values and a gap of each part
    per = sorted((r["a"], r["lo"], r["hi"], r["d"]) for r in values.mapInArrow(gaps, "a int, lo double, hi double, d double").collect())
    found = [r[3] for r in per if r[3] is not None] + [y[1] - x[2] for x, y in zip(per, per[1:]) if x[0] == y[0]]
    return float(min([d for d in found if d > 0], default=np.inf))


def _cells(lo, hi, first: float, width: float, cells: int):
    """Numbers of the coarse cells of one attribute that an interval crosses."""

    def cell(x):
        return F.greatest(F.lit(0.0), F.least(F.lit(float(cells - 1)), F.floor((x - first) / width).cast("double"))).cast("int")

    return F.sequence(cell(lo), cell(hi))


def _meet(lo: np.ndarray, hi: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Positions of the boxes ``lo, hi`` that meet or touch one of the boxes ``low, high``."""
    keep = np.ones(len(lo), bool)
    for j in range(lo.shape[1]):
        # the union of the searched intervals rules out most boxes, one attribute at a time
        by = np.argsort(low[:, j], kind="stable")
        first, last = low[by, j], np.maximum.accumulate(high[by, j])
        new = np.concatenate([[True], first[1:] > last[:-1]])
        first, last = first[new], last[np.concatenate([new[1:], [True]])]
        at = np.minimum(np.searchsorted(last, lo[:, j]), len(last) - 1)
        keep &= (first[at] <= hi[:, j]) & (last[at] >= lo[:, j])
    rest = np.flatnonzero(keep)
    step = max(1, (1 << 21) // len(low))
    out = [part[((lo[part, None] <= high[None]) & (hi[part, None] >= low[None])).all(axis=2).any(axis=1)] for i in range(0, len(rest), step) for part in [rest[i : i + step]]]
    return np.concatenate(out) if out else rest


def boxes_meeting(groups: DataFrame, ranges: list[tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """Rows of ``groups`` that meet or touch a range, with the ``level`` of the first list that has one.

    A list ``(lo, hi)`` has a range for each group that waits, no more than
    candidates of a layer; lists grow wider.  Ranges go to the tasks, boxes stay there.
    """

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            lo, hi = (np.stack(batch.column(c).to_numpy(zero_copy_only=False)) for c in ("lo", "hi"))
            level = np.full(len(lo), -1, np.int32)
            left = np.arange(len(lo))
            for i, (low, high) in reversed(list(enumerate(ranges))):
                # what a wider list does not have, no narrower one has
                left = left[_meet(lo[left], hi[left], low, high)]
                level[left] = i
            at = np.flatnonzero(level >= 0)
            if len(at):
                yield pa.RecordBatch.from_arrays([*batch.take(pa.array(at)).columns, pa.array(level[at])], [*batch.schema.names, "level"])

    return groups.mapInArrow(run, "gid long, lo array<double>, hi array<double>, cnt long, obj double, level int")


def boxes_of_points(points: DataFrame, groups: DataFrame, buckets: int = 64) -> DataFrame:
    """``pid, gid`` of points ``pid, p`` by a join with boxes, for layers too large for the driver.

    Points and boxes meet on a coarse cell of the first attribute; a box lies in
    every cell it crosses.
    """
    s = points.agg(F.min(F.col("p")[0]).alias("lo"), F.max(F.col("p")[0]).alias("hi")).first()
    if s["lo"] is None:
        return points.sparkSession.createDataFrame([], "pid long, gid long")
    lo, width = s["lo"], max((s["hi"] - s["lo"]) / buckets, 1e-300)
    first = F.col("p")[0]
    left = points.withColumn("cell", _cells(first, first, lo, width, buckets)[0])
    right = groups.select("gid", "lo", "hi").withColumn("cell", F.explode(_cells(F.col("lo")[0], F.col("hi")[0], lo, width, buckets)))
    inside = F.forall(F.arrays_zip("p", "lo", "hi"), lambda z: (z["p"] >= z["lo"]) & (z["p"] < z["hi"]))
    return left.join(right, "cell").where(inside).select("pid", "gid")
