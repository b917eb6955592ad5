"""Partitioning of rows into groups of low variance.

``scan_line`` cuts one attribute into pieces whose population variance stays
within a bound; ``partition_low_variance`` applies it again and again to the group
with the largest total variance, along that group's most variable attribute;
``partition_bucketed`` runs it on a relation of any size, bucket by bucket on the
executors; ``partition_mean_split`` is the baseline that halves groups at a mean.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.tables import checkpoint_folder, first_rows, reclaim

#: Sample size, tolerance (share of the largest variance) and steps of the estimator.
SAMPLE, TOLERANCE, STEPS = 10_000, 1e-6, 60
#: Rows of a bucket that one task partitions: at most, and at least where there are so many.
BUCKET_ROWS, BUCKET_LEAST = 2_000_000, 20_000
#: Buckets that one cut makes at most; what is still too full is cut again.
BUCKET_CUTS = 4096
#: Different values up to which a scan goes one by one in place of by stretches (fixed value).
SHORT = 256
#: The constant that suits the data sets of the published experiments (fixed value).
PUBLISHED_SCALE = 13.5


def scan_line(values: np.ndarray, weights: np.ndarray | None, beta: float) -> np.ndarray:
    """Delimiters of pieces of variance at most ``beta``: piece i is [d[i-1], d[i]).

    Values are scanned in order; a piece is closed before the value that would
    push its running population variance over the bound.  Equal values stay
    together (a scan that would stop among them stops before the first), so
    half-open pieces fit the rows exactly and the bound holds for every piece.
    """
    v, inverse = np.unique(np.asarray(values, float), return_inverse=True)
    w = np.bincount(inverse, weights=weights, minlength=len(v)).astype(float)
    n = len(v)
    if n < 2:
        return np.zeros(0)
    if n <= SHORT:
        return np.asarray(_scan_short(v.tolist(), w.tolist(), beta * (1 + 1e-12)))
    out, at = [], 0
    while at < n:
        # the running variance of the open piece, a stretch of values at a time
        width, end, base = 64, None, v[at]
        done_w = done_1 = done_2 = 0.0
        lo = at
        while end is None and lo < n:
            hi = min(n, lo + width)
            x = v[lo:hi] - base
            cw = done_w + np.cumsum(w[lo:hi])
            c1 = done_1 + np.cumsum(w[lo:hi] * x)
            c2 = done_2 + np.cumsum(w[lo:hi] * x * x)
            # the variance rises and falls while copies of one value are added: the
            # running scan would stop inside the run where its peak is over the bound
            pw, p1, p2 = (np.concatenate([[d], c[:-1]]) for d, c in ((done_w, cw), (done_1, c1), (done_2, c2)))
            with np.errstate(divide="ignore", invalid="ignore"):
                spread, gap2 = p2 / pw - (p1 / pw) ** 2, (x - p1 / pw) ** 2
                peak = np.clip(pw * (gap2 - spread) / (gap2 + spread), 1, w[lo:hi])
                high = np.maximum.reduce([pw * spread / (pw + c) + pw * c * gap2 / (pw + c) ** 2 for c in (np.floor(peak), np.minimum(np.ceil(peak), w[lo:hi]), w[lo:hi])])
            over = high > beta * (1 + 1e-12)
            if lo == at:
                over[0] = False
            if over.any():
                end = lo + int(np.argmax(over))
            else:
                done_w, done_1, done_2, lo, width = cw[-1], c1[-1], c2[-1], hi, width * 4
        if end is None:
            break
        out.append(v[end])
        at = end
    return np.asarray(out)


def _scan_short(v: list[float], w: list[float], most: float) -> list[float]:
    """The scan of few values, one at a time: the same sums in the same order."""
    out, base, pw, p1, p2 = [], v[0], w[0], 0.0, 0.0
    for value, c in zip(v[1:], w[1:]):
        x = value - base
        mean = p1 / pw
        spread, gap2 = p2 / pw - mean * mean, (x - mean) * (x - mean)
        high = pw * spread / (pw + c) + pw * c * gap2 / ((pw + c) * (pw + c))
        if c > 1 and gap2 + spread != 0:
            peak = min(max(pw * (gap2 - spread) / (gap2 + spread), 1.0), c)
            for k in (math.floor(peak), min(math.ceil(peak), c)):
                high = max(high, pw * spread / (pw + k) + pw * k * gap2 / ((pw + k) * (pw + k)))
        if high > most:
            out.append(value)
            base, pw, p1, p2 = value, c, 0.0, 0.0
        else:
            pw, p1, p2 = pw + c, p1 + c * x, p2 + c * x * x
    return out


def theory_beta(variance: float, n: int) -> float:
    """The bound 24 var / n^2, for which at most 3n/4 + 1/2 pieces and a ratio score of 24/n are proved."""
    return 24 * variance / n**2


def ratio_score(values: np.ndarray, delimiters: np.ndarray) -> float:
    """Sum of the pieces' variances over the variance of all."""
    values = np.asarray(values, float)
    total = values.var()
    piece = np.searchsorted(delimiters, values, side="right")
    return float(sum(values[piece == p].var() for p in np.unique(piece)) / total) if total > 0 else 0.0


def scale_factors_of(sample: np.ndarray, d_f: float) -> np.ndarray:
    """For each attribute of a sample, c such that a bound of c var / d_f^2 cuts it into d_f pieces."""
    out = []
    for column in sample.T:
        variance = column.var()
        if variance <= 0:
            out.append(1.0)
            continue
        lo, hi = 0.0, (column.max() - column.min()) ** 2 / 4
        beta, least = hi, TOLERANCE * hi
        for _ in range(STEPS):
            beta = (lo + hi) / 2
            pieces = len(scan_line(column, None, beta)) + 1
            if pieces == round(d_f) or hi - lo <= least:
                break
            lo, hi = (lo, beta) if pieces < d_f else (beta, hi)
        # a bound of 0 would never be met by ties: keep it positive
        out.append(max(beta, 1e-12 * variance) * d_f**2 / variance)
    return np.asarray(out)


def estimate_scale_factors(df: DataFrame, attrs: list[str], d_f: float, sample: int = SAMPLE, seed: int = 0, tid: str = "tid") -> np.ndarray:
    """``scale_factors_of`` on a sample of at most ``sample`` rows, drawn by a hash of the row id."""
    rows = df.select(*[F.col(a).cast("double").alias(a) for a in attrs], F.xxhash64(F.col(tid), F.lit(seed)).alias("_h"))
    rows = first_rows(rows, sample, "_h").drop("_h").toPandas().to_numpy(float)
    return scale_factors_of(rows, d_f) if len(rows) else np.ones(len(attrs))


@dataclass
class Groups:
    """Group number of each row, and the boxes of the groups (half-open)."""

    assign: np.ndarray
    lo: np.ndarray
    hi: np.ndarray


def variances(points: np.ndarray, weights: np.ndarray | None = None) -> np.ndarray:
    """Population variance of each attribute, of rows that count ``weights`` times."""
    if weights is None or (weights == 1).all():
        return points.var(axis=0)
    total = weights.sum()
    return weights @ (points - weights @ points / total) ** 2 / total


def partition_low_variance(points: np.ndarray, d_f: float, scale: np.ndarray | str | float | None = None, rank: str = "total_variance", box: tuple | None = None, target: int | None = None, unit: np.ndarray | None = None, weights: np.ndarray | None = None) -> Groups:
    """Split rows into about ``len(points) / d_f`` groups of low variance.

    ``scale`` is the factors per attribute, one number for all, ``None`` to
    estimate them on these rows, or ``"search"`` to look for the right bound
    anew at every split.  ``rank`` orders the groups by ``total_variance`` (size
    times variance) or ``variance``; variances of different attributes are compared
    in squares of ``unit`` (raw by default).  Splitting stops early where no group
    has any variance left.  A row with a weight counts as so many equal rows.
    """
    points = np.asarray(points, float)
    n, k = points.shape
    if weights is not None and (weights == 1).all():
        weights = None
    rows = n if weights is None else int(weights.sum())
    square = np.ones(k) if unit is None else np.asarray(unit, float) ** 2
    target = target if target is not None else max(1, math.ceil(rows / d_f))
    order = np.arange(n)
    lo0 = np.full(k, -np.inf) if box is None else np.asarray(box[0], float)
    hi0 = np.full(k, np.inf) if box is None else np.asarray(box[1], float)
    if n == 0:
        return Groups(np.zeros(0, np.int64), np.zeros((0, k)), np.zeros((0, k)))
    if scale is None:
        at = np.arange(0, rows, max(1, rows // SAMPLE))[:SAMPLE]
        scale = scale_factors_of(points[at if weights is None else np.searchsorted(np.cumsum(weights), at, side="right")], d_f)
    elif not isinstance(scale, str):
        scale = np.broadcast_to(np.asarray(scale, float), (k,))

    heap, done, ticket = [], [], 0

    def push(edge, walls):
        # all pieces of one split at once: variances by stretches of the order
        nonlocal ticket
        at = order[edge[0] : edge[-1]]
        part, first, size = points[at], edge[:-1] - edge[0], np.diff(edge)
        own = None if weights is None else weights[at][:, None]
        mass = size if own is None else np.add.reduceat(own[:, 0], first)
        mean = np.add.reduceat(part if own is None else part * own, first, axis=0) / mass[:, None]
        away = (part - np.repeat(mean, size, axis=0)) ** 2
        variance = np.add.reduceat(away if own is None else away * own, first, axis=0) / mass[:, None]
        axis, each = np.argmax(variance / square, axis=1), np.arange(len(size))
        top, most = variance[each, axis], np.maximum.reduceat(np.abs(part), first, axis=0)[each, axis]
        still = (size < 2) | (top <= 1e-24 * (1 + most**2))
        key = top / square[axis] * (mass if rank == "total_variance" else 1)
        for i, (start, end, j, stays) in enumerate(zip(edge[:-1].tolist(), edge[1:].tolist(), axis.tolist(), still.tolist())):
            if stays:
                done.append((start, end, *walls(i)))
                continue
            heapq.heappush(heap, (-float(key[i]), ticket, start, end, j, float(top[i]), *walls(i)))
            ticket += 1

    push(np.asarray([0, n]), lambda i: (lo0, hi0))
    while heap and len(heap) + len(done) < target:
        _, _, start, end, j, variance, lo, hi = heapq.heappop(heap)
        index = order[start:end]
        x = points[index, j]
        if isinstance(scale, str):
            beta = scale_factors_of(x[:, None], d_f)[0] * variance / d_f**2
        else:
            beta = scale[j] * variance / d_f**2
        own = None if weights is None else weights[index]
        cuts = scan_line(x, own, beta)
        while not len(cuts):
            beta /= 2
            cuts = scan_line(x, own, beta)
        piece = np.searchsorted(cuts, x, side="right")
        by = np.argsort(piece, kind="stable")
        order[start:end] = index[by]
        edge = start + np.searchsorted(piece[by], np.arange(len(cuts) + 2))
        walls = np.concatenate([[lo[j]], cuts, [hi[j]]])

        def between(i, j=j, lo=lo, hi=hi, walls=walls):
            new_lo, new_hi = lo.copy(), hi.copy()
            new_lo[j], new_hi[j] = walls[i], walls[i + 1]
            return new_lo, new_hi

        push(edge, between)
    parts = sorted(done + [(s, e, lo, hi) for _, _, s, e, _, _, lo, hi in heap], key=lambda p: p[0])
    assign = np.empty(n, np.int64)
    for g, (s, e, _, _) in enumerate(parts):
        assign[order[s:e]] = g
    return Groups(assign, np.stack([p[2] for p in parts]), np.stack([p[3] for p in parts]))


# ---------------------------------------------------------------- on Spark


def profile(df: DataFrame, attrs: list[str]) -> dict[str, dict[str, float]]:
    """Count, mean, population variance, minimum and maximum of each attribute (one job)."""
    aggs = [f(F.col(a).cast("double")).alias(f"{name}:{a}") for a in attrs for name, f in (("mean", F.avg), ("var", F.var_pop), ("min", F.min), ("max", F.max))]
    row = df.agg(F.count("*").alias("n"), *aggs).first()
    return {a: {"n": row["n"], **{s: row[f"{s}:{a}"] for s in ("mean", "var", "min", "max")}} for a in attrs}


def _case(x: Column, edges: list[float]) -> Column:
    """Number of interior edges at or below a value, as a balanced CASE tree."""

    def tree(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(x < F.lit(edges[mid]), tree(lo, mid)).otherwise(tree(mid + 1, hi))

    return tree(0, len(edges))


def _cell(x: Column, edges: list[float]) -> Column:
    """As ``_case`` for many edges: a search by halves in an array, so that plans and their code stay small."""
    if not edges:
        return F.lit(0)
    bits = len(edges).bit_length()
    held = F.array(*[F.lit(float(e)) for e in [*edges, *[math.inf] * ((1 << bits) - 1 - len(edges))]])
    steps = F.array(*[F.lit(1 << i) for i in reversed(range(bits))])
    return F.least(F.lit(len(edges)), F.aggregate(steps, F.lit(0), lambda at, step: at + F.when(F.get(held, at + step - 1) <= x, step).otherwise(0)))


def bucket_edges(df: DataFrame, attr: str, stats: dict[str, float], rows: int, bucketing: str = "equal_width", most: int = 4096) -> list[float]:
    """Interior edges of buckets of at most ``rows`` rows along one attribute.

    ``equal_width`` doubles the number of equal buckets until all fit (or
    ``most`` is reached); ``quantile`` joins fine equal cells up to the limit.
    Only counts of at most ``16 * most`` cells reach the driver.
    """
    n, lo, hi = stats["n"], stats["min"], stats["max"]
    need = max(1, math.ceil(n / rows))
    if need == 1 or not hi > lo:
        return []
    fine = 1 << max(6, math.ceil(math.log2(need * 16)))
    fine = min(fine, 16 * most)
    cell = F.least(F.lit(fine - 1), F.floor((F.col(attr).cast("double") - F.lit(lo)) / F.lit(hi - lo) * F.lit(fine)).cast("int"))
    counts = np.zeros(fine, np.int64)
    for r in df.select(cell.alias("cell")).groupBy("cell").agg(F.count("*").alias("n")).collect():
        counts[r["cell"]] = r["n"]
    if bucketing == "equal_width":
        number = 1 << math.ceil(math.log2(need))
        while number < min(fine, most) and counts.reshape(number, -1).sum(axis=1).max() > rows:
            number *= 2
        cut = np.arange(1, number) * (fine // number)
    elif bucketing == "quantile":
        cut, held = [], 0
        for i, c in enumerate(counts):
            if held and held + c > rows:
                cut.append(i)
                held = 0
            held += c
    else:
        raise ValueError(f"unknown bucketing {bucketing!r}")
    return [lo + (hi - lo) * int(i) / fine for i in cut]


GROUP_SHIFT = 40


def bucket_rows(n: int) -> int:
    """Rows of a bucket of a relation of ``n``: 64 buckets between the two limits; cores play no part."""
    return int(min(BUCKET_ROWS, max(BUCKET_LEAST, math.ceil(n / 64))))


def cut_buckets(df: DataFrame, attrs: list[str], rows: int, bucketing: str = "equal_width", rounds: int = 16) -> tuple[DataFrame, dict[int, tuple]]:
    """``df`` with ``bucket``, and the boxes ``(lo, hi)`` of the buckets.

    The most variable attribute of all rows is cut first.  A bucket of more than
    ``rows`` rows is cut again along its own most variable attribute, so a value
    range that holds a third of all rows is as many buckets as it needs; only one
    whose rows are all equal stays whole.  Counts and ranges of buckets reach the
    driver, never rows.
    """
    k = len(attrs)
    boxes: dict[int, tuple] = {0: (np.full(k, -np.inf), np.full(k, np.inf))}
    now, open_, fresh = df.withColumn("bucket", F.lit(0)), {0}, 1
    aggs = [f(F.col(a)).alias(f"{s}:{a}") for a in attrs for s, f in (("var", F.var_pop), ("min", F.min), ("max", F.max))]
    for _ in range(rounds):
        base = now if len(open_) == len(boxes) else now.where(F.col("bucket").isin(sorted(open_)))
        stats = {r["bucket"]: r for r in base.groupBy("bucket").agg(F.count("*").alias("n"), *aggs).collect()}
        plan = []
        for b in sorted(open_):
            r = stats.get(b)
            if r is None or r["n"] <= rows:
                continue
            j = max(range(k), key=lambda i: r[f"var:{attrs[i]}"] or 0.0)
            lo, hi = r[f"min:{attrs[j]}"], r[f"max:{attrs[j]}"]
            if not hi > lo:
                continue
            s = {"n": r["n"], "min": lo, "max": hi}
            # a few times the least number of equal cuts; what that leaves too full is cut again
            most = min(BUCKET_CUTS, 4 << math.ceil(math.log2(math.ceil(r["n"] / rows))))
            edges = bucket_edges(base.where(F.col("bucket") == b), attrs[j], s, rows, bucketing, most)
            if edges:
                plan.append((b, j, edges, fresh))
                fresh += len(edges)
        if not plan:
            break
        to, open_ = F.col("bucket"), set()
        for b, j, edges, first in plan:
            # the lowest part keeps the bucket's number
            names = F.array(F.lit(b), *[F.lit(first + i) for i in range(len(edges))])
            to = F.when(F.col("bucket") == b, F.get(names, _cell(F.col(attrs[j]), edges))).otherwise(to)
            low, high = boxes[b]
            for i in range(len(edges) + 1):
                lo, hi = low.copy(), high.copy()
                if i > 0:
                    lo[j] = edges[i - 1]
                if i < len(edges):
                    hi[j] = edges[i]
                name = b if i == 0 else first + i - 1
                boxes[name] = (lo, hi)
                open_.add(name)
        now = now.withColumn("bucket", to)
    return now, boxes


def partition_bucketed(df: DataFrame, attrs: list[str], d_f: float, rows: int | None = None, bucketing: str = "equal_width", scale=None, rank: str = "total_variance", seed: int = 0, tid: str = "tid", scaling: str = "raw", carry: list[str] | None = None, average: list[str] = (), weighted: bool = False, placed: bool = True) -> tuple[DataFrame | None, DataFrame]:
    """``(assignment, groups)`` of a relation of any size.

    ``cut_buckets`` makes buckets of at most ``rows`` rows, one
    shuffle brings each bucket to one task, and the in-memory partitioner runs
    there with its own queue.  ``assignment`` is ``tid, gid``; ``groups`` is
    ``gid, cnt, lo, hi`` with half-open boxes that are disjoint and cover the
    space.  ``gid`` is the bucket number shifted left plus a local number.  With ``scaling``
    ``zscore`` attributes of unlike magnitude weigh alike.

    With ``carry`` the assignment has the attributes and these columns, among
    them ``w``, too; the groups have the means of ``average`` (of rows by ``w`` where
    ``weighted``), the sum of ``w`` and the attributes' variances.  A group lies whole
    in one task, so neither takes another shuffle.  Without ``placed`` only the groups are
    kept, and the assignment is None.
    """
    stats = profile(df, attrs)
    n = stats[attrs[0]]["n"]
    schema = "kind int, tid long, gid long, cnt long, lo array<double>, hi array<double>"
    if scaling not in ("raw", "zscore"):
        raise ValueError(f"unknown scaling {scaling!r}")
    unit = np.asarray([math.sqrt(stats[a]["var"] or 0.0) or 1.0 for a in attrs]) if scaling == "zscore" else None
    factors = estimate_scale_factors(df, attrs, d_f, seed=seed, tid=tid) if scale is None else scale
    more = list(carry or ())
    x = df.select(F.col(tid).cast("long").alias("tid"), *[F.col(a).cast("double").alias(a) for a in attrs], *more)
    if carry is not None:
        schema += "".join(f", `{c}` {kind}" for c, kind in x.dtypes if c != "tid") + "".join(f", `var_{a}` double" for a in attrs)
    x, walls = cut_buckets(x, attrs, rows or bucket_rows(n), bucketing)

    def cut(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        points = np.column_stack([table.column(a).to_numpy() for a in attrs])
        ids = table.column("tid").to_numpy()
        # a fixed order: the result must not depend on how rows arrive
        by = np.argsort(ids, kind="stable")
        points, ids, table = points[by], ids[by], table.take(pa.array(by)) if more else table
        lo, hi = walls[bucket]
        got = partition_low_variance(points, d_f, factors, rank, (lo, hi), unit=unit)
        base = bucket << GROUP_SHIFT
        count = np.bincount(got.assign, minlength=len(got.lo))
        g, m = len(got.lo), len(ids)
        extra = {}
        if carry is not None:
            w = table.column("w").to_numpy().astype(float)
            for c in [*attrs, *more]:
                kind, own = table.schema.field(c).type, pa.nulls(g, table.schema.field(c).type)
                if c == "w":
                    own = pa.array(np.bincount(got.assign, weights=w, minlength=g)).cast(kind)
                elif c in average:
                    v = table.column(c).to_numpy().astype(float)
                    each = np.where(np.isnan(v), 0.0, w if weighted else 1.0)
                    with np.errstate(invalid="ignore"):
                        mean = np.bincount(got.assign, weights=each * np.nan_to_num(v), minlength=g) / np.bincount(got.assign, weights=each, minlength=g)
                    own = pa.array(mean, from_pandas=True).cast(kind)
                extra[c] = pa.chunked_array([*table.column(c).chunks, own], kind)
            for a, v in zip(attrs, points.T):
                mean = np.bincount(got.assign, weights=v, minlength=g) / count
                var = np.bincount(got.assign, weights=(v - mean[got.assign]) ** 2, minlength=g) / count
                extra[f"var_{a}"] = pa.concat_arrays([pa.nulls(m, pa.float64()), pa.array(var)])
        out = pa.table(
            {
                "kind": pa.array(np.repeat([0, 1], [m, g]).astype(np.int32)),
                "tid": pa.array(np.concatenate([ids, np.zeros(g, np.int64)])),
                "gid": pa.array(np.concatenate([got.assign, np.arange(g)]) + base),
                "cnt": pa.array(np.concatenate([np.ones(m, np.int64), count])),
                "lo": pa.array([None] * m + got.lo.tolist(), pa.list_(pa.float64())),
                "hi": pa.array([None] * m + got.hi.tolist(), pa.list_(pa.float64())),
                **extra,
            }
        )
        return out if placed else out.slice(m)

    # a stated number of tasks: small buckets would else be coalesced into one
    tasks = min(len(walls), 4 * max(8, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    out = persist(x.repartition(tasks, "bucket").groupBy("bucket").applyInArrow(cut, schema))
    if carry is not None:
        means = [c for c in average if c in (*attrs, *more)]
        return out.where("kind = 0").select("tid", *attrs, *more, "gid") if placed else None, out.where("kind = 1").select("gid", "lo", "hi", *means, "w", "cnt", *[f"var_{a}" for a in attrs])
    return out.where("kind = 0").select("tid", "gid") if placed else None, out.where("kind = 1").select("gid", "cnt", "lo", "hi")


def persist(df: DataFrame) -> DataFrame:
    """Cut lineage in the session's shared checkpoint folder (a temporary one if none is named)."""
    checkpoint_folder(df.sparkSession)
    out = df.checkpoint(eager=True)
    reclaim(df.sparkSession)
    return out


def scan_line_df(df: DataFrame, attr: str, beta: float, parts: int = 1) -> DataFrame:
    """``piece, lo, hi, n`` of a bounded-variance scan of one attribute.

    Rows are first counted by value on the executors; the scan then needs only
    distinct values.  With ``parts`` > 1 equal-width ranges are scanned on their
    own and pieces also end at the ranges' borders.
    """
    values = df.select(F.col(attr).cast("double").alias("v")).where("v is not null and not isnan(v)").groupBy("v").agg(F.count("*").alias("n"))
    if parts > 1:
        s = profile(df, [attr])[attr]
        step = (s["max"] - s["min"]) / parts or 1.0
        values = values.withColumn("part", F.least(F.lit(parts - 1), F.floor((F.col("v") - s["min"]) / step)).cast("int"))
    else:
        values = values.withColumn("part", F.lit(0))

    def cut(table: pa.Table) -> pa.Table:
        v, n = table.column("v").to_numpy(), table.column("n").to_numpy()
        piece = np.searchsorted(scan_line(v, n, beta), v, side="right")
        k = int(piece.max()) + 1
        lo, hi = np.full(k, np.inf), np.full(k, -np.inf)
        np.minimum.at(lo, piece, v)
        np.maximum.at(hi, piece, v)
        return pa.table({"part": pa.array(np.full(k, table.column("part")[0].as_py(), np.int32)), "lo": lo, "hi": hi, "n": pa.array(np.bincount(piece, weights=n).astype(np.int64))})

    cuts = values.groupBy("part").applyInArrow(cut, "part int, lo double, hi double, n long")
    from pyspark.sql import Window as W

    # as many rows as pieces
    return cuts.select((F.row_number().over(W.orderBy("part", "lo")) - 1).cast("long").alias("piece"), "lo", "hi", "n")


def mean_split_level(df: DataFrame, attrs: list[str], tau: float, omega: float = math.inf) -> DataFrame:
    """One round of the baseline: oversized or overwide groups of ``gid`` are halved.

    A group splits at the mean of its most variable attribute while it has more
    than ``tau`` rows or a radius (largest distance of an attribute to its mean)
    over ``omega``; groups without variance stay.  Children get ``2 gid`` and
    ``2 gid + 1``; a group that stays keeps its ``gid`` and is marked ``open = false``.
    """
    aggs = [f(F.col(a).cast("double")).alias(f"{s}_{i}") for i, a in enumerate(attrs) for s, f in (("mean", F.avg), ("var", F.var_pop), ("min", F.min), ("max", F.max))]
    stats = df.where("open").groupBy("gid").agg(F.count("*").alias("_n"), *aggs)
    radius = F.greatest(*[F.greatest(F.col(f"max_{i}") - F.col(f"mean_{i}"), F.col(f"mean_{i}") - F.col(f"min_{i}")) for i in range(len(attrs))], F.lit(0.0)) if attrs else F.lit(0.0)
    widest = F.greatest(*[F.col(f"var_{i}") for i in range(len(attrs))], F.lit(-1.0))
    axis = F.lit(None).cast("int")
    for i in reversed(range(len(attrs))):
        axis = F.when(F.col(f"var_{i}") == widest, F.lit(i)).otherwise(axis)
    where = reduce(lambda acc, i: F.when(F.col("_axis") == i, F.col(f"mean_{i}")).otherwise(acc), range(len(attrs)), F.lit(None).cast("double"))
    cuts = stats.withColumn("_axis", axis).withColumn("_cut", where).where(((F.col("_n") > tau) | (radius > omega)) & (widest > 0)).select("gid", "_axis", "_cut")
    # one row per group that splits; Spark broadcasts it only below its own threshold
    joined = df.join(cuts, "gid", "left")
    value = reduce(lambda acc, i: F.when(F.col("_axis") == i, F.col(attrs[i]).cast("double")).otherwise(acc), range(len(attrs)), F.lit(None).cast("double"))
    right = F.when(value > F.col("_cut"), 1).otherwise(0)
    split = F.col("open") & F.col("_cut").isNotNull()
    return joined.withColumn("gid", F.when(split, F.col("gid") * 2 + right).otherwise(F.col("gid"))).withColumn("open", split).drop("_axis", "_cut")


def partition_mean_split(df: DataFrame, attrs: list[str], tau: float, omega: float = math.inf, levels: int = 60, tid: str = "tid") -> tuple[DataFrame, DataFrame]:
    """Baseline partition ``(tid, gid)`` and ``gid, cnt``: halving at means, level by level."""
    now = df.select(F.col(tid).cast("long").alias("tid"), *[F.col(a).cast("double").alias(a) for a in attrs]).withColumn("gid", F.lit(1).cast("long")).withColumn("open", F.lit(True))
    for _ in range(levels):
        now = persist(mean_split_level(now, attrs, tau, omega))
        if now.where("open").isEmpty():
            break
    else:
        raise RuntimeError(f"groups are still to be split after {levels} levels")
    return now.select("tid", "gid"), now.groupBy("gid").agg(F.count("*").alias("cnt"))
