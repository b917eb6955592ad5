"""Connected components of an edge list that never leaves the executors."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lineage import settle

#: Edges that one task contracts at a time.
HELD = 2_000_000
#: Edges to a task of a round; fewer tasks mean fewer shuffle files.
TASK_EDGES = 100_000


def contract(batches):
    """Edges ``a, b`` of a task as stars ``u, v`` with ``v`` the smallest of each part.

    Bounded batches of edges are contracted one by one, so the output joins
    the same nodes and has no more rows than the input.
    """

    def stars(held):
        a, b = (np.concatenate(x) for x in zip(*held))
        node, index = np.unique(np.concatenate([a, b]), return_inverse=True)
        i, j = index[: len(a)], index[len(a) :]
        up = np.arange(len(node))
        while True:
            # hook the larger root to the smaller one, then shorten all paths
            x, y = up[i], up[j]
            lo, hi = np.minimum(x, y), np.maximum(x, y)
            if (lo == hi).all():
                break
            np.minimum.at(up, hi, lo)
            while True:
                far = up[up]
                if (far == up).all():
                    break
                up = far
        child = np.flatnonzero(up != np.arange(len(node)))
        return pa.RecordBatch.from_arrays([pa.array(node[child]), pa.array(node[up[child]])], ["u", "v"])

    held, n = [], 0
    for batch in batches:
        held.append((batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)))
        n += batch.num_rows
        if n >= HELD:
            yield stars(held)
            held, n = [], 0
    if n:
        yield stars(held)


def connected_components(edges: DataFrame, rounds: int = 60, contracted: bool = False) -> DataFrame:
    """``node, component`` (the smallest node it reaches) of ``a, b`` edges.

    ``contracted`` says that the edges' tasks have sent them through ``contract``.

    First every task contracts its own edges to stars.  Until the whole is a
    forest of stars, two star operations alternate: every node hands its larger
    neighbours, then its smaller ones, to its smallest neighbour.  Both are a
    grouped minimum (pre-aggregated before the shuffle) joined back, so a node
    with very many neighbours is split like any skewed join.  Each round is cut
    from its lineage in the shared folder.
    """
    own = edges.select(F.col("a").cast("long").alias("u"), F.col("b").cast("long").alias("v"))
    now = settle((own if contracted else own.mapInArrow(contract, "u long, v long")).distinct())
    for _ in range(rounds):
        # a forest of stars: every child has one parent, and no parent is a child
        roles = now.select(F.col("u").alias("n"), F.lit(1).alias("child"), F.lit(0).alias("parent")).unionAll(now.select("v", F.lit(0), F.lit(1)))
        state = roles.groupBy("n").agg(F.sum("child").alias("child"), F.max("parent").alias("parent")).agg(F.sum(F.when(F.col("child") + F.col("parent") > 1, 1).otherwise(0)).alias("open"), F.sum("child").alias("edges")).first()
        if not state["open"]:
            break
        now = now.coalesce(max(1, state["edges"] // TASK_EDGES))
        both = now.unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a != b").mapInArrow(contract, "u long, v long")
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("a"), F.col("m").alias("b")).where("a != b")
        now = settle(small.mapInArrow(contract, "u long, v long").distinct())
    else:
        raise RuntimeError("components did not settle")
    tops = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionAll(tops)
