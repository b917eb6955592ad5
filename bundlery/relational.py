"""Relational operators of package work, each as a query with its SQL.

Sub-queries, joins, windows and set operations that users of packages prepare
their rows with, on the given tables.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions.metrics import gap_column
from .operators.expand import BoxTable, boxes_of_points
from .operators.hierarchy import Pyramid, readjust
from .operators.partition import _case, bucket_edges, mean_split_level, profile, scan_line_df
from .sources.tables import events_view, lineitem_view, load
from .streaming.windows import drain, event_stream, window_stats


def gap_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gap as a column over a table of runs: orders, with a bound by their priority."""
    runs = load(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("obj"), (F.col("o_totalprice") * (1 + F.length("o_orderpriority") / 100)).alias("lp"), F.when(F.col("o_orderstatus") == "F", "min").otherwise("max").alias("sense"))
    return runs.select("o_orderkey", F.round(gap_column("obj", "lp", "sense"), 6).alias("gap"))


def runs_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority")
    return t.agg(F.count("*").alias("n"), F.round(F.avg("o_totalprice"), 0).alias("mean"), F.round(F.percentile("o_totalprice", 0.5), 0).alias("median"))


def cube_returnflag(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 0).alias("quantity"))


def topk_alpha(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of too many candidates the worst by objective go first; ties by the smaller key."""
    t = load(spark, sf_dir, "orders").where("o_orderstatus = 'O'")
    return t.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey", "o_totalprice")


def set_ops_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supports of two relaxations: all, common, and only in the first."""
    part = load(spark, sf_dir, "part")
    a = part.orderBy(F.desc("p_retailprice"), "p_partkey").limit(200).select("p_partkey")
    b = part.orderBy(F.desc("p_size"), "p_partkey").limit(200).select("p_partkey")
    kinds = (("union", a.union(b).distinct()), ("intersect", a.intersect(b)), ("except", a.exceptAll(b)))
    out = [t.select(F.lit(k).alias("op"), "p_partkey") for k, t in kinds]
    return out[0].unionByName(out[1]).unionByName(out[2])


def join_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A relation for packages from four tables; sizes decide how they are joined."""
    li, o = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    c, n = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    t = li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, o["o_custkey"] == c["c_custkey"]).join(n, c["c_nationkey"] == n["n_nationkey"])
    return t.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 0).alias("revenue"))


def semi_anti_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with open orders, and those without, by segment."""
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders").where("o_orderstatus = 'O'")
    on = c["c_custkey"] == o["o_custkey"]
    out = [c.join(o, on, how).groupBy("c_mktsegment").agg(F.count("*").alias("n")).select(F.lit(how).alias("side"), "c_mktsegment", "n") for how in ("left_semi", "left_anti")]
    return out[0].unionByName(out[1])


def window_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prefix sums, ranks and neighbours of orders within a customer."""
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    t = load(spark, sf_dir, "orders")
    return t.select(
        "o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(W.unboundedPreceding, 0)), 2).alias("spent"), F.row_number().over(w).cast("long").alias("place"),
        F.round(F.col("o_totalprice") - F.lag("o_totalprice").over(w), 2).alias("step"), F.round(F.var_pop("o_totalprice").over(w.rowsBetween(-2, 0)), 0).alias("spread"),
    )


def json_attr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A numeric attribute from inside JSON, by type of event."""
    return events_view(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("k"), 4).alias("mean_k"), F.max("k").alias("max_k"))


BETAS = (1.0, 4.0, 9.0, 25.0, 64.0)


def downscale_by_beta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows per piece of one scan over a grid of bounds: few rows a piece need a tiny bound."""
    li = load(spark, sf_dir, "lineitem")
    out = None
    for b in BETAS:
        one = scan_line_df(li, "l_quantity", b).agg(F.count("*").alias("pieces"), F.sum("n").alias("n")).select(F.lit(b).alias("beta"), "pieces", F.round(F.col("n") / F.col("pieces"), 4).alias("downscale"))
        out = one if out is None else out.unionByName(one)
    return out


BETA_SQL = f"""WITH RECURSIVE b AS (SELECT unnest([{", ".join(map(str, BETAS))}])::DOUBLE AS beta),
d AS (SELECT CAST(l_quantity AS DOUBLE) AS v, count(*) AS n, row_number() OVER (ORDER BY CAST(l_quantity AS DOUBLE)) AS i FROM lineitem GROUP BY 1),
s AS (SELECT beta, i, n, CAST(0 AS BIGINT) AS piece, CAST(n AS DOUBLE) AS w, n * v AS s1, n * v * v AS s2 FROM d, b WHERE i = 1
UNION ALL SELECT s.beta, d.i, d.n, s.piece + t.cut, CASE WHEN t.cut = 1 THEN 0 ELSE s.w END + d.n, CASE WHEN t.cut = 1 THEN 0 ELSE s.s1 END + d.n * d.v, CASE WHEN t.cut = 1 THEN 0 ELSE s.s2 END + d.n * d.v * d.v
FROM s JOIN d ON d.i = s.i + 1, LATERAL (SELECT CASE WHEN (s.s2 + d.n * d.v * d.v) / (s.w + d.n) - power((s.s1 + d.n * d.v) / (s.w + d.n), 2) > s.beta THEN 1 ELSE 0 END AS cut) t)
SELECT beta, max(piece) + 1 AS pieces, round(CAST(sum(n) AS DOUBLE) / (max(piece) + 1), 4) AS downscale FROM s GROUP BY beta"""


def mean_split_level2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups after two rounds of mean splits."""
    now = lineitem_view(spark, sf_dir).select("quantity", "price").withColumn("gid", F.lit(1).cast("long")).withColumn("open", F.lit(True))
    for _ in range(2):
        now = mean_split_level(now, ["quantity", "price"], 1.0)
    return now.groupBy("gid").agg(F.count("*").alias("cnt"), F.round(F.avg("price"), 2).alias("price"))


MEAN2_SQL = """WITH a AS (SELECT l_extendedprice AS p, CASE WHEN l_extendedprice > avg(l_extendedprice) OVER () THEN 3 ELSE 2 END AS g FROM lineitem),
b AS (SELECT p, 2 * g + CASE WHEN p > avg(p) OVER (PARTITION BY g) THEN 1 ELSE 0 END AS gid FROM a)
SELECT CAST(gid AS BIGINT) AS gid, count(*) AS cnt, round(avg(p), 2) AS price FROM b GROUP BY gid"""


def bucket_reps_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Representatives of equal-width buckets."""
    df = lineitem_view(spark, sf_dir).select("price", "quantity")
    s = profile(df, ["price"])["price"]
    edges = bucket_edges(df, "price", s, -(-s["n"] // 24))
    return df.select(_case(F.col("price"), edges).cast("long").alias("bucket"), "price", "quantity").groupBy("bucket").agg(F.count("*").alias("cnt"), F.round(F.avg("price"), 2).alias("price"), F.round(F.avg("quantity"), 4).alias("quantity"))


REPS_SQL = """WITH s AS (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, ceil(count(*) / 24.0) AS most FROM lineitem),
c AS (SELECT CAST(least(511, floor((l_extendedprice - lo) / (hi - lo) * 512)) AS BIGINT) AS cell, l_extendedprice AS p, l_quantity AS q FROM lineitem, s),
b AS (SELECT k, cell // (512 // k) AS bucket, count(*) AS cnt FROM c, (SELECT unnest([32, 64, 128, 256, 512]) AS k) GROUP BY 1, 2),
m AS (SELECT coalesce(min(k), 512) AS k FROM (SELECT k, max(cnt) AS top FROM b GROUP BY k) WHERE top <= (SELECT most FROM s))
SELECT cell // (512 // (SELECT k FROM m)) AS bucket, count(*) AS cnt, round(avg(p), 2) AS price, round(avg(q), 4) AS quantity FROM c GROUP BY 1"""


def first_split_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first split of a partition: a scan of the retail prices."""
    return scan_line_df(load(spark, sf_dir, "part"), "p_retailprice", 400.0).select("piece", F.round("lo", 4).alias("lo"), F.round("hi", 4).alias("hi"), "n")


FIRST_SQL = """WITH RECURSIVE d AS (SELECT p_retailprice AS v, count(*) AS n, row_number() OVER (ORDER BY p_retailprice) AS i FROM part GROUP BY 1),
s AS (SELECT i, v, n, CAST(0 AS BIGINT) AS piece, CAST(n AS DOUBLE) AS w, 0.0::DOUBLE AS s1, 0.0::DOUBLE AS s2, v AS base FROM d WHERE i = 1
UNION ALL SELECT d.i, d.v, d.n, s.piece + t.cut, CASE WHEN t.cut = 1 THEN 0 ELSE s.w END + d.n, CASE WHEN t.cut = 1 THEN 0 ELSE s.s1 + d.n * (d.v - s.base) END,
  CASE WHEN t.cut = 1 THEN 0 ELSE s.s2 + d.n * (d.v - s.base) * (d.v - s.base) END, CASE WHEN t.cut = 1 THEN d.v ELSE s.base END
FROM s JOIN d ON d.i = s.i + 1, LATERAL (SELECT CASE WHEN (s.s2 + d.n * (d.v - s.base) * (d.v - s.base)) / (s.w + d.n) - power((s.s1 + d.n * (d.v - s.base)) / (s.w + d.n), 2) > 400 THEN 1 ELSE 0 END AS cut) t)
SELECT piece, round(min(v), 4) AS lo, round(max(v), 4) AS hi, CAST(sum(n) AS BIGINT) AS n FROM s GROUP BY piece"""


def readjusted_reps_flag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Representatives over the rows of a predicate; groups without such rows vanish."""
    df = lineitem_view(spark, sf_dir).select("tid", "price", "quantity", "returnflag", F.lit(1).cast("long").alias("w"))
    placed = df.withColumn("gid_up", F.floor(F.col("price") / 5000).cast("long"))
    boxes = placed.groupBy("gid_up").agg(F.avg("price").alias("price"), F.avg("quantity").alias("quantity"), F.sum("w").alias("w"))
    table = boxes.select(F.col("gid_up").alias("gid"), F.array(F.col("gid_up") * 5000.0).alias("lo"), F.array((F.col("gid_up") + 1) * 5000.0).alias("hi"))
    top = boxes.select(F.col("gid_up").alias("tid"), "price", "quantity", "w", F.lit(None).cast("long").alias("gid_up"))
    p = readjust(Pyramid([placed, top], [table], ["price"], [0, 0], 1.0), "returnflag = 'R' and quantity > 45 and price > 60000")
    return p.groups[0].select("gid", "cnt", F.round("price", 2).alias("price"), F.round("quantity", 4).alias("quantity"))


def _pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes of the scan of quantities: each piece up to where the next one begins."""
    scan = scan_line_df(load(spark, sf_dir, "lineitem"), "l_quantity", 4.0)
    w = W.orderBy("piece")  # one row a piece
    lo = F.when(F.col("piece") == 0, F.lit(float("-inf"))).otherwise(F.col("lo"))
    return scan.select(F.col("piece").alias("gid"), F.array(lo).alias("lo"), F.array(F.coalesce(F.lead("lo").over(w), F.lit(float("inf")))).alias("hi"), F.col("n").alias("cnt"))


def neighbour_points_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The groups beside each group, by probes just outside its box."""
    t = BoxTable.of(_pieces(spark, sf_dir).withColumn("obj", F.lit(0.0)).toPandas())
    rows = [(int(t.gid[g]), int(t.gid[i])) for g in range(len(t.gid)) for i in t.neighbours(g, 0.5)]
    return spark.createDataFrame(rows, "gid long, neighbour long")


def group_lookup_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The group of each point, by a join with boxes."""
    points = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("pid"), F.array(F.col("p_size").cast("double") + 0.25).alias("p"))
    return boxes_of_points(points, _pieces(spark, sf_dir)).select("pid", F.col("gid").cast("long").alias("gid"))


PIECES_SQL = """WITH RECURSIVE d AS (SELECT CAST(l_quantity AS DOUBLE) AS v, count(*) AS n, row_number() OVER (ORDER BY CAST(l_quantity AS DOUBLE)) AS i FROM lineitem GROUP BY 1),
s AS (SELECT i, v, CAST(0 AS BIGINT) AS piece, CAST(n AS DOUBLE) AS w, n * v AS s1, n * v * v AS s2 FROM d WHERE i = 1
UNION ALL SELECT d.i, d.v, s.piece + t.cut, CASE WHEN t.cut = 1 THEN 0 ELSE s.w END + d.n, CASE WHEN t.cut = 1 THEN 0 ELSE s.s1 END + d.n * d.v, CASE WHEN t.cut = 1 THEN 0 ELSE s.s2 END + d.n * d.v * d.v
FROM s JOIN d ON d.i = s.i + 1, LATERAL (SELECT CASE WHEN (s.s2 + d.n * d.v * d.v) / (s.w + d.n) - power((s.s1 + d.n * d.v) / (s.w + d.n), 2) > 4 THEN 1 ELSE 0 END AS cut) t),
p AS (SELECT piece, min(v) AS lo FROM s GROUP BY piece)"""

OFFERS = """SELECT c_custkey, o AS offer, 1 + o * 2 + (c_custkey + o) % 5 AS cost, 3 * o + (c_custkey * o) % 7 AS gain FROM customer, (SELECT unnest([1, 2, 3]) AS o)"""


def offers_best(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best of three offers for each person: one row a person is left for the package."""
    c = load(spark, sf_dir, "customer").select("c_custkey", F.explode(F.array(*[F.lit(i) for i in (1, 2, 3)])).alias("offer"))
    o = c.select("c_custkey", "offer", (1 + F.col("offer") * 2 + (F.col("c_custkey") + F.col("offer")) % 5).cast("long").alias("cost"), (3 * F.col("offer") + (F.col("c_custkey") * F.col("offer")) % 7).cast("long").alias("gain"))
    w = W.partitionBy("c_custkey").orderBy(F.desc(F.col("gain") / F.col("cost")), "offer")
    return o.withColumn("r", F.row_number().over(w)).where("r = 1").select("c_custkey", F.col("offer").cast("long").alias("offer"), "cost", "gain")


def stream_window_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics of days, from the events as a stream."""
    got = drain(window_stats(event_stream(spark, sf_dir), ["value"]))
    return got.select(F.date_format(F.to_utc_timestamp("start", F.current_timezone()), "yyyy-MM-dd").alias("day"), "n", F.round("mean_value", 4).alias("mean"), F.round("std_value", 4).alias("std"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        gap_table, runs_rollup, cube_returnflag, topk_alpha, set_ops_support, join_base, semi_anti_groups, window_prefix, json_attr, downscale_by_beta, mean_split_level2,
        bucket_reps_price, first_split_price, readjusted_reps_flag, neighbour_points_1d, group_lookup_1d, offers_best, stream_window_stats,
    )
}

ORACLE_SQL: dict[str, str] = {
    "gap_table": "SELECT o_orderkey, round(CASE WHEN o_orderstatus = 'F' THEN (o_totalprice + 0.1) / (o_totalprice * (1 + length(o_orderpriority) / 100.0) + 0.1) ELSE (o_totalprice * (1 + length(o_orderpriority) / 100.0) + 0.1) / (o_totalprice + 0.1) END, 6) AS gap FROM orders",
    "runs_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(avg(o_totalprice), 0) AS mean, round(quantile_cont(o_totalprice, 0.5), 0) AS median FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "cube_returnflag": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 0) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "topk_alpha": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'O' ORDER BY o_totalprice DESC, o_orderkey LIMIT 100",
    "set_ops_support": """WITH a AS (SELECT p_partkey FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 200), b AS (SELECT p_partkey FROM part ORDER BY p_size DESC, p_partkey LIMIT 200)
SELECT 'union' AS op, p_partkey FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', p_partkey FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', p_partkey FROM (SELECT * FROM a EXCEPT SELECT * FROM b)""",
    "join_base": "SELECT n_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 0) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "semi_anti_groups": "SELECT side, c_mktsegment, count(*) AS n FROM (SELECT c_mktsegment, CASE WHEN c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'O') THEN 'left_semi' ELSE 'left_anti' END AS side FROM customer) GROUP BY 1, 2",
    "window_prefix": """SELECT o_orderkey, round(sum(o_totalprice) OVER (w ROWS UNBOUNDED PRECEDING), 2) AS spent, row_number() OVER w AS place, round(o_totalprice - lag(o_totalprice) OVER w, 2) AS step,
round(var_pop(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 0) AS spread FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""",
    "json_attr": "SELECT event_type, count(*) AS n, round(avg(k), 4) AS mean_k, max(k) AS max_k FROM (SELECT event_type, CAST(regexp_extract(props, '([0-9]+)', 1) AS DOUBLE) AS k FROM events) GROUP BY event_type",
    "downscale_by_beta": BETA_SQL,
    "mean_split_level2": MEAN2_SQL,
    "bucket_reps_price": REPS_SQL,
    "first_split_price": FIRST_SQL,
    "readjusted_reps_flag": "SELECT CAST(floor(l_extendedprice / 5000) AS BIGINT) AS gid, count(*) AS cnt, round(avg(l_extendedprice), 2) AS price, round(avg(l_quantity), 4) AS quantity FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 45 AND l_extendedprice > 60000 GROUP BY 1",
    "neighbour_points_1d": PIECES_SQL + " SELECT a.piece AS gid, b.piece AS neighbour FROM p a JOIN p b ON abs(a.piece - b.piece) = 1",
    "group_lookup_1d": PIECES_SQL + " SELECT p_partkey AS pid, (SELECT max(piece) FROM p WHERE p.piece = 0 OR p.lo <= p_size + 0.25) AS gid FROM part",
    "offers_best": f"SELECT c_custkey, CAST(offer AS BIGINT) AS offer, CAST(cost AS BIGINT) AS cost, CAST(gain AS BIGINT) AS gain FROM (SELECT *, row_number() OVER (PARTITION BY c_custkey ORDER BY gain / cost DESC, offer) AS r FROM ({OFFERS})) WHERE r = 1",
    "stream_window_stats": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n, round(avg(value), 4) AS mean, round(stddev_pop(value), 4) AS std FROM events GROUP BY 1",
}
