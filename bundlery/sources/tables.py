"""Reading tables, row identity, and the views that experiments run on."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "csv", "json", "orc", "text")


def checkpoint_folder(spark: SparkSession) -> str:
    """The session's shared checkpoint folder; in local mode a temporary one where none is named."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get()


def reclaim(spark: SparkSession) -> None:
    """Give back the driver's heap, and shuffle files of steps that are over, where the heap has grown past half its limit.

    Plans and task results are short-lived, but the heap grows with them to its limit and
    stays there; what is in use is a small part of it.
    """
    jvm = spark.sparkContext._jvm
    now = jvm.java.lang.Runtime.getRuntime()
    if now.totalMemory() > now.maxMemory() / 2:
        jvm.System.gc()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of a folder of Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A source in one of Spark's formats, with a fixed schema where given."""
    if format not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    reader = spark.read.format(format).options(**{k: str(v) for k, v in options.items()})
    return (reader.schema(schema) if schema else reader).load(path)


def read_database(spark: SparkSession, url: str, table: str, column: str, lower: int, upper: int, parts: int, **options) -> DataFrame:
    """A database table, read by ranges of one numeric column in parallel."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=column, lowerBound=lower, upperBound=upper, numPartitions=parts, **options).load()


def write(df: DataFrame, path: str, format: str = "parquet", mode: str = "errorifexists", by: tuple[str, ...] = ()) -> None:
    """A package, report or run log as files; ``by`` are partition columns."""
    out = df.write.mode(mode).format(format)
    (out.partitionBy(*by) if by else out).save(path)


def with_row_id(df: DataFrame, key: str | None = None) -> DataFrame:
    """``df`` with a stable ``tid``: its unique key, or file and position of stored rows.

    The fallback hashes the file's name into the upper bits over the row's
    position in it, so the id does not depend on scheduling.
    """
    if key:
        return df.withColumn("tid", F.col(key).cast("long"))
    file = F.pmod(F.xxhash64(F.col("_metadata.file_name")), F.lit(1 << 22))
    return df.select("*", (file * (1 << 40) + F.col("_metadata.row_index")).cast("long").alias("tid"))


def hash_sample(df: DataFrame, share: float, seed: int = 0, tid: str = "tid") -> DataFrame:
    """A repeatable sample of about a ``share`` of the rows, by a hash of the row id."""
    grain = 1 << 30
    return df.where(F.pmod(F.xxhash64(F.col(tid), F.lit(seed)), F.lit(grain)) < int(share * grain))


def first_rows(df: DataFrame, n: int, *order) -> DataFrame:
    """The first ``n`` rows by an order, in one part.

    To be collected: a limit that is collected as it stands brings up to ``n`` rows of
    every part to the driver, here a task has merged them.
    """
    return df.orderBy(*order).limit(n).coalesce(1)


def lineitem_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with discount and tax as amounts of money."""
    t = with_row_id(load(spark, sf_dir, "lineitem"))
    price = F.col("l_extendedprice")
    return t.select(
        "tid", F.col("l_quantity").alias("quantity"), price.alias("price"), (price * F.col("l_discount")).alias("discount"), (price * F.col("l_tax")).alias("tax"),
        F.col("l_returnflag").alias("returnflag"), F.col("l_linestatus").alias("linestatus"), F.col("l_shipdate").alias("shipdate"),
    )


def events_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with four numeric attributes; ``sec`` is the second of the day."""
    t = load(spark, sf_dir, "events")
    sec = F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")
    k = F.get_json_object("props", "$.k")
    return t.select(F.col("event_id").alias("tid"), F.col("value").cast("double").alias("value"), k.cast("double").alias("k"), F.col("user_id").cast("double").alias("user_id"), sec.cast("double").alias("sec"), "event_type", "ts")
