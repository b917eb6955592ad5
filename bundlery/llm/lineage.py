"""Cutting lineage in the folder that all executors share."""

from __future__ import annotations

import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder of the session; in local mode a temporary one where it names none.

    A cluster must name a folder that all of its machines see.
    """
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get()


def remove_folder(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared store."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def settle(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and go on from those files."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def bucket_count(spark: SparkSession) -> int:
    """Buckets of a packed exchange: four for each shuffle partition."""
    return 4 * max(12, int(spark.conf.get("spark.sql.shuffle.partitions")))


PACKED = "bucket int, body binary"


def packed_batches(bucket: np.ndarray, record: np.ndarray, buckets: int):
    """Deal the rows of a structured array into one binary value per bucket.

    A shuffle then moves a few wide rows in place of millions of narrow ones.
    """
    order = np.argsort(bucket, kind="stable")
    record = record[order]
    edge = np.searchsorted(bucket[order], np.arange(buckets + 1))
    full = np.flatnonzero(edge[1:] > edge[:-1])
    for part in np.array_split(full, max(1, len(record) * record.itemsize >> 24)):
        if len(part):
            yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), pa.array([record[edge[b] : edge[b + 1]].tobytes() for b in part], pa.binary())], ["bucket", "body"])


def bucket_stream(batches, dtype):
    """Records of one bucket after another, from rows sorted by bucket."""
    at, held = None, []
    for batch in batches:
        for b, body in zip(batch.column(0).to_pylist(), batch.column(1)):
            if b != at and held:
                yield at, np.concatenate(held)
                held = []
            at = b
            held.append(np.frombuffer(body.as_buffer(), dtype))
    if held:
        yield at, np.concatenate(held)
