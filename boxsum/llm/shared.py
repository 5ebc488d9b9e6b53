"""What the operators have in common: the folder all executors share, and blocks of Arrow rows."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession

#: Bytes of text that a vectorised kernel takes at once.
BLOCK_BYTES = 1 << 20


def shared_root(spark: SparkSession) -> str:
    """The folder from spark.checkpoint.dir, or that set in the session; a temporary one in local mode alone, where one machine is all."""
    if root := spark.conf.get("spark.checkpoint.dir", None):
        return root
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isEmpty():
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="boxsum-"))
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
    return held.get()


def shared_path(spark: SparkSession, what: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_root(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Take a path of the shared folder away, if it is there."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def cut(df: DataFrame) -> DataFrame:
    """df, computed once and kept in the shared folder."""
    shared_root(df.sparkSession)
    return df.checkpoint(eager=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def blocks(batches: Iterator[pa.RecordBatch], column: str, most: int = BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in slices whose column holds about `most` bytes; a longer value is a slice of its own."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pa.compute.binary_length(batch.column(column)).to_pylist()
        first = held = 0
        for row, size in enumerate(sizes):
            if row > first and held + (size or 0) > most:
                yield batch.slice(first, row - first)
                first, held = row, 0
            held += size or 0
        yield batch.slice(first)
