"""Cutting lineage through the folder that driver and executors share."""

from __future__ import annotations

import os
import tempfile
import uuid

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The session's checkpoint folder; where none is set on one machine, a temporary one, and an error on a cluster."""
    sc = spark.sparkContext
    at = sc.getCheckpointDir()
    if not at and (conf := sc.getConf().get("spark.checkpoint.dir", "")):
        sc.setCheckpointDir(conf)
        at = sc.getCheckpointDir()
    if not at:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        at = sc.getCheckpointDir()
    return at


def shared_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame) -> DataFrame:
    """A checkpoint: computed once, kept apart from executors."""
    shared_root(df.sparkSession)
    return df.checkpoint()


def keep(df: DataFrame) -> DataFrame:
    """As settle, in compressed Parquet: a checkpoint holds its rows as they lie in memory, which vectors fill mostly with zeros."""
    path = shared_folder(df.sparkSession, "kept")
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.parquet(path)


def _store(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri.removeprefix('file:')}")


def put_batch(uri: str, batch: pa.RecordBatch) -> None:
    """One batch as a compressed file; names are never used twice, so a lost task's file is only left over."""
    where, path = _store(uri)
    where.create_dir(os.path.dirname(path), recursive=True)
    with where.open_output_stream(path) as f, pa.ipc.new_stream(f, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(batch)


def get_batch(uri: str) -> pa.RecordBatch:
    where, path = _store(uri)
    with where.open_input_stream(path) as f, pa.ipc.open_stream(f) as r:
        return r.read_next_batch()
