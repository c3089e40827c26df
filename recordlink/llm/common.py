"""Arrow batches of texts, tokens as dictionary codes, and files in the shared folder.

Words are runs of bytes outside ``[\\x20\\x09-\\x0D]``; lower-casing touches A-Z only.  Both are
what Arrow's ASCII kernels do, so tokenising stays in C++ and Python sees each distinct word of a
chunk once.
"""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
import zlib
from collections import OrderedDict
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of text handled at once inside a task.
CHUNK_BYTES = 4 << 20


def chunks(batch: pa.RecordBatch, text_col: str = "text", limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about ``limit`` bytes of text each (one row at least)."""
    n = batch.num_rows
    if not n:
        return
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(text_col)), 0).cast(pa.int64()))
    part = (np.cumsum(sizes) - sizes) // limit
    edges = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), n]
    for lo, hi in zip(edges, edges[1:], strict=False):
        yield batch.slice(lo, hi - lo)


def texts(column: pa.Array) -> pa.Array:
    """The texts as large strings, null as empty.

    A slice is copied first: Arrow's cast of one keeps its offset over a buffer of new offsets, and ``ascii_lower`` then reads beside it.
    """
    return pc.fill_null(pa.concat_arrays([column]).cast(pa.large_string()), "")


def text_bytes(column: pa.Array) -> list[bytes]:
    """Each text as UTF-8, null as empty."""
    return texts(column).cast(pa.large_binary()).to_pylist()


@dataclass
class Tokens:
    """``codes[offsets[i]:offsets[i+1]]`` are the words of text i, as indices into ``words``."""

    offsets: np.ndarray
    codes: np.ndarray
    words: pa.Array

    def __len__(self) -> int:
        return len(self.offsets) - 1

    @property
    def lengths(self) -> np.ndarray:
        return np.diff(self.offsets)

    def owner(self) -> np.ndarray:
        """The text that each word belongs to."""
        return np.repeat(np.arange(len(self)), self.lengths)


def tokenize(column: pa.Array, lower: bool = True) -> Tokens:
    text = texts(column)
    split = pc.ascii_split_whitespace(pc.ascii_lower(text) if lower else text)
    offsets = np.asarray(split.offsets).astype(np.int64)
    flat = split.values.slice(offsets[0], offsets[-1] - offsets[0])
    offsets = offsets - offsets[0]
    real = np.asarray(pc.not_equal(flat, ""))
    if not real.all():
        before = np.concatenate(([0], np.cumsum(real)))
        offsets, flat = before[offsets], flat.filter(pa.array(real))
    coded = flat.dictionary_encode()
    return Tokens(offsets, np.asarray(coded.indices), coded.dictionary)


def crc_mod(column: pa.Array, mod: int) -> np.ndarray:
    """crc32 of each id written as text, modulo ``mod``; a null id counts as the empty text."""
    return np.array([zlib.crc32(b"" if v is None else str(v).encode()) % mod for v in column.to_pylist()], dtype=np.int64)


def release() -> None:
    """Give freed memory back: a worker lives on after its task, and the next one's needs may differ."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass


def map_arrow(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch], schema: T.StructType | str, text_col: str = "text", limit: int = CHUNK_BYTES, done: Callable[[], None] | None = None) -> DataFrame:
    """Apply ``fn`` to chunks of bounded text size; it gives a record batch of ``schema`` or None.  ``done`` ends a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, text_col, limit):
                out = fn(part)
                if out is not None and out.num_rows:
                    yield out
        if done:
            done()
        release()

    return df.mapInArrow(run, schema)


def free_names(keep: list[str], out) -> list[tuple[str, str]]:
    """(column, its name beside the outputs) for each kept column: ``_in`` is added until no other column has the name, letter case
    aside."""
    wanted = {c.lower() for c in keep}
    taken, names = {c.lower() for c in out}, []
    for c in keep:
        new = c
        while new.lower() in taken or (new != c and new.lower() in wanted):
            new += "_in"
        taken.add(new.lower())
        names.append((c, new))
    return names


def annotate(df: DataFrame, fn: Callable[[pa.Array], dict[str, pa.Array]], out: dict[str, str], keep: list[str], text_col: str = "text", done: Callable[[], None] | None = None) -> DataFrame:
    """The columns ``keep`` of df beside ``out`` (name: type), which ``fn`` makes from the text column.

    A kept column whose name equals an output's (letter case aside) comes back under a free name (see free_names); columns that
    are not kept are never read.  A null text is an empty one.
    """
    names = free_names(keep, out)
    src = df.select(*[F.col(f"`{c}`").alias(f"k{i}") for i, (c, _) in enumerate(names)], F.col(f"`{text_col}`").cast("string").alias("text"))
    fields = [T.StructField(new, df.schema[old].dataType) for old, new in names]
    schema = T.StructType(fields + T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in out.items())).fields)
    final = [f.name for f in schema.fields]

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        made = fn(part.column(part.num_columns - 1))
        return pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(names))), *(made[c] for c in out)], names=final)

    return map_arrow(src, run, schema, done=done)


# ---------------------------------------------------------------- shared files


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share, as a URI: the session's checkpoint folder.

    Where none is set (tests on one machine) a temporary one is made and set; on a cluster that is an error.
    """
    sc = spark.sparkContext
    at = sc.getCheckpointDir()
    if not at and (conf := sc.getConf().get("spark.checkpoint.dir", "")):
        sc.setCheckpointDir(conf)
        at = sc.getCheckpointDir()
    if not at:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        at = sc.getCheckpointDir()
    return at if "://" in at else "file://" + at.removeprefix("file:")


def shared_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def drop_folder(spark: SparkSession, path: str) -> None:
    """Remove a folder of the shared store, by Spark's own readers of paths."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def settle(df: DataFrame) -> DataFrame:
    """Cut the lineage through the shared folder; what was computed outlives lost executors."""
    shared_root(df.sparkSession)
    return df.checkpoint()


def sweep(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of what has been settled: it does when the driver's garbage is collected, which may be late."""
    gc.collect()
    spark._jvm.System.gc()


def put_file(uri: str, data: bytes) -> None:
    """Write one file as a whole: a repeated or lost task leaves either no file or the full one."""
    where, path = pafs.FileSystem.from_uri(uri)
    where.create_dir(os.path.dirname(path), recursive=True)
    if isinstance(where, pafs.LocalFileSystem):
        tmp = f"{path}.{uuid.uuid4().hex}"
        with open(tmp, "wb") as f:
            f.write(data)
        os.replace(tmp, path)
    else:
        with where.open_output_stream(path) as f:
            f.write(data)


def read_file(uri: str) -> bytes | None:
    """The file's bytes; None if there is none."""
    where, path = pafs.FileSystem.from_uri(uri)
    try:
        with where.open_input_file(path) as f:
            return f.read()
    except FileNotFoundError:
        return None


def drop_file(uri: str) -> None:
    where, path = pafs.FileSystem.from_uri(uri)
    try:
        where.delete_file(path)
    except FileNotFoundError:  # another attempt of the task was faster
        pass


#: Bytes of files from a remote store that a worker keeps; local ones are mapped, and cost nothing.
KEPT_BYTES = 256 << 20
_kept: OrderedDict[str, np.ndarray] = OrderedDict()


def map_file(uri: str) -> np.ndarray:
    """The file's bytes: memory-mapped from a shared folder that is mounted, fetched from any other store (and kept a while)."""
    where, path = pafs.FileSystem.from_uri(uri)
    if isinstance(where, pafs.LocalFileSystem):
        return _map_local(path)
    if uri in _kept:
        _kept.move_to_end(uri)
        return _kept[uri]
    with where.open_input_file(path) as f:
        got = np.frombuffer(f.read(), np.uint8)
    _kept[uri] = got
    while len(_kept) > 1 and sum(len(x) for x in _kept.values()) > KEPT_BYTES:
        _kept.popitem(last=False)
    return got


@lru_cache(maxsize=4096)
def _map_local(path: str) -> np.ndarray:
    # A plain view: every slice of a memmap makes an object of that class.
    return np.memmap(path, dtype=np.uint8, mode="r").view(np.ndarray) if os.path.getsize(path) else np.empty(0, np.uint8)


def pack(arrays: dict[str, np.ndarray]) -> bytes:
    """Arrays as one blob that unpack() views without copying."""
    head, body, at = [], [], 0
    for name, a in arrays.items():
        raw = np.ascontiguousarray(a).tobytes()
        pad = -len(raw) % 8
        head.append(f"{name}:{a.dtype.str}:{at}:{len(a)}")
        body += [raw, b"\0" * pad]
        at += len(raw) + pad
    top = ";".join(head).encode()
    return len(top).to_bytes(8, "little") + top + b"\0" * (-len(top) % 8) + b"".join(body)


def unpack(raw: np.ndarray) -> dict[str, np.ndarray]:
    n = int.from_bytes(raw[:8].tobytes(), "little")
    base, out = 8 + n + -n % 8, {}
    for item in raw[8 : 8 + n].tobytes().decode().split(";"):
        name, kind, at, size = item.split(":")
        dt = np.dtype(kind)
        start = base + int(at)
        out[name] = raw[start : start + int(size) * dt.itemsize].view(dt)
    return out


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
