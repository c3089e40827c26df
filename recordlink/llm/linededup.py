"""Line dedup by a sharded minimal perfect hash over line hashes.

1. Each text gives the 128-bit hashes of its distinct keys (trimmed, A-Z lower-cased lines); documents are counted per
   hash, summed within each task first.
2. Hashes of at least ``index_from`` documents are dealt to shards by their top bits.  A task builds one shard: levels of
   bit arrays with ranks (a hash that is alone on its bit keeps it, the others go on to the next level), which number the
   shard's n hashes 0..n-1 without gaps, and beside it a fingerprint and a count array of n entries.  Shards are files in
   the shared folder.
3. The texts are read once more; each chunk's distinct hashes probe the memory-mapped shards.  Nothing is joined or
   shuffled, and the texts never move.

A hash outside the index lands on some entry whose 64-bit fingerprint differs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

GAMMA = 2.0
MASK = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit finaliser of x under a seed."""
    with np.errstate(over="ignore"):
        x = x ^ (np.uint64(seed + 1) * np.uint64(0x9E3779B97F4A7C15))
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))


class PerfectHash:
    """Levels of bits in one array of 64-bit words, with the number of ones before each word."""

    def __init__(self, words: np.ndarray, before: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> None:
        self.words, self.before, self.starts, self.sizes = words, before, starts, sizes

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        """keys: distinct unsigned 64-bit integers."""
        left, words, starts, sizes, at, level = keys, [], [], [], 0, 0
        while len(left):
            n = max(64, int(len(left) * GAMMA) + 63 & ~63)
            slot = mix(left, level) % np.uint64(n)
            hits = np.bincount(slot.astype(np.int64), minlength=n)
            words.append(np.packbits(hits == 1, bitorder="little").view(np.uint64))
            starts.append(at)
            sizes.append(n)
            at += n
            left = left[hits[slot.astype(np.int64)] > 1]
            level += 1
        every = np.concatenate(words) if words else np.empty(0, np.uint64)
        ones = np.bitwise_count(every).astype(np.int64)
        return cls(every, np.cumsum(ones) - ones, np.array(starts, np.int64), np.array(sizes, np.int64))

    def index(self, keys: np.ndarray) -> np.ndarray:
        """0..n-1 for the built keys; another key gets some index or -1."""
        out = np.full(len(keys), -1, np.int64)
        left = np.arange(len(keys))
        for level, (start, n) in enumerate(zip(self.starts.tolist(), self.sizes.tolist(), strict=True)):
            if not len(left):
                break
            bit = start + (mix(keys[left], level) % np.uint64(n)).astype(np.int64)
            word, shift = self.words[bit >> 6], (bit & 63).astype(np.uint64)
            hit = (word >> shift & np.uint64(1)).astype(bool)
            below = word[hit] & ((np.uint64(1) << shift[hit]) - np.uint64(1))
            out[left[hit]] = self.before[bit[hit] >> 6] + np.bitwise_count(below)
            left = left[~hit]
        return out


def line_key(line: bytes) -> bytes:
    return line.strip().lower()


def _hash(key: bytes) -> int:
    return xxhash.xxh3_128_intdigest(key)


def shard_blob(high: np.ndarray, low: np.ndarray, counts: np.ndarray) -> bytes:
    """One shard: hashes (high selects the entry, low is its fingerprint) with their document counts.

    Of hashes with the same upper half the first is indexed, and the others are listed at the shard's end by both halves.
    """
    order = np.lexsort((low, high))
    high, low, counts = high[order], low[order], np.minimum(counts[order], 0xFFFFFFFF)
    again = np.concatenate(([False], high[1:] == high[:-1])) if len(high) else np.zeros(0, bool)
    ph = PerfectHash.build(high[~again])
    at = ph.index(high[~again])
    prints, n = np.empty(len(at), np.uint64), np.empty(len(at), np.uint32)
    prints[at], n[at] = low[~again], counts[~again]
    twins = {"twin_high": high[again], "twin_low": low[again], "twin_counts": counts[again].astype(np.uint32)}
    return common.pack({"words": ph.words, "before": ph.before, "starts": ph.starts, "sizes": ph.sizes, "prints": prints, "counts": n} | twins)


def count_lines(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``(high, low, n)``: the number of documents that hold each non-empty key."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        found: dict[int, int] = {}
        for text in common.text_bytes(part.column(0)):
            for key in {line_key(x) for x in text.split(b"\n")}:
                if key:
                    h = _hash(key)
                    found[h] = found.get(h, 0) + 1
        raw = np.frombuffer(b"".join(h.to_bytes(16, "little") for h in found), np.int64).reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(raw[:, 1].copy()), pa.array(raw[:, 0].copy()), pa.array(list(found.values()), pa.int64())], names=["high", "low", "n"])

    some = common.map_arrow(df.select(F.col(text_col).cast("string").alias("text")), run, "high long, low long, n long")
    return some.groupBy("high", "low").agg(F.sum("n").alias("n"))


def build_index(counted: DataFrame, folder: str, index_from: int, shard_rows: int = 400_000) -> int:
    """Write the shards of the hashes counted at least ``index_from`` times; gives the number of shards (a power of two)."""
    known = common.settle(counted.where(F.col("n") >= index_from))
    bits = max(0, (max(1, known.count()) // shard_rows).bit_length())
    dealt = known.withColumn("shard", F.shiftrightunsigned("high", 64 - bits) if bits else F.lit(0).cast("long")).repartition(1 << bits, "shard")

    def run(batches):
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        t = pa.Table.from_batches(parts)
        shard = np.asarray(t["shard"])
        high, low, n = (np.asarray(t[c]) for c in ("high", "low", "n"))
        for s in np.unique(shard):
            own = shard == s
            common.put_file(f"{folder}/shard-{s}", shard_blob(high[own].view(np.uint64), low[own].view(np.uint64), n[own]))
            yield pa.RecordBatch.from_arrays([pa.array([int(s)], pa.int64())], names=["shard"])

    made = {r["shard"] for r in dealt.mapInArrow(run, "shard long").collect()}  # a number a shard
    for s in set(range(1 << bits)) - made:  # hashes fill all shards but where there are hardly any
        common.put_file(f"{folder}/shard-{s}", shard_blob(np.empty(0, np.uint64), np.empty(0, np.uint64), np.empty(0, np.int64)))
    return 1 << bits


def probe(folder: str, shards: int, high: np.ndarray, low: np.ndarray) -> np.ndarray:
    """The count of each hash, 0 outside the index."""
    out = np.zeros(len(high), np.int64)
    bits = shards.bit_length() - 1
    shard = (high >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(high), np.int64)
    order = np.argsort(shard, kind="stable")
    edges = np.searchsorted(shard[order], np.arange(shards + 1))
    for s in np.unique(shard):
        own = order[edges[s] : edges[s + 1]]
        a = common.unpack(common.map_file(f"{folder}/shard-{s}"))
        if len(a["prints"]):
            at = PerfectHash(a["words"], a["before"], a["starts"], a["sizes"]).index(high[own])
            real = (at >= 0) & (a["prints"][at] == low[own])
            out[own[real]] = a["counts"][at[real]]
        for h, lo, c in zip(a["twin_high"], a["twin_low"], a["twin_counts"], strict=True):
            out[own[(high[own] == h) & (low[own] == lo)]] = c
    return out


def _kept(texts: list[bytes], folder: str, shards: int, min_docs: int) -> list[tuple[int, list[bytes]]]:
    """For each text, its number of lines and the lines that stay."""
    lines = [t.split(b"\n") for t in texts]
    keys = [[line_key(x) for x in each] for each in lines]
    known = list({k for each in keys for k in each if k})
    raw = np.frombuffer(b"".join(_hash(k).to_bytes(16, "little") for k in known), np.uint64).reshape(-1, 2)
    counts = probe(folder, shards, raw[:, 1].copy(), raw[:, 0].copy())
    drop = {known[i] for i in np.flatnonzero(counts >= min_docs)}
    if not drop:
        return [(len(each), each) for each in lines]
    return [(len(each), [x for x, k in zip(each, ks, strict=True) if k not in drop]) for each, ks in zip(lines, keys, strict=True)]


class LineDedup:
    """Counts and index over all texts of ``df``; ``min_docs`` documents make a line common."""

    def __init__(self, df: DataFrame, text_col: str = "text", min_docs: int = 10, index_from: int = 2, shard_rows: int = 400_000) -> None:
        if not 1 <= index_from <= min_docs:
            raise ValueError("index_from lies between 1 and min_docs")
        self.min_docs, self.text_col = min_docs, text_col
        self.folder = common.shared_folder(df.sparkSession, "lines")
        self.shards = build_index(count_lines(df, text_col), self.folder, index_from, shard_rows)

    def apply(self, df: DataFrame, keep: list[str]) -> DataFrame:
        """``keep`` beside ``kept_text``, ``n_lines`` (before), ``n_dropped``.

        A null or empty text is one empty line, which stays; of equal lines all go or all stay, in repeated rows too (each counts as a
        document); texts of any number of lines are handled whole; an empty table gives no rows; kept columns come back under
        free names.
        """
        folder, shards, least = self.folder, self.shards, self.min_docs

        def run(column: pa.Array) -> dict[str, pa.Array]:
            got = _kept(common.text_bytes(column), folder, shards, least)
            return {
                "kept_text": pa.array([b"\n".join(x) for _, x in got], pa.binary()).cast(pa.string()),
                "n_lines": pa.array([n for n, _ in got], pa.int64()),
                "n_dropped": pa.array([n - len(x) for n, x in got], pa.int64()),
            }

        return common.annotate(df, run, {"kept_text": "string", "n_lines": "long", "n_dropped": "long"}, keep, self.text_col)


    def clean(self, df: DataFrame) -> DataFrame:
        """df itself, with what stays of each text in the text column; all other columns, whatever their names, are as they were.

        A null text becomes an empty one.
        """
        folder, shards, least, names = self.folder, self.shards, self.min_docs, df.columns
        at = names.index(self.text_col)

        def run(batches):
            for batch in batches:
                for part in common.chunks(batch, names[at]):
                    got = _kept(common.text_bytes(part.column(at)), folder, shards, least)
                    columns = list(part.columns)
                    columns[at] = pa.array([b"\n".join(x) for _, x in got], pa.binary()).cast(columns[at].type)
                    yield pa.RecordBatch.from_arrays(columns, schema=part.schema)
            common.release()

        return df.mapInArrow(run, df.schema)


def digests(df: DataFrame, min_docs: int = 10) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256."""
    done = LineDedup(df, min_docs=min_docs).apply(df, ["doc_id"])
    return done.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


#: DuckDB: the same table by plain joins.
ORACLE_SQL = r"""
WITH lines AS (
  SELECT row_number() OVER () AS r, doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents
), each_line AS (
  SELECT r, doc_id, unnest(parts) AS line, generate_subscripts(parts, 1) AS pos FROM lines
), keyed AS (
  SELECT *, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM each_line
), common_keys AS (
  SELECT k FROM keyed WHERE k <> '' GROUP BY k HAVING count(DISTINCT r) >= 10
), marked AS (
  SELECT keyed.*, k IN (SELECT k FROM common_keys) AS gone FROM keyed
)
SELECT any_value(doc_id) AS doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY r
"""
