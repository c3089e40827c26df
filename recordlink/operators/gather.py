"""Candidates from vectors: exact search (flat, grid, pruned), cells, forests, hashing, density clusters.

All give (qid, rid, rank, sim), nearest first, ties by rid.  Inputs are (qid, vec) and (rid, vec).
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.vectors import arrow_matrix, block_similarity, block_top, dot, matrix, similarity, unit
from ..sources.shared import get_batch, put_batch, settle, shared_folder
from .graph import connected

CANDS = "qid long, rid long, rank int, sim double"
#: A reference of at most so many bytes as doubles may be sent to every task.
BROADCAST_BYTES = 64 << 20
#: Rows of a side in one block of the grid; 4096 x 4096 similarities are 128 MB.
BLOCK_ROWS = 4096


def _check(k: int, m: int | None = None) -> None:
    if k < 1:
        raise ValueError("k is at least 1")


def merge_top(cands: DataFrame, k: int) -> DataFrame:
    """The k best of each query over all its partial lists; a pair found twice counts once."""
    best = cands.groupBy("qid", "rid").agg(F.max("sim").alias("sim"))
    return rank_top(best, k)


def rank_top(scored: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("qid").orderBy(F.desc("sim"), "rid")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rid", "rank", "sim")


def _block_files(ref: DataFrame, rows: int, cols: tuple[str, ...] = ("vec",)) -> list[tuple[str, int, int]]:
    """(file, rows, dimensions) of the reference's blocks (rid and ``cols``, lists) in the shared folder; the list has an entry a block."""
    folder = shared_folder(ref.sparkSession, "vectors")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def put(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
            one = pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
            name = f"{folder}/{uuid.uuid4().hex}"
            put_batch(name, one)
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(one)]), pa.array([len(one.column(1)[0])])], names=["file", "n", "d"])

        held, n = [], 0
        for whole in batches:
            lo = 0
            while lo < whole.num_rows:
                part = whole.slice(lo, rows - n)
                held.append(part)
                lo, n = lo + len(part), n + len(part)
                if n == rows:
                    yield put(held)
                    held, n = [], 0
        if held:
            yield put(held)

    made = ref.select(F.col("rid").cast("long").alias("rid"), *cols).mapInArrow(run, "file string, n long, d long").collect()
    return sorted((r["file"], r["n"], r["d"]) for r in made)


def knn_exact(q: DataFrame, ref: DataFrame, k: int = 5, metric: str = "cosine", exclude_self: bool = False, broadcast_bytes: int = BROADCAST_BYTES, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """The k most similar reference rows of every query.

    The reference is computed once, into compressed files of ``block_rows`` rows in the shared folder.  One of at most
    ``broadcast_bytes`` goes through the driver, which holds it twice for a moment, to every task; past a larger one's files each task
    leads its queries, so that neither side is written more than once.  Both give the same rows.
    """
    _check(k)
    files = _block_files(ref, block_rows)
    if sum(n * d * 8 for _, n, d in files) <= broadcast_bytes:
        return _knn_broadcast(q, [f for f, _, _ in files], k, metric, exclude_self)
    return _knn_files(q, [f for f, _, _ in files], k, metric, exclude_self)


def once(df: DataFrame) -> DataFrame:
    """df computed into the shared folder, unless it already lies in files or checkpoints: encoders run once."""
    plan = df._jdf.queryExecution().optimizedPlan()
    while plan.children().size() == 1 and plan.nodeName() == "Project":
        plan = plan.children().apply(0)
    return df if plan.children().isEmpty() else settle(df)


def spread(df: DataFrame, by: str) -> DataFrame:
    """Rows dealt to all cores: few bytes, which Spark would keep in one or two partitions, can be much work."""
    spark = df.sparkSession
    return df.repartition(max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions", "200"))), by)


def _load(file: str) -> tuple[np.ndarray, np.ndarray]:
    b = get_batch(file)
    return b.column(0).to_numpy(), arrow_matrix(b.column(1))


def _knn_broadcast(q: DataFrame, files: list[str], k: int, metric: str, exclude_self: bool) -> DataFrame:
    parts = [_load(f) for f in files] or [(np.empty(0, np.int64), np.empty((0, 0)))]
    shared = q.sparkSession.sparkContext.broadcast((np.concatenate([a for a, _ in parts]), np.concatenate([b for _, b in parts])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rid, r = shared.value
        y = unit(r) if metric == "cosine" else r  # once a task, not once a block
        for whole in batches:
            for lo in range(0, whole.num_rows if len(rid) else 0, 1024):
                part = whole.slice(lo, 1024)
                x = arrow_matrix(part.column(1))
                s = np.round(unit(x) @ y.T, 9) if metric == "cosine" else block_similarity(x, y, metric)
                got = block_top(part.column(0).to_numpy().astype(np.int64), rid, s, k, exclude_self)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in got], names=["qid", "rid", "rank", "sim"])

    return spread(q.select(F.col("qid").cast("long").alias("qid"), "vec"), "qid").mapInArrow(run, CANDS)


def _frame(cols: tuple[np.ndarray, ...]) -> pd.DataFrame:
    return pd.DataFrame(dict(zip(("qid", "rid", "rank", "sim"), cols, strict=True)))


#: Queries that a task leads past the blocks at once.
LED_ROWS = 2048


def _reach(x: np.ndarray, y: np.ndarray, metric: str, least: np.ndarray, k: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, column, similarity in nine decimals) of all pairs that reach the row's ``least``, or with ``k`` the k-th of this block,
    should that be more.  Cosines (of unit rows) are sifted in single precision, with its error to spare, and computed in double."""
    if metric == "cosine":
        slack = (x.shape[1] + 8) * 1.2e-7
        s = x.astype(np.float32) @ y.astype(np.float32).T
    else:
        slack, s = 0.0, block_similarity(x, y, metric)
    if k is not None and k < s.shape[1] and not np.isfinite(least).all():
        least = np.maximum(least, np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k] - slack)
    row, col = np.nonzero(s >= (least - slack)[:, None])
    if metric != "cosine":
        return row, col, s[row, col]
    sim = np.empty(len(row))
    for lo in range(0, len(row), 1 << 14):
        hi = lo + (1 << 14)
        sim[lo:hi] = np.einsum("ij,ij->i", x[row[lo:hi]], y[col[lo:hi]])
    return row, col, np.round(sim, 9)


def _led(q: DataFrame, files: list[str], metric: str, visit) -> DataFrame:
    """``visit(qid, x, blocks)`` gives (qid, rid, rank, sim) for chunks of queries, blocks being (rid, y) of each file in turn."""
    scaled = unit if metric == "cosine" else (lambda x: x)
    return _lead(q, ("vec",), files, lambda parts: scaled(np.concatenate([arrow_matrix(p.column(1)) for p in parts])), lambda b: scaled(arrow_matrix(b.column(1))), visit)


def _lead(q: DataFrame, cols: tuple[str, ...], files: list[str], asked, stored, visit) -> DataFrame:
    """Chunks of queries led past all files: ``visit(qid, asked(batches), blocks)``, blocks being (rid, ``stored(batch)``).

    Each chunk reads every file, so queries lie in no more tasks than cores need: chunks are as large as ``LED_ROWS`` lets them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def blocks():
            for f in files:
                b = get_batch(f)
                yield b.column(0).to_numpy(), stored(b)

        def led(parts: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for got in visit(np.concatenate([p.column(0).to_numpy() for p in parts]), asked(parts), blocks()):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in got], names=["qid", "rid", "rank", "sim"])

        held, n = [], 0
        for whole in batches:
            for lo in range(0, whole.num_rows, 512):
                held.append(whole.slice(lo, 512))
                n += len(held[-1])
                if n >= LED_ROWS:
                    yield from led(held)
                    held, n = [], 0
        if held:
            yield from led(held)

    every = q.select(F.col("qid").cast("long").alias("qid"), *cols)
    return every.repartition(2 * q.sparkSession.sparkContext.defaultParallelism, "qid").mapInArrow(run, CANDS)


class _Best:
    """The k best of each query so far, ties by rid; ``least`` is what a further pair has to reach."""

    def __init__(self, qid: np.ndarray, k: int) -> None:
        self.qid, self.k = qid, k
        self.row, self.ids, self.sim = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
        self.least = np.full(len(qid), -np.inf)

    def add(self, row: np.ndarray, ids: np.ndarray, sim: np.ndarray) -> None:
        row, ids, sim = np.concatenate((self.row, row)), np.concatenate((self.ids, ids)), np.concatenate((self.sim, sim))
        order = np.lexsort((ids, -sim, row))
        row, ids, sim = row[order], ids[order], sim[order]
        rank = np.arange(len(row)) - np.searchsorted(row, row)
        self.row, self.ids, self.sim, rank = (c[rank < self.k] for c in (row, ids, sim, rank))
        last = rank == self.k - 1
        self.least[self.row[last]] = self.sim[last] - 1e-9

    def result(self) -> tuple[np.ndarray, ...]:
        return self.qid[self.row], self.ids, (np.arange(len(self.row)) - np.searchsorted(self.row, self.row) + 1).astype(np.int32), self.sim


def _knn_files(q: DataFrame, files: list[str], k: int, metric: str, exclude_self: bool) -> DataFrame:
    def visit(qid, x, blocks):
        best = _Best(qid, k)
        for rid, y in blocks:
            i, j, s = _reach(x, y, metric, best.least, k + exclude_self)
            if exclude_self:
                i, j, s = (c[qid[i] != rid[j]] for c in (i, j, s))
            best.add(i, rid[j], s)
        yield best.result()

    return _led(q, files, metric, visit)


def _cell_top(p: DataFrame, r: DataFrame, keys: list[str], k: int, metric: str, exclude_self: bool = False) -> DataFrame:
    """The k best of each query within its cells: rows of both sides meet by equal keys."""

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"qid": [], "rid": [], "rank": [], "sim": []})
        rid, y = b["rid"].to_numpy(np.int64), matrix(b["vec"])
        out = []
        for lo in range(0, len(a), 1024):
            part = a.iloc[lo : lo + 1024]
            out.append(_frame(block_top(part["qid"].to_numpy(np.int64), rid, block_similarity(matrix(part["vec"]), y, metric), k, exclude_self)))
        return pd.concat(out)

    return p.groupBy(*keys).cogroup(r.groupBy(*keys)).applyInPandas(run, CANDS)


def knn_sql(q: DataFrame, ref: DataFrame, k: int = 5, metric: str = "cosine", exclude_self: bool = False) -> DataFrame:
    """The same by SQL expressions over all pairs: a check on the block engines, for small inputs."""
    _check(k)
    b = ref.select("rid", F.col("vec").alias("rv"))
    pairs = q.select("qid", F.col("vec").alias("qv")).crossJoin(b)
    if exclude_self:
        pairs = pairs.where("qid != rid")
    return rank_top(pairs.select("qid", "rid", F.round(similarity(F.col("qv"), F.col("rv"), metric), 9).alias("sim")), k)


#: Pairs of a key that one task may make; a key with more is dealt to several.
PAIRS_PER_PART = 1 << 20


def pairs_by_key(a: DataFrame, b: DataFrame, key: str, a_id: str = "qid", pairs: int = PAIRS_PER_PART) -> DataFrame:
    """The equi-join of two posting tables on ``key``, keys that stand in many rows of both sides split: the rows of a are dealt
    to as many parts as the key's pairs need, and each part meets the key's rows of b.  Counts are joined, not collected."""
    n = a.groupBy(key).agg(F.count("*").alias("_a")).join(b.groupBy(key).agg(F.count("*").alias("_b")), key)
    parts = n.select(key, F.least(F.ceil(F.col("_a") * F.col("_b") / pairs), F.col("_a")).cast("int").alias("_parts"))
    left = a.join(parts, key).withColumn("_part", F.pmod(F.xxhash64(a_id), F.col("_parts")).cast("int")).drop("_parts")
    right = b.join(parts, key).withColumn("_part", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))).drop("_parts")
    spark = a.sparkSession
    wide = max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    return left.repartition(wide, key, "_part").join(right.hint("shuffle_hash"), [key, "_part"]).drop("_part")


@dataclass
class _Postings:
    """Rows of a block as postings: ``row`` has ``key`` with ``weight``; ``square`` is each row's sum of squared weights."""

    row: np.ndarray
    key: pa.Array
    weight: np.ndarray
    square: np.ndarray

    @classmethod
    def of(cls, parts: list[pa.RecordBatch]) -> _Postings:
        size = np.concatenate([np.asarray(pc.list_value_length(p.column(1))) for p in parts])
        row = np.repeat(np.arange(len(size)), size)
        weight = np.concatenate([np.asarray(p.column(2).flatten()) for p in parts])
        return cls(row, pa.concat_arrays([p.column(1).flatten() for p in parts]), weight, np.bincount(row, weight * weight, len(size)))


#: A key is multiplied out as a column of two matrices if at least one in so many pairs of rows has it, else pair by pair.
DENSE_SHARE, DENSE_KEYS, PAIRS_AT_ONCE = 256, 1024, 1 << 22


def _dots(a: _Postings, b: _Postings, rows: np.ndarray | None = None, count: bool = False) -> np.ndarray:
    """The sums of products of all rows of a (or of ``rows``) with all rows of b over their common keys, or with ``count`` the
    numbers of these."""
    words = pc.unique(b.key)
    at, bt = (np.asarray(pc.fill_null(pc.index_in(x.key, value_set=words), -1)) for x in (a, b))
    back = np.full(len(a.square), -1)
    back[np.arange(len(back)) if rows is None else rows] = np.arange(len(back) if rows is None else len(rows))
    use = (at >= 0) & (back[a.row] >= 0)
    ar, at, aw = back[a.row[use]], at[use], np.ones(int(use.sum())) if count else a.weight[use]
    br, bw = b.row, np.ones(len(bt)) if count else b.weight
    n, m, v = int(back.max(initial=-1)) + 1, len(b.square), len(words)
    na, nb = np.bincount(at, minlength=v), np.bincount(bt, minlength=v)
    out = np.zeros((n, m))
    dense = na * nb * DENSE_SHARE >= max(1, n * m)
    column = np.cumsum(dense) - 1
    for lo in range(0, int(dense.sum()), DENSE_KEYS):
        own = dense & (column >= lo) & (column < lo + DENSE_KEYS)
        width = int(own.sum())
        x, y = own[at], own[bt]
        left = np.bincount(ar[x] * width + column[at[x]] - lo, aw[x], n * width).reshape(n, width)
        right = np.bincount(br[y] * width + column[bt[y]] - lo, bw[y], m * width).reshape(m, width)
        out += left @ right.T
    rest = ~dense[at]
    ar, at, aw = ar[rest], at[rest], aw[rest]
    order = np.argsort(bt, kind="stable")
    start, reps = np.cumsum(nb) - nb, nb[at]
    ends = np.cumsum(reps)
    lo = 0
    while lo < len(at):
        hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] - reps[lo] + PAIRS_AT_ONCE, side="right")))
        r = reps[lo:hi]
        i = np.repeat(np.arange(lo, hi), r)
        j = order[np.repeat(start[at[lo:hi]], r) + np.arange(len(i)) - np.repeat(np.cumsum(r) - r, r)]
        np.add.at(out.reshape(-1), ar[i] * m + br[j], aw[i] * bw[j])
        lo = hi
    return out


def _table(p: _Postings, words: pa.Array) -> tuple[np.ndarray, float]:
    """The rows of p over ``words`` as a matrix, and how much longer one is at most than by its ``square`` (1, unless a row repeats a key)."""
    at = np.asarray(pc.fill_null(pc.index_in(p.key, value_set=words), -1))
    use, n, w = at >= 0, len(p.square), len(words)
    out = np.bincount(p.row[use] * w + at[use], p.weight[use], n * w).reshape(n, w)
    long = np.sqrt(np.einsum("ij,ij->i", out, out) / np.where(p.square > 0, p.square, 1))
    return out, float(max(1.0, long.max(initial=1.0)))


def _scaled(x: np.ndarray, square: np.ndarray) -> np.ndarray:
    return (x / np.sqrt(np.where(square > 0, square, 1))[:, None]).astype(np.float32)


def knn_sparse(qpost: DataFrame, rpost: DataFrame, k: int = 5, key: str = "bucket", weight: str = "weight", block_rows: int = BLOCK_ROWS // 2) -> DataFrame:
    """Cosine over sparse rows (id, key, weight), among the pairs with a common key.

    The reference's postings are written once, by rows, into compressed block files; each task leads its queries past them and sums the
    products of common keys, so that pairs are neither written nor sent.  Postings dealt by their id are not dealt again.  Where a chunk of
    queries has at most ``DENSE_KEYS`` keys, all its pairs are sifted by one product of matrices in single precision.
    """
    _check(k)
    by_row = lambda df, i: df.groupBy(i).agg(F.collect_list(F.struct(F.col(key).alias("key"), F.col(weight).cast("double").alias("weight"))).alias("p")).select(i, "p.key", "p.weight")
    files = [f for f, _, _ in _block_files(by_row(rpost, "rid"), block_rows, ("key", "weight"))]

    def in_nine(dots, size):
        sim = np.where(size > 0, dots / np.where(size > 0, size, 1), 0.0)
        return np.copysign(np.floor(np.abs(sim) * 1e9 + 0.5) / 1e9, sim)

    def plain(best, a, rid, b, rows):
        dots, least = _dots(a, b, rows), best.least[rows]
        scale = np.sqrt(a.square[rows])[:, None] * np.sqrt(b.square)
        s = np.where(dots != 0, dots / np.where(scale > 0, scale, 1), -np.inf)
        kth = np.partition(s, max(0, s.shape[1] - k), axis=1)[:, max(0, s.shape[1] - k)]
        # Sums of zero count where there is a common key; they matter only to queries without k better ones.
        short = np.flatnonzero(np.maximum(least, kth) <= 1e-9)
        if len(short):
            s[short] = np.where((dots[short] == 0) & (_dots(a, b, rows[short], True) > 0), 0.0, s[short])
            kth[short] = np.partition(s[short], max(0, s.shape[1] - k), axis=1)[:, max(0, s.shape[1] - k)]
        if s.shape[1] < k:
            kth[:] = -np.inf
        i, j = np.nonzero((s >= np.maximum(least, kth - 1e-9)[:, None] - 1e-9) & (s > -np.inf))
        best.add(rows[i], rid[j], in_nine(dots[i, j], np.sqrt(a.square[rows[i]] * b.square[j])))

    def visit(qid, a, blocks):
        best, words, every = _Best(qid, k), pc.unique(a.key), np.arange(len(qid))
        few = 0 < len(words) <= DENSE_KEYS
        if few:
            x, x_long = _table(a, words)
            x_unit = _scaled(x, a.square)
        for rid, b in blocks:
            if not few:
                plain(best, a, rid, b, every)
                continue
            # Cosines are sifted in single precision, with its error to spare, and computed in double.
            y, y_long = _table(b, words)
            slack = (len(words) + 8) * 1.2e-7 * x_long * y_long
            s = x_unit @ _scaled(y, b.square).T
            floor, m = best.least.copy(), s.shape[1]
            fresh = np.flatnonzero(~np.isfinite(floor))
            if len(fresh) and k <= m:
                floor[fresh] = np.partition(s[fresh], m - k, axis=1)[:, m - k] - slack
            # A row whose bound the error could take to zero needs to know which sums have a common key.
            low = np.flatnonzero(~(floor > 2 * slack + 1e-8))
            floor[low] = np.inf
            i, j = np.divmod(np.flatnonzero(s >= (floor - slack - 1e-7).astype(np.float32)[:, None]), m)
            dots = np.concatenate([np.einsum("ij,ij->i", x[i[lo : lo + 4096]], y[j[lo : lo + 4096]]) for lo in range(0, len(i), 4096)] or [np.empty(0)])
            best.add(i, rid[j], in_nine(dots, np.sqrt(a.square[i] * b.square[j])))
            if len(low):
                plain(best, a, rid, b, low)
        yield best.result()

    return _lead(by_row(qpost, "qid"), ("key", "weight"), files, _Postings.of, lambda b: _Postings.of([b]), visit)


# ------------------------------------------------------------------ models from bounded samples


def sample_vectors(ref: DataFrame, rows: int, seed: int = 7) -> np.ndarray:
    """At most ``rows`` unit vectors, chosen by hashed id: the same whatever the partitioning."""
    got = ref.select("rid", "vec").orderBy(F.xxhash64(F.lit(seed), "rid"), "rid").limit(rows).toPandas().sort_values("rid")
    return unit(matrix(got["vec"]))


def kmeans(x: np.ndarray, cells: int, seed: int = 7, rounds: int = 15) -> np.ndarray:
    """Spherical k-means on a sample: seeded by farthest points, empty cells keep their centre."""
    if not len(x):
        return np.zeros((0, 0))
    rng = np.random.default_rng(seed)
    centres = [x[rng.integers(len(x))]]
    near = x @ centres[0]
    for _ in range(min(cells, len(x)) - 1):
        p = np.clip(1 - near, 0, None)
        i = rng.choice(len(x), p=p / p.sum()) if p.sum() > 0 else rng.integers(len(x))
        centres.append(x[i])
        near = np.maximum(near, x @ x[i])
    c = np.array(centres)
    for _ in range(rounds):
        own = np.argmax(x @ c.T, axis=1)
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        c = unit(np.where((sums != 0).any(1, keepdims=True), sums, c))
    return c


def _cells(df: DataFrame, id_col: str, centres: np.ndarray, probes: int) -> DataFrame:
    """(id, vec, cell, near) with a row for each of the ``probes`` nearest centres."""
    shared = df.sparkSession.sparkContext.broadcast(centres)
    schema = T.StructType([df.schema[id_col], df.schema["vec"], T.StructField("cell", T.IntegerType()), T.StructField("near", T.DoubleType())])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        c = shared.value
        p = min(probes, len(c))
        for f in frames:
            if not len(f) or not p:
                continue
            s = unit(matrix(f["vec"])) @ c.T
            best = np.argsort(-s, axis=1, kind="stable")[:, :p]
            take = np.repeat(np.arange(len(f)), p)
            yield pd.DataFrame({id_col: f[id_col].to_numpy()[take], "vec": f["vec"].to_numpy()[take], "cell": best.ravel().astype(np.int32), "near": s[take, best.ravel()]})

    return df.select(id_col, "vec").mapInPandas(run, schema)


def _salted(p: DataFrame, r: DataFrame, keys: list[str], rows: int = 4 * BLOCK_ROWS) -> tuple[DataFrame, DataFrame, list[str]]:
    """Cells of over ``rows`` reference rows are split; queries visit each part.  Sizes are a table, joined, not collected."""
    size = r.groupBy(*keys).agg((F.floor((F.count("*") - 1) / rows) + 1).cast("int").alias("parts"))
    r = r.join(size, keys).withColumn("part", F.pmod(F.xxhash64("rid"), F.col("parts")).cast("int")).drop("parts")
    p = p.join(size, keys).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    return p, r, [*keys, "part"]


class CellIndex:
    """k-means cells over the reference; a query visits its nearest ones.  With all cells visited it is exact."""

    def __init__(self, centres: np.ndarray, table: DataFrame) -> None:
        self.centres, self.table, self.inner = centres, table, None

    @classmethod
    def fit(cls, ref: DataFrame, cells: int = 32, seed: int = 7, sample: int = 20_000) -> CellIndex:
        ref = once(ref)
        centres = kmeans(sample_vectors(ref, sample, seed), cells, seed)
        return cls(centres, settle(_cells(ref, "rid", centres, 1)))

    def query(self, q: DataFrame, k: int = 5, probes: int = 4, metric: str = "cosine", inner: str = "exact", **forest) -> DataFrame:
        _check(k)
        p = _cells(spread(q, "qid"), "qid", self.centres, probes)
        if inner == "forest":
            if self.inner is None:
                self.inner = Forest.fit(self.table, **forest)
            return self.inner.query(p, k, within="cell")
        a, b, keys = _salted(p, self.table, ["cell"])
        return merge_top(_cell_top(a, b, keys, k, metric), k)


class PivotIndex:
    """Exact cosine search with pruning: on unit vectors a cell of radius R around pivot p holds nothing nearer than
    |q - p| - R.  A query first searches its own cell, then only the cells that its k-th distance does not rule out."""

    def __init__(self, pivots: np.ndarray, radius: np.ndarray, table: DataFrame) -> None:
        self.pivots, self.radius, self.table = pivots, radius, table

    @classmethod
    def fit(cls, ref: DataFrame, pivots: int = 32, seed: int = 7, sample: int = 20_000) -> PivotIndex:
        ref = once(ref)
        centres = kmeans(sample_vectors(ref, sample, seed), pivots, seed)
        table = settle(_cells(ref, "rid", centres, 1))
        radius = np.zeros(len(centres))
        distance = F.sqrt(F.greatest(F.lit(0.0), 2 - 2 * F.col("near")))
        for r in table.groupBy("cell").agg(F.max(distance).alias("r")).collect():  # a row a pivot
            radius[r["cell"]] = r["r"]
        return cls(centres, radius, table)

    def query(self, q: DataFrame, k: int = 5) -> DataFrame:
        _check(k)
        q = once(q)
        a, b, keys = _salted(_cells(spread(q, "qid"), "qid", self.pivots, 1), self.table, ["cell"])
        first = settle(merge_top(_cell_top(a, b, keys, k, "cosine"), k))
        kth = first.groupBy("qid").agg(F.when(F.count("*") >= k, F.min("sim")).alias("least"))
        more = self._open_cells(q.join(kth, "qid", "left"))
        a, b, keys = _salted(more, self.table, ["cell"])
        return merge_top(first.unionByName(_cell_top(a, b, keys, k, "cosine")), k)

    def _open_cells(self, q: DataFrame) -> DataFrame:
        """(qid, vec, cell) of the cells besides a query's own that may hold a nearer row."""
        shared = q.sparkSession.sparkContext.broadcast((self.pivots, self.radius))

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            pivots, radius = shared.value
            for f in frames:
                if not len(f) or not len(pivots):
                    continue
                s = unit(matrix(f["vec"])) @ pivots.T
                d = np.sqrt(np.maximum(2 - 2 * s, 0))
                least = f["least"].to_numpy(float)
                reach = np.where(np.isnan(least), np.inf, np.sqrt(np.maximum(2 - 2 * np.nan_to_num(least), 0)))
                open_ = d - radius[None] <= reach[:, None] + 1e-4  # vectors are stored in single precision
                open_[np.arange(len(f)), np.argmax(s, axis=1)] = False
                row, cell = np.nonzero(open_)
                yield pd.DataFrame({"qid": f["qid"].to_numpy()[row], "vec": f["vec"].to_numpy()[row], "cell": cell.astype(np.int32)})

        schema = T.StructType([q.schema["qid"], q.schema["vec"], T.StructField("cell", T.IntegerType())])
        return q.select("qid", "vec", "least").mapInPandas(run, schema)


#: Trees and centres go to every task; more bytes than this are refused rather than broadcast.
MODEL_BYTES = 128 << 20


class Forest:
    """Trees of random hyperplanes between two sampled rows; a query visits, in each tree, the leaves it misses least."""

    def __init__(self, trees: list[Tree], table: DataFrame) -> None:
        self.trees, self.table = trees, table

    @classmethod
    def fit(cls, ref: DataFrame, trees: int = 10, leaf: int = 64, seed: int = 7, sample: int = 20_000, least: int = 8) -> Forest:
        """The splits come from a bounded sample; leaves are sized for the whole table by its share in the sample.

        A leaf holds ``least`` sampled rows at least, which bounds a tree to sample / least leaves whatever the table's size;
        larger tables have larger leaves (or get a larger ``sample``).
        """
        ref = once(ref)
        x = sample_vectors(ref, sample, seed)
        n = ref.count()
        size = max(float(least) if n > len(x) else 1.0, leaf * len(x) / max(1, n))
        rng = np.random.default_rng(seed)
        grown = [Tree.grow(x, size, rng) for _ in range(trees)]
        if sum(t.normals.nbytes for t in grown) > MODEL_BYTES:
            raise ValueError("the trees take more than MODEL_BYTES: a smaller sample, fewer trees or a larger least")
        keep = [c for c in ("cell",) if c in ref.columns]
        return cls(grown, settle(_route(ref, "rid", grown, 1, keep)))

    def query(self, q: DataFrame, k: int = 5, probes: int = 4, metric: str = "cosine", within: str | None = None) -> DataFrame:
        _check(k)
        p = _route(q, "qid", self.trees, probes, [within] if within else [])
        a, b, keys = _salted(p, self.table, ["tree", "leaf", *([within] if within else [])])
        return merge_top(_cell_top(a, b, keys, k, metric), k)


class Tree:
    """Nodes in arrays: ``normals`` and ``offsets`` of the inner ones, children as left and right (-1: a leaf)."""

    def __init__(self, normals: np.ndarray, offsets: np.ndarray, left: np.ndarray, right: np.ndarray) -> None:
        self.normals, self.offsets, self.left, self.right = normals, offsets, left, right

    @classmethod
    def grow(cls, x: np.ndarray, leaf: float, rng: np.random.Generator) -> Tree:
        normals, offsets, left, right = [], [], [], []
        todo = [(np.arange(len(x)), 0, None)]
        while todo:
            rows, depth, parent = todo.pop()
            at = len(left)
            if parent is not None:
                (left if parent[1] else right)[parent[0]] = at
            normals.append(None)
            offsets.append(0.0)
            left.append(-1)
            right.append(-1)
            if len(rows) <= leaf or len(rows) < 2 or depth > 40:
                continue
            for _ in range(3):
                i, j = rng.choice(len(rows), 2, replace=False)
                normal = x[rows[i]] - x[rows[j]]
                size = np.linalg.norm(normal)
                if size > 1e-9:
                    break
            else:
                continue
            normal = (normal / size).astype(np.float32)
            value = x[rows] @ normal
            offset = float(np.median(value))
            low = value <= offset
            if low.all() or not low.any():
                continue
            normals[at], offsets[at] = normal, offset
            todo += [(rows[low], depth + 1, (at, True)), (rows[~low], depth + 1, (at, False))]
        width = x.shape[1] if x.ndim == 2 else 0
        return cls(np.array([np.zeros(width, np.float32) if n is None else n for n in normals]), np.array(offsets), np.array(left), np.array(right))

    def leaves(self, x: np.ndarray, probes: int) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf): the ``probes`` leaves of each row with the least distance beyond split planes on the way, best first.

        Going to the nearer side costs nothing, so each of the descents ends at the next best leaf; the sides not taken wait with
        their costs, and only the nodes on the way are looked at.
        """
        n = len(x)
        every = np.arange(n)
        rows, found = [], []
        wait_node, wait_cost = np.full((n, 0), -1), np.full((n, 0), np.inf)
        node, cost, live = np.zeros(n, np.int64), np.zeros(n), every
        for turn in range(probes):
            if turn:
                if not wait_cost.shape[1]:
                    break
                pick = wait_cost.argmin(1)
                cost = wait_cost[every, pick]
                live = np.flatnonzero(np.isfinite(cost))
                if not len(live):
                    break
                node = wait_node[every, pick]
                wait_cost[every, pick] = np.inf
            new_node, new_cost = [], []
            on = live[self.left[node[live]] >= 0]
            while len(on):
                at = node[on]
                side = np.einsum("ij,ij->i", x[on], self.normals[at]) - self.offsets[at]
                low = side <= 0
                node[on] = np.where(low, self.left[at], self.right[at])
                other, price = np.full(n, -1), np.full(n, np.inf)
                other[on], price[on] = np.where(low, self.right[at], self.left[at]), cost[on] + np.abs(side)
                new_node.append(other)
                new_cost.append(price)
                on = on[self.left[node[on]] >= 0]
            rows.append(live)
            found.append(node[live].copy())
            if new_node and turn + 1 < probes:
                wait_node = np.concatenate([wait_node, np.stack(new_node, 1)], axis=1)
                wait_cost = np.concatenate([wait_cost, np.stack(new_cost, 1)], axis=1)
                if wait_cost.shape[1] > probes:  # no more can be taken
                    best = np.argpartition(wait_cost, probes - 1, axis=1)[:, :probes]
                    wait_node, wait_cost = np.take_along_axis(wait_node, best, 1), np.take_along_axis(wait_cost, best, 1)
        return np.concatenate(rows), np.concatenate(found)


def _route(df: DataFrame, id_col: str, trees: list[Tree], probes: int, keep: list[str]) -> DataFrame:
    shared = df.sparkSession.sparkContext.broadcast([(t.normals, t.offsets, t.left, t.right) for t in trees])  # at most MODEL_BYTES
    schema = T.StructType([df.schema[id_col], df.schema["vec"], *(df.schema[c] for c in keep), T.StructField("tree", T.IntegerType()), T.StructField("leaf", T.IntegerType())])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for whole in frames:
            for lo in range(0, len(whole), 2048):
                f = whole.iloc[lo : lo + 2048]
                x = unit(matrix(f["vec"]))
                for t, arrays in enumerate(shared.value):
                    row, leaf = Tree(*arrays).leaves(x, probes)
                    yield pd.DataFrame({id_col: f[id_col].to_numpy()[row], "vec": f["vec"].to_numpy()[row]} | {c: f[c].to_numpy()[row] for c in keep} | {"tree": np.int32(t), "leaf": leaf.astype(np.int32)})

    return spread(df.select(id_col, "vec", *keep), id_col).mapInPandas(run, schema)


class HashIndex:
    """Tables of codes: a bit is the side of a random plane, put at the median of a bounded sample, on which a vector lies.  Rows meet
    a query where a table gives both the same code, or one that differs in the bits of the planes nearest to the query."""

    def __init__(self, normals: np.ndarray, offsets: np.ndarray, ref: DataFrame, table: DataFrame) -> None:
        self.normals, self.offsets, self.ref, self.table = normals, offsets, ref, table

    @classmethod
    def fit(cls, ref: DataFrame, tables: int = 8, bits: int | None = None, leaf: int = 64, seed: int = 7, sample: int = 20_000) -> HashIndex:
        """``bits``: planes a table; by default as many as give codes of about ``leaf`` rows each."""
        ref = once(ref.select("rid", "vec"))
        x, n = sample_vectors(ref, sample, seed), ref.count()
        bits = bits or int(np.clip(np.round(np.log2(max(2, n / leaf))), 1, 30))
        normals = np.random.default_rng(seed).normal(size=(tables, bits, x.shape[1] if len(x) else 0)).astype(np.float32)
        if normals.nbytes > MODEL_BYTES:
            raise ValueError("the planes take more than MODEL_BYTES")
        offsets = np.median(np.einsum("nd,tbd->ntb", x, normals), axis=0) if len(x) else np.zeros((tables, bits))
        return cls(normals, offsets, ref, settle(_hashed(ref, "rid", normals, offsets, 1)))

    def query(self, q: DataFrame, k: int = 5, probes: int = 3, metric: str = "cosine") -> DataFrame:
        """A query that finds fewer than k rows so is searched exactly."""
        _check(k)
        q = once(q.select("qid", "vec"))
        a, b, keys = _salted(_hashed(q, "qid", self.normals, self.offsets, probes), self.table, ["tree", "leaf"])
        found = settle(merge_top(_cell_top(a, b, keys, k, metric), k))
        return _filled(found, q, k, lambda rest: knn_exact(rest, self.ref, k, metric))


def _hashed(df: DataFrame, id_col: str, normals: np.ndarray, offsets: np.ndarray, probes: int) -> DataFrame:
    """(id, vec, tree, leaf): a row for each table and code."""
    shared = df.sparkSession.sparkContext.broadcast((normals, offsets))  # at most MODEL_BYTES
    schema = T.StructType([df.schema[id_col], df.schema["vec"], T.StructField("tree", T.IntegerType()), T.StructField("leaf", T.IntegerType())])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        planes, at = shared.value
        weight = 1 << np.arange(planes.shape[1])
        for whole in frames:
            for lo in range(0, len(whole), 2048):
                f = whole.iloc[lo : lo + 2048]
                x = unit(matrix(f["vec"]))
                for t in range(len(planes)):
                    side = x @ planes[t].T - at[t]
                    code = (side > 0) @ weight
                    near = np.argsort(np.abs(side), axis=1, kind="stable")[:, : probes - 1]
                    codes = np.concatenate([code[:, None], code[:, None] ^ weight[near]], axis=1)
                    take = np.repeat(np.arange(len(f)), codes.shape[1])
                    yield pd.DataFrame({id_col: f[id_col].to_numpy()[take], "vec": f["vec"].to_numpy()[take], "tree": np.int32(t), "leaf": codes.ravel().astype(np.int32)})

    return spread(df.select(id_col, "vec"), id_col).mapInPandas(run, schema)


def lsh_candidates(q: DataFrame, ref: DataFrame, k: int = 5, bucket: float = 0.5, tables: int = 8, reach: float = 1.2, seed: int = 7) -> DataFrame:
    """Spark ML's random-projection hashing: pairs within ``reach`` that share a bucket in some table, the nearest re-ranked by cosine.

    A query that finds fewer than k so is searched exactly.  Spark's join carries both vectors of every pair that meets, and its
    buckets get wide against distances in many dimensions: HashIndex is the one for large tables.
    """
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    _check(k)
    ref = once(ref.select("rid", "vec"))
    size = F.sqrt(dot(F.col("vec"), F.col("vec")))
    scaled = F.transform("vec", lambda x: F.when(size > 0, x / size).otherwise(0.0).cast("double"))
    norm = lambda df, i: df.select(i, array_to_vector(scaled).alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=seed).fit(norm(ref, "rid"))
    met = model.approxSimilarityJoin(norm(q, "qid"), norm(ref, "rid"), reach, "d").select(F.col("datasetA.qid").alias("qid"), F.col("datasetB.rid").alias("rid"), "d")
    # Distances of unit vectors fall as cosines rise: only the nearest, with room for rounding, need the exact figure.
    first = met.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("d", "rid"))).where(F.col("r") <= 2 * k)
    found = settle(rerank(first.select("qid", "rid"), q, ref, k))
    return _filled(found, q, k, lambda rest: knn_exact(rest, ref, k))


def _filled(found: DataFrame, q: DataFrame, k: int, more) -> DataFrame:
    """Candidates whose queries have fewer than k of them get those of ``more(queries)`` instead."""
    enough = found.groupBy("qid").agg(F.count("*").alias("n")).where(F.col("n") >= k).select("qid")
    return found.join(enough, "qid", "left_semi").select("qid", "rid", "rank", "sim").unionByName(more(q.join(enough, "qid", "left_anti").select("qid", "vec")))


class DensityIndex:
    """Density clusters over the reference: a row with ``min_pts`` rows (itself too) within ``eps`` is a core; cores within eps
    are one cluster; other rows near a core join its nearest core's cluster, the rest are noise (-1)."""

    def __init__(self, labels: DataFrame, ref: DataFrame) -> None:
        self.labels, self.ref, self.forest, self.inside = labels, ref, None, None

    @classmethod
    def fit(cls, ref: DataFrame, eps: float, min_pts: int, pivots: int = 16, seed: int = 7) -> DensityIndex:
        """eps: Euclidean distance of unit vectors."""
        ref = once(ref.select("rid", "vec"))
        pairs = settle(eps_pairs(ref, eps, pivots, seed))
        degree = pairs.groupBy("a").agg(F.count("*").alias("n"))
        core = settle(degree.where(F.col("n") >= min_pts).select("a"))
        links = pairs.join(core, "a", "left_semi").join(core.select(F.col("a").alias("b")), "b", "left_semi").where("a < b").select("a", "b")
        clusters = connected(links)
        cores = core.join(clusters, core.a == clusters.node, "left").select(F.col("a").alias("rid"), F.coalesce("root", "a").alias("cluster"))
        border = pairs.join(core, "a", "left_anti").join(cores.select(F.col("rid").alias("b"), "cluster"), "b")
        nearest = border.groupBy("a").agg(F.min_by("cluster", F.struct("d", "b")).alias("cluster")).select(F.col("a").alias("rid"), "cluster")
        named = cores.unionByName(nearest)
        labels = ref.select("rid").join(named, "rid", "left").select("rid", F.coalesce("cluster", F.lit(-1).cast("long")).alias("cluster"))
        return cls(settle(labels), ref)

    def query(self, q: DataFrame, k: int = 5, trees: int = 8, leaf: int = 64, probes: int = 4) -> DataFrame:
        """Search in the cluster of the nearest row (by the forest), by the forest within it; noise is a cluster.

        A query that finds fewer than k there takes the forest's of all clusters, and if these are too few, the exact ones.
        """
        if self.forest is None:
            self.forest = Forest.fit(self.ref, trees, leaf)
            table = self.ref.join(self.labels, "rid").select("rid", "vec", F.col("cluster").alias("cell"))
            self.inside = Forest(self.forest.trees, settle(_route(table, "rid", self.forest.trees, 1, ["cell"])))
        q = once(q.select("qid", "vec"))
        wide = settle(self.forest.query(q, k, probes))
        near = wide.where("rank = 1").join(self.labels, "rid").select("qid", F.col("cluster").alias("cell"))
        found = settle(self.inside.query(q.join(near, "qid").select("qid", "vec", "cell"), k, probes, within="cell"))
        return _filled(found, q, k, lambda rest: _filled(wide.join(rest.select("qid"), "qid", "left_semi"), rest, k, lambda last: knn_exact(last, self.ref, k)))


def eps_pairs(ref: DataFrame, eps: float, pivots: int = 16, seed: int = 7) -> DataFrame:
    """(a, b, d) of all ordered pairs of unit vectors within eps, each row with itself too: a join through pivot cells.

    A row visits every cell whose pivot is at most 2 eps farther than its own: a neighbour within eps lies in one of them.
    """
    centres = kmeans(sample_vectors(ref, 20_000, seed), pivots, seed)
    home = _cells(ref, "rid", centres, 1)
    shared = ref.sparkSession.sparkContext.broadcast(centres)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            if not len(f):
                continue
            d = np.sqrt(np.maximum(2 - 2 * unit(matrix(f["vec"])) @ shared.value.T, 0))
            row, cell = np.nonzero(d <= d.min(1, keepdims=True) + 2 * eps + 1e-4)
            yield pd.DataFrame({"qid": f["rid"].to_numpy()[row], "vec": f["vec"].to_numpy()[row], "cell": cell.astype(np.int32)})

    schema = T.StructType([T.StructField("qid", T.LongType()), ref.schema["vec"], T.StructField("cell", T.IntegerType())])
    visits = ref.select("rid", "vec").mapInPandas(run, schema)
    p, r, keys = _salted(visits, home, ["cell"])

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = []
        y, rid = unit(matrix(b["vec"])), b["rid"].to_numpy(np.int64)
        for lo in range(0, len(a) if len(b) else 0, 1024):
            part = a.iloc[lo : lo + 1024]
            d = np.round(np.sqrt(np.maximum(2 - 2 * unit(matrix(part["vec"])) @ y.T, 0)), 6)
            i, j = np.nonzero((d <= eps) | (part["qid"].to_numpy()[:, None] == rid[None]))
            out.append(pd.DataFrame({"a": part["qid"].to_numpy(np.int64)[i], "b": rid[j], "d": d[i, j]}))
        return pd.concat(out) if out else pd.DataFrame({"a": [], "b": [], "d": []})

    return p.groupBy(*keys).cogroup(r.groupBy(*keys)).applyInPandas(near, "a long, b long, d double")


# ------------------------------------------------------------------ over candidates


def rerank(cands: DataFrame, q: DataFrame, ref: DataFrame, k: int = 5, metric: str = "cosine") -> DataFrame:
    """Exact similarities over given pairs, in blocks, then the k best."""
    pairs = cands.select("qid", "rid").distinct().join(ref.select("rid", F.col("vec").alias("rv")), "rid").join(q.select("qid", F.col("vec").alias("qv")), "qid")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for whole in frames:
            for lo in range(0, len(whole), 2048):
                f = whole.iloc[lo : lo + 2048]
                a, b = matrix(f["qv"]), matrix(f["rv"])
                if metric == "cosine":
                    a, b = unit(a), unit(b)
                s = -np.linalg.norm(a - b, axis=1) if metric == "euclidean" else np.einsum("ij,ij->i", a, b)
                yield pd.DataFrame({"qid": f["qid"], "rid": f["rid"], "sim": np.round(s, 9)})

    return rank_top(pairs.select("qid", "rid", "qv", "rv").mapInPandas(run, "qid long, rid long, sim double"), k)


def union_candidates(*cands: DataFrame) -> DataFrame:
    """The distinct pairs of several gatherers."""
    out = cands[0].select("qid", "rid")
    for c in cands[1:]:
        out = out.unionByName(c.select("qid", "rid"))
    return out.distinct()


def brute_cosine(q: DataFrame, ref: DataFrame, k: int | None = None, threshold: float | None = None, metric: str = "cosine", block_rows: int = 2048) -> DataFrame:
    """All pairs: the k best of each query, or every pair strictly over the threshold (rank by query)."""
    if (k is None) == (threshold is None):
        raise ValueError("give k or threshold")
    files = [f for f, _, _ in _block_files(ref, block_rows)]
    if k is not None:
        return _knn_files(q, files, k, metric, False)

    def visit(qid, x, blocks):
        for rid, y in blocks:
            i, j, s = _reach(x, y, metric, np.full(len(qid), threshold))
            over = s > threshold
            yield qid[i[over]], rid[j[over]], np.zeros(int(over.sum()), np.int32), s[over]

    found = _led(q, files, metric, visit)
    w = Window.partitionBy("qid").orderBy(F.desc("sim"), "rid")
    return found.withColumn("rank", F.row_number().over(w)).select("qid", "rid", "rank", "sim")
