"""SimHash near-duplicates through an inverted index of byte positions with count filtering.

A fingerprint's eight bytes, with their positions, are its tokens.  Fingerprints at most ``max_bits`` = 2
bits apart share at least 8 - 2 = 6 of them.  Lists of single bytes would have N/256 entries, which no cluster can pair
up, so the index keeps its postings under sets of four positions (lists of N/2^32): the fourteen sets {a, b, c, d} of the
eight positions with a xor b xor c xor d = 0, in which any three positions lie together in exactly one.  A pair of fingerprints
is tallied over the lists that it shares:

    positional bytes shared   0-3   4        5   6   7   8
    lists shared              0     0 or 1   1   3   7   14

so a tally of three is the guaranteed minimum of six bytes, and no pair with fewer reaches it.  What is left is verified by the
bits that differ.

A list with more than ``list_limit`` members (a large group of near copies) is not paired up.  Its
members are posted once more under the values within one bit of them: two members at most two bits
apart have such a value in common, and members with a common one are at most two bits
apart.  That is exact, and linear in the list.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

MAX_BITS = 2
SEED = 42
#: The sets of four byte positions (0: most significant) under which fingerprints are posted.
SLOTS = [x for x in combinations(range(8), 4) if x[0] ^ x[1] ^ x[2] ^ x[3] == 0]
#: Lists that fingerprints with six positional bytes in common share.
LEAST_LISTS = 3


def fingerprint(words: list[bytes], shingle: int) -> int:
    """The fingerprint of one text's words."""
    if not words:
        return 0
    spans = [b" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    hashes = np.array([xxhash.xxh64_intdigest(s, SEED) for s in spans], ">u8")
    return _majority(hashes)


def _majority(hashes: np.ndarray) -> int:
    """Bits set in over half the hashes (big-endian 64-bit)."""
    total = np.zeros(64, np.int64)
    for lo in range(0, len(hashes), 1 << 15):
        part = hashes[lo : lo + (1 << 15)]
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(total * 2 > len(hashes)).tobytes(), "big")


def _text_fingerprint(text: bytes, shingle: int) -> int:
    words = text.lower().split()
    n = len(words)
    if n <= shingle:
        return fingerprint(words, shingle)
    flat = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1)
    starts = [0, *ends[: n - shingle].tolist()]
    stops = (ends[shingle - 1 :] - 1).tolist()
    hashed = xxhash.xxh64_intdigest
    return _majority(np.array([hashed(flat[a:b], SEED) for a, b in zip(starts, stops, strict=True)], ">u8"))


def fingerprint_column(column: pa.Array, shingle: int = 3) -> pa.Array:
    """Each text's fingerprint as a signed long; those without words have 0."""
    return pa.array(np.array([_text_fingerprint(t, shingle) for t in common.text_bytes(column)], np.uint64).view(np.int64))


def fingerprints(df: DataFrame, shingle: int = 3, id_cols: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """``id_cols`` and ``fp`` (the fingerprint as a signed long); texts without words have 0, null texts too."""

    def run(column: pa.Array) -> dict[str, pa.Array]:
        return {"fp": fingerprint_column(column, shingle)}

    return common.annotate(df, run, {"fp": "long"}, list(id_cols), text_col)


def _byte(c, i: int):
    return F.shiftrightunsigned(c, 56 - 8 * i).bitwiseAND(F.lit(0xFF))


def _shared_bytes(a, b):
    x = a.bitwiseXOR(b)
    return sum(F.when(F.shiftrightunsigned(x, 8 * i).bitwiseAND(F.lit(0xFF)) == 0, 1).otherwise(0) for i in range(8))


def _key(fp, positions: tuple[int, ...]):
    out = _byte(fp, positions[0])
    for i in positions[1:]:
        out = F.shiftleft(out, 8).bitwiseOR(_byte(fp, i))
    return out


def links(distinct: DataFrame, list_limit: int = 16) -> DataFrame:
    """Links ``(a, b, shared)``, a < b, between the distinct longs of column ``fp``; ``shared``: positional bytes in common.

    Every link joins two fingerprints at most two bits apart, and any two that close are connected by links; pairs
    all of whose lists are within the limit are found by their tally, once each.
    """
    fp = F.col("fp")
    # A list's number and its four bytes, in one long.
    keys = [_key(fp, positions) + F.lit(s << 32) for s, positions in enumerate(SLOTS)]
    postings = distinct.select("fp", F.explode(F.array(*keys)).alias("key"))
    sizes = postings.groupBy("key").agg(F.count("*").alias("size")).where("size > 1")
    listed = common.settle(postings.join(sizes, "key"))

    small = listed.where(F.col("size") <= list_limit)
    a, b = small.select("key", F.col("fp").alias("a")), small.select("key", F.col("fp").alias("b"))
    tally = a.join(b, "key").where("a < b").groupBy("a", "b").agg(F.count("*").alias("lists"))
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= MAX_BITS
    pairs = tally.where(F.col("lists") >= LEAST_LISTS).where(near).select("a", "b")

    large = listed.where(F.col("size") > list_limit)
    flips = F.concat(F.array(fp), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: fp.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))))
    around = large.select("fp").distinct().select("fp", F.explode(flips).alias("mid"))
    heads = around.groupBy("mid").agg(F.min("fp").alias("a"), F.count("*").alias("n")).where("n > 1").select("mid", "a")
    stars = around.join(heads, "mid").where(fp != F.col("a")).select("a", F.col("fp").alias("b")).distinct()
    return pairs.unionByName(stars).withColumn("shared", _shared_bytes(F.col("a"), F.col("b")))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for each node of the edges ``(a, b)``; nodes of one component have the same root.

    Each round sends every node to the neighbour that is first in a hashed order and contracts the edges; the nodes left
    fall by a constant factor a round, whatever the component's shape.  Only minima travel, so a hub's
    neighbours never meet in one task.
    """
    order = lambda c: F.struct(F.xxhash64(c), c.alias("id"))
    edges = common.settle(edges.where("a != b").select("a", "b").distinct())
    steps: list[DataFrame] = []
    for _ in range(max_rounds):
        if edges.isEmpty():
            break
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        step = both.groupBy("a").agg(F.min(order(F.col("b"))).alias("m")).select(F.col("a").alias("node"), F.least(order(F.col("a")), F.col("m"))["id"].alias("root"))
        step = common.settle(step)
        steps.append(step)
        left = step.select(F.col("node").alias("a"), F.col("root").alias("ra"))
        right = step.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        edges = common.settle(edges.join(left, "a").join(right, "b").where("ra != rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct())
    else:
        raise RuntimeError("components: rounds used up")
    if not steps:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    labels = steps[-1]
    for step in reversed(steps[:-1]):
        onward = labels.select(F.col("node").alias("root"), F.col("root").alias("end"))
        labels = step.join(onward, "root", "left").select("node", F.coalesce("end", "root").alias("root"))
    return labels


def near_duplicates(df: DataFrame, shingle: int = 3, list_limit: int = 16, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, ``fp`` and ``component_id`` for every row.

    ``component_id`` is the smallest id reachable over links, its own included.  Equal texts share a fingerprint and so a
    component.  Rows without an id take part: they get their component's smallest known id, null if there is none.
    Ids may be of any type that has an order; repeated rows each give a row; texts of any length are read whole; an empty table gives
    no rows, and other columns are not read.
    """
    rows = common.settle(fingerprints(df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), shingle))
    nodes = common.settle(rows.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    found = common.settle(components(links(nodes.select("fp"), list_limit)))
    smallest = found.join(nodes.withColumnRenamed("fp", "node"), "node").groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = found.join(smallest, "root").select(F.col("node").alias("fp"), "component_id")
    named = common.settle(nodes.join(named, "fp", "left").select("fp", F.coalesce("component_id", "first_id").alias("component_id")))
    # The only join that a group of copies can skew; alone in its stage, so Spark may split the group.
    return rows.join(named, "fp").select("doc_id", "fp", "component_id")


def keep_one(df: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of df, of each component only that with the smallest id (one row, should the id repeat).

    Rows without an id cannot be told apart and all stay.
    """
    found = near_duplicates(df.where(F.col(id_col).isNotNull()), shingle, id_col=id_col, text_col=text_col)
    stay = found.groupBy("doc_id").agg(F.min("component_id").alias("c"), F.min("fp").alias("f")).where("c = doc_id").select(F.col("doc_id").alias(id_col))
    kept = df.join(stay, id_col, "left_semi").dropDuplicates([id_col])
    return kept.select(*df.columns).unionByName(df.where(F.col(id_col).isNull()))
