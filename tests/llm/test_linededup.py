import hashlib

import numpy as np
from pyspark.sql import functions as F

from recordlink.llm import common, linededup


def brute(rows, least):
    strip = lambda x: x.strip(" \t\n\x0b\x0c\r")
    low = lambda x: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x)
    lines = [(i, (t or "").split("\n")) for i, t in rows]
    held = {}
    for _, ls in lines:
        for k in {low(strip(x)) for x in ls}:
            held[k] = held.get(k, 0) + 1
    bad = {k for k, n in held.items() if k and n >= least}
    out = []
    for i, ls in lines:
        kept = [x for x in ls if low(strip(x)) not in bad]
        out.append((i, len(ls), len(ls) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


def got(df, least, **kw):
    done = linededup.LineDedup(df, min_docs=least, **kw).apply(df, ["doc_id"])
    rows = done.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("h")).collect()
    return sorted(map(tuple, rows), key=repr)


def test_documents(docs):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    for least in (2, 10):
        assert got(docs, least) == brute(rows, least)
    assert got(docs, 3, shard_rows=20) == brute(rows, 3)  # many shards


def test_odd(odd, none):
    assert got(odd, 2) == brute([(r["doc_id"], r["text"]) for r in odd.collect()], 2)
    assert got(none, 2) == []


def test_perfect_hash_is_minimal():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 63, 5000):
        keys = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64))
        assert sorted(linededup.PerfectHash.build(keys).index(keys).tolist()) == list(range(len(keys)))


def test_hashes_with_equal_halves(spark):
    rows = [(5, 1, 3), (5, 2, 4), (5, 3, 1), (6, 1, 9)]
    folder = common.shared_folder(spark, "t")
    shards = linededup.build_index(spark.createDataFrame(rows, "high long, low long, n long"), folder, 1)
    found = linededup.probe(folder, shards, np.array([5, 5, 5, 6, 5, 7], np.uint64), np.array([1, 2, 3, 1, 9, 1], np.uint64))
    assert found.tolist() == [3, 4, 1, 9, 0, 0]
