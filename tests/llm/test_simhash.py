import re
from itertools import combinations

import numpy as np
import xxhash
from pyspark.sql import functions as F

from recordlink.llm import simhash


def brute_fp(text, k):
    words = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    spans = [" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))]
    hs = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in spans]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(nodes, near):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(nodes, 2):
        if near(a, b):
            root[find(a)] = find(b)
    return {n: find(n) for n in nodes}


def check(rows, texts):
    fps = {i: brute_fp(t, 3) for i, t in texts.items()}
    root = brute_components(list(texts), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 2)
    smallest = {}
    for i, r in root.items():
        smallest[r] = min(smallest.get(r, i), i)
    for r in rows:
        assert r["fp"] & 0xFFFFFFFFFFFFFFFF == fps[r["doc_id"]]
        assert r["component_id"] == smallest[root[r["doc_id"]]]


def test_documents(docs):
    texts = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
    check(simhash.near_duplicates(docs).collect(), texts)


def test_odd(odd, none):
    known = odd.where("doc_id is not null")
    check(simhash.near_duplicates(known).collect(), {r["doc_id"]: r["text"] for r in known.collect()})
    assert simhash.near_duplicates(odd).count() == odd.count()
    assert {r["component_id"] for r in simhash.near_duplicates(odd).where("doc_id is null").collect()} == {None}
    assert simhash.near_duplicates(none).count() == 0
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == ["1", "4", "6", "7", "8", "None", "None"]
    assert simhash.keep_one(none).count() == 0


def random_fingerprints(n, groups, seed):
    rng = np.random.default_rng(seed)
    out = set()
    for _ in range(groups):
        x = int(rng.integers(0, 1 << 63)) | int(rng.integers(0, 2)) << 63
        for _ in range(n):
            out.add(x)
            for b in rng.choice(64, rng.integers(0, 4), replace=False):
                x ^= 1 << int(b)
    return sorted(out)


def test_links_and_components_match_brute_force(spark):
    """With long and short posting lists alike: lists over the limit take the other way."""
    for limit in (2, 64):
        fps = random_fingerprints(40, 6, limit)
        signed = [x - (1 << 64) if x >> 63 else x for x in fps]
        edges = simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), limit)
        rows = edges.collect()
        assert all(((r["a"] ^ r["b"]) & 0xFFFFFFFFFFFFFFFF).bit_count() <= 2 for r in rows)
        got = {r["node"]: r["root"] for r in simhash.components(edges).collect()}
        want = brute_components(signed, lambda a, b: ((a ^ b) & 0xFFFFFFFFFFFFFFFF).bit_count() <= 2)
        groups = lambda m: {frozenset(k for k in m if m[k] == v) for v in m.values()}
        assert {g for g in groups(want) if len(g) > 1} == groups(got)


def test_the_tally_of_lists_tells_the_shared_bytes():
    for n in range(9):
        tallies = {sum(set(slot) <= set(same) for slot in simhash.SLOTS) for same in combinations(range(8), n)}
        assert len(simhash.SLOTS) == 14 and (min(tallies) >= simhash.LEAST_LISTS) == (max(tallies) >= simhash.LEAST_LISTS) == (n >= 6)


def test_all_close_pairs_of_short_lists_are_links(spark):
    """Recall 1 against all pairs, and no pair beyond two bits; six shared bytes are not enough."""
    fps = random_fingerprints(12, 40, 9)
    fps = sorted({*fps, *(x ^ 0x0F00F0 for x in fps[::5])})  # two bytes differ, by eight bits
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    got = {(r["a"], r["b"]): r["shared"] for r in simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long")).collect()}
    apart = lambda a, b: (a ^ b) & 0xFFFFFFFFFFFFFFFF
    want = {(min(a, b), max(a, b)) for a, b in combinations(signed, 2) if apart(a, b).bit_count() <= 2}
    assert set(got) == want
    for (a, b), n in got.items():
        assert n == sum(x == 0 for x in apart(a, b).to_bytes(8, "big")) >= 6


def test_ids_of_text_and_a_very_long_text(spark):
    long = " ".join(f"w{i % 5000}" for i in range(300_000))
    df = spark.createDataFrame([("b", long), ("a", long), ("c", "x"), ("c", "x"), ("d", None)], "doc_id string, text string")
    got = {(r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(df).collect()}
    assert got == {("a", "a"), ("b", "a"), ("c", "c"), ("d", "d")}


def test_components_of_a_path_and_a_star(spark):
    path = spark.range(0, 500).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    star = spark.range(1001, 1500).select(F.lit(1000).cast("long").alias("a"), F.col("id").alias("b"))
    got = simhash.components(path.unionByName(star)).collect()
    assert len(got) == 501 + 500
    assert len({r["root"] for r in got}) == 2
