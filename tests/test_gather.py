import numpy as np
import pytest
from hypothesis import Phase, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from recordlink.functions.vectors import block_similarity, block_top
from recordlink.operators import gather as G
from recordlink.operators.encode import HashedNgramEncoder, PretrainedEncoder, ProjectedEncoder, TfidfEncoder, quantize_int8, save_index
from recordlink.operators.graph import connected
from recordlink.operators.lexical import edit_join, joint_query, minhash_search

RNG = np.random.default_rng(4)
X = RNG.normal(size=(300, 16))
X[250:] = X[:50] + 0.05 * RNG.normal(size=(50, 16))


def vecs(spark, x, i):
    return spark.createDataFrame([(k, v) for k, v in enumerate(x.tolist())], f"{i} long, vec array<double>")


def rows(df):
    return sorted((x["qid"], x["rank"], x["rid"]) for x in df.collect())


@pytest.fixture(scope="module")
def both(spark):
    return vecs(spark, X[:80], "qid").cache(), vecs(spark, X, "rid").cache()


@pytest.mark.parametrize("metric", ["cosine", "dot", "euclidean"])
def test_all_exact_engines_agree(both, metric):
    q, r = both
    want = rows(G.knn_sql(q, r, 4, metric))
    assert rows(G.knn_exact(q, r, 4, metric)) == want
    assert rows(G.knn_exact(q, r, 4, metric, broadcast_bytes=0, block_rows=64)) == want
    if metric == "cosine":
        assert rows(G.brute_cosine(q, r, 4, block_rows=50)) == want
        assert rows(G.PivotIndex.fit(r, 12).query(q, 4)) == want
        assert rows(G.CellIndex.fit(r, 6).query(q, 4, probes=6)) == want
        assert rows(G.Forest.fit(r, trees=2, leaf=10_000).query(q, 4)) == want


def test_blocks_and_queries_meet_whatever_the_number_of_partitions(spark, both):
    """Many blocks on both sides, over partitions that nothing joins again."""
    q, r = both
    near = {(x["qid"], x["rid"], x["sim"]) for x in G.knn_sql(q, r, 10**6).collect() if x["sim"] > 0.1}
    conf = {"spark.sql.shuffle.partitions": "31", "spark.sql.adaptive.enabled": "false"}
    before = {c: spark.conf.get(c) for c in conf}
    try:
        for c, v in conf.items():
            spark.conf.set(c, v)
        assert rows(G.knn_exact(q, r, 4, broadcast_bytes=0, block_rows=20)) == rows(G.knn_sql(q, r, 4))
        assert {(x["qid"], x["rid"], x["sim"]) for x in G.brute_cosine(q, r, threshold=0.1, block_rows=20).collect()} == near
    finally:
        for c, v in before.items():
            spark.conf.set(c, v)


def test_no_side_of_a_large_search_is_repeated(both):
    """Neither rows nor vectors are dealt to a grid; the reference is written once."""
    q, r = both
    for df in (G.knn_exact(q, r, 4, broadcast_bytes=0, block_rows=20), G.brute_cosine(q, r, threshold=0.1, block_rows=20)):
        assert "Generate" not in df._jdf.queryExecution().toString()


def test_ties_and_small_references(spark):
    q = spark.createDataFrame([(1, [1.0, 0.0])], "qid long, vec array<double>")
    r = spark.createDataFrame([(9, [1.0, 0.0]), (3, [2.0, 0.0]), (5, [0.0, 1.0]), (7, [0.0, 0.0])], "rid long, vec array<double>")
    assert rows(G.knn_exact(q, r, 10)) == [(1, 1, 3), (1, 2, 9), (1, 3, 5), (1, 4, 7)]
    assert rows(G.knn_exact(q.where("false"), r, 3)) == [] and rows(G.knn_exact(q, r.where("false"), 3)) == []
    with pytest.raises(ValueError):
        G.knn_exact(q, r, 0)
    s = block_similarity(np.zeros((1, 2)), np.ones((3, 2)), "cosine")
    assert block_top(np.array([1]), np.array([3, 2, 1]), s, 2)[1].tolist() == [1, 2]


def test_approximate_gatherers_find_most_and_only_exact_sims(both):
    q, r = both
    exact = {(a, c) for a, _, c in rows(G.knn_exact(q, r, 5))}
    for cands in (G.DensityIndex.fit(r, 0.6, 3, pivots=5).query(q, 5), G.Forest.fit(r, trees=10, leaf=40).query(q, 5, probes=4), G.CellIndex.fit(r, 8).query(q, 5, probes=4), G.CellIndex.fit(r, 4).query(q, 5, probes=2, inner="forest", trees=6, leaf=40), G.lsh_candidates(q, r, 5, bucket=1.0, reach=2.0), G.HashIndex.fit(r, leaf=40).query(q, 5)):
        got = {(a, c) for a, _, c in rows(cands)}
        assert len(got & exact) >= 0.6 * len(exact) and cands.count() == 5 * 80


def test_cells_split_when_large(both, monkeypatch):
    q, r = both
    a, b, keys = G._salted(G._cells(q, "qid", G.kmeans(X, 2), 2), G._cells(r, "rid", G.kmeans(X, 2), 1), ["cell"], rows=40)
    assert rows(G.merge_top(G._cell_top(a, b, keys, 4, "cosine"), 4)) == rows(G.knn_exact(q, r, 4))
    assert b.groupBy(*keys).count().agg(F.max("count")).first()[0] < 100


def test_density_against_brute_force(spark):
    x = np.concatenate([RNG.normal(size=(1, 8)) + 0.1 * RNG.normal(size=(25, 8)) for _ in range(3)] + [RNG.normal(size=(10, 8))])
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    d = np.round(np.sqrt(np.maximum(2 - 2 * u @ u.T, 0)), 6)
    eps, least = 0.25, 4
    near = (d <= eps) | np.eye(len(x), dtype=bool)
    core = near.sum(1) >= least
    root = list(range(len(x)))
    for _ in range(len(x)):
        for i in np.flatnonzero(core):
            m = min(root[j] for j in np.flatnonzero(near[i] & core))
            root[i] = min(root[i], m)
    want = {}
    for i in range(len(x)):
        if core[i]:
            want[i] = root[i]
        elif (near[i] & core).any():
            j = min(np.flatnonzero(near[i] & core), key=lambda j: (d[i, j], j))
            want[i] = root[j]
        else:
            want[i] = -1
    got = {r["rid"]: r["cluster"] for r in G.DensityIndex.fit(vecs(spark, x, "rid"), eps, least, pivots=5).labels.collect()}
    assert got == want


def test_components(spark):
    e = spark.range(0, 300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b")).unionByName(spark.createDataFrame([(900, 901), (903, 902), (902, 901)], "a long, b long"))
    got = connected(e).collect()
    assert {r["root"] for r in got} == {0, 900} and len(got) == 305


def test_stand_in_encoder(spark):
    df = spark.createDataFrame([(1, "Ada LOVE  x"), (2, "ada love x"), (3, ""), (4, None)], "rid long, sentence string")
    e = HashedNgramEncoder(64)
    dense = {r["rid"]: np.array(r["vec"]) for r in e.encode(df, "rid").collect()}
    assert (dense[1] == dense[2]).all() and not dense[3].any() and not dense[4].any()
    sparse = {}
    for r in e.sparse(df, "rid").collect():
        sparse.setdefault(r["rid"], np.zeros(64))[r["bucket"]] = r["weight"]
    assert set(sparse) == {1, 2} and (sparse[1] == dense[1]).all()


def test_pretrained_encoder_contract(spark):
    class Fake:  # local, so that it travels to the workers
        def run(self, texts):
            import numpy as np

            return np.array([[len(t), 1.0, 0.0] for t in texts])

    df = spark.createDataFrame([(1, "abc"), (2, "")], "rid long, sentence string")
    got = {r["rid"]: r["vec"] for r in PretrainedEncoder(dim=3, session=Fake).encode(df, "rid").collect()}
    assert np.allclose(got[1], np.array([3, 1, 0]) / np.sqrt(10)) and np.allclose(got[2], [0, 1, 0])
    with pytest.raises(Exception, match="the model gives"):
        PretrainedEncoder(dim=4, session=Fake).encode(df, "rid").collect()


def _field(number, payload):
    """A protobuf field: a number, or bytes with their length."""

    def varint(n):
        out = b""
        while True:
            out += bytes([n & 127 | (128 if n > 127 else 0)])
            n >>= 7
            if not n:
                return out

    return varint(number << 3) + varint(payload) if isinstance(payload, int) else varint(number << 3 | 2) + varint(len(payload)) + payload


def tiny_model(table):
    """An ONNX model of one node: the rows of an embedding table for (batch, length) token ids."""
    dims = lambda *names: b"".join(_field(1, _field(2, n) if isinstance(n, bytes) else _field(1, n)) for n in names)
    value = lambda name, kind, *names: _field(1, name) + _field(2, _field(1, _field(1, kind) + _field(2, dims(*names))))
    weights = _field(1, table.shape[0]) + _field(1, table.shape[1]) + _field(2, 1) + _field(8, b"table") + _field(9, table.astype("<f4").tobytes())
    node = _field(1, b"table") + _field(1, b"input_ids") + _field(2, b"hidden") + _field(4, b"Gather")
    graph = _field(1, node) + _field(2, b"g") + _field(5, weights) + _field(11, value(b"input_ids", 7, b"n", b"t")) + _field(12, value(b"hidden", 1, b"n", b"t", table.shape[1]))
    return _field(1, 8) + _field(7, graph) + _field(8, _field(2, 13))


def test_a_real_model_file(spark, tmp_path):
    """A small ONNX file and its tokenizer, through the runtime: mean-pooled token vectors at unit length, cut at max_tokens."""
    tokenizers = pytest.importorskip("tokenizers")
    pytest.importorskip("onnxruntime")
    vocab = {"[PAD]": 0, "[UNK]": 1, "ada": 2, "love": 3, "bob": 4}
    table = np.random.default_rng(1).normal(size=(5, 6)).astype(np.float32)
    (tmp_path / "m.onnx").write_bytes(tiny_model(table))
    t = tokenizers.Tokenizer(tokenizers.models.WordLevel(vocab, unk_token="[UNK]"))
    t.pre_tokenizer = tokenizers.pre_tokenizers.Whitespace()
    t.save(str(tmp_path / "t.json"))
    texts = ["ada love", "bob", "zzz ada ada", "love bob ada ada ada", None]
    df = spark.createDataFrame(list(enumerate(texts)), "rid long, sentence string")
    e = PretrainedEncoder(str(tmp_path / "m.onnx"), str(tmp_path / "t.json"), dim=6, max_tokens=3)
    got = {r["rid"]: np.array(r["vec"]) for r in e.encode(df, "rid").collect()}
    for i, x in enumerate(texts):
        own = [vocab.get(w, 1) for w in (x or "").split()][:3]
        mean = table[own].mean(0) if own else np.zeros(6)
        assert np.allclose(got[i], mean / max(np.linalg.norm(mean), 1e-12), atol=1e-6)


def test_projection_store_and_quantization(spark, tmp_path):
    df = spark.createDataFrame([(1, "ada love"), (2, "bob")], "rid long, sentence string")
    base = HashedNgramEncoder(32)
    same = ProjectedEncoder(base, np.eye(32))
    same.save(spark, str(tmp_path / "w"))
    again = ProjectedEncoder.load(spark, str(tmp_path / "w"), base)
    a = {r["rid"]: np.array(r["vec"]) for r in base.encode(df, "rid").collect()}
    b = {r["rid"]: np.array(r["vec"]) for r in again.encode(df, "rid").collect()}
    assert all(np.allclose(a[i] / np.linalg.norm(a[i]), b[i], atol=1e-6) for i in a)
    save_index(base.encode(df, "rid"), str(tmp_path / "i"))
    assert spark.read.parquet(str(tmp_path / "i")).count() == 2
    for r in quantize_int8(base.encode(df, "rid"), "rid").collect():
        assert np.allclose(np.array(r["code"]) * r["scale"] / 127, a[r["rid"]], atol=r["scale"] / 127)


def test_tfidf(spark):
    ref = spark.createDataFrame([(1, "red cat"), (2, "red dog")], "rid long, sentence string")
    e = TfidfEncoder().fit(ref, "rid")
    w = {(r["rid"], r["term"]): r["w"] for r in e.sparse(ref, "rid").collect()}
    red, cat = 1.0, np.log(3 / 2) + 1
    assert np.isclose(w[1, "red"], red / np.hypot(red, cat)) and np.isclose(w[1, "cat"], cat / np.hypot(red, cat))
    assert e.sparse(spark.createDataFrame([(5, "blue")], "rid long, sentence string"), "rid").count() == 0
    assert len(e.encode(ref, "rid").first()["vec"]) == 4096


@settings(max_examples=4, deadline=None, phases=[Phase.generate])
@given(st.lists(st.text("ab", max_size=6), min_size=1, max_size=12), st.lists(st.text("ab", max_size=6), min_size=1, max_size=12), st.integers(0, 2))
def test_edit_join_is_exact(spark, a, b, most):
    x = spark.createDataFrame(list(enumerate(a)), "a_id long, v string")
    y = spark.createDataFrame(list(enumerate(b)), "b_id long, v string")
    want = sorted((r["a_id"], r["b_id"]) for r in x.crossJoin(y.withColumnRenamed("v", "w")).where(F.levenshtein("v", "w") <= most).where("v <> '' and w <> ''").collect())
    assert sorted((r["a_id"], r["b_id"]) for r in edit_join(x, y, "v", most).collect()) == want


def test_edit_join_never_matches_blanks_and_nulls(spark):
    x = spark.createDataFrame([(1, ""), (2, None), (3, "a"), (4, "abc")], "a_id long, v string")
    y = spark.createDataFrame([(1, ""), (2, None), (3, "b"), (4, "abd")], "b_id long, v string")
    assert sorted(map(tuple, edit_join(x, y, "v", 2).collect())) == [(3, 3, 1), (3, 4, 2), (4, 3, 2), (4, 4, 1)]


def test_hot_keys_are_split_and_nothing_is_lost(spark):
    a = spark.range(0, 300).select(F.col("id").alias("qid"), F.lit("hot").alias("k"), F.lit(1).alias("qw")).unionByName(spark.range(0, 9).select(F.col("id").alias("qid"), F.concat(F.lit("k"), F.col("id")).alias("k"), F.lit(1).alias("qw")))
    b = spark.range(0, 200).select(F.col("id").alias("rid"), F.lit("hot").alias("k")).unionByName(spark.range(0, 5).select(F.col("id").alias("rid"), F.concat(F.lit("k"), F.col("id")).alias("k")))
    got = G.pairs_by_key(a, b, "k", pairs=1000)
    assert got.count() == 300 * 200 + 5 and got.distinct().count() == got.count()
    assert max(r["count"] for r in got.groupBy(F.spark_partition_id()).count().collect()) < 60_000


def test_best_leaves_by_looking_at_all(spark):
    """The descents find the same leaves as costs of all of them would, and look at few nodes."""
    rng = np.random.default_rng(9)
    x = rng.normal(size=(500, 6))
    tree = G.Tree.grow(x, 4, rng)
    q = rng.normal(size=(40, 6))

    def costs(v, node=0, cost=0.0):
        if tree.left[node] < 0:
            return [(cost, node)]
        side = float(v @ tree.normals[node] - tree.offsets[node])
        return costs(v, tree.left[node], cost + max(side, 0)) + costs(v, tree.right[node], cost + max(-side, 0))

    for probes in (1, 3, 9):
        row, leaf = tree.leaves(q, probes)
        for i in range(len(q)):
            want = sorted(costs(q[i]))
            got = [dict((n, c) for c, n in want)[x] for x in leaf[row == i]]
            assert np.allclose(got, [c for c, _ in want[:probes]])


def test_broadcast_models_have_a_bound(spark, monkeypatch):
    monkeypatch.setattr(G, "MODEL_BYTES", 100)
    with pytest.raises(ValueError, match="MODEL_BYTES"):
        G.Forest.fit(vecs(spark, X, "rid"), trees=2, leaf=8)


def test_rerank_gives_exact_similarities(both):
    q, r = both
    for metric in ("cosine", "dot", "euclidean"):
        want = {(x["qid"], x["rid"]): x["sim"] for x in G.knn_exact(q, r, 4, metric).collect()}
        again = {(x["qid"], x["rid"]): x["sim"] for x in G.rerank(G.knn_exact(q, r, 9, metric), q, r, 4, metric).collect()}
        assert want.keys() == again.keys() and all(abs(want[k] - again[k]) < 1e-6 for k in want)


def test_passages_and_copies(spark):
    from recordlink.operators.relational import containing, exact_copies

    texts = ["a b c d e f g h", "xx one two three four five six seven yy", "one two three four five six seven", "three four fiv", None, "a  b c d", "q a b c d e f g hq", ""]
    passages = ["one two three four five six seven", "b c d e f g", "e four", "two three four", "a b", "z", " c d e ", "nowhere at all in these texts"]
    t = spark.createDataFrame(list(enumerate(texts)), "i long, text string")
    p = spark.createDataFrame(list(enumerate(passages)), "j long, passage string")
    want = sorted((i, j) for i, x in enumerate(texts) for j, y in enumerate(passages) if x is not None and y in x)
    assert sorted((r["i"], r["j"]) for r in containing(t, p, "text", "passage").collect()) == want and len(want) >= 8
    c = exact_copies(spark.createDataFrame([(3, "x"), (1, "x"), (2, "y"), (5, None), (6, None)], "i long, text string"), "i", "text")
    assert sorted(map(tuple, c.collect())) == [(1, 1, 2), (3, 1, 2)]


def test_joint_query_never_matches_blanks(spark):
    cols = "long, email string, username string, domain string, servername string, status string"
    q = spark.createDataFrame([(1, "", "u", "d", "s", "A"), (2, None, "", "", "", "")], f"qid {cols}")
    r = spark.createDataFrame([(7, "", "u", "d", "s", "A"), (8, None, "", "", "", "")], f"rid {cols}")
    assert joint_query(q, r, mode="all").count() == 0
    assert rows(joint_query(q, r, mode="any")) == [(1, 1, 7)]
    assert rows(joint_query(q, r, mode="ladder")) == [(1, 1, 7)]


def test_minhash_finds_similar_word_sets_and_no_blanks(spark):
    rng = np.random.default_rng(3)
    base = [{f"w{x}" for x in rng.choice(400, 12, replace=False)} for _ in range(60)]
    near = [set(list(s)[:-2]) | {f"z{i}"} for i, s in enumerate(base)]  # ten of thirteen words in common
    q = spark.createDataFrame([(i, " ".join(s)) for i, s in enumerate(near)] + [(900, None), (901, " ,. ")], "qid long, sentence string")
    r = spark.createDataFrame([(i, " ".join(s)) for i, s in enumerate(base)] + [(900, ""), (901, None)], "rid long, sentence string")
    got = {x["qid"]: (x["rid"], x["sim"]) for x in minhash_search(q, r, 1).collect()}
    assert got == {i: (i, round(10 / 13, 9)) for i in range(60)}
    assert minhash_search(q, r.where("false"), 2).count() == 0


def test_sparse_search_writes_no_pairs_and_knows_what_shares_a_key(spark, monkeypatch):
    """Against brute force: negative and zero sums, rows without a common key, few rows, keys of both kinds in one block."""
    monkeypatch.setattr(G, "pairs_by_key", lambda *a, **kw: pytest.fail("pairs are dealt"))
    rng = np.random.default_rng(5)

    def posts(n, i):
        out = []
        for x in range(n):
            keys = set(rng.choice(30, rng.integers(1, 4), replace=False).tolist()) | ({"hot"} if x % 3 else set())
            out += [(x, str(key), int(rng.choice([-2, -1, 1, 2]))) for key in keys]
        return out, spark.createDataFrame(out, f"{i} long, bucket string, weight int")

    def vector(rows):
        got = {}
        for x, key, w in rows:
            got.setdefault(x, {})[key] = w
        return got

    (a, q), (b, r) = posts(40, "qid"), posts(70, "rid")
    x, y = vector(a), vector(b)
    square = lambda v: sum(w * w for w in v.values())
    for k, block in ((3, 16), (9, 1000), (60, 16)):
        want = []
        for i, v in x.items():
            sims = [(-round(sum(w * u.get(key, 0) for key, w in v.items()) / np.sqrt(square(v) * square(u)), 9), j) for j, u in y.items() if v.keys() & u.keys()]
            want += [(i, n, j, -s) for n, (s, j) in enumerate(sorted(sims)[:k], 1)]
        got = G.knn_sparse(q, r, k, block_rows=block)
        assert sorted((g["qid"], g["rank"], g["rid"], round(g["sim"], 6) + 0.0) for g in got.collect()) == sorted((i, n, j, round(s, 6) + 0.0) for i, n, j, s in want)
    assert G.knn_sparse(q, r.where("false"), 3).count() == 0
    assert G.knn_sparse(q.where("false"), r, 3).count() == 0


def test_region_map_keeps_its_vectors_compressed(spark, sf_dir, monkeypatch):
    """A checkpoint would hold both sides' vectors as they lie in memory."""
    from recordlink import catalog

    once = G.once
    monkeypatch.setattr(catalog.G, "once", lambda df: pytest.fail("a checkpoint of vectors") if "vec" in df.columns else once(df))
    assert catalog.QUERIES["m_region_map"](spark, sf_dir).count() > 0


def test_sparse_search_sifts_few_keys_in_single_precision(spark, monkeypatch):
    """F2: whole blocks were multiplied, scaled and partitioned in double precision; rows whose k best are positive need none of it."""
    got = {}
    monkeypatch.setattr(G, "_lead", lambda q, cols, files, asked, stored, visit: got.update(files=files, asked=asked, stored=stored, visit=visit) or q)
    rng = np.random.default_rng(11)
    x, y = (np.where(rng.random((n, 64)) < 0.4, rng.integers(1, 9, (n, 64)), 0) for n in (50, 300))
    y[40:80], y[200] = y[:40], 3 * y[100]  # equal and parallel rows: ties go by id
    side = lambda m, i: spark.createDataFrame([(int(r), int(c), int(m[r, c])) for r, c in zip(*np.nonzero(m), strict=True)], f"{i} long, bucket int, weight int")
    G.knn_sparse(side(x, "qid"), side(y, "rid"), 5, block_rows=90)
    batch = lambda m: G.pa.RecordBatch.from_pydict({"id": list(range(len(m))), "key": [np.flatnonzero(r).tolist() for r in m], "weight": [r[r != 0].astype(float).tolist() for r in m]})
    blocks = [(b.column(0).to_numpy(), got["stored"](b)) for b in (G.get_batch(f) for f in got["files"])]
    monkeypatch.setattr(G, "_dots", lambda *a: pytest.fail("a block in double precision"))
    (found,) = got["visit"](np.arange(50), got["asked"]([batch(x)]), blocks)
    sims = np.round(x @ y.T / np.sqrt((x * x).sum(1)[:, None] * (y * y).sum(1)), 9)
    want = [(i, j, n, sims[i, j]) for i in range(50) for n, j in enumerate(np.lexsort((np.arange(300), -sims[i]))[:5].tolist(), 1)]
    assert [(i, j, n) for i, j, n, _ in zip(*found, strict=True)] == [w[:3] for w in want]
    assert np.abs(found[3] - [w[3] for w in want]).max() < 2e-9
