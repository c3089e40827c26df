import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from recordlink.operators.encode import HashedNgramEncoder
from recordlink.operators.verify import attach_fields, select_best
from recordlink.plans import experiments as E
from recordlink.plans import measures as M
from recordlink.plans import truth as TR
from recordlink.plans.linker import Linker, choose_gatherer
from recordlink.schema import USER
from recordlink.sources import fixtures as X


@pytest.fixture(scope="module")
def users(spark, sf_dir):
    return X.srv_users(spark, sf_dir).cache(), X.ref_users(spark, sf_dir).cache()


def test_every_gatherer_links(users):
    q, r = users
    truth = q.select("qid", "truth_rid")
    for name, options in (("knn", {}), ("pruned", {"pivots": 8}), ("ivf", {"cells": 8, "probes": 4}), ("forest", {"trees": 6, "probes": 2}), ("lexical", {}), ("joint", {"mode": "ladder"}), ("brute_cosine", {}), ("brute_score", {}), (None, {})):
        links = Linker(USER, HashedNgramEncoder(128), gatherer=name, sentence="values", options=options).fit(r).link(q)
        assert links.count() == q.count()
        conf = M.link_confusion(links, truth).first()
        assert conf["tp"] >= (0.6 if name == "joint" else 0.9) * (conf["tp"] + conf["fn"]), name


def test_full_scores_of_candidates_agree_with_brute_force(users):
    q, r = users
    a = Linker(USER, gatherer="brute_score", k=1).fit(r).link(q).select("qid", "rid").collect()
    b = {x["qid"]: x["rid"] for x in Linker(USER, HashedNgramEncoder(), sentence="values", k=20).fit(r).link(q).collect()}
    assert sum(b[x["qid"]] == x["rid"] for x in a) >= 0.95 * len(a)


def test_adding_an_exact_copy_puts_it_first(spark, users):
    q, r = users
    one = r.limit(1).select(F.lit(77).cast("long").alias("qid"), *USER.names)
    best = Linker(USER, HashedNgramEncoder(), sentence="values").fit(r).link(one).first()
    assert best["score"] == pytest.approx(1) and best["tag"] == "consistent"


def test_choice_of_gatherer():
    assert choose_gatherer(10) == "knn" and choose_gatherer(10**8) == "pruned" and choose_gatherer(10**8, exact=False) == "ivf"


def test_loss_and_gradient():
    rng = np.random.default_rng(0)
    a, p, w = rng.normal(size=(5, 4)), rng.normal(size=(5, 4)), np.eye(4) + 0.1 * rng.normal(size=(4, 4))
    for scale in (1.0, 20.0):
        loss, grad = TR.batch_loss(a, p, w, scale)
        for i, j in ((0, 0), (1, 3), (3, 2)):
            d = np.zeros((4, 4))
            d[i, j] = 1e-6
            assert abs((TR.batch_loss(a, p, w + d, scale)[0] - TR.batch_loss(a, p, w - d, scale)[0]) / 2e-6 - grad[i, j]) < 1e-5
    same = np.ones((6, 4))
    assert abs(TR.batch_loss(same, same, np.eye(4))[0] - math.log(6)) < 1e-12
    two = np.array([[1.0, 0], [-1.0, 0]])
    for s in (1.0, 3.0):
        assert abs(TR.batch_loss(two, two, np.eye(2), s)[0] - math.log(1 + math.exp(-2 * s))) < 1e-12


def test_training_lowers_the_loss_and_does_not_hurt_recall(spark, sf_dir):
    got = E.w2_finetune(spark, sf_dir, ks=(1, 5), dim=64).collect()
    value = {(r["method"], r["variant"], r["k"]): r["value"] for r in got if r["measure"] == "recall"}
    loss = {r["measure"]: r["value"] for r in got if r["method"] == "loss"}
    assert loss["end"] < loss["start"]
    assert value["knn", "fine-tuned", 1] >= value["knn", "frozen", 1] - 0.02
    for (m, v, k), x in value.items():
        assert k == 5 or x <= value[m, v, 5]


def test_zero_steps_are_the_frozen_encoder(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0], [1.0, 0.0])], "qid long, anchor array<float>, positive array<float>")
    w, curve = TR.finetune(df, 2)  # one pair has no negative: no batch, no step
    assert (w == np.eye(2)).all() and curve.count() == 0


def test_measures_by_hand(spark):
    truth = spark.createDataFrame([(1, 10), (2, 20), (3, None), (4, None)], "qid long, truth_rid long")
    links = spark.createDataFrame([(1, 10), (2, 99), (3, 30)], "qid long, rid long")
    c = M.link_confusion(links, truth).first()
    assert (c["tp"], c["fp"], c["fn"], c["tn"], c["n"], c["right"]) == (1, 2, 1, 1, 4, 2)
    r = M.prf(M.link_confusion(links, truth)).first()
    assert (r["accuracy"], r["precision"], r["recall"], r["f1"]) == (0.5, 0.333333, 0.5, 0.4)
    cands = spark.createDataFrame([(1, 10, 2, 0.5), (2, 21, 1, 0.5)], "qid long, rid long, rank int, sim double")
    assert {x["k"]: x["recall"] for x in M.recall_at_k(cands, truth, (1, 2)).collect()} == {1: 0.0, 2: 0.5}
    ratio = {x["m"]: x["ratio"] for x in M.limit_ratio(spark).collect()}
    assert abs(ratio[1500] - 3.48e-3) < 1e-5 and abs(ratio[15000] - 3.56e-4) < 1e-6 and abs(ratio[1_000_000] - 5.6e-6) < 1e-7
    t = M.time_ratio(spark, {"a": 2.0, "b": 0.5}, "a")
    assert {x["method"]: x["ratio"] for x in t.collect()} == {"a": 1.0, "b": 4.0}
    f = spark.createDataFrame([("a", 0.9, 1.0), ("b", 0.95, 2.0), ("c", 0.85, 3.0)], "method string, recall double, seconds double")
    assert {x["method"] for x in M.frontier(f).collect()} == {"a", "b"}


def test_tag_measures_by_hand(spark):
    tags = spark.createDataFrame([(1, 10, "consistent"), (2, 20, "contradiction:email"), (3, 31, "consistent"), (4, None, "unlinked"), (5, 50, "consistent")], "qid long, rid long, tag string")
    truth = spark.createDataFrame([(1, 10, "consistent"), (2, 20, "consistent"), (3, 30, "consistent"), (4, None, "unlinked"), (5, None, "unlinked")], "qid long, truth_rid long, truth_tag string")
    got = {r["tag"]: (r["n"], r["tp"], r["fp"], r["fn"]) for r in M.tag_prf(tags, truth).collect()}
    assert got == {"consistent": (3, 1, 2, 2), "contradiction:email": (0, 0, 1, 0), "unlinked": (2, 1, 0, 1)}
    m = M.macro(M.tag_prf(tags, truth)).first()
    assert m["classes"] == 3 and m["precision"] == round((1 / 3 + 0 + 1) / 3, 6) and m["recall"] == round((1 / 3 + 0 + 0.5) / 3, 6)


def test_learned_weights_sum_to_one(users):
    q, r = users
    linker = Linker(USER, HashedNgramEncoder(128), sentence="values").fit(r)
    w = TR.learned_weights(linker.score(linker.gather(q), q), q, USER)
    assert abs(sum(w.values()) - 1) < 1e-9
    USER.with_weights(w)


def test_learned_similarity(spark, users):
    q, r = users
    linker = Linker(USER, HashedNgramEncoder(128), sentence="values").fit(r)
    pairs = attach_fields(linker.gather(q), q, r, USER)
    net = TR.LearnedSimilarity.fit(pairs, q, USER)
    scored = net.score(pairs)
    assert scored.columns == [*pairs.columns, "score"] and scored.where("score not between 0 and 1").count() == 0
    best = select_best(scored).join(q.where("truth_rid is not null").select("qid", "truth_rid"), "qid")
    assert best.where("rid = truth_rid").count() >= 0.9 * best.count() > 0
    swapped = pairs.select("qid", "rid", *[F.col(f"{'r' if s == 'q' else 'q'}_{n}").alias(f"{s}_{n}") for n in USER.names for s in "qr"])
    a, b = ({(x["qid"], x["rid"]): x["score"] for x in net.score(p).collect()} for p in (pairs, swapped))
    assert all(abs(a[k] - b[k]) < 1e-9 for k in a)
    blank = spark.createDataFrame([(1, 2, *[None] * 10)], "qid long, rid long, " + ", ".join(f"{s}_{n} string" for n in USER.names for s in "qr"))
    assert net.score(blank).count() == 1 and net.score(blank.where("false")).count() == 0
    with pytest.raises(ValueError):
        TR.LearnedSimilarity.fit(pairs.where("false"), q, USER)


def test_small_experiments(spark, sf_dir):
    w1 = {(r["method"], r["measure"]): r["value"] for r in E.w1_retrieval(spark, sf_dir, ("joint", "knn", "lexical")).collect()}
    approximate = {(r["method"], r["measure"]): r["value"] for r in E.w1_recall(spark, sf_dir, ("kmeans_ann", "forest", "density_ann", "lsh")).collect()}
    assert all(v >= 0.8 for (_, n), v in approximate.items() if n == "recall")
    assert w1["joint", "recall"] < w1["knn", "recall"] >= 0.95
    w4 = {(r["method"], r["variant"], r["measure"]): r["value"] for r in E.w4_verify(spark, sf_dir).collect()}
    assert w4["verified", "light", "f1"] >= 0.9
    assert E.w9_audit(spark, sf_dir).count() > 0 and E.w8_serialize(spark.createDataFrame([(1, "", "lee.k", "lee.example.org", "server7", "Active"), (2, "a@b.c", "x", "y", "z", "Active")], "qid long, email string, username string, domain string, servername string, status string")).count() == 1


@pytest.mark.parametrize("name", ["m_cost_model", "m_limit_ratio", "w8_serialize"])
def test_measures_follow_the_given_tables(spark, sf_dir, name):
    """Another size of the tables, another result."""
    from recordlink import catalog

    small, large = (sorted(map(str, catalog.QUERIES[name](spark, d).collect())) for d in (sf_dir, sf_dir.replace("sf0.001", "sf0.01")))
    assert small and large and (small != large or sf_dir.endswith("sf0.01"))
