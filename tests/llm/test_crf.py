from itertools import product

import numpy as np
from pyspark.sql import functions as F

from recordlink.llm import crf, lm
from recordlink.llm.queries import op8_quality_crf


def test_marginals_match_all_labelings():
    rng = np.random.default_rng(2)
    model = crf.Crf(np.zeros(crf.SIZE), rng.normal(size=(2, 2)), rng.normal(size=2))
    offsets = np.array([0, 3, 3, 4, 9])
    unary = rng.normal(size=9) * 2
    good, at, pair = model.marginals(unary, offsets, pairs=True)
    for lo, hi in zip(offsets, offsets[1:]):
        n = hi - lo
        if not n:
            continue
        p, joint, total = np.zeros(n), np.zeros((n, 2, 2)), 0.0
        for y in product((0, 1), repeat=n):
            s = model.start[y[0]] + sum(unary[lo + i] * y[i] for i in range(n)) + sum(model.trans[y[i - 1], y[i]] for i in range(1, n))
            total += np.exp(s)
            p += np.exp(s) * np.array(y)
            for i in range(1, n):
                joint[i, y[i - 1], y[i]] += np.exp(s)
        assert np.allclose(good[lo:hi], p / total)
        for i in range(1, n):
            assert np.allclose(pair[list(at).index(lo + i)], joint[i] / total)


def test_neighbours_change_a_label():
    bad, fine = b"| x | y | z | w |", b"These are ordinary words that end well."
    docs = [[fine] * 5, [bad] * 5] * 20
    model = crf.fit(docs, [1, 0] * 20)
    x, offsets, _ = crf._layout([[b"maybe some words"] + [fine] * 3, [b"maybe some words"] + [bad] * 3])
    good, _, _ = model.marginals(x @ model.weights, offsets)
    assert good[0] > good[4]


def test_held_out_accuracy(spark, sf_dir):
    big = sf_dir.replace("0.001", "0.01")
    labels = spark.read.parquet(f"{big}/labels.parquet")
    scored = op8_quality_crf(spark, big)
    assert scored.count() == spark.read.parquet(f"{big}/documents.parquet").count()
    held = scored.where("held_out").join(labels, "doc_id")
    right = held.where(F.col("predicted") == F.col("quality")).count()
    assert right >= 0.93 * held.count()
    assert scored.where("score < 0 or score > 1 or score is null").count() == 0


def test_labels_of_held_out_rows_are_not_used(spark, docs, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    turned = labels.withColumn("quality", F.when(lm.held_out_column(labels, 4, {2}), 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = (crf.labelled_sample(docs, x, crf.train_rows(4, {2}), 500) for x in (labels, turned))
    assert a == b and len(a[0]) > 20


def test_odd(spark, odd, none):
    labels = spark.createDataFrame([(1, 1), (4, 1), (5, 0), (5, 1), (7, 0), (8, None), (None, 1), (99, 1)], "doc_id long, quality int")
    lines, y = crf.labelled_sample(odd, labels, None, 100)
    assert sorted(y) == [0, 0, 1, 1] and lines[y.index(1)] in ([b""], [b"One two three", b"One two three", b"four"])
    model = crf.fit(lines, y)
    rows = crf.score(odd, model, keep=("doc_id", "n_words")).collect()
    assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
    assert crf.score(none, model).count() == 0
    empty = crf.fit(*crf.labelled_sample(odd, labels.where("false"), None, 100))
    assert crf.score(odd, empty).count() == odd.count()
    made = crf.line_labels(odd.where("doc_id = 5"), model).first()["lines"]
    assert [x["text"] for x in made] == ["one TWO three", "one two THREE", "four"]


def test_the_sample_is_bounded_by_documents_and_bytes_and_cuts_none(spark):
    df = spark.createDataFrame([(f"d{i}", f"line {i}\n" * (i % 7 + 1)) for i in range(60)] + [("d3", "zz")], "doc_id string, text string")
    labels = spark.createDataFrame([(f"d{i}", i % 2) for i in range(60)], "doc_id string, quality int")
    every, y = crf.labelled_sample(df, labels)
    assert len(every) == 60 and sorted(y) == [0] * 30 + [1] * 30 and [b"line 3"] * 4 + [b""] in every  # the first of repeated ids
    few, z = crf.labelled_sample(df, labels, max_docs=20)
    assert (few, z) == (every[:20], y[:20])
    some, z = crf.labelled_sample(df, labels, max_bytes=200)
    size = [sum(map(len, d)) + len(d) - 1 for d in every]
    n = len(some)
    assert some == every[:n] and sum(size[: n - 1]) < 200 <= sum(size[:n])
    assert crf.labelled_sample(df.repartition(5), labels.repartition(3), max_bytes=200) == (some, z)


def test_stay_weights_end_within_their_bound_and_the_others_fit_them():
    bad, fine = b"| x | y | z | w |", b"These are ordinary words that end well."
    docs, y = [[fine] * 5, [bad] * 5, [fine, bad, fine], [bad, fine, bad]] * 10, [1, 0, 1, 0] * 10
    free, held = crf.fit(docs, y, max_stay=99.0), crf.fit(docs, y, max_stay=0.2)
    assert np.abs(np.diag(held.trans)).max() <= 0.2 < np.abs(np.diag(free.trans)).max()
    assert np.linalg.norm(held.weights - free.weights) > 1e-3


def test_a_score_is_the_length_weighted_mean_of_marginals(spark):
    """Brute force over all labelings of a few lines, from the line facts on."""
    rng = np.random.default_rng(3)
    model = crf.Crf(rng.normal(size=crf.SIZE), rng.normal(size=(2, 2)), rng.normal(size=2), 1.3, 0.2)
    text = "One fine line here.\n| a | b |\n\nxx 12 $$"
    lines = text.encode().split(b"\n")
    unary, total, good = crf.features(lines) @ model.weights, 0.0, np.zeros(len(lines))
    for y in product((0, 1), repeat=len(lines)):
        p = np.exp(model.start[y[0]] + sum(u * v for u, v in zip(unary, y)) + sum(model.trans[a, b] for a, b in zip(y, y[1:])))
        total, good = total + p, good + p * np.array(y)
    size = np.array([len(x) for x in lines])
    mean = (good / total * size).sum() / size.sum()
    want = 1 / (1 + np.exp(-(1.3 * np.log(mean / (1 - mean)) + 0.2)))
    long = "\n".join(f"line {i} of many." for i in range(60_000))
    rows = {r["doc_id"]: r for r in crf.score(spark.createDataFrame([("a", text), ("b", long)], "doc_id string, text string"), model).collect()}
    assert abs(rows["a"]["score"] - want) < 1e-5 and rows["b"]["n_lines"] == 60_000 and 0 <= rows["b"]["score"] <= 1
