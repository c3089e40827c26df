"""Ground truth by exhaustive search, and the training of the encoder behind it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.similarity import field_similarity
from ..functions.vectors import cosine, matrix, unit
from ..operators.gather import brute_cosine
from ..operators.tag import tag_pairs
from ..operators.verify import attach_fields, composite_score, select_best
from ..schema import RecordSchema
from ..sources.shared import settle, shared_folder


def exhaustive_pairs(q: DataFrame, ref: DataFrame, threshold: float = 0.8) -> DataFrame:
    """All pairs of vectors with a cosine strictly over the threshold."""
    return brute_cosine(q, ref, threshold=threshold)


def exhaustive_truth(pairs: DataFrame, queries: DataFrame, ref: DataFrame, schema: RecordSchema) -> DataFrame:
    """(qid, truth_rid, truth_tag): the pairs over the threshold, approximately matched, the best of each query tagged."""
    scored = composite_score(attach_fields(pairs.select("qid", "rid", "sim"), queries, ref, schema), schema)
    tags = tag_pairs(select_best(scored), queries, ref, schema)
    return tags.select("qid", F.col("rid").alias("truth_rid"), F.col("tag").alias("truth_tag"))


def truth_sweep(pairs: DataFrame, truth: DataFrame, thresholds: tuple[float, ...] = (0.5, 0.55, 0.6, 0.65, 0.7, 0.75, 0.8, 0.85, 0.9, 0.95)) -> DataFrame:
    """(threshold, pairs, true_pairs, precision, recall) for pairs gathered at the lowest threshold."""
    known = truth.where("truth_rid is not null").select("qid", F.col("truth_rid").alias("rid"), F.lit(1).alias("t"))
    total = F.broadcast(known.agg(F.count("*").alias("total")))
    df = pairs.join(known, ["qid", "rid"], "left").select("sim", "t", F.explode(F.array(*[F.lit(t) for t in thresholds])).alias("threshold")).where("sim > threshold")
    c = df.groupBy("threshold").agg(F.count("*").alias("pairs"), F.count("t").alias("true_pairs")).join(total)
    return c.select("threshold", "pairs", "true_pairs", F.round(F.col("true_pairs") / F.col("pairs"), 6).alias("precision"), F.round(F.col("true_pairs") / F.col("total"), 6).alias("recall"))


# ------------------------------------------------------------------ contrastive training of a linear head


def batch_loss(a: np.ndarray, p: np.ndarray, w: np.ndarray, scale: float = 1.0) -> tuple[float, np.ndarray]:
    """Mean over anchors of the negative log-softmax of the own positive among the batch's, on cosines times ``scale`` after
    projecting both sides by w; and the gradient by w."""
    za, zp = a @ w.T, p @ w.T
    na, np_ = np.linalg.norm(za, axis=1, keepdims=True), np.linalg.norm(zp, axis=1, keepdims=True)
    na, np_ = np.where(na > 0, na, 1), np.where(np_ > 0, np_, 1)
    ua, up = za / na, zp / np_
    s = scale * ua @ up.T
    s -= s.max(1, keepdims=True)
    e = np.exp(s)
    soft = e / e.sum(1, keepdims=True)
    n = len(a)
    loss = float(-np.log(np.maximum(np.diag(soft), 1e-300)).mean())
    g = scale * (soft - np.eye(n)) / n
    ga, gp = g @ up, g.T @ ua
    ga = (ga - ua * (ga * ua).sum(1, keepdims=True)) / na
    gp = (gp - up * (gp * up).sum(1, keepdims=True)) / np_
    return loss, ga.T @ a + gp.T @ p


def loss_sql(batches: DataFrame, scale: float = 1.0) -> DataFrame:
    """(batch, loss) of (batch, i, anchor, positive): the same loss by joins, for checks."""
    a = batches.select("batch", "i", "anchor")
    p = batches.select("batch", F.col("i").alias("j"), "positive")
    s = a.join(p, "batch").select("batch", "i", "j", (scale * cosine(F.col("anchor"), F.col("positive"))).alias("s"))
    each = s.groupBy("batch", "i").agg(F.log(F.sum(F.exp("s"))).alias("z"), F.max(F.when(F.col("i") == F.col("j"), F.col("s"))).alias("own"))
    return each.groupBy("batch").agg(F.round(F.avg(F.col("z") - F.col("own")), 6).alias("loss"))


def mine_pairs(truth: DataFrame, queries: DataFrame, ref: DataFrame, train: str | None = "train") -> DataFrame:
    """(qid, anchor, positive) vectors of true pairs; ``train``: a boolean column of truth that chooses them."""
    t = truth.where("truth_rid is not null")
    if train:
        t = t.where(F.col(train))
    q = queries.select("qid", F.col("vec").alias("anchor"))
    r = ref.select(F.col("rid").alias("truth_rid"), F.col("vec").alias("positive"))
    return t.select("qid", "truth_rid").join(q, "qid").join(r, "truth_rid").select("qid", "anchor", "positive")


def assign_batches(pairs: DataFrame, size: int = 64, seed: int = 7) -> DataFrame:
    """``batch`` by hashed order: within hash buckets of about a thousand rows, so that no task sorts all pairs."""
    buckets = max(1, pairs.count() // 1024)
    df = pairs.select("qid", F.col("anchor").cast("array<float>").alias("anchor"), F.col("positive").cast("array<float>").alias("positive")).withColumn("bucket", F.pmod(F.xxhash64(F.lit(seed), "qid"), F.lit(buckets)))
    w = Window.partitionBy("bucket").orderBy(F.xxhash64(F.lit(seed + 1), "qid"), "qid")
    df = df.withColumn("row", F.row_number().over(w) - 1)
    return df.withColumn("batch", F.col("bucket") * 100_000 + F.floor(F.col("row") / size)).drop("bucket", "row")


def finetune(pairs: DataFrame, dim: int, epochs: int = 1, size: int = 64, rate: float = 0.5, scale: float = 20.0, seed: int = 7, parallel: int = 1) -> tuple[np.ndarray, DataFrame]:
    """(w, loss curve): a square matrix after the frozen encoder, from the identity, by plain gradient steps.

    A step takes about ``parallel`` batches in one job: tasks send back one gradient each, their mean moves w, and w (dim x dim
    numbers) goes out again.  Pairs are written once, a folder a step, so that a step reads its own alone.  Batches too small to
    hold a negative are skipped.
    """
    spark = pairs.sparkSession
    batched = assign_batches(pairs, size, seed)
    whole = batched.groupBy("batch").agg(F.count("*").alias("n")).where("n > 1").select("batch")
    total = whole.count()
    if not total:
        return np.eye(dim), spark.createDataFrame([], "step int, loss double")
    # Batches in hashed order, so many a step; the ranks are made in hash buckets, so that no task sorts all batches.
    steps = -(-total // parallel)
    step = F.pmod(F.xxhash64(F.lit(seed + 2), "batch"), F.lit(steps)) if parallel > 1 else F.row_number().over(Window.orderBy(F.xxhash64(F.lit(seed + 2), "batch"), "batch")) - 1
    path = shared_folder(spark, "training")
    batched.join(whole.withColumn("step", step.cast("int")), "batch").repartition("step").sortWithinPartitions("batch", "qid").write.partitionBy("step").parquet(path)
    data = spark.read.schema("qid long, anchor array<float>, positive array<float>, batch long, step int").parquet(path)
    w, curve, at = np.eye(dim), [], 0
    schema = T.StructType([T.StructField("loss", T.DoubleType()), T.StructField("grad", T.BinaryType())])
    for _ in range(epochs):
        for k in range(steps):
            shared = spark.sparkContext.broadcast(w)

            def run(frames: Iterator[pd.DataFrame], shared=shared) -> Iterator[pd.DataFrame]:
                rows = [f for f in frames if len(f)]
                if rows:
                    for _, f in pd.concat(rows).groupby("batch"):
                        loss, g = batch_loss(unit(matrix(f["anchor"])), unit(matrix(f["positive"])), shared.value, scale)
                        yield pd.DataFrame({"loss": [loss], "grad": [g.tobytes()]})

            got = data.where(F.col("step") == k).mapInPandas(run, schema).collect()  # a gradient a batch of the step
            shared.unpersist()
            if got:
                w = w - rate * sum(np.frombuffer(r["grad"]).reshape(dim, dim) for r in got) / len(got)
                curve.append((at, float(np.mean([r["loss"] for r in got]))))
                at += 1
    return w, spark.createDataFrame(curve, "step int, loss double")


def learned_weights(scored: DataFrame, truth: DataFrame, schema: RecordSchema) -> dict[str, float]:
    """Field weights by logistic regression on the similarities of true and false candidate pairs (negative ones become 0)."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    rows = scored.join(truth.select("qid", "truth_rid"), "qid")
    rows = rows.select(*[F.col("sims")[n].alias(n) for n in schema.names], F.coalesce(F.col("rid") == F.col("truth_rid"), F.lit(False)).cast("double").alias("label"))
    model = LogisticRegression(maxIter=50, regParam=1e-3).fit(VectorAssembler(inputCols=schema.names, outputCol="features").transform(rows))
    c = np.maximum(model.coefficients.toArray(), 0)
    c = c / c.sum() if c.sum() > 0 else np.full(len(c), 1 / len(c))
    return {n: float(x) for n, x in zip(schema.names, c, strict=True)}


class LearnedSimilarity:
    """A small net over the fields' similarities of a pair, the same for both orders of its sides, in place of the weighted mean."""

    def __init__(self, model, schema: RecordSchema) -> None:
        self.model, self.schema = model, schema

    @classmethod
    def fit(cls, pairs: DataFrame, truth: DataFrame, schema: RecordSchema, hidden: int = 8, seed: int = 7) -> LearnedSimilarity:
        """From candidate pairs with both sides' fields (attach_fields); those that ``truth`` names are true, all others of its
        queries false.  There must be some of both."""
        from pyspark.ml.classification import MultilayerPerceptronClassifier

        named = truth.select("qid", "truth_rid")
        rows = settle(cls._features(pairs.join(named, "qid"), schema).withColumn("label", F.coalesce(F.col("rid") == F.col("truth_rid"), F.lit(False)).cast("double")).select("features", "label"))
        if rows.select("label").distinct().count() < 2:
            raise ValueError("true and false pairs are needed")
        net = MultilayerPerceptronClassifier(layers=[4 * len(schema.names), hidden, 2], maxIter=60, seed=seed)
        return cls(net.fit(rows), schema)

    @staticmethod
    def _features(pairs: DataFrame, schema: RecordSchema) -> DataFrame:
        """By field: similarity under two norms, equality, and whether both sides have a value."""
        from pyspark.ml.functions import array_to_vector

        each = []
        for n in schema.names:
            a, b = (schema[n].normal(F.coalesce(F.col(f"{side}_{n}"), F.lit(""))) for side in "qr")
            each += [field_similarity(a, b), field_similarity(a, b, "metric"), (a == b).cast("double"), ((a != "") & (b != "")).cast("double")]
        return pairs.withColumn("features", array_to_vector(F.array(*each)))

    def score(self, pairs: DataFrame) -> DataFrame:
        """``pairs`` with ``score``, the net's probability that they are true."""
        from pyspark.ml.functions import vector_to_array

        done = self.model.transform(self._features(pairs, self.schema))
        return done.withColumn("score", vector_to_array("probability")[1]).select(*[c for c in pairs.columns if c != "score"], "score")
