"""Recall, precision, accuracy, time, cost: how linkage is judged."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.shared import settle

KS = (1, 5, 10, 20, 50)


def recall_at_k(cands: DataFrame, truth: DataFrame, ks: tuple[int, ...] = KS) -> DataFrame:
    """(k, n, hits, recall): of the queries with a true row, the share that have it among their k first."""
    known = truth.where("truth_rid is not null").select("qid", "truth_rid")
    found = cands.select("qid", F.col("rid").alias("truth_rid"), "rank")
    best = known.join(found, ["qid", "truth_rid"], "left").groupBy("qid").agg(F.min("rank").alias("rank"))
    rows = best.select("rank", F.explode(F.array(*[F.lit(k) for k in ks])).alias("k"))
    hit = F.when(F.col("rank") <= F.col("k"), 1).otherwise(0)
    out = rows.groupBy("k").agg(F.count("*").alias("n"), F.sum(hit).cast("long").alias("hits"))
    return out.withColumn("recall", F.round(F.col("hits") / F.col("n"), 6))


def index_recall(approx: DataFrame, exact: DataFrame, ks: tuple[int, ...] = KS) -> DataFrame:
    """(k, recall): the share of the exact k nearest that an approximate gatherer has among its k first."""
    a = approx.select("qid", "rid", F.col("rank").alias("a"))
    rows = exact.join(a, ["qid", "rid"], "left").select("rank", "a", F.explode(F.array(*[F.lit(k) for k in ks])).alias("k")).where("rank <= k")
    return rows.groupBy("k").agg(F.round(F.avg(F.when(F.col("a") <= F.col("k"), 1.0).otherwise(0.0)), 6).alias("recall"))


def link_confusion(links: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """tp: the right row; fp: a wrong row, or any row for an orphan; fn: a linkable query not rightly linked; tn: an orphan
    left alone.  A wrongly linked query counts as fp and fn."""
    df = truth.join(links.select("qid", "rid"), "qid", "left")
    linkable, linked = F.col("truth_rid").isNotNull(), F.col("rid").isNotNull()
    right = linkable & F.coalesce(F.col("rid") == F.col("truth_rid"), F.lit(False))
    cases = {"tp": right, "fp": linked & ~right, "fn": linkable & ~right, "tn": ~linkable & ~linked}
    aggs = [F.sum(c.cast("long")).alias(n) for n, c in cases.items()]
    aggs += [F.count("*").alias("n"), F.sum((right | (~linkable & ~linked)).cast("long")).alias("right")]
    return df.groupBy(*(by or [])).agg(*aggs)


def prf(conf: DataFrame, average: str = "micro") -> DataFrame:
    """accuracy, precision, recall, f1 of a confusion table's rows; ``macro`` is the mean over them."""
    div = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    p, r = div(tp, tp + fp), div(tp, tp + fn)
    measures = {"accuracy": div(F.col("right"), F.col("n")), "precision": p, "recall": r, "f1": div(2 * p * r, p + r)}
    if average == "macro":
        return conf.select(*[c.alias(n) for n, c in measures.items()]).agg(*[F.round(F.avg(n), 6).alias(n) for n in measures])
    return conf.withColumns({n: F.round(c, 6) for n, c in measures.items()})


def pair_prf(pairs: DataFrame, truth_pairs: DataFrame) -> DataFrame:
    """Precision and recall of a set of pairs against another."""
    a = pairs.select("qid", "rid").distinct().withColumn("found", F.lit(1))
    b = truth_pairs.select("qid", F.col("truth_rid").alias("rid")).where("rid is not null").distinct().withColumn("true", F.lit(1))
    both = a.join(b, ["qid", "rid"], "full_outer")
    f, t = F.col("found").isNotNull(), F.col("true").isNotNull()
    c = both.agg(F.sum((f & t).cast("long")).alias("tp"), F.sum((f & ~t).cast("long")).alias("fp"), F.sum((~f & t).cast("long")).alias("fn"))
    return c.withColumns({"precision": F.round(F.col("tp") / F.greatest(F.col("tp") + F.col("fp"), F.lit(1)), 6), "recall": F.round(F.col("tp") / F.greatest(F.col("tp") + F.col("fn"), F.lit(1)), 6)})


def time_method(fn: Callable[[], DataFrame], repeat: int = 3, warmup: int = 1) -> float:
    """Median seconds to run a plan into nothing."""
    took = []
    for i in range(warmup + repeat):
        began = time.perf_counter()
        fn().write.mode("overwrite").format("noop").save()
        if i >= warmup:
            took.append(time.perf_counter() - began)
    return statistics.median(took)


def time_ratio(spark: SparkSession, seconds: dict[str, float], base: str) -> DataFrame:
    """(method, seconds, ratio): how many times faster than the base each method is."""
    return spark.createDataFrame([(m, s, seconds[base] / s) for m, s in seconds.items()], "method string, seconds double, ratio double")


def latency(spark: SparkSession, seconds: dict[str, float], queries: int, pairs: dict[str, int]) -> DataFrame:
    """(method, ms_per_query, pairs_per_s)."""
    return spark.createDataFrame([(m, 1000 * s / queries, pairs.get(m, 0) / s) for m, s in seconds.items()], "method string, ms_per_query double, pairs_per_s double")


def cost_model(spark: SparkSession, n: int, m: int, d: int = 768, k: int = 5, length: int = 25) -> DataFrame:
    """(stage, ours, brute) basic steps of n queries against m rows; the last row counts edit distances as tables of length^2."""
    lg = F.log2(F.lit(float(m)))
    one = spark.range(1)
    enc = F.lit(float((n + m) * d * d))
    rows = [
        ("encoding", enc, enc),
        ("search", n * lg, F.lit(float(n) * m)),
        ("verification", F.lit(float(n * k * length)), F.lit(float(n) * m * length)),
        ("total", enc + n * (lg + k * length), enc + F.lit(float(n) * m * (1 + length))),
        ("verification_quadratic", F.lit(float(n * k * length * length)), F.lit(float(n) * m * length * length)),
    ]
    items = [F.struct(F.lit(s).alias("stage"), F.round(a, 3).alias("ours"), F.round(b, 3).alias("brute")) for s, a, b in rows]
    return one.select(F.inline(F.array(*items)))


def limit_ratio(spark: SparkSession, ms: tuple[int, ...] | DataFrame = (1500, 15_000, 1_000_000), k: int = 5, length: int = 25) -> DataFrame:
    """(m, ratio): a query's search and verification against brute force's; it vanishes as m grows."""
    df = ms if isinstance(ms, DataFrame) else spark.createDataFrame([(m,) for m in ms], "m long")
    return df.withColumn("ratio", F.round((F.log2("m") + k * length) / (F.col("m") * F.lit(1.0 + length)), 12))


def observed_cost(cands: DataFrame, n: int, m: int) -> DataFrame:
    """What a gatherer really left to verify, beside all pairs."""
    return cands.agg(F.count("*").alias("pairs"), F.countDistinct("qid").alias("queries")).withColumns({"all_pairs": F.lit(n * m).cast("long"), "reduction": F.round(1 - F.col("pairs") / F.lit(float(n * m)), 9)})


def reduction(cands: DataFrame, n: int, m: int) -> DataFrame:
    return observed_cost(cands, n, m).select("pairs", "reduction")


def completeness(cands: DataFrame, truth: DataFrame) -> DataFrame:
    """The share of true pairs among the candidates."""
    t = truth.where("truth_rid is not null").select("qid", F.col("truth_rid").alias("rid"))
    hit = t.join(cands.select("qid", "rid").distinct().withColumn("hit", F.lit(1)), ["qid", "rid"], "left")
    return hit.agg(F.count("*").alias("n"), F.count("hit").alias("covered")).withColumn("completeness", F.round(F.col("covered") / F.col("n"), 6))


def region_tightness(cands: DataFrame, sample: int | None = 12) -> DataFrame:
    """(qid, neighbours, mean_distance): the mean cosine distance of a query's candidates, for queries chosen by hash."""
    df = cands
    if sample is not None:
        chosen = cands.select("qid").distinct().orderBy(F.md5(F.col("qid").cast("string")), "qid").limit(sample)
        df = cands.join(chosen, "qid", "left_semi")
    return df.groupBy("qid").agg(F.count("*").alias("neighbours"), F.round(F.avg(1 - F.col("sim")), 6).alias("mean_distance"))


def region_map(cands: DataFrame, queries: DataFrame, ref: DataFrame, sample: int = 12) -> DataFrame:
    """(qid, id, x, y, mean_distance): sampled queries and their candidates on two principal components of these few vectors, with the
    mean cosine distance of each query's region."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    regions = region_tightness(cands, sample).select("qid", "mean_distance")
    own = regions.join(queries.select("qid", "vec"), "qid").select("qid", F.col("qid").alias("id"), "vec", "mean_distance")
    near = cands.join(regions, "qid").join(ref.select("rid", "vec"), "rid").select("qid", F.col("rid").alias("id"), "vec", "mean_distance")
    both = own.unionByName(near)
    v = settle(both.select("qid", "id", "mean_distance", array_to_vector(F.col("vec").cast("array<double>")).alias("f")))
    p = PCA(k=2, inputCol="f", outputCol="p").fit(v).transform(v).select("qid", "id", vector_to_array("p").alias("p"), "mean_distance")
    return p.select("qid", "id", F.col("p")[0].alias("x"), F.col("p")[1].alias("y"), "mean_distance")


def finetune_gain(recalls: DataFrame) -> DataFrame:
    """From (method, finetuned, k, recall): (method, k, gain)."""
    return recalls.groupBy("method", "k").agg(F.max(F.when(F.col("finetuned"), F.col("recall"))).alias("a"), F.max(F.when(~F.col("finetuned"), F.col("recall"))).alias("b")).select("method", "k", F.round(F.col("a") - F.col("b"), 6).alias("gain"))


def verify_gain(prfs: DataFrame) -> DataFrame:
    """From (verified, f1): points that verification adds."""
    return prfs.agg(F.round(100 * (F.max(F.when(F.col("verified"), F.col("f1"))) - F.max(F.when(~F.col("verified"), F.col("f1")))), 4).alias("points"))


def errors_by_drift(links: DataFrame, cands: DataFrame, truth: DataFrame, op: str = "op") -> DataFrame:
    """(op, n, missed_gather, missed_verify, false_links): where the linkable queries of each kind of drift get lost."""
    t = truth.select("qid", "truth_rid", op)
    seen = cands.select("qid", F.col("rid").alias("truth_rid")).distinct().withColumn("seen", F.lit(True))
    df = t.join(seen, ["qid", "truth_rid"], "left").join(links.select("qid", "rid"), "qid", "left")
    linkable = F.col("truth_rid").isNotNull()
    right = F.coalesce(F.col("rid") == F.col("truth_rid"), F.lit(False))
    there = F.col("seen").isNotNull()
    return df.groupBy(op).agg(F.count("*").alias("n"), F.sum((linkable & ~there).cast("long")).alias("missed_gather"), F.sum((linkable & there & ~right).cast("long")).alias("missed_verify"), F.sum((~linkable & F.col("rid").isNotNull()).cast("long")).alias("false_links"))


def frontier(results: DataFrame, cost: str = "seconds") -> DataFrame:
    """Of (method, recall, cost), those that no other beats in one without losing in the other; a row a method, few rows."""
    a, b = results.alias("a"), results.alias("b")
    ra, rb, ca, cb = F.col("a.recall"), F.col("b.recall"), F.col(f"a.{cost}"), F.col(f"b.{cost}")
    return a.join(b, (rb >= ra) & (cb <= ca) & ((rb > ra) | (cb < ca)), "left_anti")


def tag_prf(tags: DataFrame, truth: DataFrame) -> DataFrame:
    """(tag, n, tp, fp, fn, precision, recall, f1) for each class of tags, from (qid, rid, tag) and (qid, truth_rid, truth_tag).

    A query counts for its class where both its row and its tag are right (or it is rightly left unlinked).
    """
    t = truth.select("qid", "truth_rid", "truth_tag").join(tags.select("qid", "rid", "tag"), "qid")
    good = F.col("rid").eqNullSafe(F.col("truth_rid")) & (F.col("tag") == F.col("truth_tag"))
    rows = t.select(good.alias("good"), F.array_distinct(F.array("tag", "truth_tag")).alias("both"), F.col("tag").alias("found"), F.col("truth_tag").alias("true"))
    each = rows.select("good", "found", "true", F.explode("both").alias("tag"))
    own, real = F.col("found") == F.col("tag"), F.col("true") == F.col("tag")
    c = each.groupBy("tag").agg(F.sum(real.cast("long")).alias("n"), F.sum((own & F.col("good")).cast("long")).alias("tp"), F.sum((own & ~F.col("good")).cast("long")).alias("fp"), F.sum((real & ~F.col("good")).cast("long")).alias("fn"))
    div = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    return c.withColumns({"precision": div(F.col("tp"), F.col("tp") + F.col("fp")), "recall": div(F.col("tp"), F.col("tp") + F.col("fn")), "f1": div(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn"))})


def macro(prfs: DataFrame) -> DataFrame:
    """The mean over classes of a table with precision, recall and f1."""
    return prfs.agg(F.count("*").alias("classes"), *[F.round(F.avg(n), 6).alias(n) for n in ("precision", "recall", "f1")])


def loss_smooth(curve: DataFrame, width: int = 5) -> DataFrame:
    """(step, loss, smooth): a running mean; the curve has a row a step."""
    w = Window.orderBy("step").rowsBetween(-(width - 1), 0)
    return curve.withColumn("smooth", F.avg("loss").over(w))
