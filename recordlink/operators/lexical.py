"""Candidates without vectors: word overlap and relational equality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import RecordSchema
from .gather import once, pairs_by_key, rank_top


def spread_count(df: DataFrame) -> int:
    """Partitions for joins that make far more rows than they read, which Spark would merge into few by their bytes."""
    spark = df.sparkSession
    return max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


SCORERS = ("bm25", "tfidf", "overlap", "trigram")


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z0-9]+"), lambda w: w != "")


def trigrams(text: Column) -> Column:
    t = F.concat(F.lit("  "), F.lower(F.coalesce(text, F.lit(""))), F.lit(" "))
    return F.transform(F.sequence(F.lit(1), F.char_length(t) - 2), lambda i: F.substring(t, i, F.lit(3)))


def lexical_search(q: DataFrame, ref: DataFrame, k: int = 5, scorer: str = "bm25", k1: float = 1.2, b: float = 0.75, text: str = "sentence", df_share: float | None = None) -> DataFrame:
    """The k reference sentences that share most words with each query, over an inverted index.

    bm25; tfidf (sum of tf * idf^2 over common terms, by both lengths); overlap (common distinct words); trigram (Jaccard of
    character trigrams).  ``df_share`` leaves out terms of more than that share of the reference (None: all count).
    """
    if scorer not in SCORERS:
        raise ValueError(f"scorer is one of {SCORERS}")
    cut = trigrams if scorer == "trigram" else words
    qt = q.select("qid", F.explode(cut(F.col(text))).alias("term")).groupBy("qid", "term").agg(F.count("*").alias("qtf"))
    rt = ref.select("rid", F.explode(cut(F.col(text))).alias("term")).groupBy("rid", "term").agg(F.count("*").alias("tf"))
    qt, rt = once(qt), once(rt)
    n = ref.agg(F.count("*").cast("double").alias("n"))
    df = rt.groupBy("term").agg(F.count("*").cast("double").alias("df")).join(F.broadcast(n))
    if df_share is not None:
        df = df.where(F.col("df") <= F.col("n") * df_share)
    if scorer in ("overlap", "trigram"):
        common = pairs_by_key(qt if df_share is None else qt.join(df.select("term"), "term"), rt, "term")
        pairs = common.groupBy("qid", "rid").agg(F.count("*").cast("double").alias("c"))
        if scorer == "overlap":
            return rank_top(pairs.select("qid", "rid", F.col("c").alias("sim")), k)
        qn, rn = qt.groupBy("qid").agg(F.count("*").alias("qn")), rt.groupBy("rid").agg(F.count("*").alias("rn"))
        sim = F.round(F.col("c") / (F.col("qn") + F.col("rn") - F.col("c")), 9)
        return rank_top(pairs.join(qn, "qid").join(rn, "rid").select("qid", "rid", sim.alias("sim")), k)
    if scorer == "bm25":
        length = rt.groupBy("rid").agg(F.sum("tf").cast("double").alias("len"))
        mean = F.broadcast(length.agg(F.avg("len").alias("mean")))
        idf = df.select("term", F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5)).alias("idf"))
        post = rt.join(length, "rid").join(mean).select("rid", "term", (F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))).alias("w"))
        scored = pairs_by_key(qt.join(idf, "term"), post, "term").groupBy("qid", "rid").agg(F.round(F.sum(F.col("qtf") * F.col("idf") * F.col("w")), 9).alias("sim"))
        return rank_top(scored, k)
    idf = df.select("term", (F.log((1 + F.col("n")) / (1 + F.col("df"))) + 1).alias("idf"))
    qw = qt.join(idf, "term").select("qid", "term", (F.col("qtf") * F.col("idf")).alias("qw"))
    rw = rt.join(idf, "term").select("rid", "term", (F.col("tf") * F.col("idf")).alias("rw"))
    qn = qw.groupBy("qid").agg(F.sqrt(F.sum(F.col("qw") * F.col("qw"))).alias("qn"))
    rn = rw.groupBy("rid").agg(F.sqrt(F.sum(F.col("rw") * F.col("rw"))).alias("rn"))
    dots = pairs_by_key(qw, rw, "term").groupBy("qid", "rid").agg(F.sum(F.col("qw") * F.col("rw")).alias("d"))
    return rank_top(dots.join(qn, "qid").join(rn, "rid").select("qid", "rid", F.round(F.col("d") / (F.col("qn") * F.col("rn")), 9).alias("sim")), k)


def _bands(sentences: DataFrame, i: str, text: str, tables: int, rows: int) -> tuple[DataFrame, DataFrame]:
    """(id and distinct words, id and band): a band joins the least hashes of the words under ``rows`` functions, four to an md5."""
    sets = once(sentences.select(i, F.array_distinct(words(F.col(text))).alias("w")).where(F.size("w") > 0))
    least = lambda n: F.array_min(F.transform("w", lambda x: F.substring(F.md5(F.concat(F.lit(f"{n // 4}:"), x).cast("binary")), n % 4 * 8 + 1, 8)))
    bands = [F.concat(F.lit(f"{t}:"), *[least(t * rows + j) for j in range(rows)]) for t in range(tables)]
    return sets, once(sets.select(i, F.explode(F.array(*bands)).alias("band")))


def minhash_search(q: DataFrame, ref: DataFrame, k: int = 5, tables: int = 24, rows: int = 4, text: str = "sentence") -> DataFrame:
    """The k reference sentences of highest Jaccard similarity of words among those that share a MinHash band with the query.

    A pair of similarity j shares one of the ``tables`` bands of ``rows`` hashes with probability 1 - (1 - j^rows)^tables: 0.99 at
    two thirds for the defaults.  Words that all sentences have (a template's) make all alike: pass the values alone.  Sentences without words match nothing; a query that shares no band has no row.
    """
    (qs, qb), (rs, rb) = _bands(q, "qid", text, tables, rows), _bands(ref, "rid", text, tables, rows)
    met = pairs_by_key(qb, rb, "band").select("qid", "rid").distinct()
    both = met.join(qs.withColumnRenamed("w", "a"), "qid").join(rs.withColumnRenamed("w", "b"), "rid")
    common = F.size(F.array_intersect("a", "b")).cast("double")
    return rank_top(both.select("qid", "rid", F.round(common / (F.size("a") + F.size("b") - common), 9).alias("sim")), k)


def joint_query(q: DataFrame, ref: DataFrame, keys: tuple[str, ...] = ("email", "username", "domain", "servername", "status"), mode: str = "all", k: int | None = None, steps: tuple[tuple[str, ...], ...] = (("email",), ("username", "domain"), ("domain", "servername"))) -> DataFrame:
    """Candidates by equal fields: hash joins only, blanks never match.

    all: every key equal; any: at least one (the sim is their share), as a union of one join a key; ladder: the first of
    ``steps`` at which a query finds rows (the sim falls by step).  ``k`` keeps that many a query.
    """

    def equal(a: DataFrame, on: tuple[str, ...]) -> DataFrame:
        solid = [F.coalesce(F.col(c), F.lit("")) != "" for c in on]
        left, right = a.select("qid", *on), ref.select("rid", *on)
        for s in solid:
            left, right = left.where(s), right.where(s)
        return left.join(right, list(on)).select("qid", "rid")

    if mode == "all":
        out = equal(q, keys).withColumn("sim", F.lit(1.0))
    elif mode == "any":
        union = None
        for c in keys:
            part = equal(q, (c,)).withColumn("hit", F.lit(1))
            union = part if union is None else union.unionByName(part)
        out = union.groupBy("qid", "rid").agg((F.sum("hit") / F.lit(float(len(keys)))).alias("sim"))
    elif mode == "ladder":
        every = None
        for i, on in enumerate(steps):
            found = equal(q, on).withColumn("step", F.lit(i))
            every = found if every is None else every.unionByName(found)
        first = every.withColumn("least", F.min("step").over(Window.partitionBy("qid"))).where("step = least")
        out = first.select("qid", "rid", (1.0 - F.col("step") / len(steps)).alias("sim"))
    else:
        raise ValueError("mode is all, any or ladder")
    w = Window.partitionBy("qid").orderBy(F.desc("sim"), "rid")
    out = out.withColumn("rank", F.row_number().over(w)).select("qid", "rid", "rank", "sim")
    return out if k is None else out.where(F.col("rank") <= k)


def brute_score(q: DataFrame, ref: DataFrame, schema: RecordSchema, k: int = 1, partitions: int | None = None) -> DataFrame:
    """Every pair's composite score, the k best of each query: the baseline that candidates replace.

    Queries are dealt to chunks and each chunk meets the whole reference, so the pairs are spread evenly whatever the sizes.
    """
    from .verify import composite_score

    chunks = partitions or spread_count(q)
    a = q.select("qid", *[F.col(n).alias(f"q_{n}") for n in schema.names], F.pmod(F.xxhash64("qid"), F.lit(chunks)).cast("int").alias("chunk"))
    b = ref.select("rid", *[F.col(n).alias(f"r_{n}") for n in schema.names], F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))).alias("chunk"))
    pairs = a.repartition(chunks, "chunk").join(b.hint("merge"), "chunk")
    scored = composite_score(pairs, schema).select("qid", "rid", F.round("score", 9).alias("sim"))
    return rank_top(scored, k)


def edit_join(a: DataFrame, b: DataFrame, col: str, max_dist: int, q: int = 2, a_id: str = "a_id", b_id: str = "b_id") -> DataFrame:
    """(a_id, b_id, d): all pairs whose values are within ``max_dist`` edits, exactly, without comparing all pairs; nulls and blanks
    match nothing.

    An edit destroys at most q of a value's q-grams (padded, numbered by occurrence).  So near values share one of the
    q * max_dist + 1 rarest grams of either; values too short for that many meet by length.
    """
    size = q * max_dist + 1
    a, b = (once(d.where(F.coalesce(F.col(col), F.lit("")) != "").select(i, col)) for d, i in ((a, a_id), (b, b_id)))

    def grams(df: DataFrame, i: str) -> DataFrame:
        df = df.select(F.col(i), F.col(col).alias("v"))
        pad = F.concat(F.repeat(F.lit("\u0001"), F.lit(q - 1)), "v", F.repeat(F.lit("\u0002"), F.lit(q - 1)))
        each = F.transform(F.sequence(F.lit(1), F.char_length(pad) - (q - 1)), lambda j: F.substring(pad, j, F.lit(q)))
        whole = df.withColumn("each", F.when(F.char_length(pad) >= q, each).otherwise(F.array(F.lit(""))))
        numbered = F.transform("each", lambda g, j: F.concat(g, F.lit("#"), F.size(F.filter(F.slice("each", F.lit(1), j + 1), lambda x: x == g))))
        return once(whole.select(i, "v", F.explode(numbered).alias("g")))

    ga, gb = grams(a, a_id), grams(b, b_id)
    freq = ga.select("g").unionByName(gb.select("g")).groupBy("g").agg(F.count("*").alias("f"))

    def prefix(g: DataFrame, i: str) -> DataFrame:
        w = Window.partitionBy(i).orderBy("f", "g")
        return g.join(freq, "g").withColumn("r", F.row_number().over(w)).where(F.col("r") <= size).select(i, "v", "g")

    pa_, pb = prefix(ga, a_id).withColumnRenamed("v", "va"), prefix(gb, b_id).withColumnRenamed("v", "vb")
    by_gram = pa_.join(pb, "g").where(F.abs(F.char_length("va") - F.char_length("vb")) <= max_dist).select(a_id, b_id, "va", "vb")
    short = q * max_dist  # a value with no more grams than edits can destroy may share none
    va, vb = (d.select(i, F.coalesce(F.col(col), F.lit("")).alias(n)) for d, i, n in ((a, a_id, "va"), (b, b_id, "vb")))
    sa = va.where(F.char_length("va") + q - 1 <= short).withColumn("n", F.explode(F.sequence(F.char_length("va") - max_dist, F.char_length("va") + max_dist)))
    sb = vb.where(F.char_length("vb") + q - 1 <= short + max_dist).withColumn("n", F.char_length("vb"))
    by_length = sa.join(sb, "n").select(a_id, b_id, "va", "vb")
    ta = va.where(F.char_length("va") + q - 1 <= short + max_dist).withColumn("n", F.explode(F.sequence(F.char_length("va") - max_dist, F.char_length("va") + max_dist)))
    tb = vb.where(F.char_length("vb") + q - 1 <= short).withColumn("n", F.char_length("vb"))
    by_length = by_length.unionByName(ta.join(tb, "n").select(a_id, b_id, "va", "vb"))
    every = by_gram.unionByName(by_length).distinct()
    return every.withColumn("d", F.levenshtein(F.col("va"), F.col("vb"), max_dist)).where("d >= 0").select(a_id, b_id, "d")


