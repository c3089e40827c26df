"""Scoring candidate pairs field by field, and choosing among them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import field_similarity, similarity_bound
from ..schema import RecordSchema


def attach_fields(cands: DataFrame, queries: DataFrame, ref: DataFrame, schema: RecordSchema) -> DataFrame:
    """Candidates (qid, rid, ...) with both sides' fields as q_<field> and r_<field>; only strings travel."""
    q = queries.select("qid", *[F.col(n).alias(f"q_{n}") for n in schema.names])
    r = ref.select("rid", *[F.col(n).alias(f"r_{n}") for n in schema.names])
    return cands.join(r, "rid").join(q, "qid")


def _pair(schema: RecordSchema, name: str) -> tuple[Column, Column]:
    f = schema[name]
    return f.normal(F.col(f"q_{name}")), f.normal(F.col(f"r_{name}"))


def similarities(schema: RecordSchema, norm: str = "maxlen") -> dict[str, Column]:
    return {n: field_similarity(*_pair(schema, n), norm) for n in schema.names}


def composite_score(pairs: DataFrame, schema: RecordSchema, norm: str = "maxlen", missing: str = "zero", prune: float | None = None) -> DataFrame:
    """``score`` (weighted mean of the fields' similarities) and ``sims`` (by field).

    ``missing="renormalize"`` leaves out fields that are blank on either side and scales the other weights (score 0 if none is
    left).  ``prune``: pairs that provably stay under this score get a null score, at the first field, heaviest first, where the
    rest cannot make up for it; their remaining edit distances are not computed, and ``sims`` is null.
    """
    if prune is not None:
        if missing != "zero" or norm != "maxlen":
            raise ValueError("pruning bounds hold for maxlen with missing='zero'")
        return _pruned(pairs, schema, prune)
    sims = similarities(schema, norm)
    df = pairs.withColumns({f"s_{n}": c for n, c in sims.items()})
    if missing == "zero":
        score = sum((F.lit(f.weight) * F.col(f"s_{f.name}") for f in schema.fields), F.lit(0.0))
    elif missing == "renormalize":
        there = {n: (a != "") & (b != "") for n, (a, b) in ((n, _pair(schema, n)) for n in schema.names)}
        top = sum((F.when(there[f.name], F.lit(f.weight) * F.col(f"s_{f.name}")).otherwise(0.0) for f in schema.fields), F.lit(0.0))
        low = sum((F.when(there[f.name], F.lit(f.weight)).otherwise(0.0) for f in schema.fields), F.lit(0.0))
        score = F.when(low > 0, top / low).otherwise(0.0)
    else:
        raise ValueError("missing is zero or renormalize")
    table = F.create_map(*[x for n in schema.names for x in (F.lit(n), F.col(f"s_{n}"))])
    return df.withColumns({"score": score, "sims": table}).drop(*[f"s_{n}" for n in schema.names])


def _pruned(pairs: DataFrame, schema: RecordSchema, least: float) -> DataFrame:
    order = sorted(schema.fields, key=lambda f: -f.weight)
    bounds = [F.lit(f.weight) * similarity_bound(*_pair(schema, f.name)) for f in order]
    df, so_far = pairs, F.lit(0.0)
    for i, f in enumerate(order):
        rest = sum(bounds[i:], F.lit(0.0))
        value = F.when(F.col(f"s_{order[i - 1].name}").isNull() if i else F.lit(False), None).when(so_far + rest < least - 1e-12, None).otherwise(field_similarity(*_pair(schema, f.name)))
        df = df.withColumn(f"s_{f.name}", value)
        so_far = so_far + F.lit(f.weight) * F.col(f"s_{f.name}")
    total = sum((F.lit(f.weight) * F.col(f"s_{f.name}") for f in schema.fields), F.lit(0.0))
    table = F.create_map(*[x for n in schema.names for x in (F.lit(n), F.col(f"s_{n}"))])
    whole = F.when(total >= least - 1e-12, total)
    return df.withColumns({"score": whole, "sims": F.when(whole.isNotNull(), table)}).drop(*[f"s_{n}" for n in schema.names])


def select_best(scored: DataFrame, accept: float | None = None, how: str = "max_by") -> DataFrame:
    """The best pair of each query: highest score, then highest sim, then lowest rid; none under ``accept``.

    ``max_by`` needs one hash aggregate; ``window`` ranks, and shows the same rows.  Both carry every column.
    """
    df = scored.where(F.col("score").isNotNull())
    sim = F.col("sim") if "sim" in df.columns else F.lit(0.0)
    if how == "max_by":
        cols = [c for c in df.columns if c != "qid"]
        key = F.struct(F.col("score"), sim, -F.col("rid"))
        best = df.groupBy("qid").agg(F.max_by(F.struct(*cols), key).alias("b")).select("qid", "b.*")
    elif how == "window":
        w = Window.partitionBy("qid").orderBy(F.desc("score"), F.desc(sim), "rid")
        best = df.withColumn("rn", F.row_number().over(w)).where("rn = 1").drop("rn")
    else:
        raise ValueError("how is max_by or window")
    return best if accept is None else best.where(F.col("score") >= accept)


def select_nearest(cands: DataFrame) -> DataFrame:
    """Without verification: the first candidate, its sim as the score."""
    return cands.where("rank = 1").withColumn("score", F.col("sim"))


def mutual_best(scored: DataFrame, accept: float | None = None) -> DataFrame:
    """Pairs that are each other's best: one-to-one links."""
    df = scored.where(F.col("score").isNotNull())
    a = Window.partitionBy("qid").orderBy(F.desc("score"), "rid")
    b = Window.partitionBy("rid").orderBy(F.desc("score"), "qid")
    both = df.withColumns({"a": F.row_number().over(a), "b": F.row_number().over(b)}).where("a = 1 and b = 1").drop("a", "b")
    return both if accept is None else both.where(F.col("score") >= accept)


def explain_pair(scored: DataFrame, schema: RecordSchema) -> DataFrame:
    """A row for each field of each pair: its similarity, weight and part of the score."""
    rows = F.array(*[F.struct(F.lit(f.name).alias("field"), F.lit(f.weight).alias("weight"), F.col("sims")[f.name].alias("similarity")) for f in schema.fields])
    return scored.select("qid", "rid", "score", F.inline(rows)).withColumn("part", F.col("weight") * F.col("similarity"))
