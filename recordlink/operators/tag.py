"""Tags of linked pairs, and what they say about a system."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import RecordSchema

CONSISTENT, UNLINKED = "consistent", "unlinked"


def tag_pairs(best: DataFrame, queries: DataFrame, ref: DataFrame, schema: RecordSchema, accept: float | None = None, multi: bool = False) -> DataFrame:
    """``tag`` and ``fields`` (those that differ after normalizing, in the schema's order) for every query.

    ``consistent``: none differs; ``contradiction:<field>``: the heaviest that differs (``multi``: all of them, by name);
    ``unlinked``: no best pair, or one under ``accept``.
    """
    b = best.select("qid", "rid", "score")
    if accept is not None:
        b = b.where(F.col("score") >= accept)
    q = queries.select("qid", *[F.col(n).alias(f"q_{n}") for n in schema.names])
    r = ref.select("rid", *[F.col(n).alias(f"r_{n}") for n in schema.names])
    df = q.join(b.join(r, "rid"), "qid", "left")
    differ = [F.when(f.normal(F.col(f"q_{f.name}")) != f.normal(F.col(f"r_{f.name}")), F.lit(f.name)) for f in schema.fields]
    linked = F.col("rid").isNotNull()
    df = df.withColumn("fields", F.when(linked, F.array_compact(F.array(*differ))).otherwise(F.array().cast("array<string>")))
    heaviest = F.coalesce(*[F.when(F.array_contains("fields", f.name), F.lit(f.name)) for f in sorted(schema.fields, key=lambda f: -f.weight)])
    named = F.concat(F.lit("{"), F.array_join(F.array_sort("fields"), ","), F.lit("}")) if multi else heaviest
    tag = F.when(~linked, UNLINKED).when(F.size("fields") == 0, CONSISTENT).otherwise(F.concat(F.lit("contradiction:"), named))
    return df.select("qid", "rid", "score", tag.alias("tag"), "fields")


def audit(tags: DataFrame, queries: DataFrame, by: tuple[str, ...] = ("servername",), how: str = "groupBy") -> DataFrame:
    """Counts of queries and contradictions, and their rate, by columns of the queries (groupBy, rollup or cube)."""
    df = tags.select("qid", "tag").join(queries.select("qid", *by), "qid")
    bad = F.col("tag").startswith("contradiction")
    out = getattr(df, how)(*by).agg(F.count("*").alias("n"), F.sum(bad.cast("long")).alias("contradictions"), F.sum((F.col("tag") == UNLINKED).cast("long")).alias("unlinked"))
    return out.withColumn("rate", F.col("contradictions") / F.col("n"))
