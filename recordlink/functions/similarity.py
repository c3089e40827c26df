"""Normalized edit similarities as column expressions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

NORMS = ("maxlen", "sumlen", "metric", "indel")


def field_similarity(a: Column, b: Column, norm: str = "maxlen") -> Column:
    """1 for equal values (two blanks too), 0 for nothing in common; nulls are blank.

    maxlen: 1 - d / the longer length; sumlen: 1 - d / both lengths; metric: 1 - 2d / (both lengths + d), whose
    complement is a metric; indel: edits without replacement over both lengths.
    """
    a, b = F.coalesce(a, F.lit("")), F.coalesce(b, F.lit(""))
    if norm == "indel":
        return indel_ratio(a, b)
    d = F.levenshtein(a, b).cast("double")
    both = (F.char_length(a) + F.char_length(b)).cast("double")
    if norm == "maxlen":
        return 1 - d / F.greatest(F.char_length(a), F.char_length(b), F.lit(1)).cast("double")
    if norm == "sumlen":
        return 1 - d / F.greatest(both, F.lit(1.0))
    if norm == "metric":
        return 1 - 2 * d / F.greatest(both + d, F.lit(1.0))
    raise ValueError(f"norm is one of {NORMS}")


def similarity_bound(a: Column, b: Column) -> Column:
    """No maxlen similarity is higher: the shorter length over the longer."""
    la, lb = F.char_length(F.coalesce(a, F.lit(""))), F.char_length(F.coalesce(b, F.lit("")))
    return F.when(F.greatest(la, lb) == 0, 1.0).otherwise(F.least(la, lb) / F.greatest(la, lb, F.lit(1)))


def _lcs(a: str, b: str) -> int:
    """Length of the longest common subsequence, a row of bits at a time."""
    if not a or not b:
        return 0
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    row = full = (1 << len(a)) - 1
    for c in b:
        hit = row & where.get(c, 0)
        row = (row + hit | row - hit) & full
    return len(a) - row.bit_count()


@F.pandas_udf(T.DoubleType())
def indel_ratio(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([2 * _lcs(x, y) / (len(x) + len(y)) if x or y else 1.0 for x, y in zip(a, b, strict=True)], dtype=float)


def register(spark: SparkSession) -> None:
    """SQL functions of the session: field_similarity, composite_score, serialize_record."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION field_similarity(a STRING, b STRING) RETURNS DOUBLE RETURN 1 - cast(levenshtein(coalesce(a, ''), coalesce(b, '')) as double) / greatest(char_length(coalesce(a, '')), char_length(coalesce(b, '')), 1)")
    args = ", ".join(f"{s}{i} STRING" for s in "ab" for i in range(5))
    body = " + ".join(f"{w}D * field_similarity(a{i}, b{i})" for i, w in enumerate((0.40, 0.30, 0.15, 0.10, 0.05)))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION composite_score({args}) RETURNS DOUBLE RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION serialize_record(email STRING, username STRING, domain STRING, servername STRING, status STRING) RETURNS STRING RETURN concat_ws(' ', 'The username', nullif(username, ''), 'with email', nullif(email, ''), 'and domain', nullif(domain, ''), 'on', nullif(servername, ''), 'has', nullif(lower(status), ''), 'status.')")
