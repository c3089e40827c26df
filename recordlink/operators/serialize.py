"""Rows as short sentences."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import RecordSchema


#: Fixed value: the sentence of a user record, each value in its place.
PROSE = "The username {username} with email {email} and domain {domain} on {servername} has {status} status."


def default_template(schema: RecordSchema) -> str:
    """PROSE for records of its five fields; for others a clause ``name value`` for each field."""
    return PROSE if set(schema.names) == set(re.findall(r"{(\w+)}", PROSE)) else ", ".join(f"{n} {{{n}}}" for n in schema.names)


def sentence(schema: RecordSchema, missing: str = "keep", template: str | None = None, lower: tuple[str, ...] = ("status",)) -> Column:
    """The template with the fields' values for their names in braces, those of ``lower`` in lower case.

    A blank or null value leaves the words around it in place (``keep``), or takes the words before it along (``skip``), so that
    no gap is left either way.
    """
    if missing not in ("keep", "skip"):
        raise ValueError("missing is keep or skip")
    pieces = re.split(r"{(\w+)}", template or default_template(schema))
    if unknown := set(pieces[1::2]) - set(schema.names):
        raise ValueError(f"the template names no fields of the schema: {sorted(unknown)}")
    parts = []
    for text, name in zip(pieces[::2], [*pieces[1::2], None], strict=True):
        if name is None:
            parts.append(F.lit(text))
            continue
        value = F.coalesce(F.col(name).cast("string"), F.lit(""))
        value = F.lower(value) if name in lower else value
        own = F.concat(F.lit(" "), value) if text.endswith(" ") else value  # the blank goes with the value
        words = F.lit(text.removesuffix(" "))
        parts += [words, F.when(value != "", own).otherwise("")] if missing == "keep" else [F.when(value != "", F.concat(words, own)).otherwise("")]
    return F.trim(F.concat(*parts))


def serialize_records(df: DataFrame, schema: RecordSchema, missing: str = "keep", out: str = "sentence", template: str | None = None) -> DataFrame:
    return schema.check(df).withColumn(out, sentence(schema, missing, template))


def serialize_values(df: DataFrame, schema: RecordSchema, out: str = "sentence") -> DataFrame:
    """The values alone, lower-cased, without the words that every sentence shares."""
    parts = [F.lower(F.coalesce(F.col(n).cast("string"), F.lit(""))) for n in schema.names]
    return schema.check(df).withColumn(out, F.concat_ws(" ", *parts))


def serialize_generic(df: DataFrame, cols: list[str], out: str = "sentence") -> DataFrame:
    """``name value`` for any columns; nulls drop out."""
    parts = [F.when(F.col(c).isNotNull(), F.concat(F.lit(f"{c} "), F.col(c).cast("string"))) for c in cols]
    return df.withColumn(out, F.concat_ws(", ", *parts))
