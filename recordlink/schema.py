"""Records: ordered fields with weights, one id."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FieldSpec:
    """A field, its share of the score, and how its values are normalized before comparison."""

    name: str
    weight: float
    normalizer: Callable[[Column], Column] | None = None

    def normal(self, c: Column) -> Column:
        c = F.coalesce(c, F.lit(""))
        return self.normalizer(c) if self.normalizer else c


def fold(c: Column) -> Column:
    """Lower case without outer blanks."""
    return F.trim(F.lower(c))


def fold_host(c: Column) -> Column:
    """fold, without a leading www."""
    return F.regexp_replace(fold(c), r"^www\.", "")


@dataclass(frozen=True)
class RecordSchema:
    """Fields whose weights sum to one."""

    fields: tuple[FieldSpec, ...]
    _: None = field(default=None, repr=False)

    def __post_init__(self) -> None:
        names = [f.name for f in self.fields]
        if not names or len(set(names)) != len(names):
            raise ValueError("a schema has at least one field, each with its own name")
        if any(f.weight < 0 for f in self.fields) or abs(sum(f.weight for f in self.fields) - 1) > 1e-9:
            raise ValueError("weights are not negative and sum to 1")

    @property
    def names(self) -> list[str]:
        return [f.name for f in self.fields]

    def __getitem__(self, name: str) -> FieldSpec:
        for f in self.fields:
            if f.name == name:
                return f
        raise KeyError(name)

    def with_weights(self, weights: dict[str, float]) -> RecordSchema:
        if set(weights) != set(self.names):
            raise ValueError("a weight for each field, and for no other")
        return RecordSchema(tuple(replace(f, weight=weights[f.name]) for f in self.fields))

    def select(self, *names: str) -> RecordSchema:
        """Some fields, in the order given, their weights scaled to one."""
        chosen = [self[n] for n in names]
        total = sum(f.weight for f in chosen)
        return RecordSchema(tuple(replace(f, weight=f.weight / total) for f in chosen))

    def check(self, df: DataFrame) -> DataFrame:
        """df itself; an AnalysisException-like error at once if a field is missing."""
        missing = [n for n in self.names if n not in df.columns]
        if missing:
            raise ValueError(f"fields missing: {missing}")
        return df


#: The weights of the five user fields.
USER = RecordSchema((FieldSpec("email", 0.40), FieldSpec("username", 0.30), FieldSpec("domain", 0.15), FieldSpec("servername", 0.10), FieldSpec("status", 0.05)))
#: The same with values folded first.
USER_FOLDED = RecordSchema(tuple(replace(f, normalizer=fold_host if f.name == "domain" else fold) for f in USER.fields))


def align(df: DataFrame, mapping: dict[str, str], schema: RecordSchema, id_col: str, out_id: str) -> DataFrame:
    """Rename a table's columns into a schema: ``mapping`` from field to column; the id becomes ``out_id``."""
    if set(mapping) != set(schema.names):
        raise ValueError("a column for each field, and for no other")
    for c in [id_col, *mapping.values()]:
        if c not in df.columns:
            raise ValueError(f"no column {c}")
    return df.select(F.col(id_col).alias(out_id), *[F.col(mapping[n]).cast("string").alias(n) for n in schema.names])
