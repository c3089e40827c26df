"""Mixing sources to target weights by hierarchical budgets.

Documents hang under the leaves of a domain - language - source tree.  A token budget enters at the root.  Each node
divides its budget among its children by their weights, none of them getting more than it can hold (its tokens times
``max_epochs``); what one cannot take goes to its siblings by weight first, and only what the whole family cannot take was
withheld one level up already, since a node's capacity is the sum of its leaves'.

A leaf reads its documents in epochs, each in an order of its own that a seed fixes, and takes the first tokens up to its
budget: whole epochs, then a prefix of the last.  The prefix's end is found by descending through the digits of the order's
hash, so no task ever sorts a leaf.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

LEVELS = ("domain", "lang", "source")
NONE = "(none)"
#: Digits of the order's hash: so many values each, so many of them before single documents are ranked.
RADIX_BITS, DIGITS = 8, 3
#: Tables of a row a leaf (about 100 bytes) are broadcast up to so many leaves.
BROADCAST_LEAVES = 50_000


@dataclass(frozen=True)
class Target:
    """Weights of the children at each level by name (0 or more; unnamed: ``default``), and the budget.

    ``weights[level]`` applies under any parent; ``under[(parent path) + (name,)]`` overrides it for one node.
    """

    weights: dict[str, dict[str, float]] = field(default_factory=dict)
    under: dict[tuple[str, ...], float] = field(default_factory=dict)
    default: float = 1.0
    budget_share: float = 1.0
    budget_tokens: int | None = None
    max_epochs: int = 4
    seed: int = 17

    def weight(self, path: tuple[str, ...]) -> float:
        w = self.under.get(path, self.weights.get(LEVELS[len(path) - 1], {}).get(path[-1], self.default))
        if not w >= 0:
            raise ValueError(f"negative weight of {path}")
        return float(w)


def divide(budget: int, weights: list[float], room: list[int]) -> list[int]:
    """Whole-number shares of a budget by weight within each child's room.

    Children that would overflow are filled and leave; the rest is divided anew.  Once all children with weight are
    full, those of weight 0 share by room.  Rounding: largest remainders first, then the earlier child.
    """
    out = [0] * len(room)
    left = min(int(budget), sum(room))
    for use in (weights, room):
        active = [i for i, w in enumerate(use) if w > 0 and room[i] > out[i]]
        while left and active:
            total = sum(use[i] for i in active)
            full = [i for i in active if left * use[i] / total >= room[i] - out[i]]
            if full:
                for i in full:
                    got = min(left, room[i] - out[i])
                    out[i] += got
                    left -= got
                active = [i for i in active if i not in set(full)]
                continue
            exact = [left * use[i] / total for i in active]
            floor = [int(x) for x in exact]
            spare = left - sum(floor)
            by_rest = sorted(range(len(active)), key=lambda j: (floor[j] - exact[j], j))
            for rank, j in enumerate(by_rest):
                i = active[j]
                got = min(floor[j] + (rank < spare), room[i] - out[i])
                out[i] += got
                left -= got
            active = [i for i in active if room[i] > out[i]]
    return out


def plan(supply: dict[tuple[str, ...], int], target: Target) -> dict[tuple[str, ...], int]:
    """The token budget of each leaf path."""
    total = sum(supply.values())
    budget = target.budget_tokens if target.budget_tokens is not None else round(total * target.budget_share)
    out: dict[tuple[str, ...], int] = {}

    def walk(path: tuple[str, ...], leaves: list[tuple[str, ...]], amount: int) -> None:
        if len(path) == len(LEVELS):
            out[path] = amount
            return
        families: dict[tuple[str, ...], list[tuple[str, ...]]] = {}
        for leaf in leaves:
            families.setdefault(leaf[: len(path) + 1], []).append(leaf)
        names = sorted(families)
        room = [sum(supply[x] for x in families[n]) * target.max_epochs for n in names]
        for n, got in zip(names, divide(amount, [target.weight(n) for n in names], room), strict=True):
            walk(n, families[n], got)

    walk((), sorted(supply), budget)
    return out


def _count(column: pa.Array) -> dict[str, pa.Array]:
    return {"n_tokens": pa.array(common.tokenize(column, lower=False).lengths)}


def _paths(domain: Column | None) -> list[Column]:
    """A row's domain, language and source, by these names."""
    text = lambda c: F.coalesce(c.cast("string"), F.lit(NONE))
    return [text(domain if domain is not None else F.lit("all")).alias("domain"), text(F.col("lang")).alias("lang"), text(F.col("source")).alias("source")]


def _order(seed: int, epoch: Column) -> Column:
    """Where a document stands in an epoch of its leaf."""
    return F.xxhash64(F.lit(seed), epoch, F.col("doc_id"))


def select(df: DataFrame, target: Target, domain: Column | None = None, max_leaves: int = 200_000) -> tuple[DataFrame, dict[tuple[str, ...], int]]:
    """The chosen (document, epoch) rows and the budget of each leaf.

    Rows: doc_id, domain, lang, source, epoch (from 0), n_tokens (words of the whole text), take_tokens (fewer than n_tokens for
    the one document where the leaf's budget ends).  The take_tokens of a leaf sum to its budget.  Null names are a child
    "(none)"; texts without words are taken where they stand before the prefix's end; repeated rows count each, and of equal ones as many
    are taken as the budget has room for; ids may be of any type; texts of any length are counted whole; an empty table gives no
    rows; other columns are not read.
    A tree of more than ``max_leaves`` leaves is an error, since the driver plans it.
    """
    slim = df.select("doc_id", *_paths(domain), "text")
    slim = common.settle(common.annotate(slim, _count, {"n_tokens": "long"}, ["doc_id", *LEVELS]))
    leaves = slim.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("n")).limit(max_leaves + 1).collect()
    if len(leaves) > max_leaves:
        raise ValueError(f"more than {max_leaves} leaves")
    supply = {tuple(r[k] for k in LEVELS): int(r["n"]) for r in leaves}
    budgets = plan(supply, target)
    spark = df.sparkSession
    rows = [(*k, budgets[k] // supply[k] if supply[k] else 0, budgets[k] % supply[k] if supply[k] else 0) for k in sorted(supply)]
    small = len(rows) <= BROADCAST_LEAVES
    lightly = F.broadcast if small else (lambda t: t)  # a row a leaf; beyond, Spark chooses the join by size
    leaf = lightly(spark.createDataFrame(rows, "domain string, lang string, source string, whole int, rest long"))
    joined = slim.join(leaf, list(LEVELS)).withColumn("order", _order(target.seed, F.col("whole")))

    whole = joined.where("whole > 0").select("doc_id", *LEVELS, F.explode(F.sequence(F.lit(0), F.col("whole") - 1)).alias("epoch"), "n_tokens", F.col("n_tokens").alias("take_tokens"))

    # Digit by digit: the tokens of each value, the value in which the budget ends, and only that value's documents on.
    digit = lambda d: F.shiftrightunsigned("order", 64 - RADIX_BITS * (d + 1)).bitwiseAND(F.lit((1 << RADIX_BITS) - 1))
    part, sure = joined.where("rest > 0").withColumn("left", F.col("rest")), []
    upto = Window.partitionBy(*LEVELS).orderBy("digit")
    for d in range(DIGITS):
        sums = part.groupBy(*LEVELS, "left", digit(d).alias("digit")).agg(F.sum("n_tokens").alias("n"))
        ends = sums.withColumn("sum", F.sum("n").over(upto)).where("sum >= left and sum - n < left")
        cut = lightly(common.settle(ends.select(*LEVELS, F.col("digit").alias("end_digit"), (F.col("left") - F.col("sum") + F.col("n")).alias("next_left"))))
        met = part.join(cut, list(LEVELS)).withColumn("digit", digit(d))
        sure.append(met.where("digit < end_digit"))
        part = met.where("digit = end_digit").drop("left", "digit", "end_digit").withColumnRenamed("next_left", "left")
    cols = ["doc_id", *LEVELS, F.col("whole").alias("epoch"), "n_tokens"]
    pieces = [whole, *(s.select(*cols, F.col("n_tokens").alias("take_tokens")) for s in sure)]
    # Equal rows stand as one with a count, so that an id that many rows share makes no long window.
    same = part.groupBy(*LEVELS, "whole", "left", "order", "doc_id", "n_tokens").agg(F.count("*").alias("rows"))
    w = Window.partitionBy(*LEVELS).orderBy("order", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    ranked = same.withColumn("room", F.col("left") - F.coalesce(F.sum(F.col("n_tokens") * F.col("rows")).over(w), F.lit(0).cast("long"))).where("room > 0")
    # Of each, the rows that fit whole, and one more with the tokens that are left.
    fits = F.when(F.col("n_tokens") > 0, F.least(F.col("rows"), F.floor(F.col("room") / F.greatest("n_tokens", F.lit(1))))).otherwise(F.col("rows"))
    taken = ranked.withColumn("fits", fits).withColumn("more", F.when(F.col("fits") < F.col("rows"), F.col("room") - F.col("fits") * F.col("n_tokens")).otherwise(F.lit(0)))
    pieces.append(taken.where("fits > 0").select(*cols, F.col("n_tokens").alias("take_tokens"), F.explode(F.sequence(F.lit(1).cast("long"), "fits"))).drop("col"))
    pieces.append(taken.where("more > 0").select(*cols, F.col("more").cast("long").alias("take_tokens")))
    out = pieces[0]
    for p in pieces[1:]:
        out = out.unionByName(p)
    return out, budgets


def mix_documents(df: DataFrame, target: Target, domain: Column | None = None) -> DataFrame:
    """The chosen rows of df with all their columns, whole texts, once an epoch in which they are chosen.

    The document in which a leaf's budget ends is kept whole.  Rows that share an id (or have none) within a leaf are one document:
    all of them stay where any is chosen.  Columns of df may have any other names.
    """
    chosen, _ = select(df, target, domain)
    times = chosen.groupBy("doc_id", *LEVELS).agg(F.countDistinct("epoch").cast("int").alias("times"))
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), F.col("doc_id").alias("id"), *_paths(domain))
    t = times.select(F.col("doc_id").alias("t_id"), *[F.col(k).alias(f"t_{k}") for k in LEVELS], "times")
    same = F.col("id").eqNullSafe(F.col("t_id"))
    for k in LEVELS:
        same = same & (F.col(k) == F.col(f"t_{k}"))
    if target.max_epochs == 1:
        return rows.join(t.drop("times"), same, "left_semi").select("row.*")
    return rows.join(t, same).select("row", F.explode(F.sequence(F.lit(1), F.col("times")))).select("row.*")
