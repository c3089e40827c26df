from collections import defaultdict

from recordlink.llm import mixing
from recordlink.llm.mixing import LEVELS, Target, divide, plan
from recordlink.llm.queries import TARGET, domain_of_source


def test_divide():
    assert divide(100, [1, 1], [1000, 1000]) == [50, 50]
    assert divide(100, [1, 1], [10, 1000]) == [10, 90]
    assert divide(100, [3, 1, 1], [30, 20, 100]) == [30, 20, 50]
    assert divide(100, [1, 0], [40, 1000]) == [40, 60]
    assert divide(100, [1, 1], [10, 20]) == [10, 20]
    assert divide(7, [1, 1, 1], [9, 9, 9]) == [3, 2, 2]
    assert divide(5, [], []) == []


def test_siblings_take_a_shortage_before_ancestors_do():
    supply = {("a", "x", "1"): 10, ("a", "y", "1"): 1000, ("b", "x", "1"): 1000}
    got = plan(supply, Target(budget_tokens=400, max_epochs=1))
    assert got == {("a", "x", "1"): 10, ("a", "y", "1"): 190, ("b", "x", "1"): 200}
    supply["a", "y", "1"] = 50
    got = plan(supply, Target(budget_tokens=400, max_epochs=1))
    assert got == {("a", "x", "1"): 10, ("a", "y", "1"): 50, ("b", "x", "1"): 340}


def test_selection_meets_every_budget(docs):
    rows, budgets = mixing.select(docs, TARGET, domain_of_source())
    taken, whole, seen = defaultdict(int), defaultdict(set), defaultdict(int)
    for r in rows.collect():
        leaf = tuple(r[k] for k in LEVELS)
        taken[leaf] += r["take_tokens"]
        whole[leaf, r["epoch"]].add(r["doc_id"])
        seen[leaf] += r["take_tokens"] < r["n_tokens"]
        assert 0 <= r["take_tokens"] <= r["n_tokens"]
    assert {k: v for k, v in budgets.items() if v} == {k: v for k, v in taken.items() if v}
    assert all(n <= 1 for n in seen.values())
    again = mixing.select(docs.repartition(7), TARGET, domain_of_source())[0]
    assert sorted(map(tuple, rows.collect())) == sorted(map(tuple, again.collect()))


def test_prefix_equals_sorting_the_leaf(spark, docs):
    """Brute force: sort each leaf's documents by the epoch's hash and cut where the budget ends."""
    from pyspark.sql import functions as F

    target = Target(budget_share=0.5, max_epochs=1)
    rows, budgets = mixing.select(docs, target, None)
    got = {(r["doc_id"], r["take_tokens"]) for r in rows.collect()}
    hashed = docs.select("doc_id", "lang", "source", "text", F.xxhash64(F.lit(target.seed), F.lit(0), "doc_id").alias("h")).collect()
    want = set()
    for leaf, budget in budgets.items():
        left = budget
        for r in sorted((r for r in hashed if (r["lang"], r["source"]) == leaf[1:]), key=lambda r: r["h"] & 0xFFFFFFFFFFFFFFFF):
            if left <= 0:
                break
            n = len(r["text"].encode().split())
            want.add((r["doc_id"], min(n, left)))
            left -= min(n, left)
    assert {x for x in got if x[1]} == {x for x in want if x[1]}


def test_odd(odd, none):
    rows, budgets = mixing.select(odd, Target(max_epochs=2, budget_share=1.7))
    assert sum(r["take_tokens"] for r in rows.collect()) == sum(budgets.values())
    assert ("all", mixing.NONE, mixing.NONE) in budgets
    assert mixing.select(none, Target())[0].count() == 0
    mixed = mixing.mix_documents(odd, Target(max_epochs=1))
    assert mixed.columns == odd.columns and mixed.count() > 0
    assert mixing.mix_documents(odd, Target(max_epochs=3, budget_share=2.5)).count() > odd.count()
    assert mixing.mix_documents(none, Target(max_epochs=1)).count() == 0


def test_repeated_rows_at_the_cut(spark):
    """Equal rows are taken as far as the budget goes, and their tokens sum to it."""
    df = spark.createDataFrame([("a", "x y z", "en", "s")] * 50 + [("b", "u v", "en", "s"), (None, "w w w w", "en", "s")], "doc_id string, text string, lang string, source string")
    for budget in (1, 3, 76, 100, 155, 156):
        rows = mixing.select(df, Target(budget_tokens=budget, max_epochs=1))[0].collect()
        assert sum(r["take_tokens"] for r in rows) == budget and sum(r["take_tokens"] < r["n_tokens"] for r in rows) <= 1
        assert sum(r["doc_id"] == "a" for r in rows) <= 50


def test_columns_of_any_names_come_back(spark, docs):
    from pyspark.sql import functions as F

    odd = docs.select("*", F.lit(1).alias("times"), F.lit(2).alias("copy"), F.lit(3).alias("p_domain"), F.lit(4).alias("domain"), F.lit(5).alias("row"), F.lit(6).alias("n_tokens"), F.lit(7).alias("t_id"), F.lit(8).alias("a.b"))
    for epochs, share in ((1, 0.5), (3, 1.6)):
        target = Target(budget_share=share, max_epochs=epochs)
        got = mixing.mix_documents(odd, target)
        assert got.columns == odd.columns and set(got.select("times", "copy", "p_domain", "domain", "row", "n_tokens", "t_id").distinct().collect()) == {(1, 2, 3, 4, 5, 6, 7)}
        assert sorted(r["doc_id"] for r in got.collect()) == sorted(r["doc_id"] for r in mixing.mix_documents(docs, target).collect())
