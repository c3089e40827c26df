import pytest
from pyspark.sql import functions as F

from recordlink.functions.similarity import _lcs, field_similarity, register
from recordlink.operators.serialize import serialize_generic, serialize_records
from recordlink.operators.tag import tag_pairs
from recordlink.operators.verify import attach_fields, composite_score, explain_pair, mutual_best, select_best
from recordlink.schema import USER, USER_FOLDED, FieldSpec, RecordSchema, align

ROW = ("a@x.example.com", "ada.l", "ada.example.org", "server3", "Active")
COLS = "email string, username string, domain string, servername string, status string"


def users(spark, rows, i):
    return spark.createDataFrame([(k, *r) for k, r in rows], f"{i} long, {COLS}")


def score(spark, a, b, **kw):
    q, r = users(spark, [(1, a)], "qid"), users(spark, [(2, b)], "rid")
    pairs = spark.createDataFrame([(1, 2)], "qid long, rid long")
    return composite_score(attach_fields(pairs, q, r, USER), USER, **kw).first()


def test_schema_rules():
    assert USER.names == ["email", "username", "domain", "servername", "status"]
    for fields in ((), (FieldSpec("a", 0.5),), (FieldSpec("a", 0.5), FieldSpec("a", 0.5)), (FieldSpec("a", 1.5), FieldSpec("b", -0.5))):
        with pytest.raises(ValueError):
            RecordSchema(fields)
    with pytest.raises(ValueError):
        USER.with_weights({"email": 1.0})
    with pytest.raises(KeyError):
        USER["nothing"]
    assert abs(sum(f.weight for f in USER.select("email", "status").fields) - 1) < 1e-12


def test_align_and_missing_fields(spark):
    df = spark.createDataFrame([(1, "m", 3)], "k long, mail string, n int")
    small = RecordSchema((FieldSpec("email", 1.0),))
    assert align(df, {"email": "mail"}, small, "k", "qid").columns == ["qid", "email"]
    with pytest.raises(ValueError):
        align(df, {"email": "nope"}, small, "k", "qid")
    with pytest.raises(ValueError):
        USER.check(df)


def test_worked_similarities(spark):
    one = spark.range(1)
    s = lambda a, b, n="maxlen": one.select(field_similarity(F.lit(a), F.lit(b), n)).first()[0]
    assert abs(s("kitten", "sitting") - 4 / 7) < 1e-12
    assert s("", "") == 1 and s("abc", "") == 0 and s(None, None) == 1
    assert abs(s("kitten", "sitting", "sumlen") - (1 - 3 / 13)) < 1e-12
    assert abs(s("kitten", "sitting", "metric") - (1 - 6 / 16)) < 1e-12
    assert abs(s("kitten", "sitting", "indel") - 8 / 13) < 1e-12
    assert s("", "", "indel") == 1
    with pytest.raises(ValueError):
        s("a", "b", "other")
    assert _lcs("kitten", "sitting") == 4 and _lcs("", "a") == 0 and _lcs("abcbdab", "bdcaba") == 4


def test_worked_scores(spark):
    assert abs(score(spark, ROW, ROW)["score"] - 1) < 1e-12
    assert abs(score(spark, ROW, (*ROW[:4], "xxxxxxxxx"))["score"] - 0.95) < 1e-12
    assert abs(score(spark, ("", *ROW[1:]), ROW)["score"] - 0.60) < 1e-12
    assert abs(score(spark, (None, *ROW[1:]), ROW)["score"] - 0.60) < 1e-12
    assert abs(score(spark, ("", *ROW[1:]), ROW, missing="renormalize")["score"] - 1) < 1e-12
    assert score(spark, ("",) * 5, ("",) * 5, missing="renormalize")["score"] == 0
    assert abs(score(spark, ("",) * 5, ("",) * 5)["score"] - 1) < 1e-12


def test_pruning_changes_no_score_at_or_over_the_bound(spark):
    rows = [(i, (f"m{i}@x.example.com", f"user{i % 7}", f"d{i % 5}.example.org", f"server{i % 3}", "Active" if i % 2 else "")) for i in range(40)]
    q, r = users(spark, rows, "qid"), users(spark, [(k, ("n" + v[0], *v[1:])) for k, v in rows], "rid")
    pairs = attach_fields(q.select("qid").crossJoin(r.select("rid")), q, r, USER)
    whole = {(x["qid"], x["rid"]): x["score"] for x in composite_score(pairs, USER).collect()}
    for least in (0.0, 0.6, 0.8, 1.0):
        got = composite_score(pairs, USER, prune=least).where("score is not null").collect()
        assert {(x["qid"], x["rid"]) for x in got} == {k for k, v in whole.items() if v >= least - 1e-12}
        assert all(abs(x["score"] - whole[x["qid"], x["rid"]]) < 1e-12 for x in got)


def test_choosing(spark):
    df = spark.createDataFrame([(1, 5, 0.9, 0.1), (1, 4, 0.9, 0.1), (1, 3, 0.9, 0.05), (2, 4, 0.95, 0.2), (3, 9, None, 0.2)], "qid long, rid long, score double, sim double")
    for how in ("max_by", "window"):
        assert {(x["qid"], x["rid"]) for x in select_best(df, how=how).collect()} == {(1, 4), (2, 4)}
        assert {(x["qid"], x["rid"]) for x in select_best(df, 0.92, how).collect()} == {(2, 4)}
    assert {(x["qid"], x["rid"]) for x in mutual_best(df).collect()} == {(1, 3), (2, 4)}


def test_explanations_add_up(spark):
    q, r = users(spark, [(1, ROW)], "qid"), users(spark, [(2, ("b", *ROW[1:]))], "rid")
    s = composite_score(attach_fields(spark.createDataFrame([(1, 2)], "qid long, rid long"), q, r, USER), USER)
    rows = explain_pair(s, USER).collect()
    assert len(rows) == 5 and abs(sum(x["part"] for x in rows) - rows[0]["score"]) < 1e-12


def test_tags(spark):
    ref = users(spark, [(1, ROW)], "rid")
    q = users(spark, [(1, ROW), (2, ("z", *ROW[1:4], "Pending")), (3, (ROW[0].upper(), ROW[1], "www." + ROW[2], *ROW[3:])), (4, ROW), (5, ROW)], "qid")
    best = spark.createDataFrame([(1, 1, 1.0), (2, 1, 0.6), (3, 1, 0.9), (4, 1, 0.1)], "qid long, rid long, score double")
    tags = {x["qid"]: (x["tag"], x["fields"]) for x in tag_pairs(best, q, ref, USER, accept=0.5).collect()}
    assert tags[1] == ("consistent", []) and tags[2] == ("contradiction:email", ["email", "status"])
    assert tags[3][0] == "contradiction:email" and tags[4][0] == tags[5][0] == "unlinked"
    assert {x["qid"]: x["tag"] for x in tag_pairs(best, q, ref, USER_FOLDED).collect()}[3] == "consistent"
    assert {x["qid"]: x["tag"] for x in tag_pairs(best, q, ref, USER, multi=True).collect()}[2] == "contradiction:{email,status}"


def test_sentences(spark):
    df = users(spark, [(1, ("", "ada", "d.example.org", "server3", "Active"))], "qid")
    assert serialize_records(df, USER).first()["sentence"] == "The username ada with email and domain d.example.org on server3 has active status."
    assert serialize_records(df, USER, "skip").first()["sentence"] == "The username ada and domain d.example.org on server3 has active status."
    listed = serialize_records(df, USER.select("domain", "email")).first()["sentence"]
    assert listed == "domain d.example.org, email" and serialize_records(df, USER, "skip", template="<{email}> {username}!").first()["sentence"] == "> ada!"
    with pytest.raises(ValueError, match="no fields"):
        serialize_records(df, USER, template="{nothing}")
    assert serialize_generic(spark.createDataFrame([(1, None, "x")], "a int, b string, c string"), ["a", "b", "c"]).first()["sentence"] == "a 1, c x"


def test_sql_functions(spark):
    register(spark)
    row = spark.sql("SELECT field_similarity('kitten', 'sitting') AS s, composite_score('a','b','c','d','e','a','b','c','d','x') AS c, serialize_record('', 'u', 'd', 's', 'Active') AS t").first()
    assert abs(row["s"] - 4 / 7) < 1e-12 and abs(row["c"] - 0.95) < 1e-12 and row["t"] == "The username u with email and domain d on s has active status."
