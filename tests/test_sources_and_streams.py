import pytest
from pyspark.sql import functions as F

from recordlink.operators import relational as R
from recordlink.sources import tables
from recordlink.streaming import streams as S


def test_server_dump(spark, tmp_path):
    for i in range(2):
        (tmp_path / f"d{i}.txt").write_text(f'id: {i}\nusername: "u{i}"\nstatus: Active\n\nid: 1{i}\nemail: e\n')
    spark.dataSource.register(tables.ServerDump)
    df = spark.read.format("server_dump").option("paths", f"{tmp_path}/d0.txt,{tmp_path}/d1.txt").load()
    assert sorted((r["qid"], r["username"], r["email"]) for r in df.collect()) == [(0, "u0", ""), (1, "u1", ""), (10, "", "e"), (11, "", "e")]


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_formats(spark, tmp_path, kind):
    df = spark.createDataFrame([(1, "e", "u", "d", "s", "A")], f"qid long, {tables.USER_COLUMNS}")
    df.write.format(kind).save(str(tmp_path / kind))
    assert tables.read_records(spark, str(tmp_path / kind), kind).collect() == df.collect()


def test_links_are_written_by_tag(spark, tmp_path):
    df = spark.createDataFrame([(1, 2, "consistent"), (2, None, "unlinked")], "qid long, rid long, tag string")
    tables.write_links(df, str(tmp_path / "l"))
    assert spark.read.parquet(str(tmp_path / "l")).where("tag = 'unlinked'").count() == 1


def test_declared_schemas_match_the_tables(spark, sf_dir):
    for name, ddl in tables.SCHEMAS.items():
        have = tables.read_table(spark, sf_dir, name).schema
        want = spark.createDataFrame([], ddl).schema
        kinds = lambda schema: [(f.name, f.dataType.simpleString().removesuffix("_ntz")) for f in schema]
        assert kinds(have) == kinds(want), name


def test_as_of_with_tolerance(spark):
    left = spark.sql("SELECT * FROM VALUES (1, 'k', timestamp'2024-01-02'), (2, 'k', timestamp'2024-01-09'), (3, 'j', timestamp'2024-01-02') AS t(i, k, ts)")
    right = spark.sql("SELECT * FROM VALUES ('k', timestamp'2024-01-02', 'a'), ('k', timestamp'2024-01-03', 'b') AS t(k, at, v)")
    assert {r["i"]: r["v"] for r in R.as_of(left, right, "k", "ts", "at", ["v"]).collect()} == {1: "a", 2: "b", 3: None}
    assert {r["i"]: r["v"] for r in R.as_of(left, right, "k", "ts", "at", ["v"], "3 DAYS").collect()} == {1: "a", 2: None, 3: None}


def test_udtf_and_html(spark):
    R.register_udtf(spark)
    assert [r["gram"] for r in spark.sql("SELECT * FROM char_ngrams('abcd', 3)").collect()] == ["abc", "bcd"]
    one = spark.range(1)
    assert one.select(R.strip_html(F.lit("<p>a<script>x</script> <b>b</b>"))).first()[0] == "a b"
    assert one.select(R.canonical_url(F.lit("https://www.H.example/a/b.html?x#y"))).first()[0] == "h.example/a/b"


def test_late_rows_and_windows(spark, tmp_path):
    rows = [(1, "2024-01-01 10:00:00", "Active"), (2, "2024-01-01 11:30:00", "Suspended"), (3, "2024-01-05 10:00:00", "Active")]
    late = [(4, "2024-01-01 10:10:00", "Active")]
    end = [(5, "2024-01-09 10:00:00", "Active")]
    mid = [(6, "2024-01-05 11:00:00", "Suspended")]  # rows are dropped by the watermark of the batch before the last
    for part in (rows, mid, late, end):
        df = spark.createDataFrame(part, "rid long, ts string, status string").withColumn("ts", F.to_timestamp("ts")).withColumn("servername", F.lit("s"))
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    import os
    import time

    files = sorted((f for f in os.listdir(tmp_path / "in") if f.endswith(".parquet")), key=lambda f: os.path.getmtime(tmp_path / "in" / f))
    for i, f in enumerate(files):
        os.utime(tmp_path / "in" / f, (time.time() - 100 + 10 * i,) * 2)
    stream = S.replay(spark, str(tmp_path / "in"), "rid long, ts timestamp, status string, servername string")
    got = S.collect_stream(S.contradiction_windows(stream, "tumbling", "1 day", watermark="1 hour"), "late_t", "append").collect()
    assert {(str(r["start"])[:10], r["n"], r["suspended"]) for r in got} == {("2024-01-01", 2, 1), ("2024-01-05", 2, 1)}
