"""Deterministic linkage workloads from the given tables, in SQL that Spark and DuckDB both run.

Table names are placeholders in braces: Spark gets DataFrames for them, DuckDB its views' names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .tables import read_table

TABLES = ("customer", "part", "pages", "orders")
HEX = "0123456789abcdef"


def _hex(salt: str, i: int, key: str = "rid") -> str:
    return f"(instr('{HEX}', substr(md5(concat('{salt}', cast({key} as string))), {i}, 1)) - 1)"


def reference(email_digits: int = 3, user_digits: int = 4) -> str:
    """The trusted relation: rid, email, username, domain, servername, status."""
    return f"""
SELECT c.c_custkey AS rid,
  concat(replace(p.p_name, ' ', ''), substr(md5(concat('e', cast(c.c_custkey as string))), 1, {email_digits}),
         '@mail', cast(c.c_custkey % 9 as string), '.example.com') AS email,
  concat(replace(p.p_name, ' ', '.'), '_', substr(md5(concat('u', cast(c.c_custkey as string))), 1, {user_digits})) AS username,
  regexp_extract(g.url, '^https?://([^/?#]+)', 1) AS domain,
  concat('server', cast(c.c_nationkey + 1 as string)) AS servername,
  CASE l.o_orderstatus WHEN 'F' THEN 'Terminated' WHEN 'O' THEN 'Active' WHEN 'P' THEN 'Suspended' ELSE 'Pending' END AS status
FROM (SELECT c_custkey, c_nationkey, c_custkey % (SELECT count(*) FROM {{part}}) AS part_at, c_custkey % (SELECT count(*) FROM {{pages}}) AS page_at FROM {{customer}}) c
JOIN {{part}} p ON p.p_partkey = c.part_at
JOIN {{pages}} g ON g.page_id = c.page_at
LEFT JOIN (
  SELECT o_custkey, o_orderstatus FROM (
    SELECT o_custkey, o_orderstatus, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey DESC) AS rn
    FROM {{orders}}) x WHERE rn = 1) l ON l.o_custkey = c.c_custkey"""


def _orphan(column: str, other: str) -> str:
    made = {"email": "concat(substr(md5(concat('x', cast(rid as string))), 1, 9), '@mail0.example.com')", "username": "concat('new', substr(md5(concat('y', cast(rid as string))), 1, 7))"}[column]
    return f"CASE WHEN op = 15 THEN {made} ELSE {other} END AS {column}"


LOST = "concat(substr(email, 1, 2), substr(email, 4))"
SWAPPED = "concat(substr(username, 1, 2), substr(username, 4, 1), substr(username, 3, 1), substr(username, 5))"
MOVED = "concat('moved', substr(domain, 4))"
OTHER_SERVER = "concat('server', cast((rid * 7 + 3) % 25 + 1 as string))"
OTHER_STATUS = "CASE WHEN status = 'Active' THEN 'Suspended' ELSE 'Active' END"


def light() -> str:
    """One known drift for each server record."""
    return f"""
SELECT rid + 10000000 AS qid,
  {_orphan("email", f"CASE WHEN op IN (5, 13) THEN {LOST} WHEN op = 8 THEN '' WHEN op = 12 THEN replace(email, 'example.com', 'exmaple.com') ELSE email END")},
  {_orphan("username", f"CASE WHEN op IN (6, 13) THEN {SWAPPED} WHEN op = 7 THEN upper(username) ELSE username END")},
  CASE WHEN op = 7 THEN concat('www.', domain) WHEN op = 11 THEN {MOVED} ELSE domain END AS domain,
  CASE WHEN op IN (10, 14) THEN {OTHER_SERVER} ELSE servername END AS servername,
  CASE WHEN op IN (9, 14) THEN {OTHER_STATUS} ELSE status END AS status,
  CASE WHEN op = 15 THEN NULL ELSE rid END AS truth_rid, op
FROM (SELECT r.*, cast({_hex("op", 1)} as int) AS op FROM ({reference()}) r) d"""


def heavy() -> str:
    """Several fields drift at once; ``train`` marks the half for fine-tuning."""
    return f"""
SELECT rid + 10000000 AS qid,
  {_orphan("email", f"CASE WHEN e < 4 THEN '' WHEN e < 8 THEN {LOST} WHEN e < 12 THEN replace(replace(email, 'example.com', 'exmaple.com'), 'a', '') ELSE email END")},
  {_orphan("username", f"CASE WHEN u < 5 THEN {SWAPPED} WHEN u < 9 THEN upper(replace(username, '.', '')) WHEN u < 12 THEN substr(username, 1, length(username) - 1) ELSE username END")},
  CASE WHEN d < 4 THEN concat('www.', domain) WHEN d < 8 THEN replace(replace(domain, '.', '-'), 'th', 't') WHEN d < 11 THEN {MOVED} ELSE domain END AS domain,
  CASE WHEN s < 5 THEN {OTHER_SERVER} ELSE servername END AS servername,
  CASE WHEN s % 3 = 0 THEN {OTHER_STATUS} ELSE status END AS status,
  CASE WHEN op = 15 THEN NULL ELSE rid END AS truth_rid, op, split < 8 AND op < 15 AS train
FROM (SELECT r.*, cast({_hex("op", 1)} as int) AS op, {_hex("op", 2)} AS e, {_hex("op", 3)} AS u, {_hex("op", 4)} AS d,
  {_hex("op", 5)} AS s, {_hex("split", 1)} AS split FROM ({reference(2, 3)}) r) x"""


def planted() -> str:
    """Noisy copies of every embedding, straddling cosine 0.8: qid, truth_rid and, as a list of doubles, vec."""
    return """
SELECT a.vec_id + 1000000 AS qid, a.vec_id AS truth_rid, a.embedding AS a, b.embedding AS b,
  CASE a.vec_id % 4 WHEN 0 THEN 0.3e0 WHEN 1 THEN 0.6e0 WHEN 2 THEN 0.7e0 ELSE 1.0e0 END AS alpha
FROM (SELECT vec_id, embedding, (vec_id + 1) % (SELECT count(*) FROM {embeddings}) AS after FROM {embeddings}) a
JOIN {embeddings} b ON b.vec_id = a.after"""


def duck(sql: str) -> str:
    """The same SQL over DuckDB's views."""
    return sql.format(**{t: t for t in (*TABLES, "embeddings")})


def run(spark: SparkSession, sf_dir: str, sql: str, tables: tuple[str, ...] = TABLES) -> DataFrame:
    return spark.sql(sql, **{t: read_table(spark, sf_dir, t) for t in tables})


def ref_users(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    """The reference of the light workload, or with shorter suffixes (near-collisions) that of the heavy one."""
    return run(spark, sf_dir, reference(2, 3) if hard else reference())


def srv_users(spark: SparkSession, sf_dir: str, hard: bool = False) -> DataFrame:
    return run(spark, sf_dir, heavy() if hard else light())


def planted_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    df = run(spark, sf_dir, planted(), ("embeddings",))
    mixed = F.zip_with("a", "b", lambda x, y: x.cast("double") + F.col("alpha") * y.cast("double"))
    return df.select("qid", "truth_rid", mixed.alias("vec"))
