"""Readers with declared schemas, a Python data source for server dumps, and writers."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Declared columns of the tables.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}
USER_COLUMNS = "email string, username string, domain string, servername string, status string"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the given folder."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_records(spark: SparkSession, path: str, kind: str, id_name: str = "qid", **options: str) -> DataFrame:
    """User records from csv, json, orc or parquet files, under the declared schema rather than a guessed one."""
    reader = spark.read.schema(f"{id_name} long, {USER_COLUMNS}")
    for k, v in options.items():
        reader = reader.option(k, v)
    return reader.format(kind).load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, id_col: str, low: int, high: int, partitions: int = 64, **options: str) -> DataFrame:
    """A central database's table, read in parallel over ranges of its id."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=id_col, lowerBound=str(low), upperBound=str(high), numPartitions=str(partitions), **options).load()


class DumpPartition(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class ServerDumpReader(DataSourceReader):
    def __init__(self, paths: list[str]) -> None:
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [DumpPartition(p) for p in self.paths]

    def read(self, partition: DumpPartition) -> Iterator[tuple]:
        """One record a block of ``key: value`` lines; blocks are parted by empty lines."""
        names = ["email", "username", "domain", "servername", "status"]
        block: dict[str, str] = {}
        with open(partition.path, encoding="utf-8") as f:
            for line in [*f, ""]:
                line = line.strip()
                if line:
                    key, _, value = line.partition(":")
                    block[key.strip().lower()] = value.strip().strip('"')
                elif block:
                    yield (int(block.get("id", "-1")), *(block.get(n, "") for n in names))
                    block = {}


class ServerDump(DataSource):
    """``spark.read.format("server_dump").option("paths", "a,b")``: text dumps of server records, a partition a file."""

    @classmethod
    def name(cls) -> str:
        return "server_dump"

    def schema(self) -> str:
        return f"qid long, {USER_COLUMNS}"

    def reader(self, schema) -> DataSourceReader:
        return ServerDumpReader([p for p in self.options.get("paths", "").split(",") if p])


def write_links(df: DataFrame, path: str, by: tuple[str, ...] = ("tag",)) -> None:
    """Links as Parquet, a folder for each value of ``by``."""
    df.write.mode("overwrite").option("compression", "zstd").partitionBy(*by).parquet(path)


def run_noop(df: DataFrame) -> None:
    """Run the whole plan and keep nothing; for timing."""
    df.write.mode("overwrite").format("noop").save()
