"""Server records and events as streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from ..sources.shared import shared_folder
from ..sources.tables import SCHEMAS

#: Event types that set a status.
STATUS_OF = {"purchase": "Active", "error": "Suspended", "signup": "Pending"}


def replay(spark: SparkSession, path: str, schema: str | None = None, files_per_trigger: int = 1, glob: str | None = None) -> DataFrame:
    """Parquet files of a folder as a stream, so many a trigger."""
    reader = spark.readStream.schema(schema or SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger)
    if glob:
        reader = reader.option("pathGlobFilter", glob)
    return reader.parquet(path)


def as_reports(events: DataFrame) -> DataFrame:
    """Events as server reports: user, time, status (null where the event sets none) and server."""
    status = F.coalesce(*[F.when(F.col("event_type") == k, F.lit(v)) for k, v in STATUS_OF.items()])
    k = F.from_json("props", "k long")["k"]
    return events.select("event_id", F.col("user_id").alias("rid"), "ts", status.alias("status"), F.concat(F.lit("server"), (k % 25 + 1).cast("string")).alias("servername"))


def stream_link(stream: DataFrame, linker, sink: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Every micro-batch through a fitted linker, to ``sink(links, epoch)``; a repeated epoch gives the same links."""

    def each(batch: DataFrame, epoch: int) -> None:
        sink(linker.link(batch), epoch)

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def contradiction_windows(df: DataFrame, kind: str, size: str, slide: str | None = None, gap: str | None = None, watermark: str | None = None, by: tuple[str, ...] = ("servername",)) -> DataFrame:
    """Reports that set a status, counted by window (tumbling, sliding or session) and ``by``; batch and stream alike."""
    df = df.where("status is not null")
    if watermark:
        df = df.withWatermark("ts", watermark)
    if kind == "tumbling":
        w = F.window("ts", size)
    elif kind == "sliding":
        w = F.window("ts", size, slide)
    elif kind == "session":
        w = F.session_window("ts", gap or size)
    else:
        raise ValueError("kind is tumbling, sliding or session")
    out = df.groupBy(w.alias("w"), *by).agg(F.count("*").alias("n"), F.sum((F.col("status") == "Suspended").cast("long")).alias("suspended"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n", "suspended")


def dedup_reports(df: DataFrame, keys: list[str], watermark: str) -> DataFrame:
    """The first of repeated reports, remembered as long as the watermark lasts."""
    return df.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys)


DRIFT = T.StructType([T.StructField("rid", T.LongType()), T.StructField("ts", T.TimestampType()), *(T.StructField(n, T.StringType()) for n in ("field", "old", "new"))])


class DriftProcessor(StatefulProcessor):
    """Keeps each user's last values and emits every change; forgets a user after ``ttl`` without reports."""

    def __init__(self, fields: list[str], ttl_ms: int | None) -> None:
        self.fields, self.ttl_ms = fields, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        schema = T.StructType([T.StructField(f, T.StringType()) for f in self.fields])
        self.last = handle.getValueState("last", schema, self.ttl_ms) if self.ttl_ms else handle.getValueState("last", schema)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        state = list(self.last.get()) if self.last.exists() else [None] * len(self.fields)
        out = []
        for frame in [pd.concat(list(rows)).sort_values(["ts", "event_id"])]:
            for r in frame.to_dict("records"):
                for i, f in enumerate(self.fields):
                    v = r[f]
                    if v is None or v == state[i]:
                        continue
                    if state[i] is not None:
                        out.append((key[0], r["ts"], f, state[i], v))
                    state[i] = v
        self.last.update(tuple(state))
        yield pd.DataFrame(out, columns=["rid", "ts", "field", "old", "new"])

    def close(self) -> None:
        pass


def drift_detector(stream: DataFrame, fields: list[str], ttl_ms: int | None = None) -> DataFrame:
    """Changes of a user's fields: rid, ts, field, old, new.  Needs the RocksDB state store."""
    return stream.groupBy("rid").transformWithStateInPandas(DriftProcessor(fields, ttl_ms), outputStructType=DRIFT, outputMode="Append", timeMode="ProcessingTime" if ttl_ms else "None")


def drift_batch(df: DataFrame, fields: list[str]) -> DataFrame:
    """The same over a table."""
    from pyspark.sql import Window

    parts = []
    for f in fields:
        w = Window.partitionBy("rid").orderBy("ts", "event_id")
        known = df.where(F.col(f).isNotNull()).withColumn("old", F.lag(f).over(w))
        parts.append(known.where(F.col("old") != F.col(f)).select("rid", "ts", F.lit(f).alias("field"), "old", F.col(f).alias("new")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def stream_interval_join(a: DataFrame, b: DataFrame, on: str, within: str, watermark: str) -> DataFrame:
    """Pairs of equal key whose times (a.ts, b.ts2) are at most ``within`` apart; state is bounded by the watermarks."""
    a, b = a.withWatermark("ts", watermark), b.withColumnRenamed(on, f"{on}2").withWatermark("ts2", watermark)
    gap = F.expr(f"INTERVAL {within}")
    return a.join(b, (F.col(on) == F.col(f"{on}2")) & (F.col("ts2") >= F.col("ts") - gap) & (F.col("ts2") <= F.col("ts") + gap))


def collect_stream(df: DataFrame, name: str, mode: str = "append", state_store: bool = False) -> DataFrame:
    """Run a stream over what is there; give what it wrote, as Parquet in the shared folder, a folder an epoch.

    A repeated epoch overwrites its own folder.  In ``complete`` mode each epoch is the whole result, and the last one counts.
    """
    spark = df.sparkSession
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    out, epochs = shared_folder(spark, name), []

    def sink(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/epoch={epoch}")
        epochs.append(epoch)

    if state_store:
        spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = df.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", shared_folder(spark, f"{name}-progress")).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        if state_store:
            spark.conf.set(key, before) if before else spark.conf.unset(key)
    if not epochs:
        return spark.createDataFrame([], df.schema)
    chosen = sorted(set(epochs)) if mode == "append" else [max(epochs)]
    return spark.read.schema(df.schema).parquet(*[f"{out}/epoch={e}" for e in chosen])
