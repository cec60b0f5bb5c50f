"""The streaming form: draws in order become labelled records, and records become running answers.

Draws are staged as files, one set a step. One query labels them into a transport (a directory that is a log, or a
topic); another reads the transport and keeps moments by group as state. Both restart from their checkpoints.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.stateful_processor import StatefulProcessor
from pyspark.sql.types import StructType

from ..operators.estimate import half_width
from ..operators.labelers import Labeler


def stage_draws(draws: DataFrame, path: str, step: str = "step", files_per_step: int = 1) -> list[int]:
    """Writes each step's rows as files of their own, oldest step first; returns the steps.

    One job writes all steps, a folder each, beside `path`; their files then move to `path` in order (names and times of
    files only), so that a file source takes them step by step. A step is files_per_step tasks.
    """
    spark = draws.sparkSession
    draft = f"{path.rstrip('/')}-draft"
    names = [c for c in draws.columns if c != step]
    dealt = draws.withColumn("_step", F.col(step)).withColumn("_file", F.pmod(F.xxhash64(*names), F.lit(files_per_step)))
    # tasks of a given number: otherwise Spark joins few rows to one task, which writes one file a step
    by = ("_step", "_file") if files_per_step == 1 else (int(spark.conf.get("spark.sql.shuffle.partitions")), "_step", "_file")
    dealt.repartition(*by).drop("_file").write.mode("overwrite").partitionBy("_step").parquet(draft)
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    store = hadoop.Path(path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    store.mkdirs(hadoop.Path(path))
    folders = {x.getPath().getName(): x.getPath() for x in store.listStatus(hadoop.Path(draft)) if x.isDirectory()}
    steps = sorted(int(n.split("=")[1]) for n in folders if n.startswith("_step=") and n.split("=")[1].lstrip("-").isdigit())
    now = int(time.time() * 1000) - 1000 * len(steps)
    for i, s in enumerate(steps):
        for x in store.listStatus(folders[f"_step={s}"]):
            if not x.getPath().getName().startswith((".", "_")):
                to = hadoop.Path(f"{path}/step-{s:06d}-{x.getPath().getName()}")
                store.rename(x.getPath(), to)
                store.setTimes(to, now + 1000 * i, -1)
    store.delete(hadoop.Path(draft), True)
    return steps


@dataclass(frozen=True)
class DirTransport:
    """A directory of Parquet files as a log between the two queries."""

    path: str

    def write(self, stream: DataFrame, checkpoint: str) -> StreamingQuery:
        return stream.writeStream.format("parquet").option("path", self.path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()

    def read(self, spark: SparkSession, schema: StructType, files: int = 1) -> DataFrame:
        return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(self.path)


@dataclass(frozen=True)
class KafkaTransport:
    """A topic as the log; needs Spark's Kafka connector on the class path."""

    servers: str
    topic: str
    options: dict = field(default_factory=dict)

    def write(self, stream: DataFrame, checkpoint: str) -> StreamingQuery:
        rows = stream.select(F.to_json(F.struct("*")).alias("value"))
        return rows.writeStream.format("kafka").options(**{"kafka.bootstrap.servers": self.servers, "topic": self.topic} | self.options).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

    def read(self, spark: SparkSession, schema: StructType, files: int = 1) -> DataFrame:
        raw = spark.readStream.format("kafka").options(**{"kafka.bootstrap.servers": self.servers, "subscribe": self.topic, "startingOffsets": "earliest"} | self.options).load()
        return raw.select(F.from_json(F.col("value").cast("string"), schema).alias("r")).select("r.*")


def label_stream(spark: SparkSession, source: str, schema: StructType, labeler: Labeler, text: str, transport: DirTransport | KafkaTransport, checkpoint: str, files: int = 1) -> StreamingQuery:
    """Draws from a staged directory to labelled records in a transport, a file set a trigger."""
    draws = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(source)
    return transport.write(labeler.label(draws, text).drop(text), checkpoint)


@dataclass(frozen=True)
class StreamSpec:
    """AVG of value over valid records, by groups, after structured filters."""

    value: str
    group_by: tuple[str, ...] = ()
    where: str | None = None
    confidence: float = 0.95


def moments(labelled: DataFrame, spec: StreamSpec) -> DataFrame:
    """Calls, valid records and sums by group: the state is a row a group. Runs on streams and tables."""
    rows = labelled.where(spec.where) if spec.where else labelled
    v = F.when(F.col("is_valid"), F.col(spec.value).cast("double"))
    by = list(spec.group_by)
    return rows.groupBy(*by).agg(F.count("*").alias("calls"), F.count(v).alias("n_valid"), F.coalesce(F.sum(v), F.lit(0.0)).alias("s1"), F.coalesce(F.sum(v * v), F.lit(0.0)).alias("s2"))


def answers(sums: DataFrame, spec: StreamSpec) -> DataFrame:
    n = F.col("n_valid")
    var = F.when(n > 1, F.greatest(F.lit(0.0), (F.col("s2") - F.col("s1") * F.col("s1") / n) / (n - 1)))
    return sums.select(*spec.group_by, "calls", "n_valid", F.when(n > 0, F.col("s1") / n).alias("estimate"), half_width(var, n, spec.confidence).alias("half_width"))


def progressive_stream(labelled: DataFrame, spec: StreamSpec, path: str, checkpoint: str, stop: Callable[[DataFrame], bool] | None = None) -> StreamingQuery:
    """Running answers of every trigger, written to path/trigger=N (a repeated trigger replaces its own).

    stop sees a trigger's answers; where it says so, later triggers publish nothing and the caller ends the query.
    """
    done = []

    def publish(batch: DataFrame, trigger: int) -> None:
        if done:
            batch.write.format("noop").mode("overwrite").save()  # a trigger has to commit its state, answered or not
            return
        answers(batch, spec).write.mode("overwrite").parquet(f"{path}/trigger={trigger:06d}")
        if stop and stop(batch.sparkSession.read.parquet(f"{path}/trigger={trigger:06d}")):
            done.append(trigger)

    return moments(labelled, spec).writeStream.outputMode("complete").option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(publish).start()


class StratumFrequencies(StatefulProcessor):
    """Frequencies of labels by stratum in a state store: a map a stratum; emits the dominant label and the heterogeneity."""

    def init(self, handle) -> None:
        self.counts = handle.getMapState("counts", "label string", "x bigint")

    def handleInputRows(self, key, rows, timer_values):
        import pandas as pd

        for part in rows:
            for label, x in part["label"].dropna().astype(str).value_counts().items():
                old = self.counts.getValue((label,)) if self.counts.containsKey((label,)) else (0,)
                self.counts.updateValue((label,), (int(old[0]) + int(x),))
        held = {k[0]: v[0] for k, v in self.counts.iterator()}
        n = sum(held.values())
        top = min(held, key=lambda k: (-held[k], k)) if held else None
        het = 1 - sum((x / n) ** 2 for x in held.values()) if n else 0.0
        yield pd.DataFrame({"stratum": [key[0]], "n_drawn": [n], "dominant": [top], "heterogeneity": [het]})

    def close(self) -> None:
        pass


def stratum_state_stream(labelled: DataFrame) -> DataFrame:
    """Rows (stratum, label) of a stream to each trigger's changed stratum states. Needs the RocksDB state store."""
    return labelled.groupBy("stratum").transformWithStateInPandas(StratumFrequencies(), "stratum int, n_drawn bigint, dominant string, heterogeneity double", "Update", "None")


def windowed(events: DataFrame, width: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """Counts and means by event type in tumbling or sliding windows on ts (a TIMESTAMP); late rows beyond `late` are dropped in streams."""
    rows = events.withWatermark("ts", late) if late else events
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.groupBy(w, "event_type").agg(F.count("*").alias("n_events"), F.avg("value").alias("mean_value")).select(F.col("window.start").alias("window_start"), "event_type", "n_events", "mean_value")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", late) if late else events
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n_events")).select("user_id", F.col("session_window.start").alias("session_start"), "n_events")


def without_repeats(events: DataFrame, key: str, late: str) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def near_in_time(left: DataFrame, right: DataFrame, by: str, within: str, late: str) -> DataFrame:
    """Stream-stream join of rows of one key where the right one follows within an interval; state is bounded by watermarks."""
    a = left.withWatermark("ts", late).select(F.col(by).alias("by_l"), F.col("ts").alias("ts_l"), F.col("event_id").alias("left_id"))
    b = right.withWatermark("ts", late).select(F.col(by).alias("by_r"), F.col("ts").alias("ts_r"), F.col("event_id").alias("right_id"))
    return a.join(b, F.expr(f"by_l = by_r AND ts_r >= ts_l AND ts_r <= ts_l + INTERVAL {within}")).select("left_id", "right_id")
