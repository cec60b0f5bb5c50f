"""Labelers: the semantic function as an object that adds label and is_valid to rows.

A labeler is applied to draws, never to a whole table by accident, and its answers are appended to a draw log before
anything reads them twice.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.order import draw_rank


class Labeler:
    """label(df, text) gives df with label and is_valid. prepare(df) may attach, once for a table that is drawn from step by
    step, columns named _truth... that label() then reads in place of a join of its own."""

    def prepare(self, df: DataFrame) -> DataFrame:
        base = getattr(self, "base", None)
        return base.prepare(df) if base is not None else df

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        raise NotImplementedError


@dataclass(frozen=True)
class RuleLabeler(Labeler):
    """A Column over the row; a null answer is not valid."""

    rule: Column

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        return df.withColumn("label", self.rule).withColumn("is_valid", F.col("label").isNotNull())


@dataclass(frozen=True)
class LookupLabeler(Labeler):
    """The truth: answers from a table of labels. Rows without one are not valid."""

    labels: DataFrame
    key: str
    column: str

    def prepare(self, df: DataFrame) -> DataFrame:
        known = self.labels.select(F.col(self.key).alias("_k"), F.col(self.column).alias(f"_truth_{self.column}")).dropDuplicates(["_k"])
        return df.join(known, F.col(self.key) == F.col("_k"), "left").drop("_k")

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        truth = f"_truth_{self.column}"
        ready = df if truth in df.columns else self.prepare(df)
        return ready.withColumn("label", F.col(truth)).drop(truth).withColumn("is_valid", F.col("label").isNotNull())


@dataclass(frozen=True)
class NoisyLabeler(Labeler):
    """A model of given accuracy: some of another labeler's answers become the next category, always the same ones."""

    base: Labeler
    accuracy: float
    categories: tuple
    key: str = "doc_id"
    seed: int = 7

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        bucket = F.conv(F.substring(draw_rank(self.key, self.seed), 1, 8), 16, 10).cast("bigint")
        after = dict(zip(self.categories, [*self.categories[1:], self.categories[0]], strict=True))
        other = F.lit(None)
        for c, following in after.items():
            other = F.when(F.col("label") == F.lit(c), F.lit(following)).otherwise(other)
        wrong = bucket >= int(self.accuracy * (1 << 32))
        return self.base.label(df, text).withColumn("label", F.when(wrong, other).otherwise(F.col("label")))


@dataclass(frozen=True)
class ExtractLabeler(Labeler):
    """A scalar from the text; what the extractor refuses is not valid."""

    extractor: object

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        return df.withColumn("label", self.extractor.value(text)).withColumn("is_valid", F.col("label").isNotNull())


@dataclass(frozen=True)
class CategoryLabeler(Labeler):
    """Answers outside a closed domain are not valid."""

    base: Labeler
    categories: tuple

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        known = F.coalesce(F.col("label").isin(*self.categories), F.lit(False))
        return self.base.label(df, text).withColumn("is_valid", F.col("is_valid") & known)


@dataclass(frozen=True)
class PredicateLabeler(Labeler):
    """Another labeler's answer against one value: true or false; no answer is false."""

    base: Labeler
    equals: object

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        return self.base.label(df, text).withColumn("label", F.coalesce(F.col("label") == F.lit(self.equals), F.lit(False)))


@dataclass(frozen=True)
class ServiceLabeler(Labeler):
    """A served model. client(endpoint) runs once in a task and gives a function from a list of texts to answers.

    Rows are dealt to endpoints by task; a task keeps up to max_inflight requests open and repeats failed ones. With
    endpoints_per_task a task has as many endpoints of its own, asks the least busy of them, and keeps up to max_inflight
    requests open to each. An answer of None, and a request that fails for good, is not valid. A repeated task asks again:
    answers are only used from the draw log, which has one row for a draw.
    """

    client: Callable[[str], Callable[[list[str]], list]]
    endpoints: tuple[str, ...] = ("local",)
    label_type: str = "string"
    batch_size: int = 32
    max_inflight: int = 4
    retries: int = 2
    tasks_per_endpoint: int = 1
    routing: str = "round_robin"
    endpoints_per_task: int = 1

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        client, endpoints, size, inflight, retries, routing = self.client, self.endpoints, self.batch_size, self.max_inflight, self.retries, self.routing
        each = self.endpoints_per_task
        if len(endpoints) % each:
            raise ValueError(f"{len(endpoints)} endpoints are not {each} for each task")
        own = [endpoints[i : i + each] for i in range(0, len(endpoints), each)] if routing == "round_robin" else [endpoints] * len(endpoints)
        inflight *= each if routing == "round_robin" else 1
        df = df.drop("label", "is_valid").repartition(len(own) * self.tasks_per_endpoint)  # of one endpoint too: a table's own tasks would all ask it

        def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            from threading import Lock

            from pyspark import TaskContext

            asks = [client(x) for x in own[TaskContext.get().partitionId() % len(own)]]
            busy, choice = [0] * len(asks), Lock()

            def answer(texts: list[str]) -> list:
                for attempt in range(retries + 1):
                    with choice:
                        k = busy.index(min(busy))
                        busy[k] += 1
                    try:
                        return asks[k](texts)
                    except Exception:
                        if attempt == retries:
                            return [None] * len(texts)
                    finally:
                        with choice:
                            busy[k] -= 1
                return []

            with ThreadPoolExecutor(inflight) as pool:
                for part in parts:
                    texts = [x if isinstance(x, str) else "" for x in part[text]]
                    runs = [texts[i : i + size] for i in range(0, len(texts), size)]
                    labels = [y for got in pool.map(answer, runs) for y in got]
                    part = part.assign(label=pd.Series(labels, index=part.index, dtype=object))
                    yield part.assign(is_valid=[y is not None for y in labels])

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + f", label {self.label_type}, is_valid boolean"
        return df.mapInPandas(run, schema)


@dataclass
class SimulatedService(Labeler):
    """Another labeler behind a fixed service time. By default a virtual clock; with real=True a task sleeps for its rows.

    Each instance serves one row at a time. A task asks one instance, or with fewer `tasks` as many of them as the others.
    """

    base: Labeler
    seconds_per_call: float = 0.05
    instances: int = 1
    serial_share: float = 0.0
    real: bool = False
    tasks: int | None = None

    def seconds(self, calls: int) -> float:
        """Calls over instances in parallel, and a part of each call that is serial (routing, batching)."""
        serial = calls * self.seconds_per_call * self.serial_share
        return serial + -(-calls // self.instances) * self.seconds_per_call * (1 - self.serial_share)

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        out = self.base.label(df, text)
        if not self.real:
            return out
        wait, tasks = self.seconds_per_call, self.tasks or self.instances
        if self.instances % tasks:
            raise ValueError(f"{self.instances} instances are not as many for each of {tasks} tasks")
        own = self.instances // tasks

        def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in parts:
                time.sleep(wait * -(-part.num_rows // own))
                yield part

        return out.repartition(tasks).mapInArrow(run, out.schema)  # not by pandas, which makes floats of whole numbers beside nulls


@dataclass
class CachedLabeler(Labeler):
    """Asks once for each text: answers are appended to a store by the text's hash and joined back."""

    base: Labeler
    path: str
    calls: list[int] = field(default_factory=list)

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        spark = df.sparkSession
        hashed = df.drop("label", "is_valid").withColumn("_hash", F.sha2(F.coalesce(text, F.lit("")), 256))
        known = self.store(spark)
        missing = hashed.dropDuplicates(["_hash"])
        if known is not None:
            missing = missing.join(known.select("_hash"), "_hash", "left_anti")
        fresh = self.base.label(missing, text).select("_hash", "label", "is_valid")
        fresh.write.mode("append").parquet(self.path)
        now = self.store(spark)
        self.calls.append(now.count() - (known.count() if known is not None else 0))
        return hashed.join(now, "_hash", "left").drop("_hash")

    def store(self, spark: SparkSession) -> DataFrame | None:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
            return None
        return spark.read.parquet(self.path)
