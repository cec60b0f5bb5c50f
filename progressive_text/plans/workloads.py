"""The experiments on the given tables: inputs, semantic functions, truths, and the runs that compare methods."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable, Iterator
from concurrent.futures import Future, ThreadPoolExecutor, wait
from contextlib import contextmanager
from dataclasses import dataclass, field, replace
from functools import reduce
from itertools import chain

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.extract import JsonExtractor, RegexExtractor
from ..operators.embed import GivenVectors, HashedNgramEmbedder
from ..operators.labelers import ExtractLabeler, Labeler, LookupLabeler, PredicateLabeler, RuleLabeler, ServiceLabeler, SimulatedService
from ..functions import rules
from ..operators.strata import kmeans_strata, strata_bounds
from ..sources.store import saved
from ..sources.tables import balanced, labelled, table, with_counts, with_page_language
from . import baselines, metrics
from .filter_engine import progressive_filter
from .group_engine import GroupConfig, progressive_group
from .query import Clock, ProgressLog, Stop
from .select_engine import progressive_select

LANGS = ["de", "en", "es", "fr"]
CLASS3 = ["clean", "junk", "toxic"]


@dataclass(frozen=True)
class Workload:
    """A table, its text, a semantic function, and the exact answer (grp, truth)."""

    name: str
    kind: str
    df: DataFrame
    key: str
    text: str
    labeler: Labeler
    truth: DataFrame
    value: str | None = None
    group_by: tuple[str, ...] = ()
    categories: tuple = ()
    vectors: str = "text"


def _lookup(df: DataFrame, key: str, column: str, equals=None) -> Labeler:
    labeler = LookupLabeler(df.select(key, column), key, column)
    return labeler if equals is None else PredicateLabeler(labeler, equals)


def _mean(df: DataFrame, value: str, by: str | None = None) -> DataFrame:
    grp = F.col(by).cast("string") if by else F.lit("")
    return df.groupBy(grp.alias("grp")).agg(F.avg(F.col(value).cast("double")).alias("truth"))


def _share(df: DataFrame, column: str) -> DataFrame:
    n = df.count()
    return df.groupBy(F.col(column).cast("string").alias("grp")).agg((F.count("*") / F.lit(n)).alias("truth"))


def w1(spark: SparkSession, d: str) -> Workload:
    events, ex = table(spark, d, "events"), JsonExtractor("k INT", "k", 0, 99)
    return Workload("W1", "select", events, "event_id", "props", ExtractLabeler(ex), _mean(events.withColumn("k", ex.value("props")), "k", "event_type"), group_by=("event_type",))


def w2(spark: SparkSession, d: str) -> Workload:
    pages, ex = with_page_language(table(spark, d, "pages")), RegexExtractor("<p>", "int", count=True)
    return Workload("W2", "select", pages, "page_id", "html", ExtractLabeler(ex), _mean(pages.withColumn("n", ex.value("html")), "n", "page_lang"), group_by=("page_lang",))


def w3(spark: SparkSession, d: str) -> Workload:
    docs = labelled(spark, d)
    return Workload("W3", "filter", docs, "doc_id", "text", _lookup(docs, "doc_id", "quality", 1), _mean(docs.where("quality = 1"), "n_chars"), "n_chars")


def w4(spark: SparkSession, d: str) -> Workload:
    docs = balanced(labelled(spark, d), "quality").withColumn("is_en", (F.col("lang") == "en").cast("int"))
    return Workload("W4", "filter", docs, "doc_id", "text", _lookup(docs, "doc_id", "quality", 1), _mean(docs.where("quality = 1"), "is_en"), "is_en")


def w5(spark: SparkSession, d: str, value: str = "like_count") -> Workload:
    docs = with_counts(table(spark, d, "documents"))
    return Workload("W5", "filter", docs, "doc_id", "text", _lookup(docs, "doc_id", "lang", "fr"), _mean(docs.where("lang = 'fr'"), value), value)


def w6(spark: SparkSession, d: str) -> Workload:
    turns = table(spark, d, "conversations").withColumn("turn_id", F.col("conv_id") * 1000 + F.col("turn")).withColumn("n_chars", F.length("text"))
    return Workload("W6", "filter", turns, "turn_id", "text", PredicateLabeler(RuleLabeler(rules.language()), "es"), _mean(turns.where(rules.language() == "es"), "n_chars"), "n_chars")


def w7(spark: SparkSession, d: str) -> Workload:
    docs = labelled(spark, d)
    return Workload("W7", "group", docs, "doc_id", "text", _lookup(docs, "doc_id", "class3"), _share(docs, "class3"), categories=tuple(CLASS3))


def w7b(spark: SparkSession, d: str) -> Workload:
    e = table(spark, d, "embeddings").withColumn("label_text", F.col("label").cast("string")).drop("label")
    return Workload("W7b", "group", e, "vec_id", "label_text", _lookup(e, "vec_id", "label_text"), _share(e, "label_text"), categories=tuple(map(str, range(10))), vectors="embedding")


def w8(spark: SparkSession, d: str) -> Workload:
    docs = table(spark, d, "documents")
    return Workload("W8", "group", docs, "doc_id", "text", _lookup(docs, "doc_id", "lang"), _share(docs, "lang"), categories=tuple(LANGS))


def w8b(spark: SparkSession, d: str) -> Workload:
    parts = table(spark, d, "part")
    truth = _mean(parts.withColumn("noun", rules.noun()), "p_retailprice", "noun")
    nouns = tuple(sorted(r.grp for r in truth.collect()))
    return Workload("W8b", "group", parts, "p_partkey", "p_name", RuleLabeler(rules.noun()), truth, "p_retailprice", categories=nouns)


WORKLOADS: dict[str, Callable[[SparkSession, str], Workload]] = {f.__name__: f for f in (w1, w2, w3, w4, w5, w6, w7, w7b, w8, w8b)}


def with_strata(w: Workload, h: int, seed: int = 42) -> Workload:
    """The workload with vectors and K-means strata, written once: a semantic index that later runs use again."""
    embedder = GivenVectors() if w.vectors == "embedding" else HashedNgramEmbedder()
    df = embedder.embed(w.df, w.text)
    return replace(w, df=saved(kmeans_strata(df, h, seed=seed)[0], f"index-{w.name}"))


def run(w: Workload, method: str = "ours", stop: Stop | None = None, clock: Clock | None = None, config: GroupConfig | None = None, batch_share: float = 0.01, seed: int = 42) -> ProgressLog:
    """One run of a workload: 'ours', 'random', or for groups 'static'."""
    batch = max(1, round(w.df.count() * batch_share))
    if w.kind == "select":
        return progressive_select(w.df, w.key, w.text, w.labeler, list(w.group_by), batch=batch, stop=stop, clock=clock, seed=seed)
    if w.kind == "filter":
        if method == "random":
            return baselines.random_filter(w.df, w.key, w.text, w.labeler, w.value, pilot=batch, batch=batch, stop=stop, clock=clock, seed=seed)
        return progressive_filter(w.df, w.key, w.text, w.labeler, w.value, batch=batch, stop=stop, clock=clock, seed=seed)
    if method == "random":
        return baselines.random_group(w.df, w.key, w.text, w.labeler, list(w.categories), stop=stop, clock=clock, seed=seed)
    config = replace(config or GroupConfig(), adjust=method == "ours" and (config or GroupConfig()).adjust)
    return progressive_group(w.df, w.key, w.text, w.labeler, list(w.categories), w.value, "avg" if w.value else "proportion", config=config, stop=stop, clock=clock, seed=seed)


def _union(rows: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def compare(w: Workload, methods: tuple[str, ...], bound: float = 0.05, column: str = "half_width", **how) -> DataFrame:
    """method, mean share of draws to the bound (null if not all groups reach it), final absolute error by group's mean."""
    out, relative = [], w.kind != "group" or w.value is not None
    for m in methods:
        log = run(w, m, **how)
        share = metrics.share_to_bound(log.frame(), float(log.total), bound=bound, by=column if m != "random" else "half_width", relative=relative)
        error = metrics.absolute_error(log.result(), w.truth).agg(F.avg("error").alias("final_error"))
        out.append(share.crossJoin(error).select(F.lit(w.name).alias("workload"), F.lit(m).alias("method"), "share", "speedup", "final_error", F.lit(log.total).cast("bigint").alias("n_rows")))
    return _union(out)


def compare_grouping(w: Workload, methods: tuple[str, ...] = ("ours", "static", "random"), bound: float = 0.05, config: GroupConfig | None = None, seed: int = 42) -> DataFrame:
    """Mean share of draws to the bound of adjusted strata, strata as first clustered, and random draws, by like intervals.

    interval 'own' has each category's variance, 'pooled' that of all categories added up; 'fresh' is the own interval of
    the estimate that moved draws cannot bias (random draws have one estimate). A run goes on until the widest of them
    holds, so all come from the same draws.
    """
    config, out = replace(config or GroupConfig(), scope="pooled"), []
    for m in methods:
        stop = Stop(bound=bound, relative=False)
        if m == "random":
            log = baselines.random_group(w.df, w.key, w.text, w.labeler, list(w.categories), round_fraction=config.round_fraction, stop=stop, seed=seed, scope="pooled")
        else:
            log = run(w, m, config=config, stop=stop, seed=seed)
        error = metrics.absolute_error(log.result(), w.truth).agg(F.avg("error").alias("final_error"))
        for interval in ("own", "pooled", *(("fresh",) if m != "random" else ())):
            frame = log.frame("half_width_own" if interval == "own" else "half_width")
            share = metrics.share_to_bound(frame, float(log.total), bound=bound, by="half_width_stratified" if interval == "fresh" else "half_width", relative=False)
            out.append(share.crossJoin(error).select(F.lit(w.name).alias("workload"), F.lit(m).alias("method"), F.lit(interval).alias("interval"), "share", "speedup", "final_error"))
    return _union(out)


def error_against_draws(spark: SparkSession, d: str, strata: int = 5, batch_share: float = 0.05) -> DataFrame:
    """Relative error of two averages (like and view counts) at each step, for priority and for random draws."""
    out = []
    for value in ("like_count", "view_count"):
        w = with_strata(w5(spark, d, value), strata)
        for m in ("ours", "random"):
            log = run(w, m, batch_share=batch_share)
            # the published mean, and beside it the expansion by stratum, which no order of draws can bias
            for estimate in ("estimate", "estimate_stratified"):
                rows = metrics.absolute_error(log.frame(), w.truth, estimate).select("step", "calls_fraction", "n_valid", "error", "relative_error")
                out.append(rows.select(F.lit(value).alias("measure"), F.lit(m).alias("method"), F.lit(estimate).alias("form"), "*"))
    return _union(out)


def share_to_error(errors: DataFrame, bound: float = 0.01) -> DataFrame:
    """Share of draws after which the relative error stays within the bound, by measure, method and form."""
    over = Window.partitionBy("measure", "method", "form").orderBy(F.desc("step"))
    good = errors.withColumn("_good", F.min((F.col("relative_error") <= bound).cast("int")).over(over))
    return good.groupBy("measure", "method", "form").agg(F.min(F.when(F.col("_good") == 1, F.col("calls_fraction"))).alias("share"))


def interval_panels(spark: SparkSession, d: str, batch_share: float = 0.05) -> DataFrame:
    """Intervals against draws of four queries: two extractions, a filter and a grouping."""
    out = []
    for w, how in ((w1(spark, d), {}), (w2(spark, d), {}), (with_strata(w3(spark, d), 5), {}), (with_strata(w7(spark, d), 8), {"config": GroupConfig(h_max=16, gamma=0.97, scope="per_category")})):
        log = run(w, batch_share=batch_share, **how)
        shown = log.frame().select("step", "grp", "calls_fraction", "n_valid", "estimate", "half_width")
        out.append(shown.select(F.lit(w.name).alias("workload"), "*"))
    return _union(out)


def ablation_strata(w: Workload, counts: tuple[int, ...] = (1, 2, 3, 4, 5, 8), **how) -> DataFrame:
    return _union([compare(with_strata(w, h), ("ours",), **how).withColumn("strata", F.lit(h)) for h in counts])


def ablation_grouping(w: Workload, h0: tuple[int, ...] = (3, 6, 12, 24), theta: tuple[float, ...] = (0.15, 0.25, 0.35, 0.45, 0.55), gamma: tuple[float, ...] = (0.7, 0.8, 0.9, 0.95), base_h: int = 6, **how) -> DataFrame:
    """One parameter at a time around the defaults; intervals are each category's own."""
    out, default = [], GroupConfig(gamma=0.95, scope="per_category")
    grid = [("h0", h, h, default) for h in h0] + [("theta", t, base_h, replace(default, theta=t)) for t in theta] + [("gamma", g, base_h, replace(default, gamma=g)) for g in gamma]
    index, done = {h: with_strata(w, h) for h in sorted({h for _, _, h, _ in grid})}, {}
    for name, value, h, config in grid:
        if (h, config) not in done:
            done[h, config] = compare(index[h], ("ours",), config=replace(config, h_max=2 * h), **how).select("share", "final_error")
        out.append(done[h, config].select(F.lit(name).alias("parameter"), F.lit(float(value)).alias("value"), "share", "final_error"))
    return _union(out)


def total_times(workloads: list[Workload | Callable[[], Workload]], seconds_per_row: float = 0.002, bound: float = 0.05, batch_share: float = 0.1, apart: float = 60.0, **how) -> DataFrame:
    """Wall seconds of the full scan, the batch system and ours, all of which run with a labeler that takes seconds_per_row
    for each row; for ours also the share of draws and the estimated part of its time to the bound.

    Each method has as many served instances as there are task slots, and waits for them as long as it would alone. Where
    these waits take `apart` seconds or more and slots are left, a workload's methods wait side by side, and the workloads
    after it are made (those given as functions) and run meanwhile, in slots that are left; shorter ones run one method after
    the other, as their own work counts for more.
    """
    made = (w() if callable(w) else w for w in workloads)
    first = next(made)
    spark = first.df.sparkSession
    slots = spark.sparkContext.defaultParallelism
    few = next(n for n in range(-(-slots // 8), slots + 1) if slots % n == 0)  # tasks that wait, for up to 8 instances each
    room = slots // few
    most = max(3, room - 2)  # methods with long waits at a time: a place for a shorter one and a place for other jobs are left
    done: list[tuple[Workload, list[Future]]] = []
    waiting: list[Future] = []
    long, short = ThreadPoolExecutor(most), ThreadPoolExecutor(1)

    def timed(f: Callable) -> tuple:
        start = time.perf_counter()
        return f(), time.perf_counter() - start

    try:
        for w in chain([first], made):
            together = room > 3 and SimulatedService(w.labeler, seconds_per_row, slots).seconds(w.df.count()) >= apart
            if not together and most + 1 >= room:
                wait(waiting)  # there is no place beside them
            beside = together or not all(x.done() for x in waiting)
            slow = SimulatedService(w.labeler, seconds_per_row, slots, real=True, tasks=few if beside else slots)
            pool = long if together else short
            futures = [pool.submit(inheritable_thread_target(spark)(timed), f) for f in _methods(w, slow, batch_share, how)]
            done.append((w, futures))
            if together:
                waiting += futures
            else:
                for x in futures:
                    x.result()
            for x in waiting:
                if x.done():
                    x.result()  # an error ends all
        times = [(w, [x.result() for x in futures]) for w, futures in done]
    finally:
        for pool in (long, short):
            pool.shutdown(cancel_futures=True)  # after an error no further one starts
    rows = []
    for w, ((_, scanned), (_, batched), (log, seconds)) in times:
        rows += [(w.name, "full_scan", scanned, None, None), (w.name, "batch_semantic", batched, None, None)]
        share = metrics.share_to_bound(log.frame("half_width_own" if w.kind == "group" else "half_width"), float(log.total), bound=bound, relative=w.kind != "group").first().share
        rows.append((w.name, "ours", seconds, share, None if share is None else share * seconds))
    return spark.createDataFrame(rows, "workload string, method string, total_seconds double, share_to_bound double, seconds_to_bound double")


def _methods(w: Workload, labeler: Labeler, batch_share: float, how: dict) -> tuple[Callable, Callable, Callable]:
    """The full scan, the batch system and ours, each a run of the whole workload."""
    answer = {"select": F.avg(F.col("label").cast("double")), "filter": F.avg(F.col(w.value or w.key).cast("double")), "group": F.count("*")}[w.kind].alias("answer")
    by = {"select": list(w.group_by), "filter": [], "group": ["label"]}[w.kind]
    where = "is_valid AND label" if w.kind == "filter" else "is_valid"

    def scan():
        return baselines.full_scan(w.df, labeler, w.text, answer, by=by, where=where, key=w.key).collect()

    def batch():
        if w.kind == "select":
            return baselines.sem_map(w.df, labeler, w.text, "label").where("is_valid").groupBy(*w.group_by).agg(answer).collect()
        return (baselines.sem_filter(w.df, labeler, w.text).agg(F.avg(w.value)) if w.kind == "filter" else baselines.sem_group(w.df, labeler, w.text)).collect()

    def ours():
        return run(replace(w, labeler=labeler), batch_share=batch_share, **how)

    return scan, batch, ours


def scaleout_model(w: Workload, instances: tuple[int, ...] = (1, 2, 3, 4), serial_share: float = 0.3, bound: float = 0.05, **how) -> DataFrame:
    """A model, not a measure: virtual time to the same bound with more serving instances, a given part of a call being serial."""
    log, rows = run(w, **how), []
    relative = w.kind != "group"
    reached = metrics.time_to_bound(log.frame(), bound, relative=relative).agg(F.max("cost").alias("c")).first().c or log.total
    steps = sorted({(r["step"], r["calls"]) for r in log.rows if r["calls"] <= reached})
    for i in instances:
        clock, before, total = Clock(1.0, i, serial_share=serial_share), 0, 0.0
        for _, calls in steps:
            total, before = total + clock.step(calls - before), calls
        rows.append((i, total))
    return w.df.sparkSession.createDataFrame([(i, s, rows[0][1] / s) for i, s in rows], "instances int, virtual_seconds double, speedup double")


def slow_client(answer: Callable[[str], object], seconds: float) -> Callable[[str], Callable[[list[str]], list]]:
    """A stand-in for a served model: an endpoint answers one request at a time, `seconds` for each text of it."""

    def client(endpoint: str) -> Callable[[list[str]], list]:
        def ask(texts: list[str]) -> list:
            time.sleep(seconds * len(texts))
            return [answer(x) for x in texts]

        return ask

    return client


@dataclass(frozen=True)
class Served:
    """A workload, or a function that makes it, whose labels come from served instances: `answer` to a text takes one of them
    `seconds`; a run ends at the bound or after `steps` steps."""

    w: Workload | Callable[[], Workload]
    answer: Callable[[str], object]
    label_type: str
    seconds: float = 0.02
    bound: float = 0.05
    steps: int | None = None
    how: dict = field(default_factory=dict)


def scaleout(w: Workload, answer: Callable[[str], object], label_type: str, instances: tuple[int, ...] = (1, 2, 3, 4), seconds: float = 0.02, bound: float = 0.05, steps: int | None = None, **how) -> DataFrame:
    """scaleouts of one workload."""
    return scaleouts([Served(w, answer, label_type, seconds, bound, steps, how)], instances)


def scaleouts(served: list[Served], instances: tuple[int, ...] = (1, 2, 3, 4)) -> DataFrame:
    """Wall seconds of the same draws to the same bound (or of `steps` steps) through 1 to 4 served instances.

    Laying out the table is timed apart: an index that later queries use again. Each instance has one request at a time and
    a task asks up to 8 of them, so the speed-up holds what Spark's own steps cost. A run keeps no more task slots waiting
    than that and leaves the others idle, so runs go side by side where there are slots for them, those of few instances
    first, which take longest (see SideBySide); each has instances of its own and is timed by itself. Workloads that are
    given as functions are made side by side.
    """
    with ThreadPoolExecutor(len(served)) as pool:
        made = [pool.submit(inheritable_thread_target(SparkSession.active())(x.w)) if callable(x.w) else None for x in served]
        served = [x if w is None else replace(x, w=w.result()) for x, w in zip(served, made, strict=True)]
    spark = served[0].w.df.sparkSession
    order = SideBySide(spark.sparkContext.defaultParallelism - 1, len(served) * len(instances))  # a slot is left for the steps' other jobs

    def timed(x: Served, i: int) -> tuple:
        each = max(n for n in range(1, 9) if i % n == 0)  # instances that a task asks
        service = ServiceLabeler(slow_client(x.answer, x.seconds), tuple(f"instance-{j}" for j in range(i)), x.label_type, batch_size=4, max_inflight=1, endpoints_per_task=each)
        with order.run(i // each, i) as turn:
            labeler = TimedLabeler(service if x.w.kind == "group" else PredicateLabeler(service, "true"), turn)
            start = time.perf_counter()
            log = run(replace(x.w, labeler=labeler), stop=Stop(bound=x.bound, relative=x.w.kind != "group", max_steps=x.steps), **x.how)
            return x.w.name, i, log.rows[-1]["calls"], time.perf_counter() - (labeler.first or start)

    with ThreadPoolExecutor(len(served) * len(instances)) as pool:
        futures = {(n, i): pool.submit(inheritable_thread_target(spark)(timed), x, i) for n, x in enumerate(served) for i in instances}
        rows = [futures[n, i].result() for n in range(len(served)) for i in instances]
    first = {n: rows[n * len(instances)][3] for n in range(len(served))}
    return spark.createDataFrame([(*r, first[k // len(instances)] / r[3]) for k, r in enumerate(rows)], "workload string, instances int, calls bigint, seconds double, speedup double")


class SideBySide:
    """Lets timed runs go at once: none before all are set up, and each as soon as as many slots are free as it keeps busy
    (or all of them, if it wants more than there are) and no run of a lower rank waits. After an error no further one starts."""

    def __init__(self, slots: int, runs: int):
        self.slots = self.free = max(1, slots)
        self.setting_up, self.failed, self.changed = runs, None, threading.Condition()
        self.waiting: list[int] = []

    @contextmanager
    def run(self, busy: int, rank: int = 0) -> Iterator[Callable[[], None]]:
        """For one run: a function to call when it is set up, which returns when it may go on."""
        busy, started = min(busy, self.slots), False

        def turn() -> None:
            nonlocal started
            with self.changed:
                self.setting_up -= 1
                self.waiting.append(rank)
                self.changed.notify_all()
                self.changed.wait_for(lambda: self.failed or (not self.setting_up and self.free >= busy and rank == min(self.waiting)))
                started = True
                self.free -= busy
                self.waiting.remove(rank)
                self.changed.notify_all()
                if self.failed:
                    raise RuntimeError("another run has failed") from self.failed

        try:
            yield turn
        except BaseException as e:
            self.failed = self.failed or e
            raise
        finally:
            with self.changed:
                self.free += busy * started
                self.setting_up -= not started
                self.changed.notify_all()


class TimedLabeler(Labeler):
    """Another labeler that knows when it was first asked, after `turn` has let it."""

    def __init__(self, base: Labeler, turn: Callable[[], None] = lambda: None):
        self.base, self.turn, self.first = base, turn, None

    def label(self, df: DataFrame, text: str = "text") -> DataFrame:
        if self.first is None:
            self.turn()
            self.first = time.perf_counter()
        return self.base.label(df, text)


def bounds(w: Workload) -> tuple[int, int]:
    return strata_bounds(w.df.count(), max(2, len(w.categories)))
