"""Near-duplicate documents from bottom-k sketches under one hash function.

A document is the set of its word shingles, each a 64-bit hash. Its sketch is the K smallest hashes, K being the same for
all; a set of up to K values is its own sketch. Sets that are equal form a class, and classes are what is compared.

Of two sets, the K smallest hashes of their union are a random sample of it, so the shared ones among them estimate the
similarity, and both sketches hold them. At the threshold at least `least_shared` of them are shared (but for a
probability below RISK for a linked pair; sets of up to K values leave nothing to chance). So two linked sketches overlap
in that many values, and among their K - least_shared + 1 rarest values, in an order by commonness in the corpus that is
the same for all, they share one. Inverted lists of these retained values give the candidates. A candidate is dropped if
the sizes, the places of the value or the parity maps of the sets (which differ in no more bits than the sets do in
values) leave no room for a link, then if its union sketch shares too few values. Where both sketches are whole sets that is the exact
answer; for the others exact Jaccard on the full sets, from the texts, decides.

Each list is first compared with its smallest member, and members that this did not join with it then with another member,
a different one in each list. Those that are still apart are compared with all others of their list and neighbouring
sizes, a long list in blocks.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import lru_cache
from math import exp, lgamma

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import _arrow_schema, saved

#: Size of a sketch, and the probability that a linked pair shares fewer of its union's K smallest values than assumed.
K, RISK = 128, 1e-13
#: Cells that count how common values are; the broadcast order has a byte for each, whatever the data.
CELLS, CHUNKS = 1 << 24, 64
#: Words of 64 bits in a parity map.
PARITY = 8
BITMAP_BUCKETS = 512
#: Members of a list that one key of the second comparison holds, about.
BLOCK = 1000


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct shingle hashes: A-Z in lower case, words between ASCII white space; fewer words than a shingle
    has are one shingle, none are no shingle."""
    found = (text or "").encode().lower().split()
    if not found:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, found), np.uint64, len(found))
    width = min(words, len(h))
    out = np.full(len(h) - width + 1, width, np.uint64)
    for k in range(width):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - width + 1 + k])
    return np.unique(out)


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both) and both > 0


@lru_cache(maxsize=1 << 16)
def least_shared(n: int, percent: int, k: int = K) -> int:
    """How many values the sketches of a set of n values and of any set linked with it share at the least.

    Their union has at most n * 100 / percent values. Where it has no more than k, its sketch is all of it. Else the
    shared ones among its k smallest are a draw without replacement, and this is the quantile of RISK.
    """
    exact, union = -(-percent * n // 100), min(n * 100 // percent, 1 << 20)
    if union <= k:
        return exact
    shared = -(-percent * union // 100)
    log = lambda a, b: lgamma(a + 1) - lgamma(b + 1) - lgamma(a - b + 1)
    below, x = 0.0, max(0, k - (union - shared))
    while True:
        below += exp(log(shared, x) + log(union - shared, k - x) - log(union, k)) if x <= shared and k - x <= union - shared else 0.0
        if below > RISK:
            return max(1, min(exact, x))
        x += 1


def _sketched(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, n, print (128 bits of the set), sketch, parity map of each row, and rows without them that hold a task's
    counts of retained values by cell. Whole texts are read here, once."""
    schema = "doc_id bigint, n bigint, print binary, sketch binary, " + ", ".join(f"o{k} bigint" for k in range(PARITY)) + ", chunk int, cells binary"
    arrow = _arrow_schema(docs.sparkSession, schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, seen = np.zeros(CELLS, np.uint32), False
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part, n, prints, kept, maps = batch.slice(at, 512), [], [], [], []
                for text in part.column(1).to_pylist():
                    values = shingle_set(text, words)
                    n.append(len(values))
                    prints.append(xxhash.xxh3_128_digest(values.tobytes()))
                    kept.append(values[:K])
                    bits = np.bincount((values >> np.uint64(40)).astype(np.int64) % (64 * PARITY), minlength=64 * PARITY) & 1
                    maps.append(np.packbits(bits.astype(np.uint8)).view(np.int64))
                at_cell, times = np.unique((np.concatenate(kept) % np.uint64(CELLS)).astype(np.int64), return_counts=True)
                cells[at_cell] += times.astype(np.uint32)
                seen = seen or len(at_cell) > 0
                odd, none = np.stack(maps), pa.nulls(len(n))
                columns = [part.column(0), pa.array(n, pa.int64()), pa.array(prints, pa.binary()), pa.array([x.tobytes() for x in kept], pa.binary()), *[pa.array(odd[:, k]) for k in range(PARITY)], none.cast(pa.int32()), none.cast(pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, schema=arrow)
        if seen:
            size, pack = CELLS // CHUNKS, zstandard.ZstdCompressor(level=1)
            yield pa.RecordBatch.from_pylist([{"chunk": k, "cells": pack.compress(cells[k * size : (k + 1) * size].tobytes())} for k in range(CHUNKS)], schema=arrow)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(run, schema)


def _common(survey: DataFrame) -> np.ndarray:
    """How common values are, by cell, on a scale of logarithms: counts over all documents, added up chunk by chunk."""
    schema = "chunk int, cells binary"
    arrow = _arrow_schema(survey.sparkSession, schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            for k, cells in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                total[k] = total.get(k, 0) + np.frombuffer(unpack.decompress(cells), np.uint32).astype(np.int64)
        scaled = [np.minimum(np.log2(1.0 + x) * 6, 255).astype(np.uint8).tobytes() for x in total.values()]  # to 2^42
        yield pa.RecordBatch.from_pydict({"chunk": list(total), "cells": scaled}, schema=arrow)

    parts = survey.where("chunk IS NOT NULL").select("chunk", "cells")
    out, size = np.zeros(CELLS, np.uint8), CELLS // CHUNKS
    for r in parts.repartition(CHUNKS, "chunk").mapInArrow(run, schema).collect():  # CELLS bytes in all
        out[r.chunk * size : (r.chunk + 1) * size] = np.frombuffer(r.cells, np.uint8)
    return out


def _posted(classes: DataFrame, percent: int, common: np.ndarray) -> DataFrame:
    """v, cls, h for the rarest values of each sketch: as many as make sure that two linked sets share one. h holds the
    size, how many values of the sketch come from this one on, and how many a link must share."""
    held = classes.sparkSession.sparkContext.broadcast(common)  # CELLS numbers, whatever the data
    arrow = _arrow_schema(classes.sparkSession, "v bigint, cls bigint, h bigint")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = held.value
        for batch in batches:
            v, times, h = [], [], []
            for n, data in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                values = np.frombuffer(data, np.uint64)
                shared = least_shared(n, percent)
                first = np.lexsort((values, order[(values % np.uint64(CELLS)).astype(np.int64)]))[: len(values) - shared + 1]
                v.append(values[first])
                times.append(len(first))
                h.append((n << 20 | shared) + ((len(values) - np.arange(len(first), dtype=np.int64)) << 10))
            if v:
                columns = [pa.array(np.concatenate(v).view(np.int64)), pa.array(np.repeat(batch.column(0).to_numpy(), times)), pa.array(np.concatenate(h))]
                yield pa.RecordBatch.from_arrays(columns, schema=arrow)

    return classes.select("cls", "n", "sketch").mapInArrow(run, "v bigint, cls bigint, h bigint")


def _col(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _needed(percent: int, n: str | Column, m: str | Column) -> Column:
    """Values that two sets of n and m must share to be linked."""
    return F.ceil(F.lit(percent) * (_col(n) + _col(m)) / (100 + percent))


def _parity(percent: int, n: str | Column, m: str | Column, a: str, b: str, names: list[str]) -> Column:
    """The maps (or the same words of both) differ in no more bits than linked sets of these sizes may differ in values."""
    bits = sum((F.bit_count(F.col(f"{a}{k}").bitwiseXOR(F.col(f"{b}{k}"))) for k in names), F.lit(0))
    return bits <= _col(n) + _col(m) - 2 * _needed(percent, n, m)


def _size(h: str) -> Column:
    return F.shiftright(h, 20)


def _left(h: str) -> Column:
    return F.shiftright(h, 10).bitwiseAND(1023)


def _possible(percent: int, a: str, b: str) -> Column:
    """Sizes may be linked, and enough values are left in both sketches from the shared one on (it may be the first that
    they share)."""
    n, m = _size(a), _size(b)
    least = lambda h: F.col(h).bitwiseAND(1023)
    return (F.least(n, m) * 100 >= F.greatest(n, m) * percent) & (F.least(_left(a), _left(b)) >= F.greatest(least(a), least(b)))


def _star(posted: DataFrame) -> DataFrame:
    """v, cls, h, head, hh, c for each member but the smallest of each inverted list of c members."""
    lists = posted.groupBy("v").agg(F.min(F.struct("cls", "h")).alias("low"), F.count("*").alias("c")).where("c > 1")
    lists = lists.select(F.col("v").alias("_v"), F.col("low.cls").alias("head"), F.col("low.h").alias("hh"), "c")
    return posted.join(lists, F.col("v") == F.col("_v")).where("cls <> head").drop("_v")


def _estimated(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Of pairs (a, b) those that the parity maps and the union sketch leave, with `sure`: both sketches are whole sets, so
    the union sketch is the answer. No text is read."""
    side = lambda x, *c: classes.select(F.col("cls").alias(x), *[F.col(k).alias(f"{x}_{k}") for k in c])
    odd = [f"o{k}" for k in range(PARITY)]
    near = pairs.join(side("a", "n", *odd), "a").join(side("b", "n", *odd), "b").where(_parity(percent, "a_n", "b_n", "a_", "b_", odd)).select("a", "b", "a_n", "b_n")
    both = saved(near, "near").join(side("a", "sketch"), "a").join(side("b", "sketch"), "b").select("a", "b", "a_n", "b_n", "a_sketch", "b_sketch")
    arrow = _arrow_schema(pairs.sparkSession, "a bigint, b bigint, sure boolean")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, sure = [], [], []
            for x, y, n, m, p, q in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                if n <= K and m <= K:
                    good, whole = similar(p, q, percent), True
                else:
                    union, whole = np.union1d(p, q)[:K], False
                    shared = np.intersect1d(p, q, assume_unique=True)
                    good = np.searchsorted(shared, union[-1], "right") >= max(least_shared(n, percent), least_shared(m, percent))
                if good:
                    a.append(x), b.append(y), sure.append(whole)
            yield pa.RecordBatch.from_pydict({"a": a, "b": b, "sure": sure}, schema=arrow)

    return both.mapInArrow(run, "a bigint, b bigint, sure boolean")


def _confirmed(pairs: DataFrame, classes: DataFrame, docs: DataFrame, words: int, percent: int) -> DataFrame:
    """Of pairs (a, b), those whose full sets are similar enough. A class's set comes from a text of its document of smallest
    id; only rows of documents in pairs are moved, the others are left out by a bitmap of hashed ids of a fixed size."""
    spark = docs.sparkSession
    ids = pairs.select(F.col("a").alias("cls")).union(pairs.select(F.col("b").alias("cls"))).distinct()
    wanted = saved(classes.select("cls", "rep", "print").join(ids, "cls", "left_semi"), "wanted")
    place = F.pmod(F.xxhash64("rep"), F.lit(BITMAP_BUCKETS * 32768))
    bits = wanted.select(F.floor(place / 32768).cast("int").alias("bucket"), (place % 32768).alias("bit")).groupBy("bucket").agg(F.bitmap_construct_agg("bit").alias("bits"))
    held = bytearray(BITMAP_BUCKETS * 4096)
    for r in bits.collect():  # BITMAP_BUCKETS rows of 4 KB at most
        held[r.bucket * 4096 : (r.bucket + 1) * 4096] = r.bits
    shared = spark.sparkContext.broadcast(bytes(held))
    hashed = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").where("doc_id IS NOT NULL").withColumn("place", F.pmod(F.xxhash64("doc_id"), F.lit(BITMAP_BUCKETS * 32768)))
    schema = "doc_id bigint, print binary, full binary"
    arrow = _arrow_schema(spark, schema)

    def sets(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bitmap = np.frombuffer(shared.value, np.uint8)
        for batch in batches:
            at = batch.column(2).to_numpy()
            left = batch.filter(pa.array((bitmap[at >> 3] >> (at & 7) & 1).astype(bool)))
            for k in range(0, left.num_rows, 256):
                part = left.slice(k, 256)
                values = [shingle_set(x, words).tobytes() for x in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([xxhash.xxh3_128_digest(x) for x in values], pa.binary()), pa.array(values, pa.binary())], schema=arrow)

    found = hashed.mapInArrow(sets, schema).join(wanted, "print")
    found = saved(found.where("doc_id = rep").select("cls", "full").dropDuplicates(["cls"]), "full-sets")
    joined = pairs.select("a", "b").join(found.select(F.col("cls").alias("a"), F.col("full").alias("full_a")), "a")
    joined = joined.join(found.select(F.col("cls").alias("b"), F.col("full").alias("full_b")), "b").select("a", "b", "full_a", "full_b")
    out = _arrow_schema(spark, "a bigint, b bigint")

    def exact(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [similar(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64), percent) for x, y in zip(batch.column(2), batch.column(3), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(i).filter(pa.array(good, pa.bool_())) for i in (0, 1)], schema=out)

    return joined.mapInArrow(exact, "a bigint, b bigint")


def components(links: DataFrame) -> DataFrame:
    """node, root (smallest node that can be reached) of undirected links (a, b): smallest labels spread along links and
    labels are replaced by their own labels, until nothing changes. Every round is a written table."""
    edges = saved(links.select("a", "b").union(links.select("b", "a")).distinct(), "edges")
    labels = saved(edges.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("root")), "labels")
    while True:
        near = edges.join(labels, edges.b == labels.node).groupBy(F.col("a").alias("at")).agg(F.min("root").alias("low"))
        lower = labels.join(near, labels.node == near["at"]).select("node", F.least("root", "low").alias("next"), F.col("root").alias("was"))
        jump = labels.select(F.col("node").alias("mid"), F.col("root").alias("beyond"))
        step = lower.join(jump, F.col("next") == F.col("mid"), "left").select("node", F.least("next", F.coalesce("beyond", "next")).alias("root"), "was")
        step = saved(step, "labels")
        labels = step.select("node", "root")
        if step.where("root <> was").isEmpty():
            return labels


def _rooted(star: DataFrame, roots: DataFrame) -> DataFrame:
    """v, cls, h, c, r, hr of the lists of more than two members; r and hr are the roots of a member and of its list's head."""
    root = lambda name: roots.select(F.col("node").alias(name), F.col("root").alias(f"{name}_root"))
    rooted = star.where("c > 2").join(root("cls"), "cls", "left").join(root("head"), "head", "left")
    return saved(rooted.select("v", "cls", "h", "c", F.coalesce("cls_root", "cls").alias("r"), F.coalesce("head_root", "head").alias("hr")), "rooted")


def _other_heads(rooted: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of members that are not joined with the head of their list with one other member of it, a different one
    in each list: who is linked with many of a group is linked with one of these, and need not be met with all."""
    tie = F.xxhash64("cls", "v")
    heads = rooted.groupBy("v").agg(F.min(F.struct(tie.alias("t"), "cls", "h", "r")).alias("other"))
    pairs = rooted.where("r <> hr").join(heads, "v").where((F.col("r") != F.col("other.r")) & _possible(percent, "h", "other.h"))
    return pairs.select(F.least("cls", "other.cls").alias("a"), F.greatest("cls", "other.cls").alias("b")).distinct()


def _unjoined(rooted: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of list members that are not yet joined with the head of their list with the members of it that are
    elsewhere too. The key is a list, a class of sizes (linked sets are of one class or of neighbouring ones) and, for
    each BLOCK members of a long list, a part of them. Members without such a partner in their list take no part.

    Sets share many lists, but a pair is made once, in the first of their common lists that both take part in: a member
    knows its lists before this one. Of a linked pair that is the first value they share, or one of the two is the head there
    and they have met."""
    odd = [f"o{k}" for k in range(PARITY)]
    grade = F.floor(F.log(_size("h").cast("double")) / F.log(F.lit(100 / percent)) + 1e-9).cast("int")
    graded = rooted.withColumn("grade", grade)
    per = graded.groupBy("v", "grade").agg(F.min("r").alias("low"), F.max("r").alias("high"), F.max((F.col("r") != F.col("hr")).cast("int")).alias("open"))
    # a class of sizes is a logarithm, so a list has few of them, however long it is
    lists = per.groupBy("v").agg(F.max("open").alias("open"), F.collect_list(F.struct("grade", "low", "high")).alias("grades")).where("open = 1").drop("open")
    elsewhere = lambda g: (F.abs(g["grade"] - F.col("grade")) <= 1) & ((g["low"] != F.col("r")) | (g["high"] != F.col("r")))
    members = graded.join(lists, "v").where(F.exists("grades", elsewhere)).drop("grades").join(classes.select("cls", *odd), "cls")
    blocks = F.ceil(F.col("c") / BLOCK).cast("int")
    earlier = Window.partitionBy("cls").orderBy(F.desc(_left("h"))).rowsBetween(Window.unboundedPreceding, -1)  # of at most K lists
    members = members.withColumn("before", F.collect_list("v").over(earlier))
    members = saved(members.withColumn("part", F.pmod(F.xxhash64("cls"), blocks).cast("int")), "members")
    left = members.where("r <> hr").select(F.col("cls").alias("a"), "h", "r", "before", *odd, "v", F.explode(F.sequence(F.col("grade") - 1, F.col("grade") + 1)).alias("grade"), "c")
    left = left.withColumn("part", F.explode(F.sequence(F.lit(0), blocks - 1))).drop("c")
    right = members.select("v", "grade", "part", F.col("cls").alias("b"), F.col("h").alias("g"), F.col("r").alias("s"), (F.col("r") != F.col("hr")).alias("open"), F.col("before").alias("b_before"), *[F.col(c).alias(f"b_{c}") for c in odd])
    near = _parity(percent, _size("h"), _size("g"), "", "b_", odd)
    once = (~F.col("open") | (F.col("a") < F.col("b"))) & ~F.arrays_overlap("before", "b_before")
    pairs = left.join(right, ["v", "grade", "part"]).where((F.col("r") != F.col("s")) & _possible(percent, "h", "g") & near & once)
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _same_document(known: DataFrame, classes: DataFrame) -> DataFrame:
    """Links (a, b) between the classes of a document that has several texts under one id."""
    several = known.where("n > 0 AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("print").alias("low"), F.max("print").alias("high")).where("low <> high").select("doc_id")
    own = known.where("n > 0").join(several, "doc_id", "left_semi").select("doc_id", "print").distinct().join(classes.select("print", "cls"), "print")
    first = own.groupBy("doc_id").agg(F.min("cls").alias("a"))
    return own.join(first, "doc_id").where("cls <> a").select("a", F.col("cls").alias("b"))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row.

    Documents are linked where 100 x intersection >= percent x union. Null and empty texts have no shingles and are
    linked with nothing. Equal texts, and texts of equal shingles, are one class, however many rows hold them. Rows of one
    id are one document: it is linked by each of its texts, and each row has the n_shingles of its own text. Rows with a
    null id have a null component and are kept; they link nothing. Other columns are left out, whatever their names. An
    empty table gives an empty one. A text of any length is one row's work, and its sketch has K values.
    """
    docs = docs.select("doc_id", "text")
    survey = saved(_sketched(docs, words), "sketches")
    common = _common(survey)
    known = survey.where("chunk IS NULL").select("doc_id", "n", "print")
    odd = [f"o{k}" for k in range(PARITY)]
    own = survey.where("chunk IS NULL AND n > 0 AND doc_id IS NOT NULL").groupBy("print").agg(F.min("doc_id").alias("rep"), *[F.first(c).alias(c) for c in ("n", "sketch", *odd)])
    classes = saved(own.withColumn("cls", F.monotonically_increasing_id()), "classes")  # written, so the numbers stay
    star = saved(_star(_posted(classes, percent, common)), "star")

    def confirm(pairs: DataFrame) -> DataFrame:
        left = saved(_estimated(pairs, classes, percent), "estimated")
        return saved(left.where("sure").select("a", "b").union(_confirmed(left.where("NOT sure"), classes, docs, words, percent)), "links")

    first = saved(star.where(_possible(percent, "h", "hh")).select(F.col("head").alias("a"), F.col("cls").alias("b")).distinct(), "pairs")
    links = confirm(first).union(_same_document(known, classes))
    roots = components(links)
    rooted = _rooted(star, roots)
    others = saved(_other_heads(rooted, percent).join(first, ["a", "b"], "left_anti"), "pairs")
    if not others.isEmpty():
        links = links.union(confirm(others))
        roots = components(links)
        rooted = _rooted(star, roots)
    tried = first.union(others)
    second = saved(_unjoined(rooted, classes, percent).join(tried, ["a", "b"], "left_anti"), "pairs")
    if not second.isEmpty():
        roots = components(links.union(confirm(second)))

    placed = classes.select("print", "cls", "rep").join(roots, F.col("cls") == F.col("node"), "left").withColumn("root", F.coalesce("root", "cls"))
    least = placed.groupBy("root").agg(F.min("rep").alias("component"))
    spread = placed.join(least, "root").select("print", "component")
    out = known.join(spread, "print", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce(F.when(F.col("n") > 0, F.col("component")), F.col("doc_id"))).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """docs with the document of smallest id of each group, all its columns and all its rows (repeated rows too).

    Rows without text or without an id stay; a document that has both empty and other texts goes or stays as a whole.
    """
    gone = near_duplicates(docs, words, percent).where("NOT kept").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, F.col("doc_id") == F.col("_gone"), "left_anti")
