"""Best-fit packing by minimum bin slack.

Of the pieces still unpacked, a bin gets the longest one and the combination of others that leaves the least room,
found by subset sums in a bit set. All that matters of a piece is its length, so the plan is made on the counts by
length: a combination is repeated while its counts last, and the driver holds one count for each length up to the
capacity, whatever the number of documents. Pieces are then numbered within their length, and the number says which
bin and which place in it a piece gets.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import tiktoken
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .byte_bpe import default_pattern, read_ranks
from .common import map_rows, saved, tokenizer_file, whole_text

CAPACITY, END_ID = 1024, 2


def fullest(counts: dict[int, int], room: int) -> list[int]:
    """Lengths (longest first) of a combination that fills `room` best, no length more often than it is there."""
    lengths = [x for x in sorted(counts, reverse=True) if x <= room and counts[x]]
    reach, mask, steps = 1, (1 << room + 1) - 1, []
    for x in lengths:
        left, take = counts[x], 1
        while left > 0 and take * x <= room and not reach >> room & 1:
            take = min(take, left)
            steps.append((x, take, reach))
            reach |= reach << x * take & mask
            left, take = left - take, take * 2
        if reach >> room & 1:
            break
    target, out = reach.bit_length() - 1, []
    for x, take, before in reversed(steps):
        if not before >> target & 1:
            out += [x] * take
            target -= x * take
    return sorted(out, reverse=True)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[list[int], int]]:
    """(lengths of a bin, number of such bins) that hold all pieces; the longest piece left begins each bin."""
    counts, out = {k: v for k, v in histogram.items() if v > 0}, []
    while counts:
        seed = max(counts)
        counts[seed] -= 1
        chosen = [seed, *fullest(counts, capacity - seed)]
        counts[seed] += 1
        need = {x: chosen.count(x) for x in set(chosen)}
        times = min(counts[x] // n for x, n in need.items())
        out.append((chosen, times))
        for x, n in need.items():
            counts[x] -= n * times
            if not counts[x]:
                del counts[x]
    return out


def places(bins: list[tuple[list[int], int]]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, last rank + 1, pieces a bin, first bin, offset in the bin) for each length of each combination."""
    out, used, bin_id = [], {}, 0
    for chosen, times in bins:
        offset = 0
        for x in sorted(set(chosen), reverse=True):
            n, at = chosen.count(x), used.get(x, 0)
            out.append((x, at, at + n * times, n, bin_id, offset))
            used[x], offset = at + n * times, offset + n * x
        bin_id += times
    return out


def assign(pieces: DataFrame, length: str = "length", order: tuple[str, ...] = ("doc_id", "piece"), capacity: int = CAPACITY) -> DataFrame:
    """pieces, all their columns, with sequence_id and offset. Lengths are 1 to capacity; pieces is read three times, so it
    should be a table.

    Numbers within a length come from counts by (length, bucket) and a sort inside each bucket, so a length that many
    pieces share spreads over as many tasks. Equal rows are numbered apart; which gets which number is of no account.
    Columns of pieces named sequence_id or offset are kept as own_sequence_id and own_offset. Null ids are ordered by the
    rest of `order`. An empty table gives an empty one.
    """
    spark, names = pieces.sparkSession, pieces.columns
    taken = {c.lower() for c in names}
    kept = [f"own_{c}" if c.lower() in ("sequence_id", "offset") and f"own_{c}".lower() not in taken else c for c in names]
    plain = [f"c{i}" for i in range(len(names))]  # whatever the columns are called
    at = dict(zip(names, plain, strict=True))
    pieces, length, order = pieces.toDF(*plain), at[length], [at[c] for c in order]
    buckets = max(256, 1 << (pieces.count() // 1_000_000).bit_length())
    bucketed = pieces.withColumn("bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)))
    by_bucket = bucketed.groupBy(F.col(length).alias("own_length"), F.col("bucket").alias("own_bucket")).agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("own_length").orderBy("own_bucket").rowsBetween(Window.unboundedPreceding, -1))
    starts = saved(by_bucket.withColumn("before", F.coalesce(before, F.lit(0))), "starts")
    histogram = {r[0]: r[1] for r in starts.groupBy("own_length").agg(F.sum("n")).collect()}  # at most `capacity` rows
    table = places(plan(histogram, capacity))
    known = spark.createDataFrame(table or [(0,) * 6], "len int, lo bigint, hi bigint, each bigint, bin bigint, at bigint")
    by_length = known.groupBy("len").agg(F.array_sort(F.collect_list(F.struct("lo", "hi", "each", "bin", "at"))).alias("ranges"))
    rank = F.row_number().over(Window.partitionBy(length, "bucket").orderBy(*order)) - 1
    ranked = bucketed.withColumn("rank", rank.cast("bigint"))
    # grows with the pieces, and is partitioned as the ranks are: a merge join moves neither
    ranked = ranked.join(starts.drop("n").hint("merge"), (F.col(length) == F.col("own_length")) & (F.col("bucket") == F.col("own_bucket")))
    ranked = ranked.withColumn("rank", F.col("rank") + F.col("before"))
    # bounded: one row for each length, with the few combinations that use it
    placed = ranked.join(F.broadcast(by_length), F.col(length) == F.col("len"))
    found = F.filter("ranges", lambda r: (r["lo"] <= F.col("rank")) & (F.col("rank") < r["hi"]))[0]
    placed = placed.withColumn("found", found).withColumn("within", F.col("rank") - F.col("found.lo"))
    return placed.select(
        *[F.col(c).alias(name) for c, name in zip(plain, kept, strict=True)],
        (F.col("found.bin") + F.floor(F.col("within") / F.col("found.each"))).cast("bigint").alias("sequence_id"),
        (F.col("found.at") + F.col("within") % F.col("found.each") * F.col(length)).cast("bigint").alias("offset"),
    )


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> tiktoken.Encoding:
    ranks, special = read_ranks(path)
    return tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)


def _pieces(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: full ones, and before them the rest."""
    first = n % capacity
    return ([(0, first)] if first else []) + [(at, capacity) for at in range(first, n, capacity)]


def cut(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """One row for each piece of every whole text (null: empty): doc_id, piece, start, length, ids_crc32 and, if asked for, ids.

    An empty text is one piece of the end id. Repeated rows and null ids are cut as all others, other columns left out. A
    text of any length is one row's work, with as many pieces as it needs.
    """
    path, pattern = path or tokenizer_file("byte_bpe_50k.json"), default_pattern()
    schema = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids array<int>" * with_ids

    def make():
        codec = load(path, pattern)
        encode = lambda x: np.append(np.array(codec.encode(x, allowed_special="all"), np.uint32), np.uint32(END_ID))

        def each(c):
            rows = []
            for doc_id, text in zip(c["doc_id"], c["text"], strict=True):
                ids = encode(text)
                for k, (start, n) in enumerate(_pieces(len(ids), capacity)):
                    part = ids[start : start + n]
                    rows.append((doc_id, k, start, n, zlib.crc32(part.tobytes()), *([part.tolist()] if with_ids else [])))
            return dict(zip([x.split()[0] for x in schema.split(", ")], zip(*rows, strict=True), strict=True)) if rows else {x.split()[0]: [] for x in schema.split(", ")}

        return each

    return map_rows(whole_text(docs), make, schema)


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Pieces of all documents with their sequence and their place in it. Null texts are empty, null ids and repeated rows are
    packed as all others; other columns are left out. An empty table gives an empty one."""
    return assign(saved(cut(docs, path, capacity), "pieces"), order=("doc_id", "piece", "start", "ids_crc32"), capacity=capacity)


def sequences(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """sequence_id and the ids of the packed sequence; ids stay with their pieces, at most `capacity` to a sequence."""
    packed = assign(saved(cut(docs, path, capacity, with_ids=True), "pieces"), capacity=capacity)
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(F.flatten(F.transform(parts, lambda p: p["ids"])).alias("ids"))
