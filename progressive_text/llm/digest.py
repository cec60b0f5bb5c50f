"""Quartile bucket digests: hashed byte triplets are counted in buckets, each bucket becomes its quartile (two bits).

A digest is hex text: one byte of checksum, one of length on a logarithmic scale, one of quartile ratios, then the
buckets. The difference score of two digests adds the steps between their bucket quartiles (three steps count double)
and their headers, and is bounded; likeness is 1 less the score's share of what unrelated digests reach.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_rows, saved

BUCKETS = 256
#: Places of the triplets in a window; wide gaps keep the habits of a language out of the counts.
TRIPLETS = ((0, 1, 2), (0, 3, 7), (0, 5, 11), (0, 8, 17))
#: The difference score at which likeness is 0: unrelated quartile codes differ by 1.25 steps and more on average.
FAR = 1.3 * BUCKETS


def bucket_counts(data: bytes) -> np.ndarray:
    b = np.frombuffer(data, np.uint8).astype(np.uint32)
    total = np.zeros(BUCKETS, np.int64)
    for k, (i, j, m) in enumerate(TRIPLETS):
        n = len(b) - m
        if n > 0:
            h = (b[i : i + n] << 16 | b[j : j + n] << 8 | b[m : m + n]) * np.uint32(2654435761) + np.uint32(40503 * k)
            h ^= h >> 15
            h *= np.uint32(2246822519)
            total += np.bincount(h >> 24, minlength=BUCKETS)
    return total


def fingerprint(data: bytes) -> str:
    """The digest of some bytes; those too short for a triplet have no counts, and only checksum and length tell them."""
    counts = bucket_counts(data)
    q1, q2, q3 = np.sort(counts)[[BUCKETS // 4 - 1, BUCKETS // 2 - 1, 3 * BUCKETS // 4 - 1]]
    codes = (counts > q1).astype(np.uint8) + (counts > q2) + (counts > q3)
    packed = codes[0::4] << 6 | codes[1::4] << 4 | codes[2::4] << 2 | codes[3::4]
    length = min(255, round(16 * math.log2(1 + len(data)) / 2))
    ratios = min(15, 16 * int(q1) // max(1, int(q3))) << 4 | min(15, 16 * int(q2) // max(1, int(q3)))
    head = bytes([hashlib.blake2b(data, digest_size=1).digest()[0], length, ratios])
    return (head + packed.astype(np.uint8).tobytes()).hex()


def difference(x: str, y: str) -> int:
    """Bounded difference score; 0 for equal digests."""
    if x == y:
        return 0
    a, b = (np.frombuffer(bytes.fromhex(z), np.uint8) for z in (x, y))
    steps = np.abs(np.stack([(a[3:] >> s & 3).astype(np.int8) - (b[3:] >> s & 3).astype(np.int8) for s in (0, 2, 4, 6)]))
    score = int(steps.sum() + 3 * (steps == 3).sum())
    score += 2 * min(12, abs(int(a[1]) - int(b[1])))
    for s in (0, 4):
        score += min(4, abs(int(a[2] >> s & 15) - int(b[2] >> s & 15)))
    return score + int(a[0] != b[0])


def likeness(x: str, y: str) -> float:
    return max(0.0, 1.0 - difference(x, y) / FAR)


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, fingerprint of every whole text (null: empty)."""
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))

    def make():
        return lambda c: {"doc_id": c["doc_id"], "n_chars": [len(x) for x in c["text"]], "fingerprint": [fingerprint(x.encode()) for x in c["text"]]}

    return map_rows(docs, make, "doc_id bigint, n_chars bigint, fingerprint string")


def _edited(text: str, following: str) -> str:
    q = len(text) // 4
    return text[: len(text) - q] + following[:q]


def _compared(doc_id, text: str, own: str, following: str, next_print: str) -> dict:
    edited = _edited(text, following).encode()
    edited_print = fingerprint(edited)
    return {
        "doc_id": doc_id, "n_chars": len(text), "edited_sha256": hashlib.sha256(edited).hexdigest(), "fingerprint": own,
        "edited_fingerprint": edited_print, "near_edited": likeness(own, edited_print), "near_next": likeness(own, next_print),
    }


RESULT = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def compare_with_next(docs: DataFrame) -> DataFrame:
    """Each text against its edited self and against the next document in ascending doc_id (the last one's next is the first).

    Null texts are empty, null ids come first, rows of one id are ordered by a hash of their text. A range sort by id
    brings neighbours together; only the first and the last row of each partition need another partition's row, and
    these few are paired afterwards.
    """
    spark = docs.sparkSession
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    tie = F.xxhash64("text")
    ordered = docs.repartitionByRange(n, F.col("doc_id").asc_nulls_first(), tie).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), tie)
    schema = f"{RESULT}, part int, place string, text string"
    from .common import _arrow_schema

    arrow = _arrow_schema(spark, schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, held, out, n_out = TaskContext.get().partitionId(), None, [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                rows = batch.slice(at, 512)
                for doc_id, text in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
                    own = fingerprint(text.encode())
                    if held is None:
                        out.append({"part": part, "place": "first", "text": text, "fingerprint": own})
                    else:
                        out.append(_compared(*held, text, own))
                    held = (doc_id, text, own)
                yield pa.RecordBatch.from_pylist(out, schema=arrow)
                out = []
        if held is not None:
            yield pa.RecordBatch.from_pylist([{"doc_id": held[0], "part": part, "place": "last", "text": held[1], "fingerprint": held[2]}], schema=arrow)

    done = saved(ordered.mapInArrow(run, schema), "digest")
    first = done.where("place = 'first'").select("part", F.col("text").alias("next_text"), F.col("fingerprint").alias("next_print"))
    # one row for each partition at most, whatever the number of documents
    over = Window.partitionBy(F.lit(1)).orderBy("part")
    parts = first.select("part", F.lead("part").over(over).alias("following"), F.min("part").over(Window.partitionBy(F.lit(1))).alias("start"))
    parts = parts.select(F.col("part").alias("at"), F.coalesce("following", "start").alias("following"))
    last = done.where("place = 'last'").join(parts, F.col("part") == F.col("at"))
    last = last.drop("part").join(first, F.col("following") == F.col("part")).select("doc_id", "text", "fingerprint", "next_text", "next_print")

    def make():
        def each(c):
            rows = [_compared(*x) for x in zip(c["doc_id"], c["text"], c["fingerprint"], c["next_text"], c["next_print"], strict=True)]
            return {k: [r[k] for r in rows] for k in [x.split()[0] for x in RESULT.split(", ")]}

        return each

    names = [x.split()[0] for x in RESULT.split(", ")]
    return done.where("place IS NULL").select(*names).unionByName(map_rows(last, make, RESULT))
