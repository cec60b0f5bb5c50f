"""Placement by a permutation-filled lookup table.

Each shard walks the slots of a prime-sized table in an order of its own (offset and step from its name). The shards
take turns: one claims its next free slot, then the next shard does, until the table is full. A key's slot is its hash
modulo the table size. So shards own equal shares, and when a shard comes or goes few other keys move. The table is a
constant of the plan whose size is a parameter, not of the data; it is broadcast and looked up by equality of slots.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_path

SHARDS, SLOTS = 16, 4099


def _number(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def fill(names: list[str], slots: int, weights: list[int] | None = None) -> list[int]:
    """The index of the owning shard for each slot. A shard of weight w takes w turns in a row."""
    if not names or not is_prime(slots) or slots < len(names):
        raise ValueError("a table needs shards and a prime number of slots, at least one a shard")
    offset = [_number(f"{x}:offset") % slots for x in names]
    step = [_number(f"{x}:step") % (slots - 1) + 1 for x in names]
    owner, at, left = [-1] * slots, [0] * len(names), slots
    while left:
        for i in range(len(names)):
            for _ in range(weights[i] if weights else 1):
                if not left:
                    break
                while owner[slot := (offset[i] + at[i] * step[i]) % slots] >= 0:
                    at[i] += 1
                owner[slot], left = i, left - 1
    return owner


def shard_names(n: int) -> list[str]:
    return [f"shard-{i:04d}" for i in range(n)]


def _kept_apart(df: DataFrame) -> DataFrame:
    """df with its own columns slot and shard under the names own_slot and own_shard (more "own_" where those are taken)."""
    for name in [c for c in df.columns if c.lower() in ("slot", "shard")]:
        free = f"own_{name}"
        while free.lower() in {c.lower() for c in df.columns}:
            free = f"own_{free}"
        df = df.withColumnRenamed(name, free)
    return df


def place(df: DataFrame, key: str = "doc_id", names: list[str] | None = None, slots: int = SLOTS, weights: list[int] | None = None, salt: str | None = None) -> DataFrame:
    """df with the columns slot and shard (index into names). DataFrame functions only; rows stay where they are.

    Null keys get a slot too (they hash as the text "null"). Rows of one key, repeated rows too, go to one shard; name a
    `salt` column to spread a key that holds many rows. Columns of df named slot or shard are kept as own_slot and
    own_shard. Texts are not read, whatever their length. An empty table gives an empty one.
    """
    owner = fill(names or shard_names(SHARDS), slots, weights)
    spark = df.sparkSession
    text = F.coalesce(F.col(key).cast("string"), F.lit("null"))
    text = F.concat_ws("#", text, F.col(salt).cast("string")) if salt else text
    rows = _kept_apart(df.withColumn("_place", F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint") % slots)).withColumnRenamed("_place", "slot")
    table = spark.range(1).select(F.posexplode(F.split(F.lit(",".join(map(str, owner))), ",")).alias("pos", "owner"))
    table = table.select(F.col("pos").cast("bigint").alias("slot"), F.col("owner").cast("int").alias("shard"))
    # bounded: `slots` rows of 12 bytes
    return rows.join(F.broadcast(table), "slot")


def write_sharded(df: DataFrame, path: str, key: str = "doc_id", names: list[str] | None = None, rows_per_file: int = 100_000, files_per_shard: int = 4, **how) -> None:
    """One folder for each shard, its rows dealt over files_per_shard files, or as many more as rows_per_file asks for.

    A row's file comes from its key and the task that reads it, so a key that a third of the rows hold spreads over its
    shard's files, and a repeated task deals as before.
    """
    shards = len(names or shard_names(SHARDS))
    files = max(files_per_shard, -(-df.count() // (rows_per_file * shards)))
    placed = place(df, key, names, **how)
    deal = F.pmod(F.xxhash64(F.col(key).cast("string"), F.spark_partition_id()), F.lit(files))
    placed.withColumn("_file", deal).repartition(shards * files, "shard", "_file").drop("_file").write.partitionBy("shard").parquet(path)


def store_and_read(df: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """Writes whole rows into their shards and returns, from the files: key, slot, shard and the md5 of the text (null: null)."""
    path = new_path(df.sparkSession, "shards")
    write_sharded(df, path, key, **how)
    back = df.sparkSession.read.schema(place(df.limit(0), key, **how).schema).parquet(path)
    return back.select(key, "slot", "shard", F.md5(text).alias("text_md5"))


def share_table(placed: DataFrame) -> DataFrame:
    """shard, n_docs, share of all rows."""
    total = placed.agg(F.count("*").alias("total"))
    return placed.groupBy("shard").agg(F.count("*").alias("n_docs")).crossJoin(F.broadcast(total)).select("shard", "n_docs", (F.col("n_docs") / F.col("total")).alias("share"))


#: The same placement for DuckDB: turns by recursion over one list, the key's slot by the same hash.
ORACLE_SQL = f"""
WITH RECURSIVE prefs AS (
  SELECT i, ('0x' || substr(md5('shard-' || lpad(i::VARCHAR, 4, '0') || ':offset'), 1, 8))::BIGINT % {SLOTS} AS off,
         ('0x' || substr(md5('shard-' || lpad(i::VARCHAR, 4, '0') || ':step'), 1, 8))::BIGINT % {SLOTS - 1} + 1 AS step
  FROM range({SHARDS}) r(i)
), turns AS (
  SELECT 0::BIGINT AS k, [-1::BIGINT for x in range({SLOTS})] AS owner
  UNION ALL
  SELECT k + 1, list_transform(owner, lambda o, j: CASE WHEN j = free + 1 THEN p.i ELSE o END)
  FROM (
    SELECT t.k, t.owner, p.i, list_filter([(p.off + a * p.step) % {SLOTS} for a in range({SLOTS})], lambda s: t.owner[s + 1] = -1)[1] AS free
    FROM turns t JOIN prefs p ON p.i = t.k % {SHARDS} WHERE t.k < {SLOTS}
  ) p
), final AS (SELECT owner FROM turns WHERE k = {SLOTS})
SELECT doc_id, slot, owner[slot + 1]::INTEGER AS shard, text_md5 FROM (
  SELECT doc_id, md5(text) AS text_md5, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 8))::BIGINT % {SLOTS} AS slot FROM documents
) d, final
"""
