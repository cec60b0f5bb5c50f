"""Sorted-string-table shards: documents by identifier in files that answer lookups by binary search.

A shard is one file: data blocks, a Bloom filter, a block index and a footer. In a block each entry shares a prefix
with the key before it; a key is the identifier as eight big-endian bytes with the sign bit turned, so byte order is
number order. The index has each block's last key, place and counts; the footer has the places and totals.

    block  : zstd( (shared u8, rest u8, value length varint, key rest, value)* ), value: ids as little-endian u16 or u32
    index  : (last key 8, offset u64, length u32, entries u32, ids before the block in this shard u64, crc32 u32)*
    footer : index offset u64, blocks u32, bloom offset u64, bloom bits u64, hashes u32, entries u64, ids u64, width u32, magic 8
"""

from __future__ import annotations

import json
import re
import struct
import unicodedata
import uuid
import zlib
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import groupby

import numpy as np
import pyarrow as pa
import regex
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import letters
from .byte_bpe import byte_alphabet
from .common import Memo, _arrow_schema, local_or_remote, map_rows, new_path, saved, tokenizer_file

MAGIC, BLOCK_BYTES, BLOOM_HASHES, BLOOM_BITS = b"PTSST001", 1 << 16, 7, 10
INDEX, FOOTER = struct.Struct("<8sQIIQI"), struct.Struct("<QIQQIQQI8s")
MANIFEST = "shard int, path string, n_docs bigint, n_ids bigint, n_bytes bigint, first_id bigint, last_id bigint"


def key_of(doc_id: int | None) -> bytes:
    """Eight bytes; none at all for a null identifier, which therefore comes first."""
    return b"" if doc_id is None else struct.pack(">Q", doc_id + (1 << 63))


def id_of(key: bytes) -> int | None:
    return struct.unpack(">Q", key)[0] - (1 << 63) if key else None


def _varint(n: int) -> bytes:
    out = bytearray()
    while n >= 128:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes([*out, n])


def _bloom_places(key: bytes, bits: int) -> list[int]:
    h = xxhash.xxh3_128_intdigest(key)
    a, b = h & (1 << 64) - 1, h >> 64 | 1
    return [(a + i * b) % bits for i in range(BLOOM_HASHES)]


class ShardWriter:
    """Writes entries in ascending key order; holds one block, the index and eight bytes for each key."""

    def __init__(self, out, width: int):
        self.out, self.width, self.pack = out, width, zstandard.ZstdCompressor(level=1)
        self.block, self.index, self.keys, self.at = bytearray(), [], [], 0
        self.last, self.entries, self.block_entries, self.ids, self.before = b"", 0, 0, 0, 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        key, value = key_of(doc_id), ids.astype(f"<u{self.width}").tobytes()
        shared = 0
        if self.block:
            while shared < min(len(key), len(self.last)) and key[shared] == self.last[shared]:
                shared += 1
        self.block += bytes([shared, len(key) - shared]) + _varint(len(value)) + key[shared:] + value
        self.last, self.block_entries = key, self.block_entries + 1
        self.keys.append(key)
        self.ids += len(ids)
        if len(self.block) >= BLOCK_BYTES:
            self._flush()

    def _flush(self) -> None:
        if self.block:
            data = self.pack.compress(bytes(self.block))
            self.out.write(data)
            self.index.append(INDEX.pack(self.last, self.at, len(data), self.block_entries, self.before, zlib.crc32(data)))
            self.at += len(data)
            self.entries += self.block_entries
            self.block, self.block_entries, self.before = bytearray(), 0, self.ids

    def close(self) -> None:
        self._flush()
        bits = max(64, BLOOM_BITS * len(self.keys))
        bloom = np.zeros((bits + 7) // 8, np.uint8)
        for key in self.keys:
            for p in _bloom_places(key, bits):
                bloom[p >> 3] |= 1 << (p & 7)
        self.out.write(bloom.tobytes())
        self.out.write(b"".join(self.index))
        self.out.write(FOOTER.pack(self.at + len(bloom), len(self.index), self.at, bits, BLOOM_HASHES, self.entries, self.ids, self.width, MAGIC))
        self.at += len(bloom) + len(self.index) * INDEX.size + FOOTER.size


class ShardReader:
    """Reads one shard: get() by Bloom filter, binary search in the block index and one block; scan() all in order."""

    def __init__(self, file):
        self.file = file
        size = file.size()
        file.seek(size - FOOTER.size)
        at, n, self.bloom_at, self.bits, _, self.entries, self.n_ids, self.width, magic = FOOTER.unpack(file.read(FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a sorted shard")
        file.seek(at)
        data = file.read(n * INDEX.size)
        self.index = [INDEX.unpack_from(data, i * INDEX.size) for i in range(n)]
        self.bloom: bytes | None = None
        self.unpack = zstandard.ZstdDecompressor()

    def _block(self, i: int) -> Iterator[tuple[bytes, np.ndarray]]:
        _, at, length, entries, _, crc = self.index[i]
        self.file.seek(at)
        data = self.file.read(length)
        if zlib.crc32(data) != crc:
            raise ValueError(f"block {i} is damaged")
        block, p, key = self.unpack.decompress(data), 0, b""
        for _ in range(entries):
            shared, rest = block[p], block[p + 1]
            p, n, shift = p + 2, 0, 0
            while True:
                n |= (block[p] & 127) << shift
                p, shift = p + 1, shift + 7
                if block[p - 1] < 128:
                    break
            key = key[:shared] + block[p : p + rest]
            yield key, np.frombuffer(block, f"<u{self.width}", n // self.width, p + rest)
            p += rest + n

    def scan(self) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """(identifier, ids before it in this shard, ids) in order."""
        for i, (_, _, _, _, before, _) in enumerate(self.index):
            for key, ids in self._block(i):
                yield id_of(key), before, ids
                before += len(ids)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """The entries of an identifier: none, one, or one for each repeated row (for None, each row without one)."""
        key = key_of(doc_id)
        if self.bloom is None:
            self.file.seek(self.bloom_at)
            self.bloom = self.file.read((self.bits + 7) // 8)
        if not all(self.bloom[p >> 3] >> (p & 7) & 1 for p in _bloom_places(key, self.bits)):
            return []
        lo, hi = 0, len(self.index)
        while lo < hi:
            mid = (lo + hi) // 2
            lo, hi = (mid + 1, hi) if self.index[mid][0] < key else (lo, mid)
        found = []
        while lo < len(self.index):
            found += [ids for k, ids in self._block(lo) if k == key]
            if self.index[lo][0] > key:
                break
            lo += 1
        return found


class WordBpe:
    """Ids as the tokenizers library gives them for a word BPE (.json with </w> ends, lower case, white space dropped).

    A word end is written as the byte 0xFF, which no UTF-8 text has; the vocabulary's order then makes it join the
    last byte before all other merges, so a plain byte-pair merger by rank gives the library's ids. No match of the
    pattern holds white space, so runs of other characters are encoded apart and remembered. Texts with characters that
    the library and this Python know by another version of Unicode are left to the library.
    """

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as file:
            held = json.load(file)
        code, special = byte_alphabet(), {x["content"]: x["id"] for x in held["added_tokens"]}
        self.special = {x: np.array([i], np.uint32) for x, i in special.items()}
        self.find_special = re.compile("(" + "|".join(map(re.escape, special)) + ")")
        raw = lambda token: bytes(code[c] for c in token.removesuffix("</w>")) + b"\xff" * token.endswith("</w>")
        ranks = {raw(token): i for token, i in held["model"]["vocab"].items() if token not in special}
        pattern = held["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        self.words = regex.compile(pattern.replace(r"\s", r"\p{White_Space}"))
        self.single = tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self.spaces = regex.compile(r"\p{White_Space}+")
        self.odd = re.compile("[\x1c-\x1f]")
        self.path, self.differs = path, letters.Finder(letters.newer("L") | letters.newer("N") | letters.normalized_apart())
        self.memo = Memo(self._run, 250_000)
        self.vocab = 1 + max([*ranks.values(), *special.values()])

    def _run(self, run: str) -> bytes:
        ids: list[int] = []
        for word in self.words.findall(run):
            ids += self.single(word.encode() + b"\xff")
        return array("I", ids).tobytes()

    def encode(self, text: str) -> np.ndarray:
        if self.differs(text):
            return np.array(_library(self.path).encode(text, add_special_tokens=False).ids, np.uint32)
        if "<|" in text:
            parts = self.find_special.split(text)
            return np.concatenate([self.special[x] if i % 2 else self._plain(x) for i, x in enumerate(parts)])
        return self._plain(text)

    def _plain(self, text: str) -> np.ndarray:
        if not text.isascii():
            # the library lowers each character by itself; Python would make a final sigma of some
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")
        text = text.lower()
        runs = [x for x in self.spaces.split(text) if x] if self.odd.search(text) else text.split()
        memo = self.memo
        return np.frombuffer(b"".join([memo[x] for x in runs]), np.uint32)


@lru_cache(maxsize=4)
def _library(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(maxsize=4)
def load_words(path: str) -> WordBpe:
    return WordBpe(path)


def write_shards(docs: DataFrame, path: str, tokenizer: str | None = None, end_id: int = 2, shards: int | None = None) -> DataFrame:
    """Encodes every whole text (null: empty), adds end_id, writes shards in ascending doc_id order; returns the manifest.

    Rows with a null identifier come first. Rows of one identifier are all kept, ordered by a hash of their text. Other
    columns of docs are left out. A task holds one text and one block. It writes a draft of its own and renames it at the
    end, so a repeated task replaces its file; drafts of failed tasks are removed. An empty table has an empty manifest or
    shards without entries. first_id and last_id are the least and greatest identifier of a shard (null: none).
    """
    spark, tokenizer = docs.sparkSession, tokenizer or tokenizer_file("word_bpe_49k.json")
    shards = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    tie = F.xxhash64("text")
    rows = rows.repartitionByRange(shards, F.col("doc_id").asc_nulls_first(), tie).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), tie)
    arrow = _arrow_schema(spark, MANIFEST)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        words, shard = load_words(tokenizer), TaskContext.get().partitionId()
        system, folder = local_or_remote(path)
        system.create_dir(folder, recursive=True)
        draft, final = f"{folder}/.{shard:06d}-{uuid.uuid4().hex}", f"{folder}/shard-{shard:06d}.sst"
        end, first, last = np.array([end_id], np.uint32), None, None
        with system.open_output_stream(draft) as out:
            writer = ShardWriter(out, 2 if words.vocab <= 1 << 16 and end_id < 1 << 16 else 4)
            for batch in batches:
                for at in range(0, batch.num_rows, 512):
                    part = batch.slice(at, 512)
                    for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                        writer.add(doc_id, np.concatenate([words.encode(text), end]))
                        first, last = doc_id if first is None else first, doc_id
            writer.close()
        _replace(system, draft, final)
        yield pa.RecordBatch.from_pylist([{"shard": shard, "path": f"{path}/shard-{shard:06d}.sst", "n_docs": writer.entries, "n_ids": writer.ids, "n_bytes": writer.at, "first_id": first, "last_id": last}], schema=arrow)

    manifest = saved(rows.mapInArrow(run, MANIFEST), "manifest")
    _drop_drafts(path)
    return manifest


def _replace(system, draft: str, final: str) -> None:
    """draft under its final name, in place of the file of an earlier attempt; some stores do not replace by themselves."""
    try:
        system.move(draft, final)
    except OSError:
        system.delete_file(final)
        system.move(draft, final)


def _drop_drafts(path: str) -> None:
    """Removes what tasks that did not end have left; the job has ended, so no draft is still written."""
    from pyarrow import fs

    system, folder = local_or_remote(path)
    if system.get_file_info(folder).type == fs.FileType.Directory:
        for x in system.get_file_info(fs.FileSelector(folder)):
            if x.base_name.startswith(".") and not x.base_name.endswith(".crc"):
                system.delete_file(x.path)


def read_shards(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 from the files of a manifest, start over all shards.

    The driver adds up one total for each shard; each shard is then read by one task, block by block.
    """
    spark = manifest.sparkSession
    totals, base = sorted((r.shard, r.path, r.n_ids) for r in manifest.select("shard", "path", "n_ids").collect()), 0
    placed = []
    for shard, path, n in totals:
        placed.append((shard, path, base))
        base += n
    files = spark.createDataFrame(placed, "shard int, path string, base bigint").repartition(max(1, len(placed)), "shard")
    schema = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"
    arrow = _arrow_schema(spark, schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                system, name = local_or_remote(x["path"])
                with system.open_input_file(name) as file:
                    out: list[tuple] = []
                    for doc_id, before, ids in ShardReader(file).scan():
                        out.append((doc_id, x["base"] + before, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                        if len(out) == 4096:
                            yield pa.RecordBatch.from_arrays([*map(pa.array, zip(*out, strict=True))], schema=arrow)
                            out = []
                    if out:
                        yield pa.RecordBatch.from_arrays([*map(pa.array, zip(*out, strict=True))], schema=arrow)

    return files.mapInArrow(run, schema)


def _ranges(manifest: DataFrame) -> list[tuple]:
    """(first identifier, last, path) of each shard that has identifiers, in order: one row a shard."""
    rows = manifest.where("last_id IS NOT NULL").select("first_id", "last_id", "path").collect()
    return sorted(tuple(r) for r in rows)


def _get_all(path: str, doc_ids: Iterable[int]) -> Iterator[tuple[int, list[int]]]:
    system, name = local_or_remote(path)
    with system.open_input_file(name) as file:
        reader = ShardReader(file)
        for x in doc_ids:
            for ids in reader.get(x):
                yield x, ids.tolist()


def look_up(manifest: DataFrame, doc_ids: list[int]) -> dict[int, list[list[int]]]:
    """Point lookups: ids by identifier, for as many identifiers as the caller lists. Opens only shards whose range holds one."""
    out: dict[int, list[list[int]]] = {x: [] for x in doc_ids}
    for first, last, path in _ranges(manifest):
        for x, ids in _get_all(path, [x for x in out if first <= x <= last]) if any(first <= x <= last for x in out) else ():
            out[x].append(ids)
    return out


def look_up_all(manifest: DataFrame, wanted: DataFrame, key: str = "doc_id") -> DataFrame:
    """doc_id, ids array<int> of all entries of the identifiers in `wanted`, a table of any size: each identifier goes to the
    shards whose range holds it, and a task reads one shard's. Null and unknown identifiers have no rows; repeated ones
    are looked up once."""
    spark, ranges = manifest.sparkSession, _ranges(manifest)
    first, last = np.array([r[0] for r in ranges], np.int64), np.array([r[1] for r in ranges], np.int64)
    held = spark.sparkContext.broadcast((first, last, [r[2] for r in ranges]))  # a row a shard

    def send():
        lows, highs, _ = held.value

        def each(c):
            rows = [(x, at) for x in c["doc_id"] for at in range(int(np.searchsorted(highs, x)), int(np.searchsorted(lows, x, "right")))]
            return {"doc_id": [r[0] for r in rows], "shard": [r[1] for r in rows]}

        return each

    ids = wanted.select(F.col(key).cast("bigint").alias("doc_id")).where("doc_id IS NOT NULL").distinct()
    sent = map_rows(ids, send, "doc_id bigint, shard int").repartition(max(1, len(ranges)), "shard").sortWithinPartitions("shard", "doc_id")

    def read():
        paths = held.value[2]

        def each(c):
            rows = []
            for shard, part in groupby(zip(c["shard"], c["doc_id"], strict=True), key=lambda x: x[0]):
                rows += _get_all(paths[shard], [x for _, x in part])
            return {"doc_id": [r[0] for r in rows], "ids": [r[1] for r in rows]}

        return each

    return map_rows(sent, read, "doc_id bigint, ids array<int>")


def store_and_read(docs: DataFrame) -> DataFrame:
    return read_shards(write_shards(docs, new_path(docs.sparkSession, "sst")))
