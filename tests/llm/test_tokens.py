"""Encodings, counts, packing and shards against the libraries."""

from __future__ import annotations

import hashlib
import os
import random
import struct
import zlib
from collections import Counter
from math import ceil

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from progressive_text.llm import byte_bpe, letters, packing, sorted_shards, token_counts
from progressive_text.llm.common import new_path

MULTI, BYTE, WORD = P.path("byte_bpe_multi_50k.tiktoken"), P.path("byte_bpe_50k.json"), P.path("word_bpe_49k.json")
LIBRARY, WORDS = Tokenizer.from_file(BYTE), Tokenizer.from_file(WORD)
PARTS = ["a", "the", "'s", "'re", "'RE", "'", " ", "  ", "\n", "\t", "é", "É", "中", "1", "23", ".", "...", "x" * 70, "ing", "\x1c", "　", "🙂", "́", "<|endoftext|>", "<|ENDOFTEXT|>", "<|end", "Σ", "İ", "ﬁ", "\U00018d80", "\U00012550", "\U00016ea0", "\u0898"]
texts = st.lists(st.sampled_from(PARTS), max_size=25).map("".join) | st.text(st.characters(codec="utf-8"), max_size=60)


def direct() -> tiktoken.Encoding:
    return tiktoken.Encoding("direct", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.read_ranks(MULTI)[0], special_tokens={})


CODEC, SMALL = direct(), byte_bpe.ByteBpe(MULTI, P.PATTERN, leaf_chars=5, long_match=9)
COUNTER, WORD_BPE = token_counts.PrefixCounter(BYTE, P.PATTERN), sorted_shards.WordBpe(WORD)


@settings(max_examples=400, deadline=None)
@given(texts)
def test_tree_encoding_is_the_library_encoding(text):
    ids = SMALL.encode(text)
    assert ids == CODEC.encode_ordinary(text) and SMALL.decode(ids, fan=3) == text.encode()


def test_characters_of_other_unicode_versions():
    seen = sorted(letters.newer("L") | letters.newer("N") | letters.normalized_apart())
    for c in [*seen, *map(chr, range(0x80, 0x3000))]:
        text = f"ab{c}{c}d {c}e1{c}2.{c}A{c}\u0316\u0301 '{c}"
        assert WORD_BPE.encode(text).tolist() == WORDS.encode(text, add_special_tokens=False).ids
        assert SMALL.encode(text) == CODEC.encode_ordinary(text)
        assert COUNTER.counts(text)[-1] == len(LIBRARY.encode(text, add_special_tokens=False).ids)


def test_seams_inside_one_match():
    rng = random.Random(3)
    for _ in range(500):
        word = "".join(rng.choice(["er", "tion", "a", "th", "q", "zz", "ing"]) for _ in range(rng.randint(2, 60))).encode()
        k = rng.randint(1, len(word) - 1)
        assert SMALL.seam(SMALL.single(word[:k]), SMALL.single(word[k:])) == SMALL.single(word)
    long = "abcdefghijk" * 3000
    assert byte_bpe.ByteBpe(MULTI, P.PATTERN).encode(long) == CODEC.encode_ordinary(long)


def test_round_trip_query(spark, odd, docs, none):
    for df in (odd, docs, none):
        rows = df.select("doc_id", "text").collect()
        want = Counter()
        for r in rows:
            ids = CODEC.encode_ordinary(r.text or "")
            want[r.doc_id, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()] += 1
        assert Counter(tuple(r) for r in byte_bpe.round_trip(df).collect()) == want
    encoded = byte_bpe.encode_documents(odd)
    assert Counter((r.doc_id, bytes(r.decoded)) for r in byte_bpe.decode_documents(encoded).collect()) == Counter((r.doc_id, (r.text or "").encode()) for r in odd.collect())


@settings(max_examples=300, deadline=None)
@given(texts)
def test_prefix_counts_are_the_library_counts(text):
    want = [len(LIBRARY.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
    assert COUNTER.counts(text).tolist() == want and COUNTER.counts_all([text])[0].tolist() == want


def test_counts_of_matches_beyond_a_byte(spark):
    held = [c * n for c in ("\U00020000", "\U00013000", "\U00010348") for n in (63, 64, 65)]
    want = [len(LIBRARY.encode(x, add_special_tokens=False).ids) for x in held]
    assert max(want) > 255
    fresh = token_counts.PrefixCounter(BYTE, P.PATTERN)
    assert [int(x[-1]) for x in fresh.counts_all(held)] == want
    df = spark.createDataFrame(list(enumerate(held)), "doc_id bigint, text string")
    assert [r.n_tokens for r in token_counts.count_tokens(df).orderBy("doc_id").collect()] == want


@settings(max_examples=60, deadline=None)
@given(st.integers(60, 70), st.sampled_from(["\U00010000", "\U00010001", "\U00020000", "\U00013000"]), st.sampled_from(["", " ", "a", "\n"]))
def test_runs_of_four_byte_characters(n, c, around):
    text = around + c * n + around
    want = [len(LIBRARY.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1)]
    counts = token_counts.PrefixCounter.counts_all(COUNTER, [text])[0]
    assert counts.tolist() == want and token_counts.unpack_counts(token_counts.pack_counts(counts)).tolist() == want


def test_stored_counts_answer_without_texts(spark, odd, docs, none):
    for df in (odd, docs, none):
        stored = token_counts.prefix_counts(df)
        held = Counter((r.doc_id, r.text or "") for r in df.collect())
        got = Counter()
        for r in stored.collect():
            got[r.doc_id, tuple(token_counts.unpack_counts(r.counts).tolist())] += 1
        assert got == Counter({(i, tuple(COUNTER.counts(t).tolist())): n for (i, t), n in held.items()})
        for budget in (0, 7, 1024):
            fits = Counter((r.doc_id, r.fit_chars) for r in token_counts.answer(stored, budget).collect())
            want = Counter()
            for (i, t), n in held.items():
                want[i, COUNTER.truncate(COUNTER.counts(t), budget)] += n
            assert fits == want
    spans = spark.createDataFrame([(9, 2, 11), (9, -3, 999), (1, 0, 4), (999, 0, 1), (None, 0, 1), (4, None, 1)], "doc_id bigint, start bigint, stop bigint")
    found = {(r.doc_id, r.start): (r.n_before, r.n_after) for r in token_counts.tokens_between(token_counts.prefix_counts(odd), spans).collect()}
    text = dict((r.doc_id, r.text) for r in odd.collect())[9]
    own = COUNTER.counts(text)
    assert found == {(9, 2): (own[2], own[11]), (9, -3): (0, own[-1]), (1, 0): (0, 0), (999, 0): (None, None), (None, 0): (None, None), (4, None): (None, None)}


def test_counts_of_a_long_text_in_bounded_memory(spark):
    import tracemalloc

    text = "The quick brown fox; 12 jumps over é lazy dogs.\n" * 110_000  # over 5 MB
    assert len(token_counts.unpack_counts(token_counts.pack_counts(COUNTER.counts(text)))) == len(text) + 1
    tracemalloc.start()
    COUNTER.counts(text)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 1 << 30
    assert [len(x) for x in token_counts._runs(["a" * 200_000] * 3 + [text, "b", "c"])] == [1, 1, 1, 1, 2]


def test_count_query(odd, docs, none):
    for df in (odd, docs, none):
        want = Counter()
        for r in df.collect():
            n = len(LIBRARY.encode(r.text or "", add_special_tokens=False).ids)
            want[r.doc_id, len((r.text or "").encode()), n, n > 1024] += 1
        got = token_counts.count_tokens(df).collect()
        assert Counter(tuple(r)[:4] for r in got) == want
        assert all(r.over_limit or r.fit_chars is not None for r in got)


def test_truncation(docs):
    text = docs.where("n_chars > 5000").first().text
    counts = COUNTER.counts(text)
    k = COUNTER.truncate(counts, 100)
    assert counts[k] <= 100 and all(counts[k + 1 :] > 100)


@settings(max_examples=300, deadline=None)
@given(texts)
def test_word_ids_are_the_library_ids(text):
    assert WORD_BPE.encode(text).tolist() == WORDS.encode(text, add_special_tokens=False).ids


def test_shards_round_trip_and_look_up(spark, odd, docs, none):
    for df in (odd, docs, none):
        manifest = sorted_shards.write_shards(df, new_path(spark, "sst"), shards=3)
        first = lambda x: (x[0] is not None, x[0] or 0, x[1])
        got = sorted((tuple(r) for r in sorted_shards.read_shards(manifest).collect()), key=first)
        rows = sorted(((r.doc_id, i) for i, r in enumerate(df.collect())), key=first)
        held, at, want = df.collect(), 0, []
        for doc_id, i in rows:
            ids = [*WORDS.encode(held[i].text or "", add_special_tokens=False).ids, 2]
            want.append((doc_id, at, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids))))
            at += len(ids)
        assert got == want
    manifest = sorted_shards.write_shards(odd, new_path(spark, "sst"), shards=3)
    found = sorted_shards.look_up(manifest, [5, -5, 11, 999])
    assert found[5] == [[*WORDS.encode("the same text in two rows", add_special_tokens=False).ids, 2]] and len(found[11]) == 2 and found[999] == [] and len(found[-5]) == 1
    wanted = spark.createDataFrame([(x,) for x in [*range(-9, 40), None, 5, 999]], "doc_id bigint")
    every = Counter((r.doc_id, tuple(r.ids)) for r in sorted_shards.look_up_all(manifest, wanted).collect())
    assert every == Counter((r.doc_id, (*WORDS.encode(r.text or "", add_special_tokens=False).ids, 2)) for r in odd.collect() if r.doc_id is not None)
    assert sorted_shards.look_up_all(manifest, wanted.where("false")).count() == 0
    assert sorted_shards.look_up_all(sorted_shards.write_shards(none, new_path(spark, "sst")), wanted).count() == 0


def test_drafts_are_removed_and_files_replaced(tmp_path):
    from pyarrow import fs

    for name in (".000001-aa", "shard-000000.sst", ".x.crc"):
        (tmp_path / name).write_bytes(b"1")
    sorted_shards._replace(fs.LocalFileSystem(), str(tmp_path / ".000001-aa"), str(tmp_path / "shard-000000.sst"))
    (tmp_path / ".000002-bb").write_bytes(b"2")
    sorted_shards._drop_drafts(f"file://{tmp_path}")
    assert sorted(x.name for x in tmp_path.iterdir()) == [".x.crc", "shard-000000.sst"]


def test_blocks_and_damage(tmp_path):
    from pyarrow import fs

    path = str(tmp_path / "one.sst")
    with open(path, "wb") as out:
        w = sorted_shards.ShardWriter(out, 4)
        for i in range(-300, 9000, 3):
            w.add(i, np.arange(i % 40, dtype=np.uint32))
        w.close()
    with fs.LocalFileSystem().open_input_file(path) as file:
        r = sorted_shards.ShardReader(file)
        assert len(r.index) > 1 and r.entries == 3100
        assert [i for i, *_ in r.scan()] == list(range(-300, 9000, 3))
        assert all(len(r.get(i)) == (i % 3 == 0) for i in range(-300, 500)) and r.get(-303) == []
        assert r.get(-300)[0].tolist() == list(range(-300 % 40))
    data = bytearray(open(path, "rb").read())
    data[3] ^= 255
    open(path, "wb").write(data)
    with fs.LocalFileSystem().open_input_file(path) as file, pytest.raises(ValueError):
        list(sorted_shards.ShardReader(file).scan())


@settings(max_examples=150, deadline=None)
@given(st.dictionaries(st.integers(1, 32), st.integers(1, 9), min_size=1))
def test_plans_hold_all_pieces(histogram):
    bins = packing.plan(histogram, 32)
    used = Counter()
    for chosen, times in bins:
        assert sum(chosen) <= 32 and times > 0
        for x in chosen:
            used[x] += times
    assert used == histogram
    # no piece of a later bin fits into an earlier one, so any two bins hold more than a capacity together
    total, number, spread = sum(k * v for k, v in histogram.items()), sum(t for _, t in bins), [c for c, t in bins for _ in range(t)]
    assert all(sum(c) + min(map(min, spread[i + 1 :])) > 32 for i, c in enumerate(spread[:-1]))
    assert number == 1 or number * 32 < 2 * total
    # pieces over half a capacity need a bin each; no plan has fewer bins than that, nor than the total asks for
    assert number >= max(ceil(total / 32), sum(v for k, v in histogram.items() if k > 16))


def test_first_bin_has_the_least_slack():
    for room in range(1, 20):
        counts = {7: 2, 5: 1, 3: 3}
        best = max(x * 7 + y * 5 + z * 3 for x in range(3) for y in range(2) for z in range(4) if x * 7 + y * 5 + z * 3 <= room)
        assert sum(packing.fullest(counts, room)) == best


def test_assigning_a_table_with_names_of_its_own(spark):
    rows = [(i, 0, 1 + i % 9, "b", 1, 2, 3, 4, 5) for i in range(400)] + [(None, 0, 3, "x", 1, 2, 3, 4, 5)] * 5
    pieces = spark.createDataFrame(rows, "doc_id bigint, piece int, length int, bucket string, rank int, offset int, `before` int, c0 int, _len int")
    got = packing.assign(pieces, capacity=10)
    assert got.columns == ["doc_id", "piece", "length", "bucket", "rank", "own_offset", "before", "c0", "_len", "sequence_id", "offset"]
    bins: dict[int, list] = {}
    for r in got.collect():
        assert (r.own_offset, r.rank) == (2, 1)
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert sum(map(len, bins.values())) == 405 and len(bins) <= ceil(sum(r[2] for r in rows) / 10) + 2
    for parts in bins.values():
        assert [o for o, _ in sorted(parts)] == [sum(n for _, n in sorted(parts)[:i]) for i in range(len(parts))]
    assert packing.assign(pieces.where("false"), capacity=10).count() == 0


def test_packing_query(odd, docs, none):
    for df in (odd, docs, none):
        got = packing.pack(df).collect()
        want = Counter()
        for r in df.collect():
            ids = np.array([*LIBRARY.encode(r.text or "", add_special_tokens=False).ids, 2], np.uint32)
            for k, (start, n) in enumerate(packing._pieces(len(ids), 1024)):
                want[r.doc_id, k, start, n, zlib.crc32(ids[start : start + n].tobytes())] += 1
        assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == want
        bins: dict[int, list] = {}
        for r in got:
            bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
        for parts in bins.values():
            at = 0
            for offset, n in sorted(parts):
                assert offset == at
                at += n
            assert at <= 1024
        if got:
            assert len(bins) <= ceil(sum(r.length for r in got) / 1024) * 1.05 + 1
    whole = {r.sequence_id: len(r.ids) for r in packing.sequences(docs).collect()}
    assert sum(whole.values()) == sum(r.length for r in packing.pack(docs).collect())


def test_common_prefixes_of_words_in_order():
    """Also where one word is the beginning of the next, ends in NUL, or is too long for a square."""
    for more in ([], ["x" * 300, "x" * 299 + "y"]):
        words = sorted(x.encode() for x in ["", "a", "a\0", "a\0\0b", "ab", "abc", "abd", "é", "è", "z", *more])
        want = [0, *(len(os.path.commonprefix([a, b])) for a, b in zip(words, words[1:], strict=False))]
        assert token_counts._common_prefixes(words) == want
    assert token_counts._common_prefixes([]) == [] and token_counts._common_prefixes([b"ab"]) == [0]


def test_new_words_take_few_calls():
    import cProfile
    import pstats

    fresh, words = token_counts.PrefixCounter(BYTE, P.PATTERN), [f" w{i * 7919 % 99991}x" for i in range(3000)]
    fresh._learn([words])
    fresh.words.clear()
    profile = cProfile.Profile()
    profile.runcall(fresh._learn, [words])
    assert pstats.Stats(profile).total_calls < 65_000  # 58,942, and 71,506 with the greatest count of each word looked for
