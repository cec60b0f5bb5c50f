"""Exact token counts of every prefix of a text by dynamic programming.

The last token of a prefix's encoding is the one token t that ends there such that the encoding of the prefix before
t ends in a token that agrees with t (their concatenation encodes to just these two). So one pass over the bytes gives
the count of each prefix. A text is first cut where a space follows a non-space: such a place bounds a match in any
text, so chunks count independently, and a prefix is some whole chunks and a prefix of the next one.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import regex
import zstandard
from pyspark.sql import DataFrame

from .byte_bpe import ByteBpe, default_pattern
from .common import Memo, map_rows, saved, tokenizer_file, whole_text

#: White space, and the separators that some definitions count as such.
SPACES = "".join(map(chr, [*range(9, 14), *range(28, 33), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]))


class PrefixCounter:
    """counts(text)[i] is the number of tokens of text[:i], for i from 0 to len(text)."""

    def __init__(self, path: str, pattern: str, memo_chars: int = 64):
        self.bpe = ByteBpe(path, pattern)
        self.rank = {t: i for i, t in enumerate(self.bpe.bytes_of) if t and t.decode("utf-8", "replace") not in self.bpe.special}
        self.longest = max(map(len, self.rank))
        self.width = list(map(len, self.bpe.bytes_of))
        self.memo_chars, self.words = memo_chars, Memo(lambda match: (x := self._match(match)) and (bytes(x) if x[-1] < 256 > max(x) else x), 400_000)
        self.agree = Memo(self._agrees, 400_000)
        self.two_spaces = re.compile(f"[{SPACES}][{SPACES}]")
        self.cut = regex.compile(rf"(?<=[^{SPACES}])(?= )")
        self.special = re.compile("|".join(map(re.escape, self.bpe.special))) if self.bpe.special else None

    def counts_all(self, texts: list[str]) -> list[np.ndarray]:
        """counts() of some texts, whose new words share the work for common prefixes."""
        parts = [self.bpe.matcher(x).findall(x) for x in texts]
        self._learn(parts)
        return [self.counts(x, p) for x, p in zip(texts, parts, strict=True)]

    def counts(self, text: str, parts: list[str] | None = None) -> np.ndarray:
        """Counts of all prefixes; special strings inside a text are one token each, their proper prefixes plain text."""
        if not self.special or not (found := [*self.special.finditer(text)]):
            return np.concatenate([[0], self._plain(text, parts)])
        parts, base, at = [np.zeros(1, np.int64)], 0, 0
        for m in found:
            plain = self._plain(text[at : m.end()])
            whole = base + (plain[m.start() - at - 1] if m.start() > at else 0) + 1
            parts += [base + plain[:-1], [whole]]
            base, at = whole, m.end()
        return np.concatenate([*parts, base + self._plain(text[at:])])

    def _agrees(self, pair: int) -> bool:
        a, b = pair >> 32, pair & 0xFFFFFFFF
        return self.bpe.single(self.bpe.bytes_of[a] + self.bpe.bytes_of[b]) == [a, b]

    def _chunks(self, text: str) -> list[str]:
        return [x for x in self.cut.split(text) if x]

    def _plain(self, text: str, parts: list[str] | None = None) -> np.ndarray:
        """Counts of text[:1], text[:2], ... without special strings."""
        if not text:
            return np.zeros(0, np.int64)
        words = self.words
        if self._simple(text):
            parts = self.bpe.matcher(text).findall(text) if parts is None else parts
            flat = [words[x] for x in parts]
        else:
            parts = self._chunks(text)
            flat = [self._chunk(x) for x in parts]
        lengths = np.fromiter(map(len, parts), np.int64, len(parts))
        if set(map(type, flat)) == {bytes}:
            flat = np.frombuffer(b"".join(flat), np.uint8).astype(np.int64)
        else:
            flat = np.concatenate([np.array([*x], np.int64) for x in flat])
        totals = flat[np.cumsum(lengths) - 1]
        return flat + np.repeat(np.cumsum(totals) - totals, lengths)

    def _simple(self, text: str) -> bool:
        """No apostrophe and no two white spaces in a row: each prefix of a match is a match."""
        return "'" not in text and not self.two_spaces.search(text)

    def _chunk(self, chunk: str) -> list[int]:
        """Counts of a chunk's prefixes, match by match.

        The prefix of a match is a match of its own kind, but for a contraction ('r of 're is two matches) and for the
        space that begins a match after other white space (in a prefix that ends there, all of it is one match).
        """
        out, base, run, words, match = [], 0, None, self.words, self.bpe.matcher(chunk)
        for m in match.finditer(chunk):
            s, e = m.span()
            own = [*words[chunk[s:e]]]
            if chunk[s] == "'" and 1 < e - s <= 3 and chunk[s + 1].isalpha():
                for j in range(2, e - s):
                    own[j - 1] = sum(len(self.bpe.single(x.group().encode())) for x in match.finditer(chunk[s : s + j]))
            total = own[-1]
            if run is not None and chunk[s] in SPACES:
                own[0] = run[1] - base + self._match(chunk[run[0] : s + 1])[-1]
            out += [base + x for x in own] if base else own
            run = (s, base) if chunk[s] in SPACES and not chunk[s:e].strip(SPACES) else None
            base += total
        return out

    def _match(self, match: str) -> list[int]:
        raw = match.encode()
        return _at_characters(raw, self._sweep([raw])[0])

    def _sweep(self, words: list[bytes]) -> list[bytes | list[int]]:
        """Counts at each byte of some words. Of neighbours with a common prefix (words in order), it is counted once."""
        agree, find, width, longest = self.agree, self.rank.get, self.width, self.longest
        out, last, count = [], [-1], [0]
        for raw, k in zip(words, _common_prefixes(words), strict=True):
            del last[k + 1 :], count[k + 1 :]
            for end in range(k + 1, len(raw) + 1):
                for start in range(end - 1, end - 1 - longest if end > longest else -1, -1):
                    t = find(raw[start:end])
                    if t is not None and (start == 0 or agree[last[start] << 32 | t]):
                        break
                last.append(t)
                count.append(count[end - width[t]] + 1)
            out.append(count[1:])
        return out

    def _learn(self, texts: list[list[str]]) -> None:
        seen = set().union(*texts)
        new = [x for x in seen if x not in self.words and len(x) <= self.memo_chars]
        if len(self.words) + len(new) > self.words.most:
            self.words.clear()
            new = [x for x in seen if len(x) <= self.memo_chars]
        new.sort()  # the order of their bytes too
        raws = [x.encode() for x in new]
        for x, raw, counts in zip(new, raws, self._sweep(raws), strict=True):
            counts = counts if len(raw) == len(x) else _at_characters(raw, counts)
            self.words[x] = bytes(counts) if len(raw) < 256 or max(counts) < 256 else counts  # no count exceeds its place

    def truncate(self, counts: np.ndarray, budget: int) -> int:
        """Characters of the longest prefix of at most `budget` tokens."""
        return int(np.flatnonzero(counts <= budget)[-1])


def _common_prefixes(words: list[bytes]) -> list[int]:
    """Of each word, how many bytes it begins with as the word before it does."""
    if len(words) < 2:
        return [0] * len(words)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    if sizes.max() > 256:  # a square of such would not fit
        return [0, *(next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b))) for a, b in zip(words, words[1:], strict=False))]
    square = np.array(words, dtype=f"S{sizes.max() + 1}").view(np.uint8).reshape(len(words), -1)
    differ = np.argmax(square[1:] != square[:-1], axis=1)  # 0 too where padded words are equal
    same = (square[1:] == square[:-1]).all(axis=1)
    least = np.minimum(sizes[1:], sizes[:-1])
    return [0, *np.where(same, least, np.minimum(differ, least)).tolist()]


def _at_characters(raw: bytes, counts: list[int]) -> list[int]:
    """Of counts at bytes, those at the ends of characters."""
    return [c for c, following in zip(counts, raw[1:] + b"a", strict=True) if following & 0xC0 != 0x80]


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> PrefixCounter:
    return PrefixCounter(path, pattern)


def pack_counts(counts: np.ndarray) -> bytes:
    """Counts of all prefixes as zstd of their steps: a byte each, or four where a step does not fit into one."""
    steps = np.diff(counts)
    narrow = steps.size == 0 or (steps.min() >= -128 and steps.max() <= 127)
    return (b"1" if narrow else b"4") + _pack().compress(steps.astype(np.int8 if narrow else "<i4").tobytes())


def unpack_counts(data: bytes) -> np.ndarray:
    steps = np.frombuffer(_unpack().decompress(data[1:]), np.int8 if data[:1] == b"1" else "<i4")
    return np.concatenate([[0], np.cumsum(steps, dtype=np.int64)])


@lru_cache(maxsize=1)
def _pack() -> zstandard.ZstdCompressor:
    return zstandard.ZstdCompressor(level=1)


@lru_cache(maxsize=1)
def _unpack() -> zstandard.ZstdDecompressor:
    return zstandard.ZstdDecompressor()


#: Characters whose counts are held at a time.
RUN_CHARS = 1 << 18


def _runs(texts: list[str]) -> Iterator[list[str]]:
    """texts in order, in runs of about RUN_CHARS characters; a longer text is a run of its own."""
    run, held = [], 0
    for x in texts:
        if run and held + len(x) > RUN_CHARS:
            yield run
            run, held = [], 0
        run.append(x)
        held += len(x)
    if run:
        yield run


def prefix_counts(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_bytes, n_chars, n_tokens, counts: the token count of every prefix of every whole text, packed.

    Null and empty texts: no tokens and one prefix. Rows are kept as they are, repeats and null ids too; other columns
    of docs are left out. A task holds the counts of RUN_CHARS characters, or of one longer text.
    """
    path, pattern = path or tokenizer_file("byte_bpe_50k.json"), default_pattern()

    def make():
        counter = load(path, pattern)

        def each(c):
            total, packed = [], []
            for run in _runs(c["text"]):
                for counts in counter.counts_all(run):
                    total.append(int(counts[-1]))
                    packed.append(pack_counts(counts))
            return {"doc_id": c["doc_id"], "n_bytes": [len(x.encode()) for x in c["text"]], "n_chars": [len(x) for x in c["text"]], "n_tokens": total, "counts": packed}

        return each

    return map_rows(whole_text(docs), make, "doc_id bigint, n_bytes bigint, n_chars bigint, n_tokens bigint, counts binary")


def answer(stored: DataFrame, budget: int = 1024) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (n_tokens > budget) and fit_chars, the longest prefix within the budget, from
    stored counts alone: no text is read or encoded again. Null counts: null fit_chars."""

    def make():
        def fit(n: int, chars: int, data: bytes | None) -> int | None:
            if data is None or n <= budget:
                return None if data is None else chars
            return int(np.flatnonzero(unpack_counts(data) <= budget)[-1])

        def each(c):
            fits = [fit(*x) for x in zip(c["n_tokens"], c["n_chars"], c["counts"], strict=True)]
            return {"doc_id": c["doc_id"], "n_bytes": c["n_bytes"], "n_tokens": c["n_tokens"], "over_limit": [n > budget for n in c["n_tokens"]], "fit_chars": fits}

        return each

    return map_rows(stored, make, "doc_id bigint, n_bytes bigint, n_tokens bigint, over_limit boolean, fit_chars bigint")


def tokens_between(stored: DataFrame, spans: DataFrame) -> DataFrame:
    """doc_id, start, stop of spans (characters, clipped to the text) with n_before, n_after: the counts of the prefixes
    that end there. Spans of unknown or null identifiers have nulls; an identifier with several rows answers for each."""
    joined = spans.select("doc_id", "start", "stop").join(stored.select("doc_id", "counts"), "doc_id", "left")

    def make():
        def one(start, stop, data):
            if data is None or start is None or stop is None:
                return None, None
            counts = unpack_counts(data)
            return tuple(int(counts[min(max(x, 0), len(counts) - 1)]) for x in (start, stop))

        def each(c):
            found = [one(*x) for x in zip(c["start"], c["stop"], c["counts"], strict=True)]
            return {"doc_id": c["doc_id"], "start": c["start"], "stop": c["stop"], "n_before": [x[0] for x in found], "n_after": [x[1] for x in found]}

        return each

    return map_rows(joined, make, "doc_id bigint, start bigint, stop bigint, n_before bigint, n_after bigint")


def count_tokens(docs: DataFrame, path: str | None = None, budget: int = 1024) -> DataFrame:
    """prefix_counts written as a table, and the answers for one budget from what it holds."""
    return answer(saved(prefix_counts(docs, path), "counts"), budget)
