"""Byte-level BPE as a monoid: halves are encoded apart and joined at their seam.

Encodings form a monoid under `join`: only a window around the seam is encoded again, and it grows until what lies
outside cannot change any more. Two facts prove that:

- The splitting pattern never has a match that goes from a letter to a non-letter, from a number to a non-number or
  from a non-space to a white space. Such a place is a match boundary in whatever text surrounds it.
- Inside one match, a token sequence is the encoding of its bytes if and only if each two neighbours are the
  encoding of their own concatenation: the first merge that crossed a boundary would need a merge of two neighbours.

A very long match (no boundary in thousands of characters) is joined by the second fact, other seams by the first.
"""

from __future__ import annotations

import base64
import hashlib
import json
from functools import lru_cache

import regex
import tiktoken
from pyspark.sql import DataFrame

from . import letters
from .common import Memo, map_rows, tokenizer_file, whole_text

#: Places that bound a match in any context.
BOUNDARY = r"(?<=\P{White_Space})(?=\p{White_Space})|(?<=\p{L})(?=\P{L})|(?<=\p{N})(?=\P{N})"


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of the 256 bytes in byte-level vocabularies: themselves, or the next free code from 256."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


def read_ranks(path: str) -> tuple[dict[bytes, int], dict[str, int]]:
    """(ranks, special tokens) of a .tiktoken rank file or of a byte-level BPE .json whose ids follow its merges."""
    if path.endswith(".tiktoken"):
        with open(path, "rb") as lines:
            return {base64.b64decode(token): int(rank) for token, rank in (x.split() for x in lines if x.strip())}, {}
    with open(path, encoding="utf-8") as file:
        held = json.load(file)
    if held["normalizer"] or held["pre_tokenizer"]["type"] != "ByteLevel" or held["pre_tokenizer"]["add_prefix_space"]:
        raise ValueError(f"{path} is not a plain byte-level BPE")
    special = {x["content"]: x["id"] for x in held["added_tokens"]}
    code = byte_alphabet()
    ranks = {bytes(code[c] for c in token): i for token, i in held["model"]["vocab"].items() if token not in special}
    made = [ranks[bytes(code[c] for c in "".join(x.split(" ") if isinstance(x, str) else x).replace(" ", ""))] for x in held["model"]["merges"]]
    if any(a >= b for a, b in zip(made, made[1:])):
        raise ValueError(f"the ids of {path} do not follow the order of its merges")
    return ranks, special


class ByteBpe:
    """Encoder and decoder over a rank file."""

    def __init__(self, path: str, pattern: str, leaf_chars: int = 1024, long_match: int = 4096):
        ranks, self.special = read_ranks(path)
        self.codec = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens=self.special)
        self.single = self.codec._core_bpe.encode_single_piece
        self.bytes_of = [b""] * (1 + max([*ranks.values(), *self.special.values()]))
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
        for token, rank in self.special.items():
            self.bytes_of[rank] = token.encode()
        self.leaf, self.long_match = leaf_chars, long_match
        self.boundary = regex.compile(letters.exact(BOUNDARY), regex.V1)
        self.match = regex.compile(letters.exact(pattern), regex.V1)
        self.quick = regex.compile(pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}"))
        self.differs = letters.library_differs()
        self.agree = Memo(lambda pair: self.single(self.bytes_of[pair[0]] + self.bytes_of[pair[1]]) == [*pair])

    def matcher(self, text: str) -> regex.Pattern:
        """Finds the pattern's matches in this text; the exact form takes twice as long and is seldom needed."""
        return self.match if self.differs(text) else self.quick

    def encode(self, text: str) -> list[int]:
        return self._tree(text, 0, len(text))

    def _tree(self, text: str, lo: int, hi: int) -> list[int]:
        if hi - lo <= self.leaf:
            return self.codec.encode_ordinary(text[lo:hi])
        mid = (lo + hi) // 2
        return self.join(text, lo, mid, hi, self._tree(text, lo, mid), self._tree(text, mid, hi))

    def join(self, text: str, lo: int, mid: int, hi: int, left: list[int], right: list[int]) -> list[int]:
        """The encoding of text[lo:hi] from those of text[lo:mid] and text[mid:hi]."""
        a = self._last_boundary(text, lo, mid)
        if a == mid:
            return left + right
        found = self.boundary.search(text, mid + 1, hi)
        b = found.start() if found else hi
        if b - a > self.long_match and (joined := self._join_match(text, a, mid, b, left, right)) is not None:
            return joined
        keep = self._take(left, len(text[a:mid].encode()), last=True)
        drop = self._take(right, len(text[mid:b].encode()), last=False)
        return left[:keep] + self.codec.encode_ordinary(text[a:b]) + right[drop:]

    def _last_boundary(self, text: str, lo: int, mid: int) -> int:
        width = 32
        while True:
            start = max(lo + 1, mid - width)
            found = [m.start() for m in self.boundary.finditer(text, start, min(mid + 1, len(text)))]
            if found or start == lo + 1:
                return found[-1] if found else lo
            width *= 4

    def _take(self, ids: list[int], n_bytes: int, last: bool) -> int:
        """Where the ids that make up the last (first) n_bytes begin (end)."""
        at, step = (len(ids), -1) if last else (0, 1)
        while n_bytes > 0:
            n_bytes -= len(self.bytes_of[ids[at - 1 if last else at]])
            at += step
        return at

    def _join_match(self, text: str, a: int, mid: int, b: int, left: list[int], right: list[int]) -> list[int] | None:
        """Joins a match that crosses the seam by its tokens; None if the halves' own matches do not meet there."""
        cross = next((m for m in self.match.finditer(text, a, b) if m.start() < mid < m.end()), None)
        if cross is None:
            return None
        s, e = cross.span()
        before = [m.start() for m in self.match.finditer(text, a, mid)]
        after = self.match.match(text, mid, b)
        if before[-1] != s or after is None or after.end() != e:
            return None
        keep = self._take(left, len(text[s:mid].encode()), last=True)
        drop = self._take(right, len(text[mid:e].encode()), last=False)
        return left[:keep] + self.seam(left[keep:], right[:drop]) + right[drop:]

    def seam(self, left: list[int], right: list[int]) -> list[int]:
        """Tokens of one match from those of its halves: the window doubles until its ends agree with their neighbours."""
        width = 4
        while True:
            n, m = min(width, len(left)), min(width, len(right))
            window = self.single(b"".join(self.bytes_of[i] for i in left[len(left) - n :] + right[:m]))
            if (n == len(left) or self.agree[left[-n - 1], window[0]]) and (m == len(right) or self.agree[window[-1], right[m]]):
                return left[: len(left) - n] + window + right[m:]
            width *= 2

    def decode(self, ids: list[int], fan: int = 64) -> bytes:
        """Bytes concatenated up a tree."""
        parts = [self.bytes_of[i] for i in ids]
        while len(parts) > 1:
            parts = [b"".join(parts[i : i + fan]) for i in range(0, len(parts), fan)]
        return parts[0] if parts else b""


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> ByteBpe:
    return ByteBpe(path, pattern)


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def encode_documents(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids array<int> of every whole text. Null and empty texts: no ids. Rows are kept as they are, repeats too."""
    path, pattern = path or tokenizer_file("byte_bpe_multi_50k.tiktoken"), default_pattern()

    def make():
        bpe = load(path, pattern)
        return lambda c: {"doc_id": c["doc_id"], "ids": [bpe.encode(x) for x in c["text"]]}

    return map_rows(whole_text(docs), make, "doc_id bigint, ids array<int>")


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, decoded binary of rows (doc_id, ids). Null ids: no bytes."""
    path, pattern = path or tokenizer_file("byte_bpe_multi_50k.tiktoken"), default_pattern()

    def make():
        bpe = load(path, pattern)
        return lambda c: {"doc_id": c["doc_id"], "decoded": [bpe.decode(x or []) for x in c["ids"]]}

    return map_rows(encoded.select("doc_id", "ids"), make, "doc_id bigint, decoded binary")


def round_trip(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Encodes and decodes every whole text and returns digests: doc_id, n_tokens, ids_sha256, decoded_sha256.

    Null texts are empty: no ids, and the digest of no bytes. Repeated rows and null ids stay, a row each; other columns are
    left out, whatever their names. A text of any length is one row's work. An empty table gives an empty one.
    """
    path, pattern = path or tokenizer_file("byte_bpe_multi_50k.tiktoken"), default_pattern()

    def make():
        bpe = load(path, pattern)
        sha = lambda x: hashlib.sha256(x).hexdigest()

        def each(c):
            ids = [bpe.encode(x) for x in c["text"]]
            return {
                "doc_id": c["doc_id"],
                "n_tokens": [len(x) for x in ids],
                "ids_sha256": [sha(",".join(map(str, x)).encode()) for x in ids],
                "decoded_sha256": [sha(bpe.decode(x)) for x in ids],
            }

        return each

    return map_rows(whole_text(docs), make, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
