"""Unicode classes as the tokenizer libraries have them; `regex` and Python may know another version of Unicode."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterable
from functools import lru_cache

import regex
import tiktoken

#: Planes with assigned characters (the others hold private or no characters), without surrogates.
POINTS = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x40000), *range(0xE0000, 0xE1000)]))


def as_class(points: Iterable[str]) -> str:
    """The inside of a character class of some characters."""
    runs: list[list[int]] = []
    for c in sorted(map(ord, points)):
        if runs and runs[-1][1] == c - 1:
            runs[-1][1] = c
        else:
            runs.append([c, c])
    return "".join(f"\\U{a:08x}" if a == b else f"\\U{a:08x}-\\U{b:08x}" for a, b in runs)


@lru_cache(maxsize=8)
def newer(kind: str) -> frozenset[str]:
    """Characters of class L or N for `regex` alone, not for the libraries."""
    ranks = {bytes([i]): i for i in range(256)}
    codec = tiktoken.Encoding(f"class {kind}", pat_str=rf"\p{{{kind}}}", mergeable_ranks=ranks, special_tokens={})
    theirs = set(bytes(codec.encode_ordinary(POINTS)).decode())
    ours = set(regex.findall(rf"\p{{{kind}}}", POINTS))
    if theirs - ours:
        raise RuntimeError(f"the regex library is older than the tokenizer libraries: {sorted(theirs - ours)[:9]}")
    return frozenset(ours - theirs)


def exact(pattern: str) -> str:
    """A pattern for regex.V1 whose letters and numbers are those of the libraries."""
    for kind in "LN":
        if found := newer(kind):
            own = rf"[\p{{{kind}}}--[{as_class(found)}]]"
            pattern = pattern.replace(rf"\p{{{kind}}}", own).replace(rf"\P{{{kind}}}", f"[^{own}]")
    return pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")


@lru_cache(maxsize=1)
def normalized_apart() -> frozenset[str]:
    """Characters that NFC or lower case of the tokenizers library may treat in another way than Python does."""
    from tokenizers import normalizers

    nfc, lower = normalizers.NFC(), normalizers.Lowercase()
    marks = "̖́\n"  # below and above: their order around a mark tells its combining class
    points, out = [c for c in POINTS if c != "\n"], {"\n"}
    pairs = (
        (lower.normalize_str("\n".join(points)), "\n".join(points).replace("Σ", "σ").lower()),
        (nfc.normalize_str("".join("a" + c + marks for c in points)), unicodedata.normalize("NFC", "".join("a" + c + marks for c in points))),
        (nfc.normalize_str("\n".join(points)), unicodedata.normalize("NFC", "\n".join(points))),
        (nfc.normalize_str("\n".join(unicodedata.normalize("NFD", c) for c in points)), "\n".join(unicodedata.normalize("NFC", c) for c in points)),
    )
    for theirs, ours in pairs:
        a, b = theirs.rstrip("\n").split("\n"), ours.rstrip("\n").split("\n")
        out |= {x for c, p, q in zip(points, a, b, strict=True) if p != q for x in (c, *unicodedata.normalize("NFD", c)[1:])}
    return frozenset(out - {"\n"})


class Finder:
    """Tells texts that hold any of some characters, at little cost for the others."""

    def __init__(self, points: Iterable[str]):
        self.least = min(points, default=chr(0x10FFFF))
        self.search = regex.compile(f"[{as_class(points)}]").search if points else lambda text: None

    def __call__(self, text: str) -> bool:
        return not text.isascii() and max(text) >= self.least and self.search(text) is not None


def library_differs() -> Finder:
    return Finder(newer("L") | newer("N"))
