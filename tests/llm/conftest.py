from __future__ import annotations

import pytest

SF = "/root/testdata/sf0.001"

#: Nulls, empty and blank texts, ties, repeated rows, special strings, odd characters, a long text without spaces.
ODD = [
    (1, None), (2, ""), (3, " "), (4, "a"), (5, "the same text in two rows"), (6, "the same text in two rows"), (7, "<|endoftext|> in the <|endoftext|>text"),
    (8, "x" * 9000), (9, "l'été  \n\n\t don't WE'RE  12 345!!! \U0001f642 Σίσυφος İ ́ "), (10, "\x1c\x85　中文字符" * 40), (11, "word " * 3000), (None, "no id"), (11, "word " * 3000), (12, "\n\n"), (-5, "negative id"),
]


@pytest.fixture(scope="session")
def odd(spark):
    """Odd documents, with columns whose names clash with those that operators use."""
    rows = [(i, t, "en", "s", len(t or ""), 7, "x", "y", b"z") for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, slot int, shard string, n string, ids binary").cache()


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")  # a cached scan would take the place of scans in tests of plans


@pytest.fixture(scope="session")
def none(odd):
    return odd.where("false")


def pairs(rows) -> list[tuple]:
    return sorted(((r.doc_id, r.text or "") for r in rows), key=lambda x: (x[0] is not None, x[0] or 0, x[1]))
