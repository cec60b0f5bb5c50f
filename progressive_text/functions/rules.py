"""Rule labelers' expressions: stand-ins for a semantic function that any machine can run, with DuckDB twins.

Each rule is a Column over a text column and an SQL text over the same column.
"""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Words of insults, marks of noise, and frequent words of four languages.
INSULTS = "trash scum idiot clown worthless moron pathetic loser stupid disgusting".split()
NOISE = r"(\*\*\*|###|\$\$\$|%%%|&&&|!!)"
FREQUENT = {
    "de": "der die und das ist nicht ein eine zu den von mit auf für im dem des sich auch".split(),
    "en": "the of and to in that is was it for on with as by this be are at from".split(),
    "es": "el los las una por con para es como más pero sus del se lo al su no y".split(),
    "fr": "le les des et une du est que qui pour sur dans au par avec pas ce il elle".split(),
}
LETTERS = "[^a-zäöüßéèêçñáíóú]+"


def _words(text: str) -> Column:
    return F.split(F.regexp_replace(F.lower(text), LETTERS, " "), " ")


def toxic(text: str = "text") -> Column:
    return F.arrays_overlap(_words(text), F.array(*map(F.lit, INSULTS)))


def low_quality(text: str = "text") -> Column:
    parts = F.split(text, " ")
    n = F.size(parts)
    noisy = F.regexp_count(F.col(text), F.lit(NOISE)) > 0.3 * n
    tabled = F.regexp_count(F.col(text), F.lit(r" \| ")) >= 5
    repeated = F.size(F.array_distinct(parts)) < 0.2 * n
    return noisy | tabled | repeated


def language(text: str = "text") -> Column:
    """The language of most frequent words; on a tie the first by name. Words are counted in place, without an array of them."""
    words = F.concat(F.lit(" "), F.regexp_replace(F.lower(text), LETTERS, " "), F.lit(" "))
    count = lambda frequent: F.regexp_count(words, F.lit(f"(?<= )(?:{'|'.join(frequent)})(?= )"))
    votes = F.array(*[F.struct((-count(frequent)).alias("v"), F.lit(k).alias("k")) for k, frequent in sorted(FREQUENT.items())])
    return F.array_min(votes)["k"]


def language_of(text: str) -> str:
    """The same for one text in Python, for clients that serve as models."""
    words = re.sub(LETTERS, " ", text.lower()).split(" ")
    return min((-sum(w in frequent for w in words), k) for k, frequent in FREQUENT.items())[1]


def low_quality_of(text: str) -> bool:
    parts = text.split(" ")
    return len(re.findall(NOISE, text)) > 0.3 * len(parts) or len(re.findall(r" \| ", text)) >= 5 or len(set(parts)) < 0.2 * len(parts)


def licence(text: str = "text") -> Column:
    return F.lower(text).rlike("licen[sc]e|all rights reserved|copyright")


def class3(text: str = "text") -> Column:
    return F.when(toxic(text), "toxic").when(low_quality(text), "junk").otherwise("clean")


def noun(name: str = "p_name") -> Column:
    return F.regexp_extract(name, "([a-z]+)$", 1)


def _list(words: list[str]) -> str:
    return "[" + ", ".join(f"'{w}'" for w in words) + "]"


def _sql_words(text: str) -> str:
    return f"string_split(regexp_replace(lower({text}), '{LETTERS}', ' ', 'g'), ' ')"


def toxic_sql(text: str = "text") -> str:
    return f"list_has_any({_sql_words(text)}, {_list(INSULTS)})"


def low_quality_sql(text: str = "text") -> str:
    n = f"len(string_split({text}, ' '))"
    return rf"(len(regexp_extract_all({text}, '{NOISE}')) > 0.3 * {n} OR len(regexp_extract_all({text}, ' \| ')) >= 5 OR len(list_distinct(string_split({text}, ' '))) < 0.2 * {n})"


def language_sql(text: str = "text") -> str:
    votes = ", ".join(f"{{'v': -len(list_filter({_sql_words(text)}, lambda w: list_contains({_list(ws)}, w))), 'k': '{k}'}}" for k, ws in sorted(FREQUENT.items()))
    return f"list_sort([{votes}])[1].k"


def class3_sql(text: str = "text") -> str:
    return f"CASE WHEN {toxic_sql(text)} THEN 'toxic' WHEN {low_quality_sql(text)} THEN 'junk' ELSE 'clean' END"
