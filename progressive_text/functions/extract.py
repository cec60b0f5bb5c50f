"""Text to declared fields. What does not satisfy the declaration is not valid."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


@dataclass(frozen=True)
class JsonExtractor:
    """One field of JSON text. A wrong type, broken JSON and null text give null."""

    schema: str
    field: str
    lo: float | None = None
    hi: float | None = None

    def value(self, text: str | Column) -> Column:
        return _in_range(F.from_json(F.col(text) if isinstance(text, str) else text, StructType.fromDDL(self.schema), {"mode": "PERMISSIVE"})[self.field], self.lo, self.hi)


@dataclass(frozen=True)
class RegexExtractor:
    """A group of a pattern, cast to a type; with count=True the number of matches."""

    pattern: str
    type: str = "string"
    group: int = 1
    count: bool = False
    lo: float | None = None
    hi: float | None = None

    def value(self, text: str | Column) -> Column:
        text = F.col(text) if isinstance(text, str) else text
        if self.count:
            return _in_range(F.regexp_count(text, F.lit(self.pattern)).cast(self.type), self.lo, self.hi)
        found = F.nullif(F.regexp_extract(text, self.pattern, self.group), F.lit(""))
        return _in_range(found.try_cast(self.type), self.lo, self.hi)


def _in_range(value: Column, lo: float | None, hi: float | None) -> Column:
    if lo is None and hi is None:
        return value
    inside = (value >= lo if lo is not None else F.lit(True)) & (value <= hi if hi is not None else F.lit(True))
    return F.when(inside, value)
