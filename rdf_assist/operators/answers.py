"""The answer table: search, order, hide, reuse and print."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ir import SelectQuery, Term


def search(df: DataFrame, word: str) -> DataFrame:
    """Rows with a column that contains word, whatever the case."""
    hits = [F.contains(F.lower(F.coalesce(F.col(c).cast("string"), F.lit(""))), F.lit(word.lower())) for c in df.columns]
    return df.where(reduce(lambda a, b: a | b, hits))


def sort(df: DataFrame, column: str, descending: bool = False) -> DataFrame:
    return df.orderBy(F.desc(column) if descending else F.asc(column))


def columns(df: DataFrame, keep: list[str]) -> DataFrame:
    return df.select(*keep)


def bind(q: SelectQuery, variable: str, value: Term) -> SelectQuery:
    """The query with a variable replaced by an answer."""
    from dataclasses import replace

    def swap(t: Term) -> Term:
        return value if t.kind == "var" and t.value == variable else t

    made = tuple(replace(p, s=swap(p.s), p=swap(p.p), o=swap(p.o)) for p in q.patterns)
    return replace(q, patterns=made, variables=tuple(v for v in q.variables if v != variable))


def to_text(df: DataFrame, n: int = 50) -> str:
    """The first n rows as aligned text."""
    rows = [df.columns, *[["" if v is None else str(v) for v in r] for r in df.limit(n).collect()]]
    widths = [max(len(r[i]) for r in rows) for i in range(len(df.columns))]
    return "\n".join("  ".join(v.ljust(w) for v, w in zip(r, widths, strict=True)).rstrip() for r in rows)
