"""One query over several sources: which sources can answer which pattern, and joins across them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import compile as plan
from ..plans.ir import Pattern, SelectQuery
from .mapping import Graph


def sources_of(g: Graph) -> list[str]:
    return sorted({e.source for e in g.entities})


def select_sources(g: Graph, q: SelectQuery) -> dict[Pattern, list[str]]:
    """The sources that may answer each pattern, from their predicates first and from a first matching row only where an end is bound."""
    return {p: [s for s in sources_of(g) if plan.ask(g, p, s)] for p in q.patterns}


def source_table(g: Graph, q: SelectQuery) -> DataFrame:
    """(pattern_no, source) of the selection."""
    chosen = select_sources(g, q)
    return g.spark.createDataFrame([(i, s) for i, p in enumerate(q.patterns) for s in chosen[p]], "pattern_no int, source string")


def federated(g: Graph, q: SelectQuery) -> DataFrame:
    """The answers over all sources. Patterns that a single source answers alone go first, so joins stay within a source as long as they can."""
    chosen = select_sources(g, q)
    if any(not s for s in chosen.values()):
        return plan.run(g, q).limit(0)
    return plan.run(g, q, sources=chosen, rank=lambda p: exclusive(g, chosen, p))


def exclusive(g: Graph, chosen: dict[Pattern, list[str]], p: Pattern) -> tuple:
    """Join order: bound ends, then patterns of a single source, then as in one source."""
    bound, *rest = plan.weight(g, p)
    return (bound, len(chosen[p]) > 1, tuple(chosen[p]), *rest)


def exists(a: DataFrame, b: DataFrame, on: list[str]) -> DataFrame:
    return a.join(b, on, "left_semi")


def not_exists(a: DataFrame, b: DataFrame, on: list[str]) -> DataFrame:
    return a.join(b, on, "left_anti")


def by_source(g: Graph) -> DataFrame:
    return g.triples().groupBy("source").agg(F.count("*").alias("n_triples"))
