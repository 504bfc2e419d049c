"""The interaction loop: complete, run, suggest, accept."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from ..plans import compile as plan
from ..plans.ir import SelectQuery, Term, validate
from ..plans.parse import parse
from . import complete as comp
from .index import Cache, build_cache, open_cache, store
from .mapping import Graph
from .relax import Connection, relax, suggest_shapes
from .suggest import describe, prefetch, suggest_terms


def register(spark: SparkSession, graph: Graph, folder: str, m: int = 40_000) -> Cache:
    """The cache of a source, built and stored in a folder the first time and opened from there from then on."""
    try:
        return open_cache(spark, folder)
    except AnalysisException:
        return store(build_cache(graph, m), folder)


class Assistant:
    """One user's session over a graph and its cache."""

    def __init__(self, spark: SparkSession, graph: Graph, cache: Cache | None = None, k: int = 10, budget: int = 100):
        self.spark, self.graph, self.cache = spark, graph, cache or build_cache(graph)
        self.k, self.budget = k, budget
        self.held: comp.SuffixCache | None = None
        self.query: SelectQuery | None = None
        self.suggestions: DataFrame | None = None
        self.shapes: list[SelectQuery] = []
        self.prefetched: DataFrame | None = None

    def complete(self, text: str) -> DataFrame:
        """At most k completions. The indexed terms are held here from the first call on, as m bounds them; the rest is scanned."""
        if self.held is None:
            self.held = comp.SuffixCache(self.cache)
        return comp.complete(self.cache, text, self.k, held=self.held)

    def run(self, query: str | SelectQuery) -> DataFrame:
        """The answers; the query becomes the session's."""
        self.query = parse(query) if isinstance(query, str) else query
        self.suggestions, self.prefetched, self.shapes = None, None, []
        return plan.run(self.graph, self.query)

    def problems(self, query: str | SelectQuery) -> list[str]:
        return validate(parse(query) if isinstance(query, str) else query)

    def suggest(self, structure: bool = True) -> DataFrame:
        """Alternative terms and relaxed structures with answers, told apart by `kind`; always offered, also when the query has answers.

        A relaxed query's alt_id is negative; the queries are in `shapes`.
        """
        found = suggest_terms(self.graph, self.cache, self.query, self.k)
        if structure and len(self.query.literals()) > 1:
            made: Connection
            made, self.shapes = relax(self.graph, self.query, budget=self.budget)
            found = found.unionByName(suggest_shapes(self.graph, self.query, self.shapes, made.cost))
        self.suggestions = describe(found)
        return self.suggestions

    def prefetch(self) -> DataFrame:
        """Answers of all suggested terms, for display on acceptance."""
        found = self.suggestions
        self.prefetched = prefetch(self.graph, self.query, found.where("kind <> 'structure'"))
        for r in found.where("kind = 'structure'").select("alt_id").collect():  # a few trees
            own = plan.run(self.graph, self.shapes[-1 - r.alt_id]).withColumn("alt_id", F.lit(r.alt_id))
            self.prefetched = self.prefetched.unionByName(own, allowMissingColumns=True)
        return self.prefetched

    def accept(self, alt_id: int) -> DataFrame:
        """The query with a suggested term; its answers, from the prefetched ones where they are there."""
        r = self.suggestions.where(f"alt_id = {int(alt_id)}").first()
        if r is None:
            raise KeyError(alt_id)
        held = self.prefetched
        if r.kind == "structure":
            query = self.shapes[-1 - int(alt_id)]
        else:
            query = self.query.with_term(r.pattern_no, r.position, Term("iri" if r.position == "p" else "literal", r.new))
        if held is not None:
            self.query = query
            return held.where(f"alt_id = {int(alt_id)}").drop("alt_id")
        return self.run(query)

    def accept_shape(self, i: int) -> DataFrame:
        return self.run(self.shapes[i])

    def edit(self, i: int, **terms: Term) -> DataFrame:
        """One triple changed, and run again."""
        return self.run(self.query.with_pattern(i, replace(self.query.patterns[i], **terms)))

    def views(self) -> None:
        """Temp views for SQL: triples, predicates, terms, suffixes, residual, classes."""
        from .mapping import class_hierarchy

        self.graph.triples().createOrReplaceTempView("triples")
        self.spark.createDataFrame([(p,) for p in self.graph.predicates], "p string").createOrReplaceTempView("predicates")
        for name in ("terms", "suffixes", "residual"):
            getattr(self.cache, name).createOrReplaceTempView(name)
        class_hierarchy(self.spark).createOrReplaceTempView("classes")
