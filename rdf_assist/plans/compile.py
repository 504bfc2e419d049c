"""Queries to DataFrames: joins of pattern extents on shared variables, then filters, groups and modifiers.

Each variable becomes a column of its own name; literals also bring their number, time and language along,
in columns _num_x, _ts_x and _lang_x, so that filters compare values and not their spelling.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.mapping import Graph
from .ir import Body, Filter, Group, Pattern, SelectQuery, Term, validate

EXTRA = ("_num_", "_ts_", "_lang_")
#: Rows up to which one side of a product may go to every task.
MAX_PRODUCT = 10_000


def _is(column: str, t: Term) -> Column:
    if t.kind == "literal" and t.dtype in ("integer", "double"):
        return F.col("o_num") == float(t.value)
    same = F.col(column) == t.value
    if column == "o":
        same = same & (F.col("o_kind") == t.kind)
        if t.lang:
            same = same & (F.col("o_lang") == t.lang)
    return same


def match(g: Graph, p: Pattern, sources: list[str] | None = None) -> DataFrame:
    """Bindings of a pattern's variables. A bound predicate scans its columns alone."""
    df = g.extent(p.p.value) if p.p.kind == "iri" else g.triples()
    if sources is not None:
        df = df.where(F.col("source").isin(*sources))
    for position in "so":
        t = getattr(p, position)
        if t.kind != "var":
            df = df.where(_is(position, t))
    columns, seen = [], {}
    for position in "spo":
        t = getattr(p, position)
        if t.kind != "var":
            continue
        if t.value in seen:
            df = df.where(F.col(position) == F.col(seen[t.value]))
            continue
        seen[t.value] = position
        columns.append(F.col(position).alias(t.value))
        if position == "o":
            columns += [F.col("o_num").alias(f"_num_{t.value}"), F.col("o_ts").alias(f"_ts_{t.value}"), F.col("o_lang").alias(f"_lang_{t.value}")]
    return df.select(*columns) if columns else df.select(F.lit(True).alias("_matched")).distinct()


def weight(g: Graph, p: Pattern) -> tuple:
    """Smaller first: bound ends before free ones; then by the triples of the predicate where they were counted, or by its tables."""
    bound = sum(getattr(p, x).kind != "var" for x in "so")
    return (-bound, p.p.kind == "var", g.counts.get(p.p.value, 0), sum(p.p.value in e.facts for e in g.entities))


def order(g: Graph, patterns: list[Pattern], rank: Callable | None = None) -> list[Pattern]:
    """A join order in which each pattern shares a variable with an earlier one where it can; constants first."""
    rank = rank or (lambda p: weight(g, p))
    left = sorted(patterns, key=rank)
    out: list[Pattern] = []
    known: set[str] = set()
    while left:
        linked = [p for p in left if known & set(p.variables())] or left
        best = min(linked, key=lambda p: (rank(p), left.index(p)))
        left.remove(best)
        out.append(best)
        known |= set(best.variables())
    return out


def join(a: DataFrame, b: DataFrame, how: str = "inner", hint: str | None = None) -> DataFrame:
    """Natural join on variables. Without a shared one the kind decides: a difference removes nothing; absence and optional parts
    ask whether b has rows; the rest is a product, one side of which must have at most MAX_PRODUCT rows."""
    shared = [c for c in a.columns if c in b.columns and not c.startswith("_")]
    if hint:
        b = b.hint(hint)
    if not shared:
        if how == "minus":
            return a
        if how == "absent":
            return a.join(F.broadcast(b.select(F.lit(1).alias("_one")).limit(1)), F.lit(True), "left_anti")
        b = b.drop(*[c for c in b.columns if c in a.columns])
        if b.limit(MAX_PRODUCT + 1).count() <= MAX_PRODUCT:
            return a.join(F.broadcast(b), F.lit(True), "left" if how == "left" else "inner")
        if how != "left" and a.limit(MAX_PRODUCT + 1).count() <= MAX_PRODUCT:
            return b.join(F.broadcast(a), F.lit(True)).select(*a.columns, *b.columns)
        raise ValueError(f"a product of two sides of more than {MAX_PRODUCT} rows each: the patterns share no variable")
    twice = [c for c in b.columns if c in a.columns and c not in shared]
    return a.join(b.drop(*twice), shared, {"minus": "left_anti", "absent": "left_anti"}.get(how, how))


def bgp(g: Graph, patterns, sources: dict | None = None, hint: str | None = None, rank: Callable | None = None) -> DataFrame:
    """The bindings of all patterns together."""
    out = None
    for p in order(g, list(patterns), rank):
        df = match(g, p, None if sources is None else sources[p])
        out = df if out is None else join(out, df, hint=hint)
    return out


def condition(f: Filter, columns: list[str]) -> Column:
    c = F.col(f.variable)
    if f.op == "contains":
        return F.contains(F.lower(c), F.lit(str(f.value).lower()))
    if f.op == "starts":
        return c.startswith(str(f.value))
    if f.op == "regex":
        return c.rlike(str(f.value))
    if f.op == "lang":
        return F.col(f"_lang_{f.variable}") == f.value
    if f.op in ("minlen", "maxlen"):
        n = F.length(c)
        return n >= int(f.value) if f.op == "minlen" else n <= int(f.value)
    value = F.lit(f.value)
    if isinstance(f.value, float) and f"_num_{f.variable}" in columns:
        c = F.col(f"_num_{f.variable}")
    elif isinstance(f.value, str) and f"_ts_{f.variable}" in columns and f.value[:4].isdigit() and "-" in f.value:
        c, value = F.col(f"_ts_{f.variable}"), F.lit(f.value).cast("timestamp")
    return {"=": c == value, "!=": c != value, "<": c < value, "<=": c <= value, ">": c > value, ">=": c >= value}[f.op]


def body(g: Graph, b: Body, sources: dict | None = None, hint: str | None = None, rank: Callable | None = None) -> DataFrame:
    """The bindings of a body: patterns, then unions, then optional parts and differences in their order, then filters."""
    df = bgp(g, b.patterns, sources, hint, rank) if b.patterns else None
    for part in sorted(b.groups, key=lambda x: x.kind != "union"):
        if part.kind == "union":
            whole = None
            for inner in part.parts:
                own = body(g, inner)
                whole = own if whole is None else whole.unionByName(own, allowMissingColumns=True)
            df = whole if df is None else join(df, whole)
        else:
            how = {"optional": "left", "minus": "minus", "absent": "absent"}[part.kind]
            df = join(df if df is not None else g.spark.range(1).select(F.lit(True).alias("_matched")), body(g, part.parts[0]), how)
    for f in b.filters:
        df = df.where(condition(f, df.columns))
    return df


def _value(name: str, columns: list[str]) -> str:
    return f"_num_{name}" if f"_num_{name}" in columns else name


def run(g: Graph, q: SelectQuery, sources: dict | None = None, hint: str | None = None, rank: Callable | None = None) -> DataFrame:
    """The answer table of a query."""
    if problems := validate(q):
        raise ValueError("; ".join(problems))
    df = body(g, q.body(), sources, hint, rank)
    if q.aggregates:
        made = []
        for a in q.aggregates:
            column = F.lit(1) if a.variable is None else F.col(a.variable if a.function == "count" else _value(a.variable, df.columns))
            if a.function == "count":
                value = F.countDistinct(column) if a.distinct else F.count(column)
            else:
                value = getattr(F, a.function)(column)
            made.append(value.alias(a.name))
        df = df.groupBy(*q.group_by).agg(*made)
        for f in q.having:
            df = df.where(condition(f, df.columns))
        names = [*q.group_by, *(a.name for a in q.aggregates)]
    else:
        names = [v for v in (q.variables or q.all_variables()) if v not in q.hide]
        if q.distinct:
            kept = [F.first(c).alias(c) for c in df.columns if c.startswith(EXTRA) and c.split("_", 2)[2] in names]
            df = df.groupBy(*names).agg(*kept) if kept else df.select(*names).distinct()
    if q.order_by:
        df = df.orderBy(*[F.desc(_value(v, df.columns)) if down else F.asc(_value(v, df.columns)) for v, down in q.order_by])
    if q.offset:
        df = df.offset(q.offset)
    if q.limit is not None:
        df = df.limit(q.limit)
    return df.select(*names)


def shape_of(q: SelectQuery) -> tuple[SelectQuery, tuple[str, ...]]:
    """(the query with its text literals as variables _k0, _k1, ...; the literals)."""
    held: list[str] = []

    def open_(t: Term) -> Term:
        if t.kind != "literal" or t.dtype or t.lang:
            return t
        if t.value not in held:
            held.append(t.value)
        return Term("var", f"_k{held.index(t.value)}")

    return replace(q, patterns=tuple(replace(p, o=open_(p.o)) for p in q.patterns)), tuple(held)


def join_asked(g: Graph, patterns, asked: DataFrame, slots: list[str], first: DataFrame | None = None, bound: tuple[str, ...] = ()) -> DataFrame:
    """asked, a small table of literals in the columns `slots`, joined by all patterns. first: what one more pattern, with the variables `bound`, has made of it."""
    known, left, df = {*slots, *bound}, list(patterns), asked if first is None else first
    while left:
        linked = [p for p in left if known & set(p.variables())]
        if not linked:
            raise ValueError("the patterns share no variable")
        p = min(linked, key=lambda p: (not set(slots) & set(p.variables()), weight(g, p), left.index(p)))
        left.remove(p)
        own = match_open(g, p, slots)
        on = sorted(known & set(p.variables()))
        df = df.join(own, on) if df is not asked else own.join(F.broadcast(df), on)
        known |= set(p.variables())
    return df


def match_open(g: Graph, p: Pattern, slots: list[str]) -> DataFrame:
    """match() without the columns that filters need; a slot stands for a literal."""
    # a literal's own kind and not an IRI of the same text is asked for
    own = match(g, p) if p.o.value not in slots else match(g, replace(p, o=Term("var", "_o"))).withColumnRenamed("_o", p.o.value).drop("_num__o", "_ts__o", "_lang__o")
    return own.drop(*[c for c in own.columns if c.startswith(EXTRA)])


def _shapes(g: Graph, queries: list[tuple[int, SelectQuery]]) -> list[tuple[SelectQuery, list[str], DataFrame]]:
    """(shape, slots, bindings with _qid) of queries of plain patterns that differ in literals alone."""
    shapes: dict[SelectQuery, list[tuple]] = {}
    for qid, q in queries:
        if q.groups or q.filters or q.aggregates:
            raise ValueError("only queries of plain patterns run together")
        shape, held = shape_of(q)
        shapes.setdefault(shape, []).append((qid, *held))
    out = []
    for shape, rows in shapes.items():
        slots = [f"_k{i}" for i in range(len(rows[0]) - 1)]
        asked = g.spark.createDataFrame(rows, ", ".join(["_qid long", *[f"{k} string" for k in slots]]))
        if slots:
            df = join_asked(g, shape.patterns, asked, slots)
        else:
            df = bgp(g, shape.patterns).withColumn("_all", F.lit(1)).join(F.broadcast(asked.withColumn("_all", F.lit(1))), "_all")
        out.append((shape, slots, df))
    return out


def run_many(g: Graph, queries: list[tuple[int, SelectQuery]]) -> DataFrame:
    """(qid, answer): the first column of many queries of plain patterns. Queries that differ in literals alone run as one plan.

    The literals of such queries make a small table, one row a query, that the patterns join; so a plan's number of scans is
    that of one query. Answers are distinct.
    """
    parts = []
    for shape, slots, df in _shapes(g, queries):
        name = (shape.variables or [v for v in shape.all_variables() if v not in slots])[0]
        parts.append(df.select(F.col("_qid").alias("qid"), F.col(name).cast("string").alias("answer")).distinct())
    if not parts:
        return g.spark.createDataFrame([], "qid long, answer string")
    return reduce(DataFrame.unionByName, parts)


def count_many(g: Graph, queries: list[tuple[int, SelectQuery]]) -> list[DataFrame]:
    """(qid, n_answers) of queries of plain patterns that have answers, a plan for each shape: the numbers of rows that run() gives."""
    if any(q.limit is not None or q.offset for _, q in queries):
        raise ValueError("only whole answers are counted together")
    parts = []
    for shape, slots, df in _shapes(g, queries):
        if shape.distinct:
            df = df.select("_qid", *[v for v in (shape.variables or shape.all_variables()) if v not in slots and v not in shape.hide]).distinct()
        parts.append(df.groupBy(F.col("_qid").alias("qid")).agg(F.count("*").alias("n_answers")))
    return parts


def ask(g: Graph, p: Pattern, source: str) -> bool:
    """Whether a source has a match: by its predicates if the pattern's ends are free, else by its first matching row."""
    own = [e for e in g.entities if e.source == source]
    if p.p.kind == "iri" and not any(p.p.value in e.facts for e in own):
        return False
    if p.s.kind == "var" and p.o.kind == "var":
        return True
    return not match(g, p, [source]).limit(1).isEmpty()
