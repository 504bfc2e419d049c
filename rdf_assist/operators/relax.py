"""Relaxing a query's structure: its literals joined through light paths of the data graph, under an expansion budget.

Each literal with its alternatives is a group of seeds. Groups grow in turns by shortest distance; a logical
expansion of a vertex is one query to an endpoint and is charged to the ledger once. Execution is by level: all
vertices admitted at a distance are expanded by one scan, for at most `budget` vertices. What is reached is held on the driver as
long as it is no more than LOCAL_ROWS rows, and a round is one job; beyond that it is a distributed table, of which only
expanded vertices and aggregates come to the driver. Both ways take the same steps. Where many searches go together, or a vertex has very many
neighbours, these stay in the tables: such hubs are asked again for what another group, or a path, has to do with.
"""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, field
from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans import compile as plan
from ..plans.ir import SelectQuery, Term, text_of
from ..sources.tables import remove_folder, shared_folder
from . import tree as trees
from .index import Cache
from .mapping import Graph
from .suggest import literal_alternatives, query_terms, top_k

# What kind of entity each table and each linking predicate gives.
SUBJECTS = {"region": "region", "nation": "nation", "customer": "customer", "orders": "order", "lineitem": "lineitem", "supplier": "supplier", "part": "part", "pages": "page", "conversations": "turn", "benchmark": "benchmark", "events": "event", "embeddings": "vector", "labels": "document"}
TARGETS = {"region": "region", "nation": "nation", "customer": "customer", "order": "order", "part": "part", "supplier": "supplier", "origin": "origin", "host": "host", "linksTo": "path", "conversation": "conversation", "user": "user", "type": "class", "subClassOf": "class"}

W_QUERY, W_DEFAULT = 1, 2
#: Rows of what is reached that the driver may hold.
LOCAL_ROWS = 100_000
#: The same for all searches that go together.
BATCH_ROWS = 200_000
#: Neighbours of a vertex by one predicate that are listed also where the rows are too many.
HUB = 1_000
# What a literal that stands for a number or a point in time looks like.
NUMBER, TIME = re.compile(r"-?\d+(\.\d+)?([eE]-?\d+)?\Z"), re.compile(r"\d{4}-\d\d-\d\d([ T]\d\d:\d\d(:\d\d(\.\d+)?)?)?\Z")


def seed_groups(g: Graph, c: Cache | None, q: SelectQuery, k: int = 10) -> DataFrame:
    """(group_id, vertex, is_original, similarity): each literal of the query with its k - 1 best alternatives."""
    rows = _own_seeds(q)
    if c is not None and rows:
        found = top_k(literal_alternatives(query_terms(g, q), c), k - 1).collect()  # at most k - 1 for each literal
        number = {lit: i for i, lit in enumerate(q.literals())}
        rows += [(number[r.term], '"' + r.alternative, False, r.similarity) for r in found]
    return g.spark.createDataFrame(rows, "group_id int, vertex string, is_original boolean, similarity double")


def _own_seeds(q: SelectQuery) -> list[tuple]:
    return [(i, '"' + lit, True, 1.0) for i, lit in enumerate(q.literals())]


def edge_weight(p: Column, liked: list[str], w_query: int = W_QUERY, w_default: int = W_DEFAULT) -> Column:
    """Predicates of the query and their alternatives are lighter; weights are never stored."""
    return F.when(p.isin(*liked), w_query).otherwise(w_default) if liked else F.lit(w_default)


def vertex_key(kind: str, text: Column) -> Column:
    return F.concat(F.lit('"'), text) if kind == "literal" else text


# The whole-number columns that name a table's entity, the first one of several, and the target of a predicate.
OWN_KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "supplier": "s_suppkey", "part": "p_partkey"}
TARGET_KEYS = {("nation", "region"): "n_regionkey", ("customer", "nation"): "c_nationkey", ("orders", "customer"): "o_custkey", ("lineitem", "order"): "l_orderkey", ("lineitem", "part"): "l_partkey", ("lineitem", "supplier"): "l_suppkey", ("supplier", "nation"): "s_nationkey"}


def _among(value: Column, names: list[str], key: str | None) -> Column:
    """Whether an IRI is among some; by its number too where the column is known, as that reaches the file scan."""
    found = value.isin(*names)
    return F.col(key).isin(sorted({int(v.split("/", 1)[1].split("-")[0]) for v in names})) & found if key else found


EDGES = "array<struct<v:string,p:string,u:string,forward:boolean>>"


def expand(g: Graph, vertices: list[str], edges: DataFrame | None = None, skip: tuple[str, ...] = ("label",)) -> DataFrame:
    """(v, p, u, forward) of all triples at the vertices: as object for a literal, on either side for an IRI.

    Virtual triples: only tables whose entities or targets match the vertices' kinds are read, once each, by the vertices'
    values. A literal that spells a number or a time stands for its value. With a stored edge table (v, p, u, forward) its files are pruned by the same list instead.
    """
    if edges is not None:
        return edges.where(F.col("v").isin(*vertices))
    lits = [v[1:] for v in vertices if v.startswith('"')]
    numbers, times = [x for x in lits if NUMBER.match(x)], [x for x in lits if TIME.match(x)]
    at_numbers = [F.lit(n) for x in sorted({float(x) for x in numbers}) for n in ([0.0, -0.0] if x == 0 else [x])]
    at_lits = [F.lit(x) for x in lits]  # made once, as each costs a call
    at_times = [F.lit(x).cast("timestamp") for x in times]
    spelled = F.transform(F.array(*[F.lit(x) for x in numbers]), lambda x: F.struct(x.cast("double").alias("n"), x.alias("x")))
    dated = F.transform(F.array(*[F.lit(x) for x in times]), lambda x: F.struct(x.cast("timestamp").alias("n"), x.alias("x")))
    iris: dict[str, list[str]] = {}
    for v in vertices:
        if not v.startswith('"'):
            iris.setdefault(v.split("/", 1)[0], []).append(v)
    parts = []
    for e in g.entities:
        subject = "origin" if e.table == "documents" and "name" in e.facts else "document" if e.table == "documents" else SUBJECTS[e.table]
        wanted: list[Column] = []
        made: list[Column] = []
        many: list[Column] = []

        def edge(when: Column, v: Column, p: str, u: Column, forward: bool, wanted=wanted, made=made) -> None:
            wanted.append(when)
            made.append(F.when(when, F.struct(v.alias("v"), F.lit(p).alias("p"), u.alias("u"), F.lit(forward).alias("forward"))))

        def edges_of(value: Column, among: list, spellings: Column, p: str, u: Column, wanted=wanted, many=many) -> None:
            """An edge for each literal that stands for the value: one expression however many there are."""
            when = value.isin(*among)
            wanted.append(when)
            many.append(F.when(when, F.transform(F.filter(spellings, lambda s: s["n"] == value), lambda s: F.struct(F.concat(F.lit('"'), s["x"]).alias("v"), F.lit(p).alias("p"), u.alias("u"), F.lit(False).alias("forward")))).otherwise(F.array().cast(EDGES)))

        own = _among(e.subject, iris[subject], OWN_KEYS.get(e.table)) if subject in iris else None
        for p, f in e.facts.items():
            if p in skip:
                continue
            value = f.value.cast("string")
            if own is not None:
                edge(own & value.isNotNull(), e.subject, p, vertex_key(f.kind, value), True)
            if f.kind == "iri" and TARGETS.get(p) in iris:
                edge(_among(value, iris[TARGETS[p]], TARGET_KEYS.get((e.table, p))), value, p, e.subject, False)
            if f.kind == "literal" and f.dtype == "string" and lits:
                edge(value.isin(*at_lits), vertex_key("literal", value), p, e.subject, False)
            if f.kind == "literal" and f.dtype in ("double", "integer") and numbers:
                edges_of(f.value.cast("double"), at_numbers, spelled, p, e.subject)
            if f.kind == "literal" and f.dtype == "timestamp" and times:
                edges_of(f.value.cast("timestamp"), at_times, dated, p, e.subject)
        if wanted:
            rows = e.shape(g.table(e.table)).where(reduce(lambda a, b: a | b, wanted))
            parts.append(rows.select(F.explode(F.concat(F.array_compact(F.array(*made)).cast(EDGES), *many)).alias("x")).select("x.*"))
    if not parts:
        return g.spark.createDataFrame([], "v string, p string, u string, forward boolean")
    return reduce(DataFrame.unionByName, parts)


@dataclass
class Connection:
    """The outcome: the trees with their cost, and the ledger."""

    found: bool
    cost: int | None = None
    trees: list[frozenset] = field(default_factory=list)
    terminals: list[str] = field(default_factory=list)
    expanded: list[str] = field(default_factory=list)
    refused: int = 0
    rounds: int = 0
    capped: bool = False


REACHED = "group_id int, vertex string, dist int, parents array<struct<v:string,p:string,forward:boolean>>, refused boolean"


class Search:
    """The state of one search."""

    def __init__(self, g: Graph, seeds: DataFrame, liked: list[str], budget: int, w_query: int, w_default: int, edges: DataFrame | None, strategy: str):
        self.g, self.liked, self.budget, self.edges, self.strategy = g, liked, budget, edges, strategy
        self.w_query, self.w_default = w_query, w_default
        self.folder, self.round = shared_folder(g.spark), 0
        self.cut = False
        self.expanded: dict[str, int] = {}
        self.done: set[tuple[int, str]] = set()
        none = F.array().cast("array<struct<v:string,p:string,forward:boolean>>")
        rows = seeds.select("group_id", "vertex", F.lit(0).alias("dist"), none.alias("parents"), F.lit(False).alias("refused"))
        self.reached = self.save(rows)
        self.groups = sorted(r.group_id for r in seeds.select("group_id").distinct().collect())

    def save(self, df: DataFrame) -> DataFrame:
        """The reached table of this round, on shared storage: lineage ends here and lost executors cost nothing."""
        self.round += 1
        path = f"{self.folder}/{self.round}"
        df.write.parquet(path)
        return self.g.spark.read.schema(REACHED).parquet(path)

    def part_levels(self, joined: set[int], part: set[str]) -> dict[int, int]:
        """How near each group that is not joined yet has come to the connected part."""
        rows = self.reached.where(F.col("vertex").isin(*sorted(part)) & ~F.col("group_id").isin(*sorted(joined))).groupBy("group_id").agg(F.min("dist").alias("d")).collect()
        return {r.group_id: r.d for r in rows}

    def parents(self, groups: tuple) -> dict[tuple[int, str], list]:
        """The parents of expanded vertices."""
        rows = self.reached.where(F.col("vertex").isin(*sorted(self.expanded)) & F.col("group_id").isin(*groups)).collect()
        return {(x.group_id, x.vertex): x.parents for x in rows}

    def spots(self, groups: tuple, cost: int, most: int | None) -> list[tuple]:
        """(vertex, parents in the one group, parents in the other) where two groups meet at a cost."""
        a = self.reached.where(F.col("group_id") == groups[0]).select("vertex", F.col("dist").alias("da"), F.col("parents").alias("pa"))
        b = self.reached.where(F.col("group_id") == groups[1]).select("vertex", F.col("dist").alias("db"), F.col("parents").alias("pb"))
        met = a.join(b, "vertex").where(F.col("da") + F.col("db") == cost).orderBy("vertex")
        return [(x.vertex, x.pa, x.pb) for x in (met if most is None else met.limit(most)).collect()]

    def part_spots(self, group: int, part: set[str], cost: int, most: int | None) -> list[tuple]:
        met = self.reached.where((F.col("group_id") == group) & F.col("vertex").isin(*sorted(part)) & (F.col("dist") == cost)).orderBy("vertex")
        return [(x.vertex, x.parents) for x in (met if most is None else met.limit(most)).collect()]

    def refusals(self):
        yield from ()
        return self.reached.where("refused").select("vertex").distinct().count()

    def close(self) -> None:
        """Removes the rounds' tables."""
        remove_folder(self.g.spark, self.folder)

    def open_rows(self) -> DataFrame:
        done = self.g.spark.createDataFrame(sorted(self.done) or [(-1, "")], "group_id int, vertex string")
        return self.reached.where(~F.col("refused")).join(F.broadcast(done), ["group_id", "vertex"], "left_anti")  # at most budget x groups rows

    def open_levels(self, groups) -> dict[int, int]:
        rows = self.open_rows().where(F.col("group_id").isin(*groups)).groupBy("group_id").agg(F.min("dist").alias("d")).collect()
        return {r.group_id: r.d for r in rows}

    def meetings(self) -> dict[tuple[int, int], int]:
        """Lightest meeting of each pair of groups; refused vertices were reached and may be met."""
        a = self.reached.select(F.col("group_id").alias("a"), "vertex", F.col("dist").alias("da"))
        b = self.reached.select(F.col("group_id").alias("b"), "vertex", F.col("dist").alias("db"))
        rows = a.join(b, "vertex").where("a < b").groupBy("a", "b").agg(F.min(F.col("da") + F.col("db")).alias("c")).collect()
        return {(r.a, r.b): r.c for r in rows}

    def admit(self, group: int, dist: int):
        """(vertices to expand, parents whose children are refused) of a level.

        Siblings start together or not at all; few siblings go first, then by parent, so the outcome does not depend on
        partitions. A vertex that another group expanded costs nothing.
        """
        yield from ()
        level = self.open_rows().where((F.col("group_id") == group) & (F.col("dist") == dist))
        known = self.g.spark.createDataFrame([(v,) for v in sorted(self.expanded)] or [("",)], "vertex string").withColumn("paid", F.lit(True))
        level = level.join(F.broadcast(known), "vertex", "left").withColumn("parent", F.coalesce(F.array_min("parents.v"), F.lit("")))
        counts = level.groupBy("parent").agg(F.count(F.when(F.col("paid").isNull(), 1)).alias("cost")).collect()  # parents are expanded vertices
        left, start, stop = self.budget - len(self.expanded), [], []
        for r in sorted(counts, key=lambda r: (r.cost, r.parent)):
            if r.cost <= left:
                start.append(r.parent)
                left -= r.cost
            else:
                stop.append(r.parent)
        chosen = [r.vertex for r in level.where(F.col("parent").isin(*start)).select("vertex").collect()] if start else []
        return sorted(chosen), stop

    def grow(self, group: int, dist: int, vertices: list[str], stopped: list[str]):
        """Expands a level; asks for nothing, as edges stay where they are."""
        yield from ()
        self.done |= {(group, v) for v in vertices}
        for v in vertices:
            self.expanded.setdefault(v, dist)
        base = self.reached
        if stopped:
            hit = (F.col("group_id") == group) & (F.col("dist") == dist) & F.coalesce(F.array_min("parents.v"), F.lit("")).isin(*stopped)
            done = self.g.spark.createDataFrame(sorted(self.done) or [(-1, "")], "group_id int, vertex string").withColumn("_done", F.lit(True))
            base = base.join(F.broadcast(done), ["group_id", "vertex"], "left").withColumn("refused", F.col("refused") | (hit & F.col("_done").isNull())).drop("_done")
        if vertices:
            step = edge_weight(F.col("p"), self.liked, self.w_query, self.w_default)
            new = expand(self.g, vertices, self.edges).select(F.lit(group).alias("group_id"), F.col("u").alias("vertex"), (F.lit(dist) + step).cast("int").alias("dist"), F.array(F.struct("v", "p", "forward")).alias("parents"), F.lit(False).alias("refused"))
            both = base.select(new.columns).unionByName(new)
            least = F.min("dist")
            grouped = both.groupBy("group_id", "vertex").agg(least.alias("dist"), F.collect_list(F.struct("dist", "parents")).alias("all"), F.bool_or("refused").alias("refused"))
            base = grouped.select("group_id", "vertex", "dist", F.array_sort(F.array_distinct(F.flatten(F.transform(F.filter("all", lambda x: x["dist"] == F.col("dist")), lambda x: x["parents"])))).alias("parents"), "refused")
        self.reached = self.save(base.select("group_id", "vertex", "dist", "parents", "refused"))


class Wanted(NamedTuple):
    """What a search asks for: the edges at vertices, at most so many rows. far: nothing, or whether edges of the liked and of other predicates are
    of use only where they end at one of `ends`. hubs: edges (v, p, forward) that are left out; last: too many rows are given all the same."""

    vertices: list[str]
    most: int | None
    liked: list[str]
    far: tuple[bool, bool] = (False, False)
    ends: frozenset[str] = frozenset()
    hubs: frozenset[tuple] = frozenset()
    last: bool = False


class Fans(NamedTuple):
    """What a search asks for: of what it wanted, the edges (v, p, forward) of which there are more than HUB."""

    wanted: Wanted


class Hubs(NamedTuple):
    """What a search asks about the neighbours of hubs, (group, v, p, forward) → distance, that are not in `held`. 'meet': how many there are by group, distance and
    first parent, and the first `most` vertices where two groups meet at the least cost, up to `cost`; 'list': the vertices of some of these; 'count': how many
    different ones there are at some levels."""

    kind: str
    hubs: dict[tuple, int]
    held: set[str]
    most: int | None = None
    cost: int | None = None
    some: frozenset[tuple] = frozenset()


def _wanted_edges(g: Graph, wanted: dict[int, Wanted], edges: DataFrame | None) -> DataFrame:
    """(search, v, p, u, forward) that the searches asked for."""
    found = expand(g, sorted({v for w in wanted.values() for v in w.vertices}), edges)
    if any(any(w.far) for w in wanted.values()):  # what the driver holds of the searches
        ends: dict[str, list[int]] = {}
        for i, w in wanted.items():
            for u in w.ends:
                ends.setdefault(u, []).append(i)
        met = F.broadcast(g.spark.createDataFrame(list(ends.items()), "u string, met array<int>"))
        found = found.join(met, "u", "inner" if all(all(w.far) for w in wanted.values()) else "left")
    else:
        found = found.withColumn("met", F.lit(None).cast("array<int>"))
    asked = [(i, v, w.liked, not w.far[0], not w.far[1]) for i, w in wanted.items() for v in w.vertices]
    found = found.join(F.broadcast(g.spark.createDataFrame(asked, "search int, v string, liked array<string>, near_liked boolean, near_other boolean")), "v")  # the vertices of a step
    near = F.when(F.array_contains("liked", F.col("p")), F.col("near_liked")).otherwise(F.col("near_other"))
    found = found.where(near | F.coalesce(F.array_contains("met", F.col("search")), F.lit(False))).select("search", "v", "p", "u", "forward")
    hubs = [(i, *h) for i, w in wanted.items() for h in w.hubs]
    if hubs:
        found = found.join(F.broadcast(g.spark.createDataFrame(hubs, "search int, v string, p string, forward boolean")), ["search", "v", "p", "forward"], "left_anti")  # at most the vertices of a step x predicates
    return found


def neighbours(g: Graph, wanted: dict[int, Wanted], edges: DataFrame | None = None) -> dict[int, list | None]:
    """search → the rows (v, p, u, forward) that it asked for, by one job for all searches. Where together they are too many, None for each, or one job each if they are asked for the last time."""
    found = _wanted_edges(g, wanted, edges)
    room = None if any(w.most is None for w in wanted.values()) else sum(w.most for w in wanted.values())
    rows = (found if room is None else found.limit(room)).collect()
    if len(rows) == room and len(wanted) > 1:
        return {i: neighbours(g, {i: w}, edges)[i] if w.last else None for i, w in wanted.items()}
    out: dict[int, list] = {i: [] for i in wanted}
    for r in rows:
        out[r.search].append(r)
    return out


def fans(g: Graph, asked: dict[int, Fans], edges: DataFrame | None = None) -> dict[int, list]:
    """search → its hubs' edges (v, p, forward): one job for all searches, and few rows."""
    counts = _wanted_edges(g, {i: f.wanted for i, f in asked.items()}, edges).groupBy("search", "v", "p", "forward").agg(F.count("*").alias("n"))
    out: dict[int, list] = {i: [] for i in asked}
    for r in counts.where(F.col("n") > HUB).collect():
        out[r.search].append((r.v, r.p, r.forward))
    return out


def hub_edges(g: Graph, asked: dict[int, Hubs], edges: DataFrame | None = None) -> DataFrame:
    """(search, group_id, v, p, u, forward, far): the edges of hubs to vertices that are not held."""
    rows = [(i, *h, far) for i, a in asked.items() for h, far in a.hubs.items()]
    hubs = g.spark.createDataFrame(rows, "search int, group_id int, v string, p string, forward boolean, far int")
    held = g.spark.createDataFrame([(i, u) for i, a in asked.items() for u in a.held], "search int, u string")
    found = expand(g, sorted({r[2] for r in rows}), edges).join(F.broadcast(hubs), ["v", "p", "forward"])  # at most budget x predicates rows a search
    return found.join(F.broadcast(held), ["search", "u"], "left_anti")  # what the driver holds of the searches


def about_hubs(g: Graph, asked: dict[int, Hubs], edges: DataFrame | None = None) -> dict:
    """search → what it asks about hubs; all are of one kind and go together. Only counts and chosen vertices come to the driver."""
    kind, key = next(iter(asked.values())).kind, ["search", "group_id"]
    nearest = hub_edges(g, asked, edges).groupBy(*key, "u").agg(F.min(F.struct("far", "v")).alias("x")).select(*key, "u", "x.far", "x.v")
    if kind != "meet":
        some = [(i, *x) for i, a in asked.items() for x in a.some]
        names = [*key, "far"] if kind == "count" else [*key, "far", "v"]
        part = g.spark.createDataFrame(some, "search int, group_id int, far int" + ", v string" * (kind == "list"))
        found = nearest.join(F.broadcast(part), names, "left_semi").select("search", "u").distinct()
        if kind == "count":
            return dict.fromkeys(asked, 0) | {r.search: r.n for r in found.groupBy("search").agg(F.count("*").alias("n")).collect()}
        listed: dict[int, set] = {i: set() for i in asked}
        for r in found.collect():  # at most about budget rows a parent
            listed[r.search].add(r.u)
        return listed
    folder = shared_folder(g.spark)
    nearest.write.parquet(f"{folder}/t")
    nearest = g.spark.read.schema(nearest.schema).parquet(f"{folder}/t")
    out: dict[int, tuple] = {i: ({}, set()) for i in asked}
    for r in nearest.groupBy(*key, "far", "v").agg(F.count("*").alias("n")).collect():  # a row a hub
        out[r.search][0].setdefault((r.group_id, r.far), {})[r.v] = r.n
    pairs = {i: [(a, b) for a, b in itertools.combinations(sorted({h[0] for h in x.hubs}), 2)] for i, x in asked.items()}
    limits = []
    for i, x in asked.items():
        for a, b in pairs[i]:
            least = [min(far for h, far in x.hubs.items() if h[0] == y) for y in (a, b)]
            if x.cost is None or sum(least) <= x.cost:
                limits.append((i, a, b, x.cost if x.cost is not None else 1 << 30))
    if limits:
        limit = F.broadcast(g.spark.createDataFrame(limits, "search int, a int, b int, most_cost int"))
        one = nearest.join(limit.select("search", F.col("a").alias("group_id"), "b", "most_cost"), key).select("search", "u", F.col("group_id").alias("a"), "b", F.col("far").alias("da"), "most_cost")
        met = one.join(nearest.select("search", "u", F.col("group_id").alias("b"), F.col("far").alias("db")), ["search", "u", "b"]).withColumn("cost", F.col("da") + F.col("db")).where("cost <= most_cost")
        pair = Window.partitionBy("search", "a", "b")
        first = met.groupBy("search", "a", "b").agg(F.min("cost").alias("cost"))
        met = met.join(F.broadcast(first), ["search", "a", "b", "cost"])
        if all(x.most is not None for x in asked.values()):
            met = met.withColumn("i", F.row_number().over(pair.orderBy("u"))).where(F.col("i") <= max(x.most for x in asked.values()))
        for r in met.select("search", "u").distinct().collect():  # at most max_trees a pair of groups
            out[r.search][1].add(r.u)
    remove_folder(g.spark, folder)
    return out


def _together(g: Graph, searches: dict, edges: DataFrame | None = None) -> dict:
    """key → the result of each search, a generator that gives what it wants and is sent the rows; all searches take a step together."""
    waiting, out = {}, {}

    def step(key, rows) -> None:
        try:
            waiting[key] = searches[key].send(rows)
        except StopIteration as end:
            out[key] = end.value

    for key in searches:
        step(key, None)
    while waiting:
        asked, number = dict(waiting), {key: n for n, key in enumerate(searches)}
        waiting.clear()
        kinds: dict[tuple, dict] = {}
        for key, w in asked.items():
            kinds.setdefault((type(w), w.kind if isinstance(w, Hubs) else isinstance(w, Fans) or w.most is None, isinstance(w, Wanted) and w.last), {})[number[key]] = w
        for (kind, *_), part in kinds.items():
            rows = {Wanted: neighbours, Fans: fans, Hubs: about_hubs}[kind](g, part, edges)
            for key in [key for key in asked if number[key] in rows]:
                step(key, rows.pop(number[key]))
    return out


class Parent(NamedTuple):
    v: str
    p: str
    forward: bool


class LocalSearch:
    """The state of a search as long as few rows are reached: (group, vertex) → [distance, parents, refused], by the same steps as Search."""

    def __init__(self, g: Graph, seeds: list[tuple[int, str]], liked: list[str], budget: int, w_query: int, w_default: int, edges: DataFrame | None, strategy: str, most: int, max_trees: int | None = None):
        self.max_trees = max_trees
        #: What stays in the tables: (group, v, p, forward) → distance of these neighbours; how many of them by (group, distance) and first parent; levels that were admitted.
        self.hubs: dict[tuple, int] = {}
        self.buckets: dict[tuple[int, int], dict[str, int]] = {}
        self.closed: set[tuple[int, int]] = set()
        self.g, self.seeds, self.liked, self.budget, self.edges, self.strategy, self.most = g, seeds, liked, budget, edges, strategy, most
        self.w_query, self.w_default = w_query, w_default
        self.round, self.cut = 0, False
        self.expanded: dict[str, int] = {}
        self.done: set[tuple[int, str]] = set()
        self.reached: dict[tuple[int, str], list] = {x: [0, [], False] for x in seeds}
        self.groups = sorted({x for x, _ in self.reached})

    def _open(self):
        return ((k, r) for k, r in self.reached.items() if not r[2] and k not in self.done)

    def open_levels(self, groups) -> dict[int, int]:
        out: dict[int, int] = {}
        for (x, _), r in self._open():
            if x in groups:
                out[x] = min(r[0], out.get(x, r[0]))
        for x, far in self.buckets:
            if x in groups and (x, far) not in self.closed:
                out[x] = min(far, out.get(x, far))
        return out

    def meetings(self) -> dict[tuple[int, int], int]:
        at: dict[str, list] = {}
        for (x, v), r in self.reached.items():
            at.setdefault(v, []).append((x, r[0]))
        out: dict[tuple[int, int], int] = {}
        for rows in at.values():
            for (a, da), (b, db) in itertools.combinations(sorted(rows), 2):
                out[a, b] = min(da + db, out.get((a, b), da + db))
        return out

    def part_levels(self, joined: set[int], part: set[str]) -> dict[int, int]:
        out: dict[int, int] = {}
        for (x, v), r in self.reached.items():
            if v in part and x not in joined:
                out[x] = min(r[0], out.get(x, r[0]))
        return out

    def parents(self, groups: tuple) -> dict[tuple[int, str], list]:
        return {k: r[1] for k, r in self.reached.items() if k[0] in groups and k[1] in self.expanded}

    def spots(self, groups: tuple, cost: int, most: int | None) -> list[tuple]:
        a, b = groups
        met = sorted(v for x, v in self.reached if x == a and (b, v) in self.reached and self.reached[a, v][0] + self.reached[b, v][0] == cost)
        return [(v, self.reached[a, v][1], self.reached[b, v][1]) for v in met[:most]]

    def part_spots(self, group: int, part: set[str], cost: int, most: int | None) -> list[tuple]:
        met = sorted(v for x, v in self.reached if x == group and v in part and self.reached[x, v][0] == cost)
        return [(v, self.reached[group, v][1]) for v in met[:most]]

    def refusals(self):
        own = len({v for (_, v), r in self.reached.items() if r[2]})
        if not self.closed & set(self.buckets):
            return own
        return own + (yield Hubs("count", self.hubs, {v for _, v in self.reached}, some=frozenset(self.closed)))

    def _level(self, group: int, dist: int) -> list[tuple[str, str]]:
        return [(v, _first(r[1])) for (x, v), r in self._open() if x == group and r[0] == dist]

    def admit(self, group: int, dist: int):
        """As a distributed search does; a hub's neighbours are refused by their number, and listed where the budget might do for them."""
        level = self._level(group, dist)
        hubs = dict(self.buckets.get((group, dist), {})) if (group, dist) not in self.closed else {}
        few = [v for v, n in hubs.items() if n - len(level) <= self.budget]  # some may have been listed since they were counted
        if few:
            listed = yield Hubs("list", self.hubs, {v for _, v in self.reached}, some=frozenset((group, dist, v) for v in few))
            yield from self.settle(False, listed)
            level = self._level(group, dist)
        self.closed.add((group, dist))
        price: dict[str, int] = {}
        for v, parent in level:
            price[parent] = price.get(parent, 0) + (v not in self.expanded)
        for v in hubs.keys() - set(few):
            price[v] = price.get(v, 0) + hubs[v]
        left, start, stop = self.budget - len(self.expanded), set(), []
        for parent, cost in sorted(price.items(), key=lambda x: (x[1], x[0])):
            if cost <= left:
                start.add(parent)
                left -= cost
            else:
                stop.append(parent)
        return sorted(v for v, parent in level if parent in start), stop

    def put(self, group: int, e, far: int) -> None:
        """An edge to a vertex at a distance."""
        r = self.reached.setdefault((group, e.u), [far, [], False])
        if far < r[0]:
            r[0], r[1] = far, []
        if far == r[0] and (parent := Parent(e.v, e.p, e.forward)) not in r[1]:
            r[1] = sorted([*r[1], parent])

    def settle(self, fresh: bool, more=frozenset()):
        """Lists those neighbours of hubs that the search has reached otherwise, and `more`; with fresh hubs also where the hubs of two groups meet, and counts the others."""
        if fresh:
            cost = self.meetings().get(tuple(self.groups)) if len(self.groups) == 2 and self.strategy == "both" else None
            self.buckets, met = yield Hubs("meet", self.hubs, {v for _, v in self.reached}, None if self.max_trees is None else self.max_trees + 1, cost)
            more = frozenset(more) | met
        ends = frozenset(more) | {v for _, v in self.reached}
        rows = yield Wanted(sorted({h[1] for h in self.hubs}), None, self.liked, (True, True), ends)
        for e in rows:
            for x in self.groups:
                far = self.hubs.get((x, e.v, e.p, e.forward))
                if far is not None:
                    before = self.reached.get((x, e.u))
                    if before is None or far < before[0]:
                        self.reached[x, e.u] = [far, [], (x, far) in self.closed]
                    self.put(x, e, far)

    def useless(self, group: int, dist: int) -> tuple[tuple[bool, bool], frozenset[str]]:
        """(whether vertices reached by a step of a liked and of another predicate are of no use where the other group has not met them, what it has met).

        Two groups that have met at a cost: what one reaches so far off that the other could come there only beyond that cost lies on no path of the trees and is never
        expanded, as the search ends before. So a hub's neighbours need not be listed then.
        """
        cost = self.meetings().get(tuple(self.groups)) if len(self.groups) == 2 and self.strategy == "both" else None
        if cost is None:
            return (False, False), frozenset()
        other = next(x for x in self.groups if x != group)
        level = self.open_levels([other]).get(other, cost)
        least = level + min(1, self.w_query, self.w_default)
        hub = min((d for h, d in self.hubs.items() if h[0] == other), default=1 << 30)  # the other's hubs may be met too
        far = tuple(dist + w + min(least, hub) > cost for w in (self.w_query, self.w_default))
        return far, frozenset(v for x, v in self.reached if x == other) if any(far) else frozenset()

    def grow(self, group: int, dist: int, vertices: list[str], stopped: list[str]):
        """Expands a level, with the edges that it is sent. None, or where too much would be reached the search as a distributed one."""
        rows, fresh = [], []
        if vertices:
            self.round += 1
            room = self.most - len(self.reached)
            wanted = Wanted(vertices, max(1, room + 1), self.liked, *self.useless(group, dist))
            rows = yield wanted
            if rows is None or len(rows) > room:
                fresh = yield Fans(wanted)
                rows = yield wanted._replace(hubs=frozenset(fresh), last=True)
            if len(rows) > room:
                other = self.distributed()
                yield from other.grow(group, dist, vertices, stopped)
                return other
        self.done |= {(group, v) for v in vertices}
        for v in vertices:
            self.expanded.setdefault(v, dist)
        for k, r in self.reached.items():
            if k[0] == group and r[0] == dist and k not in self.done and _first(r[1]) in stopped:
                r[2] = True
        for e in rows:
            self.put(group, e, self._after(dist, e.p))
        self.hubs |= {(group, v, p, forward): self._after(dist, p) for v, p, forward in fresh}
        if self.hubs:
            yield from self.settle(bool(fresh))
        return None

    def _after(self, dist: int, p: str) -> int:
        return dist + (self.w_query if p in self.liked else self.w_default)

    def distributed(self) -> Search:
        seeds = self.g.spark.createDataFrame(self.seeds, "group_id int, vertex string")
        s = Search(self.g, seeds, self.liked, self.budget, self.w_query, self.w_default, self.edges, self.strategy)
        rows = [(x, v, d, [tuple(p) for p in parents], refused) for (x, v), (d, parents, refused) in self.reached.items()]
        held = self.g.spark.createDataFrame(rows, REACHED)
        if self.hubs:
            found = hub_edges(self.g, {0: Hubs("meet", self.hubs, {v for _, v in self.reached})}, self.edges).groupBy("group_id", "u")
            found = found.agg(F.min("far").alias("dist"), F.collect_list(F.struct("far", F.struct("v", "p", "forward").alias("parent"))).alias("all"))
            parents = F.array_sort(F.transform(F.filter("all", lambda x: x["far"] == F.col("dist")), lambda x: x["parent"]))
            closed = F.concat_ws(" ", "group_id", "dist").isin(*[f"{x} {d}" for x, d in sorted(self.closed)])
            held = held.unionByName(found.select("group_id", F.col("u").alias("vertex"), "dist", parents.alias("parents"), closed.alias("refused")))
        s.reached = s.save(held)
        s.expanded, s.done, s.cut = dict(self.expanded), set(self.done), self.cut
        return s

    def close(self) -> None:
        pass


def _first(parents: list) -> str:
    return min((p.v for p in parents), default="")


def connect_seeds(g: Graph, seeds: DataFrame, liked: list[str], budget: int = 100, w_query: int = W_QUERY, w_default: int = W_DEFAULT, strategy: str = "both", max_trees: int | None = 20, edges: DataFrame | None = None, local_rows: int = LOCAL_ROWS) -> Connection:
    """Joins all groups by light paths. strategy 'single' grows one group alone, for comparison.

    The first two groups to meet form the connected part; each further group joins where its distance to a
    vertex of that part, or to another group's reach, is least. A group stops when no open vertex can give a lighter path.
    Each round expands vertices of the budget or refuses children of one, so rounds end. Where more trees or paths are tied than max_trees,
    `capped` says so; None gives all of them.
    """
    rows = [(r.group_id, r.vertex) for r in seeds.select("group_id", "vertex").collect()]  # k for each literal
    return connect_many(g, {0: (rows, liked)}, budget, w_query, w_default, strategy, max_trees, edges, local_rows)[0]


def connect_many(g: Graph, seeds: dict, budget: int = 100, w_query: int = W_QUERY, w_default: int = W_DEFAULT, strategy: str = "both", max_trees: int | None = 20, edges: DataFrame | None = None, local_rows: int = LOCAL_ROWS, refusals: bool = True) -> dict:
    """key → what connect_seeds() gives for each (seeds as (group, vertex), liked predicates). Searches are independent and take their steps together, so a step is one job for all.

    They share BATCH_ROWS on the driver. Refused vertices are not counted where `refusals` says so.
    """
    most = min(local_rows, BATCH_ROWS // max(1, len(seeds)))

    def one(rows: list, liked: list[str]):
        s = LocalSearch(g, rows, liked, budget, w_query, w_default, edges, strategy, most, max_trees)
        made = [s.distributed() if len(s.reached) > most else s]
        try:
            return (yield from _connected(made, rows, strategy, max_trees, refusals))
        finally:
            made[-1].close()

    return _together(g, {key: one(rows, liked) for key, (rows, liked) in seeds.items()}, edges)


def _connected(made: list, seeds: list, strategy: str, max_trees: int | None, refusals: bool = True):
    """made: the search; where it becomes a distributed one, that is added."""
    s = made[-1]
    out = Connection(False)
    if len(s.groups) < 2:
        return out
    part: set[str] = set()
    joined: set[int] = set()
    paths: list[list[frozenset]] = []
    active = list(s.groups)
    while True:
        levels = s.open_levels(active if strategy == "both" else active[:1])
        best = _best(s, joined, part)
        if best is not None:
            bound = _bound(levels, joined, best[1], strategy)
            if best[0] <= bound:
                choices = _paths(s, best, part, max_trees)
                paths.append(choices)
                joined |= set(best[1])
                part |= {v for c in choices for e in c for v in (e[0], e[2])}
                if joined == set(s.groups):
                    break
                continue
        if not levels:
            if best is None:
                break
            choices = _paths(s, best, part, max_trees)
            paths.append(choices)
            joined |= set(best[1])
            part |= {v for c in choices for e in c for v in (e[0], e[2])}
            if joined == set(s.groups):
                break
            continue
        turn = min(levels, key=lambda x: (levels[x], s.groups.index(x) if strategy == "both" else 0))
        start, stop = yield from s.admit(turn, levels[turn])
        other = yield from s.grow(turn, levels[turn], start, stop)
        if other is not None:
            made.append(other)
            s = other
    out.expanded, out.rounds = sorted(s.expanded), s.round
    out.refused = (yield from s.refusals()) if refusals else 0
    if joined != set(s.groups):
        return out
    found: dict[frozenset, int] = {}
    own_seeds = {v for _, v in seeds}
    cut: list = []
    between = yield from _induced(s, {v for choices in paths for c in choices for e in c for v in (e[0], e[2])})
    for n, combo in enumerate(itertools.product(*paths)):
        if max_trees is not None and n == max_trees * 5:
            cut.append(n)
            break
        edges_ = {e for c in combo for e in c}
        keep = {v for e in edges_ for v in (e[0], e[2])}
        induced = {e for v in keep for e in between.get(v, ()) if e[0] in keep and e[2] in keep} | edges_
        terminals = keep & own_seeds
        for t in trees.spanning_trees(sorted(induced), max_trees, cut):
            t = trees.prune(t, terminals)
            found[t] = trees.cost(t)
    least = min(found.values())
    best_trees = sorted((sorted(t) for t, c in found.items() if c == least))
    out.capped = max_trees is not None and len(best_trees) > max_trees or bool(cut) or s.cut
    out.trees = [frozenset(t) for t in best_trees[:max_trees]]
    out.found, out.cost = True, least
    out.terminals = sorted({v for t in out.trees for e in t for v in (e[0], e[2])} & own_seeds)
    return out


def _best(s, joined: set[int], part: set[str]):
    """(cost, groups that it joins, kind) of the lightest path that adds a group; None if nothing meets."""
    options = []
    for (a, b), c in s.meetings().items():
        if not joined or (a in joined) != (b in joined):
            options.append((c, (a, b), "meet"))
    if joined and part:
        options += [(d, (x,), "part") for x, d in s.part_levels(joined, part).items()]
    return min(options, key=lambda o: (o[0], o[2] == "meet", o[1])) if options else None


def _bound(levels: dict[int, int], joined: set[int], groups: tuple, strategy: str) -> int:
    """No path still to be found is lighter than this."""
    if strategy == "single":
        return min(levels.values(), default=1 << 30)
    fresh = sorted(d for x, d in levels.items() if x not in joined)
    if joined:
        return fresh[0] if fresh else 1 << 30
    order = sorted(levels.values())
    return order[0] + order[1] if len(order) > 1 else 1 << 30


def _walks(s, rows: dict, group: int, v: str, most: int | None) -> list[frozenset]:
    """The edge sets of all lightest paths from a group's seeds to v; of more than `most` the search is marked as cut."""
    out: list[frozenset] = []
    stack: list[tuple[str, frozenset]] = [(v, frozenset())]
    while stack:
        if len(out) == most:
            s.cut = True
            break
        at, edges = stack.pop()
        parents = rows.get((group, at), [])
        if not parents:
            out.append(edges)
        for p in parents:
            e = (p.v, p.p, at) if p.forward else (at, p.p, p.v)
            stack.append((p.v, edges | {e}))
    return out


def _weighted(s, edges: frozenset) -> frozenset:
    return frozenset((a, p, b, s.w_query if p in s.liked else s.w_default) for a, p, b in edges)


def _paths(s, best, part: set[str], most: int | None) -> list[frozenset]:
    """All tied lightest paths (at most `most`, where that is given) that a meeting stands for. Parents are expanded vertices, so few rows come here."""
    cost, groups, kind = best
    rows = s.parents(groups)
    more = None if most is None else most + 1
    spots = s.spots(groups, cost, more) if kind == "meet" else s.part_spots(groups[0], part, cost, more)
    out: dict[frozenset, None] = {}
    for x in spots[:most]:
        if kind == "meet":
            rows |= {(groups[0], x[0]): x[1], (groups[1], x[0]): x[2]}
            for left in _walks(s, rows, groups[0], x[0], most):
                for right in _walks(s, rows, groups[1], x[0], most):
                    out.setdefault(_weighted(s, left | right))
        else:
            rows |= {(groups[0], x[0]): x[1]}
            for left in _walks(s, rows, groups[0], x[0], most):
                out.setdefault(_weighted(s, left))
    s.cut |= most is not None and (len(spots) > most or len(out) > most)
    return list(out)[:most]


def _induced(s, keep: set[str]):
    """Triples with both ends among the vertices of the tied paths, by their subject, from those vertices' expansions that were paid for: one job for all paths."""
    paid = sorted(v for v in keep if v in s.expanded)
    if not paid:
        return {}
    rows = yield Wanted(paid, None, s.liked, (True, True), frozenset(keep))
    out: dict[str, set] = {}
    for r in rows:
        a, b = (r.v, r.u) if r.forward else (r.u, r.v)
        out.setdefault(a, set()).add((a, r.p, b, s.w_query if r.p in s.liked else s.w_default))
    return out


def rooted(q: SelectQuery) -> Term | None:
    """The variable from which every literal of a query is reached along the edges' own direction, so that the query restricts this one thing; else None."""
    ahead: dict[Term, set[Term]] = {}
    for p in q.patterns:
        ahead.setdefault(p.s, set()).add(p.o)
    ends = {p.o for p in q.patterns if p.o.kind == "literal"}
    for root in sorted((t for t in ahead if t.kind == "var"), key=lambda t: t.value):
        seen, stack = {root}, [root]
        while stack:
            for t in ahead.get(stack.pop(), set()) - seen:
                seen.add(t)
                stack.append(t)
        if ends <= seen:
            return root
    return None


def relax(g: Graph, q: SelectQuery, liked: list[str] | None = None, c: Cache | None = None, k: int = 10, **kw) -> tuple[Connection, list[SelectQuery]]:
    """(connection, suggested queries): each minimum tree as a query; trees that differ in their vertices alone are one. One literal, or literals that do not connect, give none."""
    liked = liked if liked is not None else sorted({p.p.value for p in q.patterns if p.p.kind == "iri"})
    made = connect_seeds(g, seed_groups(g, c, q, k), liked, **kw)
    shapes = [trees.tree_to_query(t, {v for v in made.terminals if v.startswith('"')}, q) for t in made.trees]
    return made, list(dict.fromkeys(shapes))


def relax_many(g: Graph, asked: dict, **kw) -> dict:
    """key → what relax() gives for each query without alternatives of its literals; the searches go side by side."""
    seeds = {key: ([(i, v) for i, v, _, _ in _own_seeds(q)], sorted({p.p.value for p in q.patterns if p.p.kind == "iri"})) for key, q in asked.items()}
    out = {}
    for key, made in connect_many(g, seeds, **kw).items():
        literals = {v for v in made.terminals if v.startswith('"')}
        out[key] = made, list(dict.fromkeys(trees.tree_to_query(t, literals, asked[key]) for t in made.trees))
    return out


def first_shapes(g: Graph, found: dict[int, list[SelectQuery]]) -> dict[int, SelectQuery]:
    """key → the first of its relaxed queries in suggest_shapes()'s order, if one has answers. Queries that differ in literals alone are counted by one plan."""
    every = [(key, q) for key, qs in found.items() for q in qs]
    parts = plan.count_many(g, [(n, q) for n, (_, q) in enumerate(every)])
    best: dict[int, tuple] = {}
    for r in reduce(DataFrame.unionByName, parts).collect() if parts else []:  # at most max_trees x queries
        key, q = every[r.qid]
        best[key] = min(best.get(key, (0,)), (-r.n_answers, text_of(q), r.qid))
    return {key: every[x[2]][1] for key, x in best.items()}


def suggest_shapes(g: Graph, q: SelectQuery, found: list[SelectQuery], cost: int | None = None) -> DataFrame:
    """Relaxed queries as suggestions, in the columns of suggest_terms(): old and new are the queries' texts, similarity is the inverse of the
    tree's cost. All are counted by one plan; those without answers are left out. found: at most max_trees queries."""
    rows = g.spark.createDataFrame([(-1 - i, "structure", -1, "", text_of(q), text_of(x), 1.0 / (cost or 1)) for i, x in enumerate(found)], "alt_id int, kind string, pattern_no int, position string, old string, new string, similarity double")
    counts = [plan.run(g, x).agg(F.count("*").alias("n_answers")).select(F.lit(-1 - i).alias("alt_id"), "n_answers") for i, x in enumerate(found)]
    if not counts:
        return rows.select("*", F.lit(0).cast("long").alias("n_answers"), F.lit(0).alias("rank"))
    counted = rows.join(reduce(DataFrame.unionByName, counts).where("n_answers > 0"), "alt_id")
    return counted.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n_answers"), "new")))  # at most max_trees rows


def store_edges(g: Graph, table: str, buckets: int = 32) -> DataFrame:
    """The edge table bucketed and sorted by vertex, so that an expansion reads the buckets of its vertices alone."""
    e = g.edges().select(F.when(F.col("v_kind") == "literal", F.concat(F.lit('"'), F.col("v"))).otherwise(F.col("v")).alias("v"), "p", F.when(F.col("u_kind") == "literal", F.concat(F.lit('"'), F.col("u"))).otherwise(F.col("u")).alias("u"), "forward")
    e.write.mode("overwrite").bucketBy(buckets, "v").sortBy("v").saveAsTable(table)
    return g.spark.table(table)


def ledger(connection: Connection, spark: SparkSession, strategy: str) -> DataFrame:
    """(strategy, expansions, refused, cost): a row of the cost measure."""
    return spark.createDataFrame([(strategy, len(connection.expanded), connection.refused, connection.cost)], "strategy string, expansions long, refused long, cost int")
