"""Harvesting predicates and literals of an endpoint under its limits.

The walk is planned from one aggregation, the number of literals of each predicate over each class with its
subclasses; no endpoint query is issued inside the walk, and one semi-join then fetches all that was accepted.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .mapping import Graph, class_closure, class_hierarchy

MAX_CLASSES = 100_000


def bounded(df: DataFrame, most: int) -> list:
    """All rows; more than `most` are an error and not a cut."""
    rows = df.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} rows for a plan on the driver")
    return rows


def all_predicates(g: Graph) -> DataFrame:
    """Every predicate once; they are all cached."""
    return g.triples().select("p").distinct()


def literal_predicates(g: Graph) -> DataFrame:
    """(p, n_literals), the most frequent first."""
    return g.literals().groupBy("p").agg(F.count("*").alias("n_literals")).orderBy(F.desc("n_literals"), "p")


def predicate_stats(g: Graph) -> DataFrame:
    """(source, p, n_triples, n_literals, n_subjects): what source selection and join order go by."""
    return g.triples().groupBy("source", "p").agg(F.count("*").alias("n_triples"), F.count(F.when(F.col("o_kind") == "literal", 1)).alias("n_literals"), F.countDistinct("s").alias("n_subjects"))


def count_predicates(g: Graph) -> Graph:
    """g, with the number of triples of each predicate for join orders: a row a predicate comes to the driver."""
    g.counts = {r.p: r["count"] for r in g.triples().groupBy("p").count().collect()}
    return g


def cacheable(literals: DataFrame, max_len: int = 80, langs: tuple[str, ...] = ("en",), allow_untagged: bool = True) -> DataFrame:
    """Text literals of 1 to max_len characters in the wanted languages."""
    tagged = F.col("o_lang").isin(*langs)
    wanted = tagged | F.col("o_lang").isNull() if allow_untagged else tagged
    return literals.where((F.col("o_dtype") == "string") & F.col("o_len").between(1, max_len) & wanted)


def types(g: Graph) -> DataFrame:
    """(s, c) once for each entity, which has one class. Grouping by s also puts the rows where joins on s want them."""
    return g.extent("type").groupBy("s").agg(F.min(F.regexp_replace("o", "^class/", "")).alias("c"))


def extent_sizes(g: Graph, max_len: int = 80, langs: tuple[str, ...] = ("en",)) -> DataFrame:
    """(p, c, n_all, n_direct): cacheable literals of p over instances of c with its subclasses, and of c alone."""
    closure = class_closure(class_hierarchy(g.spark)).select("c", "anc")
    own = cacheable(g.literals(), max_len, langs).join(types(g), "s").groupBy("p", "c").count()
    up = own.join(F.broadcast(closure), "c")  # classes: at most MAX_CLASSES
    return up.groupBy("p", F.col("anc").alias("c")).agg(F.sum("count").alias("n_all"), F.sum(F.when(F.col("c") == F.col("anc"), F.col("count")).otherwise(0)).alias("n_direct"))


@dataclass(frozen=True)
class EndpointCost:
    """A stand-in for an endpoint's limits: more rows than reject_rows are refused up front, more than timeout_rows time out."""

    timeout_rows: int = 1000
    reject_rows: int | None = None
    page_size: int = 500

    def outcome(self, rows: int) -> str:
        if self.reject_rows is not None and rows > self.reject_rows:
            return "rejected"
        return "timeout" if rows > self.timeout_rows else "ok"

    def pages(self, rows: int) -> int:
        return max(1, -(-rows // self.page_size))


LOG = "query_no int, p string, c string, scope string, n_rows long, pages int, status string"


def walk(sizes: dict, predicates: list[str], children: dict, roots: list[str], cost: EndpointCost, max_queries: int | None, paged: bool = False) -> list[tuple]:
    """Predicates by frequency, classes from the roots: a class that fails is asked for its direct instances, then child by child.

    paged: what no smaller class is left for is asked page by page, each after the last value seen (keyset_page()), where a page is within the limits.
    """
    log: list[tuple] = []
    paged = paged and cost.outcome(cost.page_size) == "ok"

    def ask(p: str, c: str, scope: str, rows: int) -> str:
        if max_queries is not None and len(log) >= max_queries:
            return "budget"
        status = cost.outcome(rows) if scope != "paged" else "ok"
        last = status != "ok" and (scope == "direct" or not children.get(c))
        if last and not paged:
            status = f"{status}:lost"
        log.append((len(log), p, c, scope, rows, cost.pages(rows) if status == "ok" else 0, status))
        return ask(p, c, "paged", rows) if last and paged else status

    for p in predicates:
        pending = list(reversed(roots))
        while pending:
            c = pending.pop()
            total, direct = sizes.get((p, c), (0, 0))
            if not total:
                continue
            status = ask(p, c, "subtree", total)
            if status == "budget":
                return log
            if status != "ok" and children.get(c):
                if direct and ask(p, c, "direct", direct) == "budget":
                    return log
                pending += reversed(children[c])
    return log


def class_tree(g: Graph) -> tuple[list[str], dict[str, list[str]]]:
    """(roots, class → its children); a row a class."""
    hierarchy = {r.c: r.parent for r in bounded(class_hierarchy(g.spark), MAX_CLASSES)}
    children: dict[str, list[str]] = {}
    for c, parent in sorted(hierarchy.items()):
        if parent:
            children.setdefault(parent, []).append(c)
    return sorted(c for c, parent in hierarchy.items() if parent is None), children


def plan_harvest(g: Graph, cost: EndpointCost, max_queries: int | None = None, max_len: int = 80, langs: tuple[str, ...] = ("en",), paged: bool = False) -> DataFrame:
    """The log of the walk, a row for each logical query (LOG)."""
    rows = bounded(extent_sizes(g, max_len, langs), MAX_CLASSES * 10)
    sizes = {(r.p, r.c): (r.n_all, r.n_direct) for r in rows}
    roots, children = class_tree(g)
    predicates = [r.p for r in literal_predicates(g).collect()]
    return g.spark.createDataFrame(walk(sizes, predicates, children, roots, cost, max_queries, paged), LOG)


def type_frequency(g: Graph) -> DataFrame:
    """(c, n) of the classes that entities carry, for sources without a hierarchy."""
    named = g.extent("type").select(F.regexp_replace("o", "^class/", "").alias("c"))
    return named.groupBy("c").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "c")


def plan_harvest_flat(g: Graph, cost: EndpointCost, max_queries: int | None = None, max_len: int = 80, langs: tuple[str, ...] = ("en",)) -> DataFrame:
    """As plan_harvest() without a hierarchy: each predicate with each type, both by frequency."""
    own = cacheable(g.literals(), max_len, langs).join(types(g), "s").groupBy("p", "c").count()
    sizes = {(r.p, r.c): (r["count"], r["count"]) for r in own.collect()}
    order = [r.c for r in bounded(type_frequency(g), MAX_CLASSES)]
    predicates = [r.p for r in literal_predicates(g).collect()]
    return g.spark.createDataFrame(walk(sizes, predicates, {}, order, cost, max_queries), LOG)


def accepted_classes(g: Graph, log: DataFrame) -> DataFrame:
    """(p, c): the classes, with subclasses, that a log's accepted queries cover."""
    accepted = log.where("status = 'ok'").select("p", F.col("c").alias("anc"), "scope")
    closure = class_closure(class_hierarchy(g.spark)).select("c", "anc")
    return accepted.join(closure, "anc").where("scope = 'subtree' OR c = anc").select("p", "c")


def fetch(g: Graph, log: DataFrame, max_len: int = 80, langs: tuple[str, ...] = ("en",), flat: bool = False) -> DataFrame:
    """(source, lit, lit_len, lang, dtype): the distinct literals that the accepted queries return."""
    pairs = log.where("status = 'ok'").select("p", "c") if flat else accepted_classes(g, log)
    typed = cacheable(g.literals(), max_len, langs).join(types(g), "s")
    kept = typed.join(F.broadcast(pairs.distinct()), ["p", "c"], "left_semi")  # predicates x classes
    return kept.select("source", F.col("o").alias("lit"), F.col("o_len").alias("lit_len"), F.col("o_lang").alias("lang"), F.col("o_dtype").alias("dtype")).distinct()


def coverage(g: Graph, log: DataFrame) -> DataFrame:
    """(cached, eligible, share) of distinct literals of typed entities."""
    got = fetch(g, log).select("lit").distinct().agg(F.count("*").alias("cached"))
    all_ = cacheable(g.literals()).join(types(g), "s").select("o").distinct().agg(F.count("*").alias("eligible"))
    return got.crossJoin(all_).withColumn("share", F.round(F.try_divide("cached", "eligible"), 6))  # one row each


def cumulative(g: Graph) -> DataFrame:
    """(p, n_literals, running): literals gathered if predicates are taken by frequency."""
    counts = g.literals().groupBy("p").agg(F.count("*").alias("n_literals"))
    order = Window.orderBy(F.desc("n_literals"), "p").rowsBetween(Window.unboundedPreceding, 0)  # a row a predicate
    return counts.withColumn("running", F.sum("n_literals").over(order))


def keyset_page(df: DataFrame, column: str, after: str | None, size: int) -> DataFrame:
    """The next page in order of a column: what follows the last value seen, never a deep offset."""
    return (df if after is None else df.where(F.col(column) > after)).orderBy(column).limit(size)
