"""How significant a literal is: the number of distinct subjects that point at an entity that carries it."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import written
from . import tallies
from .harvest import LOG, MAX_CLASSES, EndpointCost, accepted_classes, bounded, cacheable, class_tree, fetch, types, walk
from .mapping import Entity, Graph, class_closure, class_hierarchy
from .repeats import bits_for, mark, repeated


def _sides(g: Graph, schema_edges: bool, **kw) -> tuple[DataFrame, DataFrame]:
    links = g.links() if schema_edges else g.triples([p for p in g.kinds("iri") if p not in ("type", "subClassOf")])
    carried = cacheable(g.literals(), **kw).select(F.col("s").alias("e"), F.col("o").alias("lit")).distinct()
    return links.select("s", F.col("o").alias("e")), carried


def significance(g: Graph, mode: str = "exact", schema_edges: bool = True, lgk: int = 12, **kw) -> DataFrame:
    """(lit, score) of every cacheable literal; literals that nothing points at score 0.

    exact: distinct subjects are counted. Where all names are made of whole numbers each subject is counted once at its entity and these
    counts meet the literals (_keyed()); else distinct (entity, subject) pairs meet the literals, in an inner join with
    the pairs on its left, so the rows of a popular entity can be split by adaptive execution. Literals that met nothing are added afterwards.
    hll: each entity's subjects become one sketch before the join, so a popular entity joins as one row.
    indegree: sums of in-degrees, an upper bound that is exact where a literal belongs to one entity.
    """
    if mode == "exact" and (met := _keyed(g, schema_edges, **kw)) is not None:
        return _with_unmet(cacheable(g.literals(), **kw).select(F.col("o").alias("lit")), met)
    links, carried = _sides(g, schema_edges, **kw)
    if mode == "indegree":
        sums = links.groupBy("e").agg(F.countDistinct("s").alias("n"))
        return carried.join(sums, "e", "left").groupBy("lit").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("score"))
    if mode == "hll":
        sketches = links.groupBy("e").agg(F.hll_sketch_agg("s", lgk).alias("k"))
        merged = carried.join(sketches, "e", "left").groupBy("lit").agg(F.hll_union_agg("k").alias("k"))
        return merged.select("lit", F.coalesce(F.hll_sketch_estimate("k"), F.lit(0)).cast("long").alias("score"))
    return _exact(links.distinct(), carried)


def _exact(pairs: DataFrame, carried: DataFrame) -> DataFrame:
    return _with_unmet(carried.select("lit"), pairs.join(carried, "e").groupBy("lit").agg(F.countDistinct("s").alias("score")))


def _with_unmet(lits: DataFrame, met: DataFrame) -> DataFrame:
    return lits.distinct().join(met, "lit", "left").select("lit", F.coalesce("score", F.lit(0)).cast("long").alias("score"))


def _keyed(g: Graph, schema_edges: bool, **kw) -> DataFrame | None:
    """(lit, score) of the literals that something points at, over key columns in place of names; None where the graph is not of that form.

    Subjects of different kinds differ, so each kind's subjects are counted alone and the counts of a literal are added. Within a kind, the few
    subjects whose fingerprints occur twice lose their repeats, the others are taken as they stand; then each is counted at the entity of each of its
    links, and counts, not subjects, meet the literals. That counts a subject twice only for a literal that entities of two kinds carry: these
    literals are set aside and counted by their distinct subjects.
    """
    if g.schema_edges and schema_edges:
        return None
    holders = [e for e in g.entities if any(f.kind == "literal" and f.dtype == "string" for f in e.facts.values())]
    linked = [(e, {p: f for p, f in e.facts.items() if f.kind == "iri" and p != "type"}) for e in g.entities]
    linked = [(e, fs) for e, fs in linked if fs]
    if any(e.named is None for e in holders) or any(e.named is None or any(f.named is None for f in fs.values()) for e, fs in linked):
        return None
    by_kind = {e.named[0]: e for e in holders}
    if len(by_kind) < len(holders) or len({e.named[0] for e, _ in linked}) < len(linked):
        return None
    counted = []
    for e, fs in linked:
        fs = {p: f for p, f in fs.items() if f.named[0] in by_kind}
        if len({f.named[0] for f in fs.values()}) < len(fs):
            return None
        if fs:
            keys, free = e.named[1], sorted({c for f in fs.values() for c in f.named[1]} - set(e.named[1]))
            counted.append((e, fs, free, g.table(e.table).select(*keys, *free).dropna(subset=list(keys))))
    if not counted:
        return None
    bits = bits_for(sum(g.table(e.table).count() for e, *_ in counted))
    counted = [(e, fs, free, rows.withColumn("h", mark(e.named[0], e.named[1], bits))) for e, fs, free, rows in counted]
    twice = written(repeated([rows.select("h") for *_, rows in counted], bits))
    parts, packets, links = [], [], 0
    for e, fs, free, rows in counted:
        keys = e.named[1]
        again = rows.join(twice, "h", "left_semi").drop("h").distinct()
        if free and not again.groupBy(*keys).count().where("count > 1").isEmpty():  # a subject with two targets of one kind
            return None
        rows = rows.drop("h") if twice.isEmpty() else rows.join(twice, "h", "left_anti").drop("h").unionByName(again)
        shared = None
        if len(fs) > 1:
            lits = reduce(DataFrame.unionByName, [_texts(g, by_kind[f.named[0]], **kw).select("o").distinct() for f in fs.values()]).withColumnRenamed("o", "lit")
            shared = lits.groupBy("lit").count().where("count > 1").select("lit")
            shared = None if shared.isEmpty() else shared
        packed = {}
        for f in fs.values():
            lits = _named(g, by_kind[f.named[0]], f.named[1], **kw)
            lits = lits if shared is None else lits.join(shared, "lit", "left_anti").select(*f.named[1], "lit")
            if len(f.named[1]) == 1:
                packed[links] = f.named[1][0]
                packets.append(tallies.names(lits, links))
                links += 1
            else:
                n = rows.groupBy(*f.named[1]).agg(F.count("*").alias("n"))
                parts.append(n.join(lits.distinct(), list(f.named[1])).groupBy("lit").agg(F.sum("n").alias("score")))
        if packed:
            packets.append(tallies.counts(rows, packed))
        if shared is not None:
            held = [_named(g, by_kind[f.named[0]], f.named[1], **kw).join(shared, "lit", "left_semi").distinct() for f in fs.values()]
            met = [rows.join(x, list(f.named[1])).select(*keys, "lit") for x, f in zip(held, fs.values(), strict=True)]
            parts.append(reduce(DataFrame.unionByName, met).distinct().groupBy("lit").agg(F.count("*").alias("score")))
    if packets:
        parts.append(tallies.met(packets))
    return reduce(DataFrame.unionByName, parts).groupBy("lit").agg(F.sum("score").alias("score"))


def _texts(g: Graph, e: Entity, keys: tuple[str, ...] = (), **kw) -> DataFrame:
    """The triples of an entity's cacheable literals, with further columns of its table."""
    return cacheable(reduce(DataFrame.unionByName, [g.facts(e, p, keys) for p, f in e.facts.items() if f.kind == "literal" and f.dtype == "string"]), **kw)


def _named(g: Graph, e: Entity, names: tuple[str, ...], **kw) -> DataFrame:
    """(names, lit): the cacheable literals of an entity, its key columns under the names of a link's."""
    return _texts(g, e, e.named[1], **kw).select(*[F.col(k).alias(n) for k, n in zip(e.named[1], names, strict=True)], F.col("o").alias("lit"))


def restricted(g: Graph, log: DataFrame) -> DataFrame:
    """Scores of the literals that a harvest log's accepted queries return, as issued class by class."""
    return significance(g).join(fetch(g, log).select("lit").distinct(), "lit", "left_semi")


def plan_significance(g: Graph, cost: EndpointCost, max_queries: int | None = None, schema_edges: bool = False) -> DataFrame:
    """The log (harvest.LOG) of asking for scores class by class from the roots: a query over a class returns a row for each distinct
    (entity, subject) pair whose entity is of the class or a subclass, and a class whose query fails is asked for child by child."""
    links, _ = _sides(g, schema_edges)
    closure = class_closure(class_hierarchy(g.spark)).select("c", "anc")
    own = links.distinct().join(types(g).withColumnRenamed("s", "e"), "e").groupBy("c").count()
    up = own.join(F.broadcast(closure), "c").groupBy(F.col("anc").alias("c")).agg(F.sum("count").alias("n_all"), F.sum(F.when(F.col("c") == F.col("anc"), F.col("count")).otherwise(0)).alias("n_direct"))
    sizes = {("significance", r.c): (r.n_all, r.n_direct) for r in bounded(up, MAX_CLASSES)}
    roots, children = class_tree(g)
    return g.spark.createDataFrame(walk(sizes, ["significance"], children, roots, cost, max_queries), LOG)


def walked(g: Graph, log: DataFrame, schema_edges: bool = False, **kw) -> DataFrame:
    """(lit, score) over the entities of the classes that a log of plan_significance() accepted: what the endpoint's limits leave of the scores."""
    links, carried = _sides(g, schema_edges, **kw)
    kinds = types(g).select(F.col("s").alias("e"), "c").join(F.broadcast(accepted_classes(g, log).select("c").distinct()), "c", "left_semi")  # classes
    return _exact(links.distinct(), carried.join(kinds, "e", "left_semi"))


def select_significant(scores: DataFrame, m: int = 40_000) -> DataFrame:
    """(lit, score) of the m most significant literals; ties by text."""
    return scores.orderBy(F.desc("score"), "lit").limit(m)
