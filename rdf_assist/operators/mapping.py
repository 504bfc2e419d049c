"""The given tables as a graph: entities, predicates, classes and triples.

Triples are virtual: every predicate knows the table columns that carry it, so a pattern with a bound
predicate scans these columns alone, with its filters pushed down, and the full triple table is only
built where every predicate is asked for.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load

COLUMNS = ["source", "s", "p", "o", "o_kind", "o_dtype", "o_lang", "o_len", "o_num", "o_ts"]

# Classes and their parents.
CLASSES = {
    "Thing": None, "Place": "Thing", "Region": "Place", "Nation": "Place",
    "Party": "Thing", "Customer": "Party", "Supplier": "Party",
    "AutomobileCustomer": "Customer", "BuildingCustomer": "Customer", "FurnitureCustomer": "Customer", "HouseholdCustomer": "Customer", "MachineryCustomer": "Customer",
    "Item": "Thing", "Part": "Item", "EconomyPart": "Part", "StandardPart": "Part", "SmallPart": "Part", "MediumPart": "Part", "LargePart": "Part", "PromoPart": "Part",
    "Transaction": "Thing", "Order": "Transaction", "FinishedOrder": "Order", "OpenOrder": "Order", "PendingOrder": "Order", "LineItem": "Transaction",
    "Content": "Thing", "Document": "Content", "EnglishDocument": "Document", "FrenchDocument": "Document", "GermanDocument": "Document", "SpanishDocument": "Document",
    "BenchmarkItem": "Content", "Page": "Content", "Origin": "Content", "Host": "Content", "Path": "Content", "Turn": "Content", "UserTurn": "Turn", "AssistantTurn": "Turn", "SystemTurn": "Turn", "Conversation": "Content",
}


@dataclass
class Fact:
    """A predicate of an entity: kind iri or literal, the value, and for literals data type and language."""

    kind: str
    value: Column
    dtype: str = "string"
    lang: Column | None = None
    named: tuple[str, tuple[str, ...]] | None = None  # of a link: the kind and the columns that its target's name is made of


@dataclass
class Entity:
    source: str
    table: str
    subject: Column
    facts: dict[str, Fact]
    shape: Callable[[DataFrame], DataFrame] = field(default=lambda df: df)

    @property
    def named(self) -> tuple[str, tuple[str, ...]] | None:
        """The kind and the columns that the subject's name is made of, where these are whole numbers."""
        return NAMED.get(self.table)


def iri(kind: str, *keys: str) -> Column:
    return F.concat(F.lit(f"{kind}/"), F.concat_ws("-", *[F.col(k).cast("string") for k in keys]))


def _link(kind: str, *keys: str) -> Fact:
    return Fact("iri", iri(kind, *keys), named=(kind, keys))


def _class(value: Column) -> Fact:
    return Fact("iri", F.concat(F.lit("class/"), value))


def _lit(column: str, dtype: str = "string", lang: Column | None = None) -> Fact:
    return Fact("literal", F.col(column), dtype, lang)


def _of(column: str, names: dict[str, str]) -> Column:
    out = F.lit(None).cast("string")
    for value, name in names.items():
        out = F.when(F.col(column) == value, name).otherwise(out)
    return out


def _lines(column: str) -> Callable[[DataFrame], DataFrame]:
    return lambda df: df.withColumn("_line", F.explode(F.array_distinct(F.split(column, "\n")))).where("_line <> ''")


TITLE, PAGE_LANG, LINK = r"<title>([^<]*)</title>", r'<html[^>]* lang="([^"]*)"', r'href="(/[^"]*)"'


def entities() -> list[Entity]:
    first = lambda c: F.initcap(F.lower(F.element_at(F.split(c, " "), 1)))
    lang = {"en": "EnglishDocument", "fr": "FrenchDocument", "de": "GermanDocument", "es": "SpanishDocument"}
    doc_lang = F.col("lang")
    return [
        Entity("geo", "region", iri("region", "r_regionkey"), {"type": _class(F.lit("Region")), "name": _lit("r_name")}),
        Entity("geo", "nation", iri("nation", "n_nationkey"), {"type": _class(F.lit("Nation")), "region": _link("region", "n_regionkey"), "name": _lit("n_name")}),
        Entity("sales", "customer", iri("customer", "c_custkey"), {
            "type": _class(F.concat(first("c_mktsegment"), F.lit("Customer"))), "nation": _link("nation", "c_nationkey"), "name": _lit("c_name"),
            "accountBalance": _lit("c_acctbal", "double"), "marketSegment": _lit("c_mktsegment")}),
        Entity("sales", "orders", iri("order", "o_orderkey"), {
            "type": _class(_of("o_orderstatus", {"F": "FinishedOrder", "O": "OpenOrder", "P": "PendingOrder"})), "customer": _link("customer", "o_custkey"),
            "orderStatus": _lit("o_orderstatus"), "totalPrice": _lit("o_totalprice", "double"), "orderDate": _lit("o_orderdate", "timestamp"), "orderPriority": _lit("o_orderpriority")}),
        Entity("sales", "lineitem", iri("lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), {
            "type": _class(F.lit("LineItem")), "order": _link("order", "l_orderkey"), "part": _link("part", "l_partkey"), "supplier": _link("supplier", "l_suppkey"),
            "quantity": _lit("l_quantity", "double"), "extendedPrice": _lit("l_extendedprice", "double"), "discount": _lit("l_discount", "double"), "tax": _lit("l_tax", "double"),
            "returnFlag": _lit("l_returnflag"), "lineStatus": _lit("l_linestatus"), "shipDate": _lit("l_shipdate", "timestamp")}),
        Entity("catalog", "supplier", iri("supplier", "s_suppkey"), {"type": _class(F.lit("Supplier")), "nation": _link("nation", "s_nationkey"), "name": _lit("s_name"), "accountBalance": _lit("s_acctbal", "double")}),
        Entity("catalog", "part", iri("part", "p_partkey"), {
            "type": _class(F.concat(first("p_type"), F.lit("Part"))), "name": _lit("p_name"), "brand": _lit("p_brand"), "partType": _lit("p_type"), "size": _lit("p_size", "integer"), "retailPrice": _lit("p_retailprice", "double")}),
        Entity("text", "documents", iri("document", "doc_id"), {"type": _class(_of("lang", lang)), "origin": Fact("iri", iri("origin", "source")), "characters": _lit("n_chars", "integer")}),
        Entity("text", "documents", iri("document", "doc_id"), {"line": Fact("literal", F.col("_line"), "string", doc_lang)}, _lines("text")),
        Entity("text", "documents", iri("origin", "source"), {"type": _class(F.lit("Origin")), "name": _lit("source")}, lambda df: df.select("source").distinct()),
        Entity("text", "benchmark", iri("benchmark", "item_id"), {"type": _class(F.lit("BenchmarkItem"))}),
        Entity("text", "benchmark", iri("benchmark", "item_id"), {"passage": Fact("literal", F.col("_line"))}, _lines("text")),
        Entity("text", "labels", iri("document", "doc_id"), {"quality": _lit("quality", "integer"), "toxic": _lit("toxic", "integer")}),
        Entity("web", "pages", iri("page", "page_id"), {
            "type": _class(F.lit("Page")), "host": Fact("iri", F.concat(F.lit("host/"), F.regexp_extract("url", "://([^/?#]*)", 1))), "url": _lit("url"),
            "title": Fact("literal", F.nullif(F.regexp_extract("html", TITLE, 1), F.lit("")), "string", F.nullif(F.regexp_extract("html", PAGE_LANG, 1), F.lit("")))}),
        Entity("web", "pages", iri("page", "page_id"), {"linksTo": Fact("iri", F.concat(F.lit("path"), F.col("_link")))},
               lambda df: df.withColumn("_link", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit(LINK), F.lit(1)))))),
        Entity("talk", "conversations", iri("turn", "conv_id", "turn"), {
            "type": _class(F.concat(F.initcap("role"), F.lit("Turn"))), "conversation": Fact("iri", iri("conversation", "conv_id")), "role": _lit("role")}),
        Entity("talk", "conversations", iri("turn", "conv_id", "turn"), {"utterance": Fact("literal", F.col("_line"))}, _lines("text")),
        Entity("log", "events", iri("event", "event_id"), {
            "type": _class(F.concat(F.initcap("event_type"), F.lit("Event"))), "user": Fact("iri", iri("user", "user_id")), "eventType": _lit("event_type"), "value": _lit("value", "double"),
            "at": _lit("ts", "timestamp"), "k": Fact("literal", F.get_json_object("props", "$.k"), "integer")}),
        Entity("vec", "embeddings", iri("vector", "vec_id"), {"type": _class(F.lit("Vector")), "cluster": _lit("label", "integer")}),
    ]


# The kind and the key columns of the entities whose names are made of whole numbers.
NAMED = {"region": ("region", ("r_regionkey",)), "nation": ("nation", ("n_nationkey",)), "customer": ("customer", ("c_custkey",)), "orders": ("order", ("o_orderkey",)), "lineitem": ("lineitem", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")), "supplier": ("supplier", ("s_suppkey",)), "part": ("part", ("p_partkey",))}


class Graph:
    """The graph of some sources of one folder of tables."""

    def __init__(self, spark: SparkSession, sf_dir: str, sources: tuple[str, ...] | None = None, schema_edges: bool = True):
        self.spark, self.sf_dir, self.schema_edges = spark, sf_dir, schema_edges
        self.entities = [e for e in entities() if sources is None or e.source in sources]
        self._tables: dict[str, DataFrame] = {}
        self.counts: dict[str, int] = {}  # triples by predicate, where harvest.count_predicates() was called: join orders go by them

    def table(self, name: str) -> DataFrame:
        if name not in self._tables:
            self._tables[name] = load(self.spark, self.sf_dir, name)
        return self._tables[name]

    @property
    def predicates(self) -> list[str]:
        own = {p for e in self.entities for p in e.facts}
        return sorted(own | ({"subClassOf", "label"} if self.schema_edges else set()))

    def facts(self, e: Entity, p: str, keys: tuple[str, ...] = ()) -> DataFrame:
        """The triples of one predicate of an entity; keys: further columns of its table to keep."""
        f = e.facts[p]
        value = f.value.cast("string")
        none = F.lit(None)
        df = e.shape(self.table(e.table)).select(
            F.lit(e.source).alias("source"), e.subject.alias("s"), F.lit(p).alias("p"), value.alias("o"), F.lit(f.kind).alias("o_kind"),
            F.lit(f.dtype if f.kind == "literal" else None).cast("string").alias("o_dtype"),
            (f.lang if f.lang is not None else none).cast("string").alias("o_lang"),
            (F.length(value) if f.kind == "literal" else none).cast("int").alias("o_len"),
            (f.value if f.dtype in ("double", "integer") else none).cast("double").alias("o_num"),
            (f.value if f.dtype == "timestamp" else none).cast("timestamp").alias("o_ts"), *keys,
        )
        return df.where("o is not null")

    def schema(self) -> DataFrame:
        """Triples of the class hierarchy: subClassOf and label."""
        rows = [("schema", f"class/{c}", "subClassOf", f"class/{p}", "iri", None) for c, p in CLASSES.items() if p] + [("schema", f"class/{c}", "label", c, "literal", "string") for c in CLASSES]
        made = self.spark.createDataFrame(rows, "source string, s string, p string, o string, o_kind string, o_dtype string")
        return made.withColumns({"o_lang": F.lit(None).cast("string"), "o_len": F.when(F.col("o_kind") == "literal", F.length("o")), "o_num": F.lit(None).cast("double"), "o_ts": F.lit(None).cast("timestamp")})

    def extent(self, p: str) -> DataFrame:
        """The triples of one predicate; none if no table carries it."""
        found = [self.facts(e, p) for e in self.entities if p in e.facts]
        if p in ("subClassOf", "label") and self.schema_edges:
            found.append(self.schema().where(F.col("p") == p))
        if not found:
            return self.schema().where(F.lit(False)).select(*COLUMNS)
        return reduce(DataFrame.unionByName, found)

    def triples(self, predicates: list[str] | None = None) -> DataFrame:
        return reduce(DataFrame.unionByName, [self.extent(p) for p in (predicates or self.predicates)])

    def kinds(self, kind: str) -> list[str]:
        """Predicates with objects of a kind."""
        own = {p for e in self.entities for p, f in e.facts.items() if f.kind == kind}
        return sorted(own | ({"label" if kind == "literal" else "subClassOf"} if self.schema_edges else set()))

    def literals(self) -> DataFrame:
        return self.triples(self.kinds("literal"))

    def links(self) -> DataFrame:
        return self.triples(self.kinds("iri"))

    def edges(self) -> DataFrame:
        """Each triple in both directions: (v, v_kind, p, u, u_kind, forward, source)."""
        t = self.triples()
        ahead = t.select(F.col("s").alias("v"), F.lit("iri").alias("v_kind"), "p", F.col("o").alias("u"), F.col("o_kind").alias("u_kind"), F.lit(True).alias("forward"), "source")
        back = t.select(F.col("o").alias("v"), F.col("o_kind").alias("v_kind"), "p", F.col("s").alias("u"), F.lit("iri").alias("u_kind"), F.lit(False).alias("forward"), "source")
        return ahead.unionByName(back)


def unpivot(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """(key, column, value) rows of the columns, as text."""
    return df.select(key, *[F.col(c).cast("string").alias(c) for c in columns]).unpivot([key], columns, "column", "value")


def class_hierarchy(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(c, p) for c, p in CLASSES.items()], "c string, parent string")


def class_closure(hierarchy: DataFrame, max_depth: int = 32) -> DataFrame:
    """(c, anc, depth) with depth 0 for the class itself; a cycle ends when its pairs repeat, or at max_depth."""
    spark = hierarchy.sparkSession
    hierarchy.where("parent is not null").createOrReplaceTempView("_hierarchy")
    hierarchy.select("c").distinct().createOrReplaceTempView("_classes")
    found = spark.sql(f"""
        WITH RECURSIVE up(c, anc, depth) AS (
            SELECT c, c, 0 FROM _classes
            UNION ALL
            SELECT up.c, h.parent, up.depth + 1 FROM up JOIN _hierarchy h ON up.anc = h.c WHERE up.depth < {max_depth} AND h.parent <> up.c)
        SELECT c, anc, min(depth) AS depth FROM up GROUP BY c, anc""")
    return found
