"""The experiment workloads on the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import compile as plan
from ..plans.ir import SelectQuery, lit
from ..plans.parse import parse
from ..sources.tables import load
from . import answers
from .federation import federated
from .index import Cache, build_cache
from .mapping import Graph
from .suggest import suggest_terms

STAR = ("geo", "sales", "catalog")


def star(spark: SparkSession, sf_dir: str, schema_edges: bool = False) -> Graph:
    return Graph(spark, sf_dir, STAR, schema_edges)


def cache(g: Graph, m: int = 1000) -> Cache:
    return build_cache(g, m)


TWO_HOPS = 'SELECT (COUNT(?c) AS ?n) WHERE { ?c a <class/MachineryCustomer> . ?c nation ?x . ?x region ?r . ?r name "ASIA" }'
MISSPELLED = 'SELECT ?c ?n WHERE { ?c marketSegment "MACHINARY" . ?c name ?n }'
PLURAL = 'SELECT ?p WHERE { ?p name "blue widgets" }'
WRONG_SHAPE = 'SELECT * WHERE { ?x customer "Customer#000000008" . ?x supplier "Supplier#000000003" }'


def w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities two hops from a named node."""
    return plan.run(star(spark, sf_dir), parse(TWO_HOPS))


def w2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A misspelled literal: suggestions with their answers."""
    g = star(spark, sf_dir)
    return suggest_terms(g, cache(g), parse(MISSPELLED))


def w3(spark: SparkSession, sf_dir: str, word: str = "99") -> DataFrame:
    """The accepted suggestion's answers, searched and ordered."""
    g = star(spark, sf_dir)
    q = parse(MISSPELLED).with_term(0, "o", lit("MACHINERY"))
    return answers.sort(answers.search(plan.run(g, q), word), "n")


def study_deal(spark: SparkSession, people: DataFrame | None = None) -> DataFrame:
    """(participant, category, slot, qid, warm_up, first_system): the participants, 16 if none are given, with 4 easy, 3 medium and 3 difficult of 27 questions, 9 of each kind.

    A participant's questions of a kind are every second one, in a round, from a place that differs by participant. The first easy one is the
    warm-up, whose data is dropped; the system used first alternates from question to question.
    """
    p, c, j = F.col("participant"), F.col("category"), F.col("slot")
    people = people if people is not None else spark.range(16).withColumnRenamed("id", "participant")
    kinds = people.withColumn("category", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(2).cast("long"))))
    slots = kinds.withColumn("slot", F.explode(F.sequence(F.lit(0).cast("long"), F.when(c == 0, 3).otherwise(2).cast("long"))))
    return slots.select("participant", "category", "slot", (9 * c + F.pmod(7 * p + 2 * j + c, F.lit(9))).alias("qid"), ((c == 0) & (j == 0)).alias("warm_up"), F.pmod(j + c, F.lit(2)).alias("first_system"))


def participant_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A study log read from events: it exercises the measures and is no evidence about people.

    Participant, question, system and outcome follow fixed rules of user, props, event id and type; what is kept is a participant's work on
    the questions dealt to them, without the warm-up.
    """
    e = load(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("long")
    dealt = study_deal(spark).where("NOT warm_up").select("participant", "qid")
    return e.select(
        F.pmod("event_id", F.lit(2)).alias("system"), F.pmod("user_id", F.lit(16)).alias("participant"), F.pmod(k, F.lit(27)).alias("qid"),
        "event_id", "ts", (F.col("event_type") == "click").alias("click"),
        F.when(F.col("event_type") == "purchase", "success").when(F.col("event_type") == "error", "gave_up").alias("outcome"), F.col("value").alias("seconds"),
        F.when(F.col("event_type") == "view", "structure").when(F.col("event_type") == "signup", "literal").when((F.col("event_type") == "click") & (F.pmod("event_id", F.lit(5)) == 0), "predicate").alias("accepted"),
    ).withColumn("category", F.floor(F.col("qid") / 9)).join(F.broadcast(dealt), ["participant", "qid"], "left_semi")


def user_verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(system, qid, processed, right, partial) read from events by fixed rules: each user answers fifty questions, an event's by its id. A purchase
    is a right answer, an error a wrong one, both a partial one."""
    e = load(spark, sf_dir, "events").select(F.concat(F.lit("user "), "user_id").alias("system"), F.pmod("event_id", F.lit(50)).alias("qid"), "event_type")
    seen = e.where("event_type IN ('purchase', 'error')").groupBy("system", "qid").agg(F.bool_or(F.col("event_type") == "purchase").alias("hit"), F.bool_or(F.col("event_type") == "error").alias("miss"))
    return seen.select("system", "qid", F.lit(True).alias("processed"), F.expr("hit AND NOT miss").alias("right"), F.expr("hit AND miss").alias("partial"))


@dataclass(frozen=True)
class Question:
    """typed: what a user writes at first, with right terms, a misspelling, a synonym or a wrong shape; gold: the right query."""

    qid: int
    category: str
    phrase: str
    typed: str
    gold: str
    factoid: bool = False


def questions(n: int = 50) -> list[Question]:
    """Instances of the question shapes, with constants taken in order of their keys."""
    seg = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    regions = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]
    out: list[Question] = []

    def add(category, phrase, typed, gold, factoid=False):
        out.append(Question(len(out), category, phrase, typed, gold, factoid))

    for i in range(10):
        c = f"Customer#{i:09d}"
        right = f'SELECT ?n WHERE {{ ?c name "{c}" ; nation ?x . ?x name ?n }}'
        typed = right if i % 3 else right.replace("nation ?x", "country ?x")
        add("easy", f"{c} nation", typed, right, True)
    for i, s in enumerate(seg):
        right = f'SELECT ?n WHERE {{ ?c marketSegment "{s}" ; name ?n }}'
        add("easy", f"customer names marketSegment {s}", right.replace(s, s[:-2] + "A" + s[-1]) if i % 2 else right, right)
    for r in regions:
        right = f'SELECT ?n WHERE {{ ?s a <class/Supplier> ; nation ?x ; name ?n . ?x region ?r . ?r name "{r}" }}'
        add("medium", f"suppliers region {r}", right.replace("nation ?x", "country ?x"), right)
    for i, s in enumerate(seg):
        r = regions[i]
        right = f'SELECT ?n WHERE {{ ?c marketSegment "{s}" ; nation ?x ; name ?n . ?x region ?r . ?r name "{r}" }}'
        add("medium", f"customers {s} region {r}", right.replace('"' + s, '"' + s[:-1] + "I") if i % 2 else right, right)
    for i in range(10):
        c = f"Customer#{i + 20:09d}"
        right = f'SELECT ?o WHERE {{ ?o customer ?c . ?c name "{c}" }}'
        add("medium", f"orders customer {c}", right.replace("customer ?c", "buyer ?c") if i % 2 else right, right)
    for i in range(15):
        c, s = f"Customer#{i:09d}", f"Supplier#{i % 7:09d}"
        right = f'SELECT ?l WHERE {{ ?l order ?o ; supplier ?s . ?o customer ?c . ?c name "{c}" . ?s name "{s}" }}'
        add("difficult", f"line items customer {c} supplier {s}", f'SELECT ?l WHERE {{ ?l customer "{c}" . ?l supplier "{s}" }}', right)
    return out[:n]


def paraphrases(q: Question) -> list[str]:
    """Up to three ways to put a question, all with its own terms: as it is, the other way round, and as a sentence."""
    words = q.phrase.split(" ")
    return [q.phrase, " ".join(reversed(words)), f"which {q.phrase} are there"]


def gold(g: Graph, qs: list[Question]) -> DataFrame:
    """(qid, answer): the answers of the right queries, a plan for each shape of query."""
    return plan.run_many(g, [(q.qid, parse(q.gold)) for q in qs])


def typed_prefixes(spark: SparkSession, sf_dir: str, least: int = 3, most: int = 8) -> DataFrame:
    """(t): growing prefixes of the words of conversations and of star names, as typed."""
    words = load(spark, sf_dir, "conversations").select(F.explode(F.split(F.regexp_replace(F.lower("text"), "[^a-z ]", " "), " +")).alias("w"))
    names = load(spark, sf_dir, "part").select(F.col("p_name").alias("w")).unionByName(load(spark, sf_dir, "nation").select(F.col("n_name").alias("w")))
    every = words.unionByName(names).where(F.length("w") >= least).select("w").distinct()
    return every.select(F.explode(F.transform(F.sequence(F.lit(least), F.least(F.lit(most), F.length("w"))), lambda n: F.substring("w", 1, n))).alias("t")).distinct()


def w18(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two-hop count over three sources."""
    return federated(star(spark, sf_dir), parse(TWO_HOPS))


def chain(q: SelectQuery) -> list[str]:
    return [str(p.p) for p in q.patterns]
