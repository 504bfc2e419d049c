"""Stand-ins for the compared systems, by what they do."""

from __future__ import annotations

import re
from collections import deque
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lexicon import WORDS
from ..functions.similarity import _winkler
from ..operators.harvest import types as entity_types
from ..operators.mapping import Graph
from ..plans import compile as plan
from ..plans.ir import Pattern, SelectQuery, iri, lit, var
from ..sources.tables import written

TOKEN = re.compile(r"[A-Za-z]+#\d+|[A-Za-z_]+\d*")


def _predicates(g: Graph, words: list[str], theta: float) -> list[str]:
    """The dataset predicate that each word names, by similarity or by the lexicon."""
    known = {v: p for p, vs in WORDS.items() for v in vs.split()}
    out = []
    for w in words:
        best = max(g.predicates, key=lambda p: (_winkler(w.lower(), p.lower()), p))
        if w in known and known[w] in g.predicates:
            out.append(known[w])
        elif _winkler(w.lower(), best.lower()) >= theta:
            out.append(best)
    return list(dict.fromkeys(out))


MAX_WORDS = 3


def spoken(phrase: str) -> list[str]:
    """The words of a phrase and the runs of up to MAX_WORDS of them, longest first: what may name an entity."""
    words = TOKEN.findall(phrase)
    return [" ".join(words[i : i + n]) for n in range(min(MAX_WORDS, len(words)), 0, -1) for i in range(len(words) - n + 1)]


def holders(g: Graph, texts: list[str]) -> dict[str, list[str]]:
    """text → the predicates that hold it as a text literal, of all texts at once; at most texts x predicates rows."""
    if not texts:
        return {}
    names = sorted({p for e in g.entities for p, f in e.facts.items() if f.kind == "literal" and f.dtype == "string"})
    found = reduce(DataFrame.unionByName, [g.extent(p) for p in names]).where(F.col("o").isin(*sorted(set(texts)))).select("o", "p").distinct()
    out: dict[str, list[str]] = {}
    for r in found.orderBy("o", "p").collect():
        out.setdefault(r.o, []).append(r.p)
    return out


def _named(phrase: str, held: dict[str, list[str]]) -> list[tuple[str, str]]:
    """(literal, predicate) of what a phrase names, in its order; a word within a longer name does not count again."""
    found: list[str] = []
    for x in spoken(phrase):
        if x in held and not any(x in y for y in found):
            found.append(x)
    return [(x, p) for x in sorted(found, key=phrase.find) for p in held[x]]


def _rest(phrase: str, entities: list[tuple[str, str]]) -> list[str]:
    for x, _ in entities:
        phrase = phrase.replace(x, " ")
    return TOKEN.findall(phrase)


def keyword_queries(g: Graph, phrase: str, held: dict[str, list[str]], theta: float = 0.9) -> list[SelectQuery]:
    """The queries of one or two patterns that a phrase may mean: one of its entities and one of its predicates, on either side."""
    out = []
    entities = _named(phrase, held)
    preds = _predicates(g, _rest(phrase, entities), theta)
    for value, own in entities:
        for p in [p for p in preds if p != own] or [own]:
            first = Pattern(var("e"), iri(own), lit(value))
            out.append(SelectQuery((first, Pattern(var("e"), iri(p), var("x"))), ("x",), distinct=True))
            if p in g.kinds("iri"):
                out.append(SelectQuery((first, Pattern(var("x"), iri(p), var("e"))), ("x",), distinct=True))
    return out


def keyword_qa(g: Graph, phrases: dict[int, list[str]], attempts: int = 3, theta: float = 0.9) -> tuple[DataFrame, dict[int, int]]:
    """NL-QA comparator: ((qid, answer), attempts used). Words become one predicate and one entity, and these a query of
    one or two patterns; up to `attempts` paraphrases are tried, and the first query with answers counts. It knows no vocabulary.

    The queries of all questions and attempts run together and their answers are written once; which of them had answers, a row a query, comes to the driver.
    """
    held = holders(g, [x for ps in phrases.values() for ph in ps[:attempts] for x in spoken(ph)])
    tried, number = [], 0
    for qid, ps in phrases.items():
        for n, phrase in enumerate(ps[:attempts], 1):
            for q in keyword_queries(g, phrase, held, theta):
                tried.append((number, qid, n, q))
                number += 1
    rows = written(plan.run_many(g, [(i, q) for i, _, _, q in tried]))
    alive = {r.qid for r in rows.select("qid").distinct().collect()}
    first: dict[int, tuple[int, int]] = {}
    for i, qid, n, _ in tried:
        if i in alive:
            first.setdefault(qid, (i, n))
    used = {qid: first[qid][1] if qid in first else min(attempts, len(ps)) for qid, ps in phrases.items()}
    chosen = g.spark.createDataFrame([(i, qid) for qid, (i, _) in first.items()], "i long, q long")
    return rows.join(F.broadcast(chosen), rows["qid"] == chosen["i"]).select(F.col("q").alias("qid"), "answer"), used


def factoid_qa(g: Graph, phrases: dict[int, str], theta: float = 0.95) -> DataFrame:
    """(qid, answer). Answers only where a phrase names exactly one entity and one predicate strictly, and the value is single; else abstains."""
    held = holders(g, [x for ph in phrases.values() for x in spoken(ph)])
    asked = []
    for qid, phrase in phrases.items():
        entities = _named(phrase, held)
        preds = _predicates(g, _rest(phrase, entities), theta)
        if len(entities) == 1 and len(preds) == 1 and preds[0] != entities[0][1] and preds[0] in g.kinds("iri"):
            value, own = entities[0]
            patterns = (Pattern(var("e"), iri(own), lit(value)), Pattern(var("e"), iri(preds[0]), var("y")), Pattern(var("y"), iri("name"), var("x")))
            asked.append((qid, SelectQuery(patterns, ("x",))))
    rows = plan.run_many(g, asked)
    return rows.groupBy("qid").agg(F.count("*").alias("n"), F.first("answer").alias("answer")).where("n = 1").select("qid", "answer")


def build_summary(g: Graph) -> DataFrame:
    """(class_s, p, class_o, n): how classes are linked; class_o is 'literal' for literals."""
    types = entity_types(g)
    subject = types.select(F.col("s"), F.col("c").alias("class_s"))
    target = types.select(F.col("s").alias("o"), F.col("c").alias("class_o"))
    links = g.triples([p for p in g.kinds("iri") if p not in ("type", "subClassOf")]).select("s", "p", "o").join(subject, "s").join(target, "o")
    lits = g.triples([p for p in g.kinds("literal") if p != "label"]).select("s", "p").join(subject, "s").withColumn("class_o", F.lit("literal"))
    return links.groupBy("class_s", "p", "class_o").agg(F.count("*").alias("n")).unionByName(lits.groupBy("class_s", "p", "class_o").agg(F.count("*").alias("n")))


def rewrite_by_summary(g: Graph, q: SelectQuery, summary: list, held: dict[str, list[str]] | None = None) -> SelectQuery | None:
    """Each pattern whose predicate points at entities but whose object is a literal is replaced by the shortest summary path from a class
    of its subject that ends with the predicate, and the literal's own predicate at the class reached. None if there is no path; terms must be right.

    held: the predicates that hold each literal; looked up if it is not given.
    """
    held = held if held is not None else holders(g, q.literals())
    carriers: dict[str, set[str]] = {}
    links: dict[str, list[tuple[str, str]]] = {}
    for r in summary:
        if r.class_o == "literal":
            carriers.setdefault(r.p, set()).add(r.class_s)
        else:
            links.setdefault(r.class_s, []).append((r.p, r.class_o))
    if any(p.p.kind != "iri" or p.p.value not in g.predicates for p in q.patterns):
        return None
    entity = g.kinds("iri")
    bent = [p for p in q.patterns if p.o.kind == "literal" and p.p.value in entity]
    out = [p for p in q.patterns if p not in bent]
    fresh = 0
    for s in dict.fromkeys(p.s for p in bent):
        own = [p for p in bent if p.s == s]
        options = []
        for c in sorted(links):
            paths = [_path(links, c, p.p.value, {x for name in held.get(p.o.value, []) for x in carriers.get(name, ())}) for p in own]
            if all(paths):
                options.append((sum(len(path) for path, _ in paths), c, paths))
        if not options:
            return None
        for p, (path, end) in zip(own, min(options, key=lambda o: o[:2])[2], strict=True):
            at = s
            for name in path:
                out.append(Pattern(at, iri(name), var(f"w{fresh}")))
                at = var(f"w{fresh}")
                fresh += 1
            name = next(n for n in held[p.o.value] if end in carriers.get(n, ()))
            out.append(Pattern(at, iri(name), p.o))
    return SelectQuery(tuple(dict.fromkeys(out)), q.variables, q.distinct)


def _path(links: dict, c: str, last: str, ends: set[str], most: int = 4) -> tuple[list[str], str] | None:
    """(the shortest chain of predicates from a class that ends with `last`, the class it reaches), a class that carries the literal."""
    queue = deque([(c, [])])
    while queue:
        at, path = queue.popleft()
        for p, o in sorted(links.get(at, [])):
            if p == last and o in ends:
                return [*path, p], o
            if len(path) + 1 < most:
                queue.append((o, [*path, p]))
    return None


def features(g: Graph, only: list[str] | None = None) -> DataFrame:
    """(e, f): outgoing predicate and object, and incoming predicate and subject, of every entity; only: of these predicates."""
    t = g.triples([p for p in g.predicates if p not in ("subClassOf", "label") and (only is None or p in only)])
    out = t.select(F.col("s").alias("e"), F.concat_ws("|", F.lit("out"), "p", "o_kind", "o").alias("f"))
    back = t.where("o_kind = 'iri'").select(F.col("o").alias("e"), F.concat_ws("|", F.lit("in"), "p", F.lit("iri"), "s").alias("f"))
    return out.unionByName(back)


def common(feats: DataFrame, entities: list[str]) -> DataFrame:
    """Features that all given entities share."""
    own = feats.where(F.col("e").isin(*entities)).distinct()
    return own.groupBy("f").agg(F.count("*").alias("k")).where(F.col("k") == len(entities)).select("f")


def with_features(feats: DataFrame, wanted: DataFrame, n: int) -> DataFrame:
    """(e) that have all wanted features."""
    hit = feats.join(F.broadcast(wanted), "f", "left_semi").distinct()  # wanted: the features of a few examples
    return hit.groupBy("e").agg(F.count("*").alias("k")).where(F.col("k") == n).select("e")


def learn_query(feats: DataFrame, positives: list[str], negatives: list[str]) -> DataFrame:
    """(e): entities that have what all positives share; features that no negative lacks are left away first."""
    if len(positives) < 2:
        raise ValueError("at least two positive examples are needed")
    shared = common(feats, positives)
    rows = sorted(r.f for r in shared.collect())
    if negatives and rows:
        lacking = {f: 0 for f in rows}
        for r in feats.where(F.col("e").isin(*negatives) & F.col("f").isin(*rows)).distinct().groupBy("f").agg(F.count("*").alias("k")).collect():
            lacking[r.f] = r.k
        useful = [f for f in rows if lacking[f] < len(negatives)]
        rows = useful or rows
    if not rows:
        return feats.select("e").limit(0)
    wanted = feats.sparkSession.createDataFrame([(f,) for f in rows], "f string")
    return with_features(feats, wanted, len(rows))


def _shared(feats: DataFrame, examples: DataFrame) -> DataFrame:
    """(qid, f): features that all examples (qid, e) of a question share."""
    n = examples.groupBy("qid").agg(F.count("*").alias("n"))
    return feats.join(F.broadcast(examples), "e").distinct().groupBy("qid", "f").agg(F.count("*").alias("k")).join(F.broadcast(n), "qid").where("k = n").select("qid", "f")


def _held(feats: DataFrame, wanted: DataFrame) -> DataFrame:
    """(e, fs): the entities that have one of the wanted features at least, with those that they have."""
    return feats.join(F.broadcast(wanted.select("f").distinct()), "f", "left_semi").groupBy("e").agg(F.collect_set("f").alias("fs"))  # wanted: the features of a few examples


def _learned(held: DataFrame, common: dict[str, int], positives: DataFrame, negatives: DataFrame) -> DataFrame:
    """(qid, e) of learn_query() for many questions at once: positives and negatives are (qid, e). held: _held() of all features that the first positives share, as later ones
    share no others; common: how many entities have each.

    Only entities with the rarest feature that a question wants are compared with its others.
    """
    feats = held.select("e", F.explode("fs").alias("f"))
    n_neg = negatives.groupBy("qid").agg(F.count("*").alias("nn"))
    shared = _shared(feats, positives)
    against = feats.join(F.broadcast(negatives), "e").distinct().groupBy("qid", "f").agg(F.count("*").alias("k"))
    marked = shared.join(against, ["qid", "f"], "left").join(F.broadcast(n_neg), "qid", "left").withColumn("useful", F.col("nn").isNull() | (F.coalesce("k", F.lit(0)) < F.col("nn")))
    own = Window.partitionBy("qid")
    wanted = marked.withColumn("any", F.bool_or("useful").over(own)).where("useful OR NOT any").select("qid", "f")
    per: dict[int, list[str]] = {}
    for r in wanted.select("qid", "f").collect():  # the features of a few examples
        per.setdefault(r.qid, []).append(r.f)
    rows = [(qid, min(fs, key=lambda f: (common.get(f, 0), f)), fs) for qid, fs in sorted(per.items())]
    asked = feats.sparkSession.createDataFrame(rows, "qid long, f string, all array<string>")
    hit = held.select("e", "fs", F.explode("fs").alias("f")).join(F.broadcast(asked), "f")  # a row a question
    return hit.where(F.size(F.array_except("all", "fs")) == 0).select("qid", "e")


def feedback_loop(feats: DataFrame, gold: DataFrame, keep, seeds: int = 2, marks: int = 3, narrow=None) -> DataFrame:
    """(qid, answer) for gold(qid, answer): answers outside gold become negatives, missed ones positives, until right or
    nothing changes. All questions go through a round together; questions of fewer than three answers are not asked.

    narrow(predicates) gives the features of some predicates alone, where that is cheaper. keep(df) writes a round's table. Rounds end, as each adds an example to every question that goes on.
    """
    number = Window.partitionBy("qid").orderBy("e")
    gold = keep(gold.select("qid", F.col("answer").alias("e")).distinct().withColumn("n", F.count("*").over(Window.partitionBy("qid"))).where("n >= 3").select("qid", "e"))
    positives = gold.withColumn("i", F.row_number().over(number)).where(F.col("i") <= seeds).select("qid", "e")
    negatives = gold.limit(0)
    first = keep(_shared(feats, positives))
    names = sorted({r.f.split("|")[1] for r in first.select("f").distinct().collect()}) if narrow else []  # the features of a few examples
    held = keep(_held(narrow(names) if names else feats, first))
    common = {r.f: r["count"] for r in held.select(F.explode("fs").alias("f")).groupBy("f").count().collect()}
    done, last = gold.limit(0), {}
    while True:
        got = keep(_learned(held, common, positives, negatives))
        both = got.withColumn("g", F.lit(1)).join(gold.withColumn("w", F.lit(1)), ["qid", "e"], "full")
        state = {r.qid: r for r in both.groupBy("qid").agg(F.count_if(F.col("w").isNull()).alias("extra"), F.count_if(F.col("g").isNull()).alias("missed"), F.sum(F.when(F.col("g") == 1, F.xxhash64("e").cast("decimal(38,0)"))).alias("print")).collect()}  # a row a question
        ends = [q for q, r in state.items() if r.extra + r.missed == 0 or last.get(q) == (r.extra, r.missed, r.print)]
        over = feats.sparkSession.createDataFrame([(q,) for q in ends], "qid long")
        done = done.unionByName(got.join(F.broadcast(over), "qid", "left_semi"))
        last = {q: (r.extra, r.missed, r.print) for q, r in state.items()}
        gold = gold.join(F.broadcast(over), "qid", "left_anti")
        if len(ends) == len(state):
            return done.select("qid", F.col("e").alias("answer"))
        more = both.join(F.broadcast(over), "qid", "left_anti")
        extra = more.where("w IS NULL").withColumn("i", F.row_number().over(number)).where(F.col("i") <= marks).select("qid", "e")
        missed = more.where("g IS NULL").withColumn("i", F.row_number().over(number)).where(F.col("i") <= marks).select("qid", "e")
        negatives = keep(negatives.unionByName(extra).distinct())
        positives = keep(positives.unionByName(missed).distinct())


def unaided_many(g: Graph, queries: dict[int, SelectQuery]) -> DataFrame:
    """(qid, answer) of users' queries as they are; those with a predicate that the data lacks have none."""
    return plan.run_many(g, [(i, q) for i, q in queries.items() if all(p.p.kind != "iri" or p.p.value in g.predicates for p in q.patterns)])


def unaided(g: Graph, q: SelectQuery) -> DataFrame:
    """The user's query as it is, without suggestions."""
    known = all(p.p.kind != "iri" or p.p.value in g.predicates for p in q.patterns)
    return plan.run(g, q) if known else g.spark.createDataFrame([], ", ".join(f"`{v}` string" for v in (q.variables or q.all_variables())))
