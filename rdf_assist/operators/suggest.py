"""Alternative terms: one predicate or literal of a query replaced by a similar one that has answers.

All alternatives of a place are counted by one plan: the constant becomes a variable that joins the
list of alternatives, so the data is read once and not once for each.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lexicon import lexicon, verbalize
from ..functions.similarity import jaro_winkler, length_band_join, may_reach
from ..plans import compile as plan
from ..plans.ir import Pattern, SelectQuery, Term
from .index import Cache
from .mapping import Graph

TERMS = "pattern_no int, position string, term string, kind string"


def query_terms(g: Graph, q: SelectQuery, iri_terms: str = "skip") -> DataFrame:
    """The constants of a query (TERMS). Subjects and objects that are IRIs are left out, or stand for their last part (iri_terms='label')."""
    return g.spark.createDataFrame(_term_rows(q, iri_terms), TERMS)


def _term_rows(q: SelectQuery, iri_terms: str = "skip") -> list[tuple]:
    rows = []
    for i, position, t in q.constants():
        if position == "p":
            rows.append((i, "p", t.value, "predicate"))
        elif t.kind == "literal":
            rows.append((i, position, t.value, "literal"))
        elif iri_terms == "label":
            rows.append((i, position, t.value.rpartition("/")[2], "literal"))
    return rows


def rank(df: DataFrame) -> DataFrame:
    order = Window.partitionBy("term").orderBy(F.desc("similarity"), "alternative")
    return df.withColumn("rank", F.row_number().over(order))


def top_k(df: DataFrame, k: int) -> DataFrame:
    return rank(df).where(F.col("rank") <= k)


def predicate_alternatives(g: Graph, terms: DataFrame, lex: DataFrame | None = None, theta: float = 0.7, strict: bool = False) -> DataFrame:
    """(term, alternative, similarity): dataset predicates similar to a term or to one of its verbalizations; the best of these counts.

    The predicate list is bounded and goes to every task; forms are few bytes but each costs a call for every predicate, so all cores share them.
    """
    lex = lex if lex is not None else lexicon(g.spark)
    forms = verbalize(terms.where("kind = 'predicate'").select("term").distinct(), lex)
    preds = g.spark.createDataFrame([(p,) for p in g.predicates], "alternative string")
    forms = forms.repartition(g.spark.sparkContext.defaultParallelism)
    scored = forms.join(F.broadcast(preds), F.col("term") != F.col("alternative")).withColumn("similarity", jaro_winkler("form", "alternative"))
    best = scored.groupBy("term", "alternative").agg(F.max("similarity").alias("similarity"))
    return best.where(F.col("similarity") > theta if strict else F.col("similarity") >= theta)


def literal_alternatives(terms: DataFrame, c: Cache, alpha: int = 2, beta: int = 3, theta: float = 0.7, include_indexed: bool = True) -> DataFrame:
    """(term, alternative, similarity): cached literals of nearly a term's length and similar to it.

    Bins of other lengths are not read; a native bound on the similarity goes before the costly function.
    """
    strings = c.residual.select("lit", "lit_len")
    if include_indexed:
        strings = strings.unionByName(c.terms.where("kind = 'literal'").select(F.col("term").alias("lit"), F.col("term_len").alias("lit_len")))
    own = terms.where("kind = 'literal'").select("term").distinct()
    near = length_band_join(own, strings, alpha, beta).where(F.col("term") != F.col("lit"))
    band = F.col("lit_len").between(F.length("term") - alpha, F.length("term") + beta)  # once more, as the costly bound may be tested before the join's condition
    scored = near.where(F.when(band, may_reach(F.col("term"), F.col("lit"), theta))).withColumn("similarity", jaro_winkler("term", "lit"))
    return scored.where(F.col("similarity") >= theta).select("term", F.col("lit").alias("alternative"), "similarity").distinct()


ALTERNATIVES = "alt_id int, pattern_no int, position string, old string, new string, similarity double"


def alternatives(g: Graph, c: Cache, q: SelectQuery, most: int = 50, **kw) -> DataFrame:
    """ALTERNATIVES of every place, the most similar first; at most `most` for each term."""
    return _numbered(g, _similar(g, c, q, most, **kw)[0])


def _similar(g: Graph, c: Cache, q: SelectQuery, most: int, **kw) -> tuple[list[tuple], list[tuple]]:
    """(alternatives as rows, and of each term that has more than `most` the last that is among them)."""
    return _similar_many(g, c, {0: q}, most, **kw)[0]


def _similar_many(g: Graph, c: Cache, asked: dict[int, SelectQuery], most: int, **kw) -> dict[int, tuple[list[tuple], list[tuple]]]:
    """qid → what _similar() gives of its query; the terms of all queries are compared by one plan."""
    places = {}
    for qid, q in asked.items():
        lost = hopeless(g, q)
        places[qid] = [x for x in _term_rows(q) if lost <= {x[0]} and (x[1] == "p" or x[0] not in lost)]
    wanted = sorted({(term, kind) for rows in places.values() for _, _, term, kind in rows})
    by: dict[tuple, list] = {}
    if wanted:
        terms = g.spark.createDataFrame(wanted, "term string, kind string")
        kinds = {"predicate": predicate_alternatives(g, terms, theta=kw.get("theta", 0.7)), "literal": literal_alternatives(terms, c, **kw)}
        kinds = {kind: df for kind, df in kinds.items() if any(k == kind for _, k in wanted)}
        found = [top_k(df, most + 1).select(F.lit(kind).alias("kind"), "term", "alternative", "similarity", "rank") for kind, df in kinds.items()]
        for r in reduce(DataFrame.unionByName, found).collect():  # most x constants
            by.setdefault((r.kind, r.term), []).append(r)
    out = {}
    for qid, rows in places.items():
        near, last = [], []
        for i, pos, term, kind in rows:
            own = by.get((kind, term), [])
            near += [(i, pos, -r.similarity, r.alternative, term) for r in own if r["rank"] <= most]
            if any(r["rank"] > most for r in own):
                last += [(i, pos, -r.similarity, r.alternative, term) for r in own if r["rank"] == most]
        out[qid] = sorted(near), last
    return out


def hopeless(g: Graph, q: SelectQuery) -> set[int]:
    """Patterns that no data can match whatever their constant: a literal where the predicate has entities alone, or the other way round, or a
    predicate that the data lacks."""
    out = {i for i, p in enumerate(q.patterns) if p.p.kind == "iri" and p.p.value not in g.predicates}
    for i, p in enumerate(q.patterns):
        if p.p.kind == "iri" and p.o.kind != "var":
            kinds = {e.facts[p.p.value].kind for e in g.entities if p.p.value in e.facts}
            if kinds and p.o.kind not in kinds:
                out.add(i)
    return out


def _numbered(g: Graph, rows: list[tuple]) -> DataFrame:
    return g.spark.createDataFrame([(n, i, pos, old, new, -s) for n, (i, pos, s, new, old) in enumerate(rows)], ALTERNATIVES)


def alternative_queries(q: SelectQuery, alts: list) -> list[tuple[int, SelectQuery]]:
    """(alt_id, query) with one term changed."""
    kind = {"p": "iri"}
    return [(a.alt_id, q.with_term(a.pattern_no, a.position, Term(kind.get(a.position, "literal"), a.new))) for a in alts]


def with_alternatives(g: Graph, q: SelectQuery, i: int, position: str, alts: DataFrame) -> DataFrame:
    """The bindings of q for every alternative of one place at once, with alt_id. alts(alt_id, new) is small."""
    p = q.patterns[i]
    rest = [x for n, x in enumerate(q.patterns) if n != i]
    if position == "p":
        names = [r.new for r in alts.select("new").distinct().collect()]
        own = reduce(DataFrame.unionByName, [plan.match(g, replace(p, p=Term("iri", n))).withColumn("_new", F.lit(n)) for n in names if n in g.predicates])
    else:
        own = plan.match(g, replace(p, **{position: Term("var", "_new")}))
    own = own.join(F.broadcast(alts.select("alt_id", F.col("new").alias("_new"))), "_new").drop("_new")
    if not rest:
        return own
    out = own
    for x in plan.order(g, rest, lambda y: (not set(y.variables()) & set(p.variables()), *plan.weight(g, y))):
        out = plan.join(out, plan.match(g, x))
    return out


def batch_counts(g: Graph, q: SelectQuery, alts: DataFrame) -> DataFrame:
    """(alt_id, n_answers) of alternatives with answers: a plan for each place, not for each alternative."""
    places = sorted({(r.pattern_no, r.position) for r in alts.select("pattern_no", "position").distinct().collect()})
    counts = [with_alternatives(g, q, i, pos, alts.where((F.col("pattern_no") == i) & (F.col("position") == pos))).groupBy("alt_id").agg(F.count("*").alias("n_answers")) for i, pos in places]
    if not counts:
        return g.spark.createDataFrame([], "alt_id int, n_answers long")
    return reduce(DataFrame.unionByName, counts)


def suggest_terms(g: Graph, c: Cache, q: SelectQuery, k: int = 10, refill: bool = False, **kw) -> DataFrame:
    """Suggestions with answers: the k / 2 most similar on the side of predicates and on that of literals.

    Alternatives are counted from the most similar on. If a side has too few with answers, or one that was not yet counted could be
    among the best, more of them are counted, so no alternative with answers is passed over.
    Places where no other constant can help, since another pattern can have no match, are left out.
    alt_id, kind, pattern_no, position, old, new, similarity, n_answers, rank. With refill a side that has
    fewer leaves its places to the other.
    """
    most = kw.pop("most", 50)
    while True:
        rows, last = _similar(g, c, q, most, **kw)
        alts = _numbered(g, rows)
        counts = batch_counts(g, q, alts)
        if not last:
            break
        counts = g.spark.createDataFrame(counts.collect(), "alt_id int, n_answers long")  # at most most x constants
        have = {r.alt_id for r in counts.collect()}
        enough = True
        for side in (True, False):
            best = sorted(((r[2], r[3]) for n, r in enumerate(rows) if n in have and (r[1] == "p") == side))[: k if refill else k // 2]
            enough &= all(len(best) == (k if refill else k // 2) and best[-1] <= (x[2], x[3]) for x in last if (x[1] == "p") == side)
        if enough:
            break
        most *= 8
    found = alts.join(counts, "alt_id").withColumn("kind", F.when(F.col("position") == "p", "predicate").otherwise("literal"))
    order = Window.partitionBy("kind").orderBy(F.desc("similarity"), "new", "alt_id")
    ranked = found.withColumn("rank", F.row_number().over(order))
    if refill:
        overall = Window.orderBy(F.col("rank") > k // 2, F.desc("similarity"), "new", "alt_id")  # bounded by the alternatives
        ranked = ranked.withColumn("place", F.row_number().over(overall)).where(F.col("place") <= k).drop("place")
    else:
        ranked = ranked.where(F.col("rank") <= k // 2)
    return ranked.select("alt_id", "kind", "pattern_no", "position", "old", "new", "similarity", "n_answers", "rank")


def with_answers(g: Graph, made: list[tuple[int, SelectQuery, int, str, str]]) -> set[int]:
    """The numbers of those (number, query, pattern_no, position, new) whose query has answers with its term changed. Queries that differ in
    literals alone are asked by one plan for each place."""
    groups: dict[tuple, list[tuple]] = {}
    for number, q, i, position, new in made:
        shape, held = plan.shape_of(q)
        groups.setdefault((shape, i, position), []).append((number, new, *held))
    parts = []
    for (shape, i, position), rows in groups.items():
        slots = [f"_k{n}" for n in range(len(rows[0]) - 2)]
        asked = g.spark.createDataFrame(rows, ", ".join(["_qid long", "_new string", *[f"{k} string" for k in slots]]))
        p = shape.patterns[i]
        if position == "p":
            names = sorted({new for _, new, *_ in rows})
            own = reduce(DataFrame.unionByName, [plan.match_open(g, replace(p, p=Term("iri", n)), slots).withColumn("_new", F.lit(n)) for n in names])
        else:
            p = replace(p, **{position: Term("var", "_new")})
            own = plan.match_open(g, p, ["_new", *slots])
        bound = tuple(p.variables())
        first = own.join(F.broadcast(asked), ["_new", *[k for k in slots if k in bound]])
        rest = [x for n, x in enumerate(shape.patterns) if n != i]
        parts.append(plan.join_asked(g, rest, asked, slots, first, bound).select("_qid").distinct())
    return {r["_qid"] for r in reduce(DataFrame.unionByName, parts).collect()} if parts else set()


def first_terms(g: Graph, c: Cache, asked: dict[int, SelectQuery], most: int = 50, **kw) -> dict[int, tuple[int, str, str]]:
    """qid → (pattern_no, position, new) of the most similar of the suggestions that suggest_terms() gives, if there is one.

    All queries go through a step together: it compares their terms by one plan and asks for answers by one.
    """
    out: dict[int, tuple[int, str, str]] = {}
    left = dict(asked)
    while left:
        near = _similar_many(g, c, left, most, **kw)
        made = [(qid, row) for qid, (rows, _) in near.items() for row in rows]
        alive = with_answers(g, [(n, left[qid], row[0], row[1], row[3]) for n, (qid, row) in enumerate(made)])
        best: dict[int, tuple] = {}
        for n, (qid, row) in enumerate(made):
            if n in alive:
                best[qid] = min(best.get(qid, (1.0,)), (row[2], row[3], n))
        for qid, (_, last) in near.items():
            if not last or (qid in best and all(best[qid][:2] <= (x[2], x[3]) for x in last)):
                del left[qid]
                if qid in best:
                    i, position, _, new, _ = made[best[qid][2]][1]
                    out[qid] = (i, position, new)
        most *= 8
    return out


def prefetch(g: Graph, q: SelectQuery, suggestions: DataFrame) -> DataFrame:
    """The answers of suggested queries by alt_id, for display on acceptance."""
    places = sorted({(r.pattern_no, r.position) for r in suggestions.select("pattern_no", "position").distinct().collect()})
    if not places:
        return g.spark.createDataFrame([], "alt_id int")
    parts = [with_alternatives(g, q, i, pos, suggestions.where((F.col("pattern_no") == i) & (F.col("position") == pos)).select("alt_id", "new")) for i, pos in places]
    names = [v for v in (q.variables or q.all_variables())]
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), [p.select("alt_id", *[v for v in names if v in p.columns]) for p in parts])


def describe(suggestions: DataFrame) -> DataFrame:
    """A sentence for each suggestion."""
    term = F.format_string("Use the %s \"%s\" in place of \"%s\": %d answers", "kind", "new", "old", "n_answers")
    shape = F.format_string("Ask %s instead: %d answers", "new", "n_answers")
    return suggestions.withColumn("text", F.when(F.col("kind") == "structure", shape).otherwise(term))
