"""Small cases of what a review found on larger tables."""

import collections
import re
import random
from dataclasses import replace
from types import SimpleNamespace

import numpy as np
import pytest

from rdf_assist.baselines import systems
from rdf_assist.operators import harvest, index, relax, repeats, significance, suggest, tallies
from rdf_assist.operators.mapping import Graph
from rdf_assist.plans import compile as plan
from rdf_assist.plans.parse import parse
from rdf_assist.queries import ALL, literal_bins
from rdf_assist.sources.tables import SCHEMAS, load, written
from rdf_assist.streaming import streams


@pytest.fixture(scope="module")
def odd(spark, tiny, tmp_path_factory):
    """The smallest star with repeated line items, and with names that parts, suppliers and orders share."""
    d = str(tmp_path_factory.mktemp("odd"))
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        df = load(spark, tiny, t)
        if t == "supplier":
            df = df.selectExpr("s_suppkey", "CASE WHEN s_suppkey % 2 = 0 THEN 'blue bolt' WHEN s_suppkey = 1 THEN 'F' ELSE s_name END AS s_name", "s_nationkey", "s_acctbal")
        if t == "part":
            df = df.selectExpr("p_partkey", "CASE WHEN p_partkey % 3 = 0 THEN 'blue bolt' ELSE p_name END AS p_name", "p_brand", "p_type", "p_size", "p_retailprice")
        if t == "lineitem":
            df = df.unionByName(df.where("l_partkey % 4 = 0"))
        df.write.parquet(f"{d}/{t}.parquet")
    return d


def test_scores_by_keys(spark, odd):
    """Subjects are counted by their keys, with the same scores as by pairs of names, also where one points twice at a literal."""
    g = Graph(spark, odd, ("geo", "sales", "catalog"), False)
    met = {r.lit: r.score for r in significance._keyed(g, True).collect()}
    links, carried = significance._sides(g, True)
    want = {r.lit: r.score for r in significance._exact(links.distinct(), carried).collect()}
    assert met == {k: n for k, n in want.items() if n} and want["blue bolt"] > 0
    assert {r.lit: r.score for r in significance.significance(g).collect()} == want


def test_packed_fingerprints():
    """Fingerprints lose nothing when packed, alone in a bucket or many of one value."""
    rng = np.random.default_rng(1)
    for h in (np.array([0]), np.array([2**48 - 1, 0, 5, 5, 5]), np.repeat(7, 3), rng.integers(0, 2**48, 20_000)):
        back = np.concatenate([repeats.unpack(*r[1:]) for r in repeats.pack(h.astype(np.int64))])
        assert (back == np.sort(h)).all()


def test_repeated_keys_alone_are_sorted_out(spark, tiny, tmp_path):
    """Keys that occur twice are found, across tasks too; where there are none no key of a line item is grouped."""
    ids = spark.range(50_000).select(repeats.mark("x", ["id"]).alias("h"))
    more = spark.range(49_990, 50_020).select(repeats.mark("x", ["id"]).alias("h"))
    want = {r.h for r in spark.range(49_990, 50_000).select(repeats.mark("x", ["id"]).alias("h")).collect()}
    assert {r.h for r in repeats.repeated([ids, more]).collect()} == want
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        df = load(spark, tiny, t)
        (df.dropDuplicates(["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]) if t == "lineitem" else df).write.parquet(f"{tmp_path}/{t}.parquet")
    g = Graph(spark, str(tmp_path), ("geo", "sales", "catalog"), False)
    met = significance._keyed(g, True)
    assert not re.search(r"Aggregate\(keys=\[[^]]*l_linenumber", met._jdf.queryExecution().executedPlan().toString())
    links, carried = significance._sides(g, True)
    assert {r.lit: r.score for r in met.collect()} == {r.lit: r.score for r in significance._exact(links.distinct(), carried).where("score > 0").collect()}


def test_a_subject_with_two_targets(spark, odd, tmp_path):
    """An order key that stands for two customers is counted by pairs."""
    for t in SCHEMAS:
        if t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
            df = load(spark, odd, t)
            (df.unionByName(df.selectExpr("o_orderkey", "o_custkey + 1 AS o_custkey", *df.columns[2:])) if t == "orders" else df).write.parquet(f"{tmp_path}/{t}.parquet")
    assert significance._keyed(Graph(spark, str(tmp_path), ("geo", "sales", "catalog"), False), True) is None


def test_what_is_too_large_is_paged(spark, tiny):
    """A class without subclasses that exceeds the limit is asked page by page, and nothing is lost."""
    g = Graph(spark, tiny, ("geo", "sales", "catalog"), False)
    cost = harvest.EndpointCost(200, page_size=50)
    log = harvest.plan_harvest(g, cost, paged=True)
    assert log.where("status LIKE '%lost'").isEmpty() and not log.where("scope = 'paged'").isEmpty()
    every = {r.o for r in harvest.cacheable(g.literals()).select("o").distinct().collect()}
    assert {r.lit for r in harvest.fetch(g, log).collect()} == every
    assert {r.lit for r in harvest.fetch(g, harvest.plan_harvest(g, cost)).collect()} < every


def test_attempts_of_a_user_in_many_frames(spark, tmp_path):
    """a user's events come in several frames in any order."""
    spark.range(3000).selectExpr("id AS event_id", "timestamp_seconds(1704067200 + (id * 7919) % 3000)::timestamp_ntz AS ts", "id % 2 AS user_id", "CASE WHEN id % 5 = 0 THEN 'purchase' WHEN id % 7 = 0 THEN 'error' WHEN id % 3 = 0 THEN 'view' ELSE 'click' END AS event_type", "1.0 AS value", "'{}' AS props").coalesce(1).write.parquet(f"{tmp_path}/in")
    size = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50")
    try:
        stream = spark.readStream.schema(SCHEMAS["events"]).parquet(f"{tmp_path}/in")
        got = streams.sink(streams.attempts(stream), f"{tmp_path}/out", "append", f"{tmp_path}/state").collect()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
    want = streams.attempts_batch(streams.with_time(spark.read.schema(SCHEMAS["events"]).parquet(f"{tmp_path}/in"))).collect()
    assert collections.Counter(map(tuple, got)) == collections.Counter(map(tuple, want)) and got


def test_all_tied_trees(spark):
    """of 25 tied trees all are given where no limit is set."""
    pairs = [(f"{side}/{i}", "h/0") for side in "ab" for i in range(5)]
    table = spark.createDataFrame([(s, "p", o, True) for s, o in pairs] + [(o, "p", s, False) for s, o in pairs], "v string, p string, u string, forward boolean")
    seeds = spark.createDataFrame([(int(s[0] == "b"), s) for s, _ in pairs], "group_id int, vertex string")
    g = SimpleNamespace(spark=spark)
    every = relax.connect_seeds(g, seeds, ["p"], edges=table, max_trees=None)
    assert (every.cost, len(every.trees), every.capped) == (2, 25, False)
    assert relax.connect_seeds(g, seeds, ["p"], edges=table, max_trees=None, local_rows=0).trees == every.trees
    some = relax.connect_seeds(g, seeds, ["p"], edges=table)
    assert len(some.trees) == 20 and some.capped


def test_structures_that_restrict_one_thing():
    """a line item with its order's customer and its supplier is such a structure; a nation or a part that two things share is none."""
    right = parse('SELECT * WHERE { ?l order ?o . ?o customer ?c . ?c name "A" . ?l supplier ?s . ?s name "B" }')
    assert relax.rooted(right).value == "l"
    assert relax.rooted(parse('SELECT * WHERE { ?c nation ?n . ?s nation ?n . ?c name "A" . ?s name "B" }')) is None
    assert relax.rooted(parse('SELECT * WHERE { ?l order ?o . ?o customer ?c . ?c name "A" . ?l part ?p . ?m part ?p . ?m supplier ?s . ?s name "B" }')) is None


@pytest.mark.parametrize("name,table", [("class_closure", "orders"), ("complete_variable", "customer"), ("lexicon_verbalizations", "conversations"), ("study_deal", "events")])
def test_given_tables_are_read(spark, tiny, name, table):
    """F24, F25, F26, F32"""
    assert any(f"/{table}.parquet" in f for f in ALL[name](spark, tiny).inputFiles())


def _reads(df) -> set[str]:
    return {f.rsplit("/", 1)[1] for f in df.inputFiles() if "rdf_assist_shared" not in f}


def test_predicate_alternatives_of_a_table(spark, tiny):
    """the terms are the words of conversations, and what was asked before."""
    got = ALL["predicate_alternatives"](spark, tiny)
    assert "conversations.parquet" in _reads(got)
    assert {"vendor", "suppliedBy", "buyer"} <= {r.term for r in got.collect()}


def test_scores_of_a_table(spark, tiny):
    """the published counts, and those of events."""
    got = ALL["published_table_recomputed"](spark, tiny)
    assert "events.parquet" in _reads(got)
    names = {r.system for r in got.collect()}
    assert "the studied tool" in names and any(n.startswith("user ") for n in names)


def test_numbers_and_times_are_one_expression(spark, tiny):
    """a literal that stands for a number or a time meets its value in every spelling, and the plan does not grow with their number."""
    g = Graph(spark, tiny, ("geo", "sales", "catalog"), False)
    size = lambda names: relax.expand(g, names)._jdf.queryExecution().analyzed().toString().count("CaseWhen") + relax.expand(g, names)._jdf.queryExecution().analyzed().toString().count("CASE WHEN")
    assert size(['"7', '"8']) == size([f'"{i}' for i in range(7, 40)])
    day = str(load(spark, tiny, "orders").selectExpr("CAST(min(o_orderdate) AS date) AS d").first().d)
    at = load(spark, tiny, "orders").where(f"o_orderdate = timestamp_ntz '{day} 00:00:00'").count()
    got = collections.Counter((r.v, r.p) for r in relax.expand(g, ['"7', '"7.0', '"-0', f'"{day}', f'"{day} 00:00:00']).collect())
    n = load(spark, tiny, "part").where("p_size = 7").count()
    assert got['"7', "size"] == got['"7.0', "size"] == n > 0
    assert got['"-0', "discount"] == load(spark, tiny, "lineitem").where("l_discount = 0").count() > 0
    assert got[f'"{day}', "orderDate"] == got[f'"{day} 00:00:00', "orderDate"] == at


def test_short_fingerprints_are_two_to_three_bytes_a_row():
    """What is shuffled to find repeats, with as many bits as the rows ask for."""
    n = 400_000
    bits = repeats.bits_for(n)
    h = np.random.default_rng(1).integers(0, 1 << bits, n)
    found = [(base, width, len(gaps) // width, repeats.squeezed(width, gaps)) for _, base, width, gaps in repeats.pack(h, bits)]
    assert sum(len(x) for *_, x in found) < 2.5 * n
    back = np.concatenate([repeats.unpack(base, width, repeats.widened(width, k, x)) for base, width, k, x in found])
    assert (back == np.sort(h)).all()


def test_tallies_meet_literals(spark):
    """Rows counted at keys meet the keys' literals as a join would have it; nulls meet nothing, a literal carried twice counts once."""
    rows = spark.sql("SELECT IF(id % 10 = 0, NULL, id * id % 9001 - 50) AS a, CAST(id % 70 AS INT) AS b FROM range(20000)")
    lits = spark.sql("SELECT id - 100 AS a, concat('é', id % 13) AS lit FROM range(9000) UNION ALL SELECT id - 100, concat('é', id % 7) FROM range(9000) UNION ALL SELECT id, CAST(NULL AS STRING) FROM range(50)")
    more = spark.sql("SELECT id AS b, concat('n', id) AS lit FROM range(60)")
    got = tallies.met([tallies.counts(rows, {0: "a", 1: "b"}), tallies.names(lits, 0), tallies.names(more, 1)]).groupBy("lit").sum("score")
    want = rows.join(lits.distinct(), "a").groupBy("lit").count().unionByName(rows.join(more, "b").groupBy("lit").count()).where("lit IS NOT NULL")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_tallies_shuffle_packets_and_no_rows(spark):
    """200,000 orders with two literals each were 400,000 rows of a shuffle, and are less than three bytes each."""
    lits = spark.sql("SELECT id AS k, concat('status ', id * 7919 % 3) AS lit FROM range(200000) UNION ALL SELECT id, concat('priority ', id * 104729 % 5) FROM range(200000)")
    assert tallies.names(lits.coalesce(1), 0).selectExpr("sum(length(data))").first()[0] < 3 * 200_000


def test_alternatives_read_bins_of_wanted_lengths_alone(spark, tmp_path):
    """names of other lengths are left out where the bins are read, and are not compared first."""
    spark.sql("SELECT concat('Customer#', lpad(id, 9, '0')) AS lit, 0L AS score, '' AS folded, 18 AS lit_len FROM range(200) UNION ALL SELECT 'blue widget', 0L, '', 11").write.partitionBy("lit_len").parquet(f"{tmp_path}/residual")
    none = spark.sql("SELECT '' AS term, 'none' AS kind, 0 AS term_len")
    c = index.Cache(none, none, spark.read.schema("lit string, score long, folded string, lit_len int").parquet(f"{tmp_path}/residual"))
    found = suggest.literal_alternatives(spark.createDataFrame([("blue widgets", "literal")], "term string, kind string"), c)
    assert [r.alternative for r in found.collect()] == ["blue widget"]
    filters = re.findall(r"PartitionFilters: \[([^]]*)\]", found._jdf.queryExecution().executedPlan().toString())
    assert any("lit_len" in f and "18" not in f for f in filters)


def test_searches_together(spark, monkeypatch):
    """searches that take their steps together give what each gives alone, with one job a step, and hubs' neighbours that no tree can use are not listed."""
    g = SimpleNamespace(spark=spark)
    rows = []

    def add(s, p, o):
        rows.extend([(s, p, o, True), (o, p, s, False)])

    for i in (1, 2, 3):
        add(f"c{i}", "name", f'"a{i}')
        for j in range(3):
            add(f"o{i}{j}", "of", f"c{i}")
            add(f"o{i}{j}", "status", '"F')
            add(f"o{i}{j}", "type", "hub")
        add(f"c{i}", "at", "n")
    add("s", "name", '"b')
    add("s", "at", "n2")
    add("n", "in", "r")
    add("n2", "in", "r")
    for j in range(150):
        add(f"l{j}", "by", "s")
        if j < 5:
            add(f"l{j}", "status", '"F')
    for j in range(300):
        add(f"m{j}", "status", '"F')
        add(f"m{j}", "type", "hub")
    table = spark.createDataFrame(rows, "v string, p string, u string, forward boolean").cache()
    seeds = {i: [(0, f'"a{i}'), (1, '"b')] for i in (1, 2, 3)}
    liked = ["of", "by"]
    calls, listed = [], []
    expand, neighbours = relax.expand, relax.neighbours
    monkeypatch.setattr(relax, "expand", lambda *a, **k: calls.append(1) or expand(*a, **k))

    def counted(*a, **k):
        out = neighbours(*a, **k)
        listed.extend(r.u for x in out.values() for r in x)
        return out

    monkeypatch.setattr(relax, "neighbours", counted)
    alone, most = {}, 0
    for i, own in seeds.items():
        calls.clear()
        alone[i] = relax.connect_many(g, {i: (own, liked)}, edges=table)[i]
        most = max(most, len(calls))
    calls.clear(), listed.clear()
    together = relax.connect_many(g, {i: (own, liked) for i, own in seeds.items()}, edges=table)
    assert together == alone and len(calls) == most
    assert all(x.found and not x.capped for x in together.values()) and not any(u.startswith("m") for u in listed)
    far = relax.connect_many(g, {1: (seeds[1], liked)}, edges=table, local_rows=0)[1]  # a distributed search lists all
    assert replace(far, rounds=0) == replace(together[1], rounds=0)


def test_first_terms(spark, tiny):
    """the first suggestions of many queries at once are those of each alone, and no literal is tried where a pattern's predicate is in no table."""
    g = Graph(spark, tiny, ("geo", "sales", "catalog"), False)
    c = index.build_cache(g, 50)
    asked = {
        3: parse('SELECT ?n WHERE { ?c name "Customer#000000003" ; country ?x . ?x name ?n }'), 5: parse('SELECT ?n WHERE { ?c name "Customer#000000005" ; country ?x . ?x name ?n }'),
        7: parse('SELECT ?n WHERE { ?c marketSegment "BUILDIAG" ; name ?n }'), 8: parse('SELECT ?l WHERE { ?l customer "Customer#000000003" . ?l supplier "Supplier#000000003" }'),
    }
    assert suggest.hopeless(g, asked[3]) == {1}
    want = {}
    for i, q in asked.items():
        best = suggest.suggest_terms(g, c, q).orderBy("similarity", ascending=False).first()
        if best is not None:
            want[i] = (best.pattern_no, best.position, best.new)
    assert suggest.first_terms(g, c, asked) == want and want[3] == (1, "p", "nation") and want[7] == (0, "o", "BUILDING") and 8 not in want
    assert suggest.first_terms(g, c, {3: asked[3], 7: asked[7]}, most=1) == {3: want[3], 7: want[7]}


def test_counts_together(spark, tiny):
    """relaxed queries counted by shape have the numbers of rows that each has alone, and the first is the same."""
    g = Graph(spark, tiny, ("geo", "sales", "catalog"), False)
    texts = ['SELECT * WHERE { ?c name "Customer#00000000%d" ; nation ?x . ?s nation ?x ; name ?n }' % i for i in (1, 2)] + ['SELECT DISTINCT ?x WHERE { ?o customer ?c . ?c name "Customer#000000001" ; nation ?x }']
    qs = [(i, parse(t)) for i, t in enumerate(texts)]
    got = {r.qid: r.n_answers for df in plan.count_many(g, qs) for r in df.collect()}
    assert got == {i: n for i, q in qs if (n := plan.run(g, q).count())} and len(plan.count_many(g, qs)) == 2
    found = [q for _, q in qs]
    shown = relax.suggest_shapes(g, found[0], found, 8).orderBy("rank").first()
    assert relax.first_shapes(g, {4: found, 9: []}) == {4: found[-1 - shown.alt_id]}


def test_learner_and_bins(spark, tiny):
    """the learner gives the same where it reads the features of the wanted predicates alone, and terms have the same alternatives by unscored bins."""
    g = Graph(spark, tiny, ("geo", "sales", "catalog"), False)
    near = [(1, r.s) for r in g.extent("customer").where("o = 'customer/1'").select("s").collect()] + [(2, r.s) for r in g.extent("region").where("o = 'region/2'").select("s").collect()]
    gold, feats = spark.createDataFrame(near, "qid long, answer string"), systems.features(g)
    read = []
    narrow = lambda names: read.extend(names) or systems.features(g, names)
    got = [sorted(map(tuple, systems.feedback_loop(feats, gold, written, **kw).collect())) for kw in ({}, {"narrow": narrow})]
    assert got[0] == got[1] and {x for x in near if x[0] == 2} <= set(got[0]) and 0 < len(set(read)) < len(g.predicates)
    q = parse('SELECT ?n WHERE { ?c marketSegment "BUILDIAG" ; name "Customer#000000003" }')
    some = [suggest._similar(g, c, q, 5) for c in (literal_bins(spark, tiny), index.build_cache(g, 50))]
    assert some[0] == some[1] and some[0][0]


@pytest.mark.parametrize("seed,budget", [(2, 5)])
def test_searches_with_hubs(spark, monkeypatch, seed, budget):
    """searches that leave hubs' neighbours in the tables give what those that list all of them give, whatever the budget; the driver is sent few of them."""
    g, r = SimpleNamespace(spark=spark), random.Random(seed)
    rows, n = [], 60

    def add(s, p, o):
        rows.extend([(s, p, o, True), (o, p, s, False)])

    for i in range(n):
        add(f"x/{i:02d}", "in", f"h/{r.randrange(3)}")
        add(f"x/{i:02d}", "kind", f"k/{r.randrange(2)}")
        for _ in range(r.randrange(2)):
            add(f"x/{i:02d}", "to", f"x/{r.randrange(n):02d}")
    for i in range(3):
        add(f"h/{i}", "of", f"w/{i % 2}")
    table = spark.createDataFrame(sorted(set(rows)), "v string, p string, u string, forward boolean").cache()
    asked = {i: ([(x, f"{r.choice(['x/%02d' % r.randrange(n), 'h/%d' % r.randrange(3), 'w/0', 'k/1'])}") for x in range(2 + i % 2)], ["in", "of"]) for i in range(3)}
    sent = []
    neighbours = relax.neighbours
    monkeypatch.setattr(relax, "neighbours", lambda *a, **k: (lambda out: sent.append(sum(len(x or ()) for x in out.values())) or out)(neighbours(*a, **k)))
    whole = relax.connect_many(g, asked, budget=budget, edges=table, max_trees=None if seed % 2 else 3)
    listed = max(sent)
    monkeypatch.setattr(relax, "HUB", 4)
    for most in (40, 10):  # some become distributed ones
        monkeypatch.setattr(relax, "BATCH_ROWS", most * len(asked))
        sent.clear()
        apart = relax.connect_many(g, asked, budget=budget, edges=table, max_trees=None if seed % 2 else 3)
        for i, x in whole.items():
            assert (apart[i].found, apart[i].cost, apart[i].trees, apart[i].expanded, apart[i].refused, apart[i].capped) == (x.found, x.cost, x.trees, x.expanded, x.refused, x.capped), (i, most)
        assert max(sent) <= (most + 1) * len(asked) < listed or most == 40
