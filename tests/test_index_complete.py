import random

import pytest
from pyspark.sql import functions as F

from rdf_assist.operators import complete, harvest, index, significance
from rdf_assist.operators.mapping import Graph, class_closure


@pytest.fixture(scope="module")
def star(spark, tiny):
    return Graph(spark, tiny, ("geo", "sales", "catalog"), False)


@pytest.fixture(scope="module")
def cache(star, tmp_path_factory):
    return index.store(index.build_cache(star, 60), f"file://{tmp_path_factory.mktemp('cache')}")


@pytest.fixture(scope="module")
def strings(cache):
    terms = [(r.term, r.kind, r.score) for r in cache.terms.collect()]
    rest = [r.lit for r in cache.residual.collect()]
    return terms, rest


def test_indexed_and_residual_split_the_cache(star, strings):
    terms, rest = strings
    literals = {t for t, k, _ in terms if k == "literal"}
    every = {r.o for r in harvest.cacheable(star.literals()).select("o").distinct().collect()}
    assert literals | set(rest) == every and not literals & set(rest) and len(literals) == 60
    assert {t for t, k, _ in terms if k == "predicate"} == set(star.predicates)


def test_lookup_equals_contains(cache, strings):
    terms, _ = strings
    held = complete.SuffixCache(cache)
    random.seed(3)
    for t, _, _ in random.sample(terms, 12):
        lo = random.randrange(len(t))
        text = t[lo : lo + random.randint(1, 4)]
        want = sorted(((-s, len(x), x) for x, _, s in terms if text.lower() in x.lower()))
        assert held.lookup(text, 1000) == [x for _, _, x in want]
    text = "ue"
    assert {r.term for r in index.suffix_lookup(cache, text).collect()} == {x for x, _, _ in terms if text in x.lower()}


@pytest.mark.parametrize("text", ["blue", "Cust", "000", "supp", "e"])
def test_completion_rules(cache, strings, text):
    terms, rest = strings
    got = complete.complete(cache, text, 10, 10).orderBy("rank").collect()
    hits = sorted((-s, len(x), x) for x, _, s in terms if text.lower() in x.lower())[:10]
    bins = sorted((len(x), x) for x in rest if text.lower() in x.lower() and len(text) <= len(x) <= len(text) + 10)
    want = [(x, "index") for _, _, x in hits] + [(x, "bin") for _, x in bins][: 10 - len(hits)]
    assert [(r.term, r.origin) for r in got] == want
    lazy = complete.complete_lazy(cache, text, 10, 10).orderBy("rank").collect()
    assert [r.term for r in lazy] == [r.term for r in got]


def test_variables_and_early_return(cache):
    assert complete.complete(cache, "?x").count() == 0
    assert len(list(complete.complete_progressive(cache, "e", 1))) == 1
    assert complete.complete(cache, "name", kinds=("predicate",)).collect()[0].term == "name"


def test_scan_reads_only_its_bins(cache):
    text = complete.residual_search(cache, "supp", 5, 3)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(lit_len" in text and "TakeOrderedAndProject" in text and "Python" not in text


@pytest.mark.parametrize("tasks", [1, 3, 8, 500])
def test_slices(spark, tasks):
    rows = [(3, 10), (4, 1), (7, 25), (9, 2)]
    got = index.assign_slices(spark.createDataFrame(rows, "lit_len int, n long"), tasks).collect()
    seen = {}
    for r in got:
        for i in range(r.start, r.stop):
            assert (r.lit_len, i) not in seen
            seen[r.lit_len, i] = r.task
    assert set(seen) == {(b, i) for b, n in rows for i in range(n)}
    order = [seen[k] for k in sorted(seen)]
    assert order == sorted(order)
    sizes = [order.count(t) for t in range(tasks)]
    assert max(sizes) - min(sizes) <= 1


def test_grams_equal_contains(cache, strings):
    _, rest = strings
    got = {r.lit for r in index.ngram_lookup(index.build_ngrams(cache.residual), "#0000").collect()}
    assert got == {x for x in rest if "#0000" in x}
    with pytest.raises(ValueError):
        index.ngram_lookup(index.build_ngrams(cache.residual), "ab")


def test_batch_equals_single(spark, cache):
    texts = ["blue", "new p", "Cust", "?x", ""]
    got = complete.complete_batch(cache, spark.createDataFrame([(t,) for t in texts], "t string")).collect()
    for t in texts:
        want = [r.term for r in complete.complete(cache, t).orderBy("rank").collect()] if len(t) > 2 else []
        assert [r.term for r in sorted((r for r in got if r.t == t), key=lambda r: r.rank)] == want


def test_significance_bounds(star):
    exact = {r.lit: r.score for r in significance.significance(star).collect()}
    upper = {r.lit: r.score for r in significance.significance(star, "indegree").collect()}
    sketch = {r.lit: r.score for r in significance.significance(star, "hll").collect()}
    assert exact.keys() == upper.keys() == sketch.keys()
    for k, v in exact.items():
        assert v <= upper[k] and abs(sketch[k] - v) <= max(2, 0.06 * v)
    bare = {r.lit: r.score for r in significance.significance(star, schema_edges=False).collect()}
    assert all(bare[k] <= exact[k] for k in bare)


def test_harvest_walk(star):
    sizes = {(r.p, r.c): (r.n_all, r.n_direct) for r in harvest.extent_sizes(star).collect()}
    log = harvest.plan_harvest(star, harvest.EndpointCost(100)).collect()
    frequency = [r.p for r in harvest.literal_predicates(star).collect()]
    order = [frequency.index(r.p) for r in log]
    assert order == sorted(order)
    failed = {(r.p, r.c) for r in log if r.scope == "subtree" and r.status != "ok"}
    from rdf_assist.operators.mapping import CLASSES

    for r in log:
        assert r.n_rows == sizes[r.p, r.c][1 if r.scope == "direct" else 0]
        assert (r.status == "ok") == (r.n_rows <= 100)
        assert CLASSES[r.c] is None or r.scope == "direct" or (r.p, CLASSES[r.c]) in failed
    for n in (1, 7):
        short = harvest.plan_harvest(star, harvest.EndpointCost(100), max_queries=n).collect()
        assert [tuple(r) for r in short] == [tuple(r) for r in log[:n]]
    whole = harvest.coverage(star, harvest.plan_harvest(star, harvest.EndpointCost(10**9))).first()
    assert whole.share == 1.0
    part = harvest.coverage(star, harvest.plan_harvest(star, harvest.EndpointCost(100))).first()
    assert 0 < part.share <= 1.0
    rejected = harvest.plan_harvest(star, harvest.EndpointCost(100, reject_rows=1000)).collect()
    assert {r.status.split(":")[0] for r in rejected} == {"ok", "timeout", "rejected"}


def test_cacheable_limits(spark):
    rows = [("a" * 80, 80, "en", "string"), ("a" * 81, 81, "en", "string"), ("x", 1, None, "string"), ("y", 1, "de", "string"), ("1", 1, None, "integer"), ("", 0, None, "string")]
    df = spark.createDataFrame(rows, "o string, o_len int, o_lang string, o_dtype string")
    assert {r.o for r in harvest.cacheable(df).collect()} == {"a" * 80, "x"}
    assert {r.o for r in harvest.cacheable(df, allow_untagged=False).collect()} == {"a" * 80}


def test_closure_of_a_cycle_ends(spark):
    df = spark.createDataFrame([("a", "b"), ("b", "a"), ("c", "a")], "c string, parent string")
    got = {(r.c, r.anc): r.depth for r in class_closure(df, 6).collect()}
    assert got["c", "b"] == 2 and got["a", "a"] == 0


def test_vectors_are_not_literals(spark, tiny):
    g = Graph(spark, tiny, ("vec",), False)
    assert "embedding" not in g.predicates and g.extent("cluster").where(F.col("o_dtype") != "integer").count() == 0


def test_short_texts_in_a_batch(spark):
    """One and two characters get the rows that complete() gives."""
    terms = spark.createDataFrame([(1, "name", "predicate", 4, 0), (2, "Blue", "literal", 4, 5)], "term_id long, term string, kind string, term_len int, score long")
    residual = spark.createDataFrame([("ab", 1, 2), ("nab", 1, 3), ("zebra", 1, 5)], "lit string, score long, lit_len int")
    c = index.Cache(terms, index.build_suffix_table(terms), residual)
    texts = ["a", "ab", "e", "lu", "q", "nam"]
    got = {}
    for r in complete.complete_batch(c, spark.createDataFrame([(t,) for t in texts], "t string")).collect():
        got.setdefault(r.t, []).append((r.rank, r.term, r.origin))
    for t in texts:
        assert sorted(got.get(t, [])) == sorted((r.rank, r.term, r.origin) for r in complete.complete(c, t).collect()), t
    assert complete.hit_ratio(c, spark.createDataFrame([("a",), ("q",)], "t string")).first()[:2] == (2, 1)


def test_batch_is_many_singles(spark, star):
    """Texts of one to eight characters, in one batch and one by one."""
    c = index.build_cache(star, 60)
    texts = ["b", "bl", "blu", "blue", "c", "cu", "custo", "customer", "r#000000", "zzz", "0", "NA", "?x", ""]
    typed = spark.createDataFrame([(t,) for t in texts], "t string")
    got = {}
    for r in complete.complete_batch(c, typed).collect():
        got.setdefault(r.t, []).append((r["rank"], r.term, r.origin))
    for t in texts:
        assert sorted(got.get(t, [])) == sorted((r["rank"], r.term, r.origin) for r in complete.complete_lazy(c, t).collect()), t


def test_long_bins_are_dealt_out(spark):
    rows = [(f"{'x' * (n - 6)}{i:06d}", 0, n) for n, many in ((10, 50), (20, 4000), (30, 300)) for i in range(many)]
    residual = spark.createDataFrame(rows, "lit string, score long, lit_len int")
    tasks, placed = index.place(residual, 500)
    sizes = {(r.lit_len, r.slice): r["count"] for r in placed.groupBy("lit_len", "slice").count().collect()}
    assert tasks == 9 and sum(sizes.values()) == len(rows)
    assert sum(n == 20 for n, _ in sizes) >= 8 and max(sizes.values()) < 700


def test_suggestions_do_not_depend_on_how_many_are_counted_first(spark, star):
    from rdf_assist.operators import suggest
    from rdf_assist.plans.parse import parse

    c = index.build_cache(star, 60)
    q = parse('SELECT ?x WHERE { ?x name "blue widgets" }')
    want = [tuple(r) for r in suggest.suggest_terms(star, c, q).select("kind", "new", "n_answers", "rank").orderBy("kind", "rank").collect()]
    assert want and want == [tuple(r) for r in suggest.suggest_terms(star, c, q, most=3).select("kind", "new", "n_answers", "rank").orderBy("kind", "rank").collect()]
