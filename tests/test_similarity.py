import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rdf_assist.functions import similarity as sim
from rdf_assist.functions.lexicon import lexicon, verbalize

VECTORS = [
    ("Kennedys", "Kennedy", 0.975), ("martha", "marhta", 0.961111), ("Viking Press", "The Viking Press", 0.805556), ("Viking Press", "The Viking", 0.618254), ("wife", "spouse", 0.472222),
    ("MACHINARY", "MACHINERY", 0.955556), ("blue widgets", "blue widget", 0.983333), ("suppliedBy", "supplier", 0.915), ("Brand#1", "Brand#11", 0.975), ("abxxxxxx", "abyyyyyyyy", 0.483333),
    ("éa", "êa", 0.666667), ("", "a", 0.0), ("x", "x", 1.0),
]


@pytest.mark.parametrize("a,b,want", VECTORS)
def test_vectors(a, b, want):
    assert sim._winkler(a, b) == pytest.approx(want, abs=1e-6)


def test_native_equals_arrow(spark):
    random.seed(7)
    made = [("".join(random.choices("abé ", k=random.randint(0, 9))), "".join(random.choices("abé ", k=random.randint(0, 9)))) for _ in range(150)]
    rows = spark.createDataFrame([*made, *[(a, b) for a, b, _ in VECTORS]], "a string, b string")
    for r in rows.select("a", "b", sim.jaro_winkler("a", "b").alias("x"), sim.jaro_winkler_native(F.col("a"), F.col("b")).alias("y"), sim.may_reach(F.col("a"), F.col("b")).alias("may")).collect():
        assert r.x == pytest.approx(r.y, abs=1e-12) and r.x == pytest.approx(sim._winkler(r.a, r.b), abs=1e-12)
        assert r.x < 0.7 or r.may
    free = rows.select(sim.jaro_winkler("a", "b", boost=0.0).alias("x"), sim.may_reach(F.col("a"), F.col("b"), boost=0.0).alias("may")).collect()
    assert all(r.x < 0.7 or r.may for r in free)


@settings(max_examples=150, deadline=None)
@given(st.text("abcé", max_size=10), st.text("abcé", max_size=10))
def test_jaro_is_a_symmetric_share(a, b):
    j = sim._jaro(a, b)
    assert 0 <= j <= 1 and j == pytest.approx(sim._jaro(b, a))
    assert sim._winkler(a, b) >= j
    if j > 0:
        m = sim.multiset_overlap(a, b)
        assert j <= (m / len(a) + m / len(b) + 1) / 3 + 1e-12


def test_alternatives_and_registration(spark):
    sim.register(spark)
    assert spark.sql("SELECT jaro_winkler('Kennedys', 'Kennedy')").first()[0] == pytest.approx(0.975)
    row = spark.createDataFrame([("night", "nacht")], "a string, b string").select(*[sim.similarity(k)(F.col("a"), F.col("b")).alias(k) for k in sim.KINDS]).first()
    assert row.levenshtein == pytest.approx(0.6) and row.prefix == pytest.approx(0.2) and row.trigram == 0.0
    assert spark.createDataFrame([("aab",)], "s string").select(sim.char_counts(F.col("s"))).first()[0] == {"a": 2, "b": 1}


def test_lexicon_works_both_ways(spark):
    got = {r.form for r in verbalize(spark.createDataFrame([("vendor",)], "term string"), lexicon(spark)).collect()}
    assert got == {"vendor", "supplier"}


def test_band_join_checks_its_size(spark):
    many = spark.range(20).select(F.col("id").cast("string").alias("term"))
    with pytest.raises(ValueError):
        sim.length_band_join(many, many.select(F.col("term").alias("lit"), F.length("term").alias("lit_len")), most=10)
