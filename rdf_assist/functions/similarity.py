"""String similarity: Jaro and Jaro-Winkler as Arrow functions and as native expressions, their bound, and alternatives."""

from __future__ import annotations

from collections import Counter
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _jaro(a: str, b: str) -> float:
    """Matches within half the longer length, less transposed ones; 0 if either text is empty."""
    if a == b:
        return 1.0 if a else 0.0
    if not a or not b:
        return 0.0
    reach = max(max(len(a), len(b)) // 2 - 1, 0)
    taken = [False] * len(b)
    first = []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not taken[j] and b[j] == x:
                taken[j] = True
                first.append(x)
                break
    m = len(first)
    if not m:
        return 0.0
    second = [b[j] for j in range(len(b)) if taken[j]]
    swaps = sum(x != y for x, y in zip(first, second, strict=True)) // 2
    return (m / len(a) + m / len(b) + (m - swaps) / m) / 3


def _winkler(a: str, b: str, scale: float = 0.1, most: int = 4, boost: float = 0.7) -> float:
    j = _jaro(a, b)
    if j <= boost:
        return j
    n = 0
    while n < min(most, len(a), len(b)) and a[n] == b[n]:
        n += 1
    return j + n * scale * (1 - j)


def _home() -> str:
    import os

    return os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def _pairs(f):
    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else f(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    return run


def _udf(kind: str, *params: float):
    """The Arrow function of _jaro or _winkler; workers find this package even if only the driver had it on its path."""
    root = _home()

    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        from rdf_assist.functions import similarity as own

        f = own._jaro if kind == "jaro" else (lambda x, y: own._winkler(x, y, *params))
        return own._pairs(f)(a, b)

    return F.pandas_udf(run, "double")


def jaro(a: Column | str, b: Column | str) -> Column:
    return _udf("jaro")(a, b)


def jaro_winkler(a: Column | str, b: Column | str, scale: float = 0.1, most: int = 4, boost: float = 0.7) -> Column:
    """Jaro-Winkler of two text columns; the prefix counts only above `boost` (0 counts it always)."""
    return _udf("winkler", scale, most, boost)(a, b)


def register(spark: SparkSession) -> None:
    """jaro_winkler(a, b) for SQL."""
    spark.udf.register("jaro_winkler", _udf("winkler"))


def _chars(s: Column) -> Column:
    return F.filter(F.split(s, ""), lambda c: c != "")


def jaro_native(a: Column, b: Column) -> Column:
    """Jaro in higher-order functions alone, for clusters without Python workers."""
    n, m = F.length(a), F.length(b)
    reach = F.greatest(F.floor(F.greatest(n, m) / 2).cast("int") - 1, F.lit(0))
    start = F.struct(F.array().cast("array<int>").alias("js"), F.lit("").alias("hit"))

    def step(acc: Column, i: Column) -> Column:
        spots = F.filter(F.sequence(F.greatest(i - reach, F.lit(1)), F.least(i + reach, m)), lambda j: (F.substring(b, j, F.lit(1)) == F.substring(a, i, F.lit(1))) & ~F.array_contains(acc["js"], j))
        none = (F.greatest(i - reach, F.lit(1)) > F.least(i + reach, m)) | (F.size(spots) == 0)
        return F.when(none, acc).otherwise(F.struct(F.concat(acc["js"], F.slice(spots, 1, 1)).alias("js"), F.concat(acc["hit"], F.substring(a, i, F.lit(1))).alias("hit")))

    found = F.aggregate(F.sequence(F.lit(1), n), start, step)
    second = F.array_join(F.transform(F.sort_array(found["js"]), lambda j: F.substring(b, j, F.lit(1))), "")
    k = F.size(found["js"])
    off = F.size(F.filter(F.sequence(F.lit(1), k), lambda i: F.substring(found["hit"], i, F.lit(1)) != F.substring(second, i, F.lit(1))))
    swaps = F.floor(off / 2)
    return F.when((n == 0) | (m == 0), 0.0).when(a == b, 1.0).when(k == 0, 0.0).otherwise((F.try_divide(k, n) + F.try_divide(k, m) + F.try_divide(k - swaps, k)) / 3)


def jaro_winkler_native(a: Column, b: Column, scale: float = 0.1, most: int = 4, boost: float = 0.7) -> Column:
    j = jaro_native(a, b)
    prefix = F.aggregate(F.sequence(F.lit(1), F.lit(most)), F.lit(0), lambda n, i: F.when((n == i - 1) & (F.length(a) >= i) & (F.length(b) >= i) & (F.substring(a, i, F.lit(1)) == F.substring(b, i, F.lit(1))), i).otherwise(n))
    return F.when(j > boost, j + prefix * scale * (1 - j)).otherwise(j)


def char_counts(s: Column) -> Column:
    """map character → count."""
    chars = _chars(s)
    return F.map_from_entries(F.transform(F.array_distinct(chars), lambda c: F.struct(c, F.size(F.filter(chars, lambda d: d == c)))))


def shared_chars(a: Column, b: Column) -> Column:
    """Characters in common, with repeats: no pair can match more."""
    left, right = char_counts(a), char_counts(b)
    return F.aggregate(F.map_keys(left), F.lit(0), lambda n, c: n + F.least(F.element_at(left, c), F.coalesce(F.element_at(right, c), F.lit(0))))


def may_reach(a: Column, b: Column, theta: float = 0.7, boost: float = 0.7, scale: float = 0.1, most: int = 4) -> Column:
    """False only where Jaro-Winkler cannot reach theta: a native filter ahead of the costly function."""
    need = theta if boost >= theta else (theta - most * scale) / (1 - most * scale)
    m = shared_chars(a, b)
    return (F.try_divide(m, F.length(a)) + F.try_divide(m, F.length(b))) >= (3 * need - 1)


def levenshtein_ratio(a: Column, b: Column) -> Column:
    return 1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))


def trigrams(s: Column) -> Column:
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(s) - 2, F.lit(1))), lambda i: F.substring(s, i, F.lit(3))))


def trigram_jaccard(a: Column, b: Column) -> Column:
    x, y = trigrams(a), trigrams(b)
    return F.size(F.array_intersect(x, y)) / F.size(F.array_union(x, y))


def same_soundex(a: Column, b: Column) -> Column:
    return (F.soundex(a) == F.soundex(b)).cast("double")


def common_prefix(a: Column, b: Column) -> Column:
    n = F.aggregate(F.sequence(F.lit(1), F.least(F.length(a), F.length(b), F.lit(32))), F.lit(0), lambda n, i: F.when((n == i - 1) & (F.substring(a, i, F.lit(1)) == F.substring(b, i, F.lit(1))), i).otherwise(n))
    return n / F.greatest(F.length(a), F.length(b), F.lit(1))


KINDS = {"jaro_winkler": jaro_winkler, "jaro": jaro, "levenshtein": levenshtein_ratio, "trigram": trigram_jaccard, "soundex": same_soundex, "prefix": common_prefix}


def similarity(kind: str):
    return KINDS[kind]


def length_band_join(terms: DataFrame, strings: DataFrame, alpha: int = 2, beta: int = 3, most: int = 10_000) -> DataFrame:
    """terms(term) with strings(lit, lit_len) of alpha characters fewer to beta more; the checked small side goes to every task. Strings of no wanted length are
    left out before the join, whose condition is tested after those of later filters."""
    sizes = [r.n for r in terms.select(F.length("term").alias("n")).limit(most + 1).collect()]  # at most `most` and one
    if len(sizes) > most:
        raise ValueError("too many terms for a broadcast band join")
    band = F.col("lit_len").between(F.length("term") - alpha, F.length("term") + beta)
    wanted = sorted({k for n in sizes if n is not None for k in range(n - alpha, n + beta + 1)})
    return strings.where(F.col("lit_len").isin(wanted)).join(F.broadcast(terms), band)


def best_match(terms: DataFrame, strings: DataFrame) -> DataFrame:
    """(term, lit, similarity): the most similar string of each term, as an aggregate."""
    scored = length_band_join(terms, strings).withColumn("similarity", jaro_winkler("term", "lit"))
    return scored.groupBy("term").agg(F.max_by("lit", F.struct(F.col("similarity"), F.col("lit"))).alias("lit"), F.max("similarity").alias("similarity"))


def multiset_overlap(a: str, b: str) -> int:
    return sum((Counter(a) & Counter(b)).values())
