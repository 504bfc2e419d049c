"""Query completion: strings that contain the text typed so far, the index first, then the length bins."""

from __future__ import annotations

import bisect
from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .index import MAX_LEN, Cache, build_ngrams, fold, scan_bins, suffix_lookup

RESULT = "rank int, term string, origin string"
#: Rows of typed text up to which a batch goes to every task of the residual scan.
MAX_TYPED = 10_000


def is_variable(text: str) -> bool:
    return text.startswith("?")


def index_hits(c: Cache, text: str, k: int = 10, kinds: tuple[str, ...] | None = None) -> DataFrame:
    found = suffix_lookup(c, text)
    if kinds:
        found = found.where(F.col("kind").isin(*kinds))
    return found.orderBy(F.desc("score"), "term_len", "term").limit(k)


def residual_search(c: Cache, text: str, k: int = 10, gamma: int = 10) -> DataFrame:
    """The k shortest residual literals that contain text, of at most gamma characters more."""
    bins = scan_bins(c, len(text), len(text) + gamma)
    return bins.where(F.contains(fold(F.col("lit")), F.lit(text.lower()))).orderBy("lit_len", "lit").limit(k)


def complete_progressive(c: Cache, text: str, k: int = 10, gamma: int = 10, kinds: tuple[str, ...] | None = None, use_index: bool = True, held: SuffixCache | None = None) -> Iterator[DataFrame]:
    """First the index's matches, at once; then, only if they are fewer than k, the rest from the bins.

    held: the index's terms on the driver, which answer without a job.
    """
    if is_variable(text) or not text:
        return
    found = 0
    if use_index:
        if held is not None and kinds is None:
            found_terms = held.lookup(text, k)
        else:
            found_terms = [r.term for r in index_hits(c, text, k, kinds).select("term").collect()]  # at most k
        rows = [(i + 1, t, "index") for i, t in enumerate(found_terms)]
        found = len(rows)
        yield c.spark.createDataFrame(rows, RESULT)
    if found < k and (kinds is None or "literal" in kinds):
        rest = residual_search(c, text, k - found, gamma)
        yield c.spark.createDataFrame([(found + i + 1, r.lit, "bin") for i, r in enumerate(rest.select("lit").collect())], RESULT)


def complete(c: Cache, text: str, k: int = 10, gamma: int = 10, kinds: tuple[str, ...] | None = None, use_index: bool = True, held: SuffixCache | None = None) -> DataFrame:
    """(rank, term, origin) of at most k completions; a variable (?name) and an empty text have none."""
    out = c.spark.createDataFrame([], RESULT)
    for part in complete_progressive(c, text, k, gamma, kinds, use_index, held):
        out = out.unionByName(part)
    return out


def complete_lazy(c: Cache, text: str, k: int = 10, gamma: int = 10) -> DataFrame:
    """As complete(), in one plan that runs when its rows are asked for."""
    if is_variable(text) or not text:
        return c.spark.createDataFrame([], RESULT)
    one = index_hits(c, text, k).select("term", F.lit(0).alias("tier"), F.col("score"), "term_len", F.lit("index").alias("origin"))
    two = residual_search(c, text, k, gamma).select(F.col("lit").alias("term"), F.lit(1).alias("tier"), F.lit(0).cast("long").alias("score"), F.col("lit_len").alias("term_len"), F.lit("bin").alias("origin"))
    order = Window.orderBy("tier", F.desc("score"), "term_len", "term")  # at most 2 k rows
    ranked = one.unionByName(two).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("rank", "term", "origin")


def scan_all(c: Cache, text: str, k: int = 10) -> DataFrame:
    """The sequential alternative: every cached string is looked at, shortest first."""
    every = c.terms.select("term").unionByName(c.residual.select(F.col("lit").alias("term")))
    found = every.where(F.contains(fold(F.col("term")), F.lit(text.lower()))).distinct()
    return found.orderBy(F.length("term"), "term").limit(k)


def contains_join(typed: DataFrame, strings: DataFrame) -> DataFrame:
    """(t, lit) for strings that contain a typed text: a nested loop over a small typed side, whose size is checked."""
    if typed.limit(MAX_TYPED + 1).count() > MAX_TYPED:
        raise ValueError("too many typed texts for a nested loop; use complete_batch()")
    return strings.join(F.broadcast(typed), F.contains(fold(F.col("lit")), F.lower("t")))


def _typed(typed: DataFrame) -> DataFrame:
    """(t, f, n): typed texts that can have completions, folded, with their length."""
    return typed.select("t").distinct().where("t <> '' AND NOT startswith(t, '?')").withColumn("f", fold(F.col("t"))).withColumn("n", F.length("f"))


def prefixes(suffixes: DataFrame, asked: DataFrame) -> DataFrame:
    """(f, term_id): suffixes under the prefixes that are asked for. A prefix is made for each typed length that is there, so a text meets its
    matches by equality and no other suffix; lengths are bounded by a suffix's."""
    lengths = sorted(r.n for r in asked.select("n").distinct().where(F.col("n") <= MAX_LEN + 1).collect())  # at most MAX_LEN + 1
    cut = F.filter(F.array(*[F.lit(n) for n in lengths]).cast("array<int>"), lambda n: n <= F.length("suffix"))
    made = suffixes.withColumn("f", F.explode(F.transform(cut, lambda n: F.substring(F.col("suffix"), F.lit(1), n))))
    return made.join(asked.select("f").distinct(), "f", "left_semi").select("f", "term_id").distinct()


def complete_batch(c: Cache, typed: DataFrame, k: int = 10, gamma: int = 10, grams: int = 3) -> DataFrame:
    """(t, rank, term, origin) of many typed texts (column t) at once.

    The index side joins a text with the prefixes of its length. The bin side joins each text's rarest gram, by the number of literals
    that have it, with the literals' grams and checks the match. Both are equi-joins, so neither side has to be small.
    Texts shorter than `grams` characters join on grams of their own length. Variables are left out.
    """
    t = _typed(typed)
    best = prefixes(c.suffixes, t).join(c.terms, "term_id")
    first = Window.partitionBy("f").orderBy(F.desc("score"), "term_len", "term")
    best = best.withColumn("i", F.row_number().over(first)).where(F.col("i") <= k)
    one = t.join(best, "f").select("t", "term", F.lit(0).alias("tier"), "score", "term_len", F.lit("index").alias("origin"))
    posting = build_ngrams(c.residual.select("lit"), grams)
    for n in range(1, grams):
        posting = posting.unionByName(build_ngrams(c.residual.select("lit"), n))
    size = F.least(F.lit(grams), F.col("n"))
    own = t.withColumn("gram", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.col("n") - size + 1), lambda i: F.substring(F.col("f"), i, size)))))
    counts = posting.join(own.select("gram").distinct(), "gram", "left_semi").groupBy("gram").agg(F.count("*").alias("k"))
    rare = own.join(counts, "gram", "left").groupBy("t", "f").agg(F.min_by("gram", F.struct(F.coalesce("k", F.lit(0)), "gram")).alias("gram"))
    two = rare.join(posting, "gram").where(F.contains(fold(F.col("lit")), F.col("f")))
    two = two.where((F.length("lit") >= F.length("t")) & (F.length("lit") <= F.length("t") + gamma))
    two = two.select("t", F.col("lit").alias("term"), F.lit(1).alias("tier"), F.lit(0).cast("long").alias("score"), F.length("lit").alias("term_len"), F.lit("bin").alias("origin"))
    order = Window.partitionBy("t").orderBy("tier", F.desc("score"), "term_len", "term")
    return one.unionByName(two).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("t", "rank", "term", "origin")


def hit_ratio(c: Cache, typed: DataFrame) -> DataFrame:
    """(asked, hits, ratio): typed texts with a match in the index."""
    t = _typed(typed)
    hit = t.join(prefixes(c.suffixes, t).select("f").distinct(), "f", "left_semi")
    sums = t.agg(F.count("*").alias("asked")).crossJoin(hit.agg(F.count("*").alias("hits")))  # one row each
    return sums.withColumn("ratio", F.round(F.try_divide("hits", "asked"), 6))


def elimination(sizes: DataFrame, lengths: DataFrame, gamma: int = 10) -> DataFrame:
    """(t_len, skipped): the share of residual literals outside the window of a typed length; from the bin counts alone."""
    total = sizes.agg(F.sum("n").alias("total"))
    inside = lengths.join(sizes, (F.col("lit_len") >= F.col("t_len")) & (F.col("lit_len") <= F.col("t_len") + gamma), "left")  # 80 bins
    kept = inside.groupBy("t_len").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return kept.crossJoin(total).select("t_len", F.round(1 - F.col("kept") / F.col("total"), 6).alias("skipped"))


class SuffixCache:
    """The index's terms on the driver as a sorted list of suffixes, for lookups without a Spark job.

    Only predicates and the m most significant literals are held: m bounds it.
    """

    def __init__(self, c: Cache, limit: int = 100_000):
        rows = c.terms.limit(limit + 1).collect()
        if len(rows) > limit:
            raise ValueError("more indexed terms than a driver should hold")
        self.terms = [(r.term, r.kind, r.score) for r in rows]
        self.keys = sorted((t.lower()[i:], n) for n, (t, _, _) in enumerate(self.terms) for i in range(len(t)))

    def lookup(self, text: str, k: int = 10) -> list[str]:
        if not text or is_variable(text):
            return []
        t = text.lower()
        at, found = bisect.bisect_left(self.keys, (t, -1)), set()
        while at < len(self.keys) and self.keys[at][0].startswith(t):
            found.add(self.keys[at][1])
            at += 1
        best = sorted((-self.terms[n][2], len(self.terms[n][0]), self.terms[n][0]) for n in found)
        return [t for _, _, t in best[:k]]
