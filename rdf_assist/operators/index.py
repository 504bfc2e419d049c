"""The index: a sorted table of suffixes for predicates and significant literals, bins by length for the rest."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import save, written
from .mapping import Graph
from .significance import select_significant, significance

MAX_LEN = 80


@dataclass
class Cache:
    """terms(term_id, term, kind, term_len, score), suffixes(suffix, term_id, pos), residual(lit, score, lit_len)."""

    terms: DataFrame
    suffixes: DataFrame
    residual: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.terms.sparkSession


def fold(text: Column) -> Column:
    return F.lower(text)


def split_terms(g: Graph, scores: DataFrame, m: int = 40_000) -> tuple[DataFrame, DataFrame]:
    """(terms, residual): every predicate and the m most significant literals; the other literals."""
    top = select_significant(scores, m)
    preds = g.spark.createDataFrame([(p,) for p in g.predicates], "term string").withColumns({"kind": F.lit("predicate"), "score": F.lit(0).cast("long")})
    lits = top.select(F.col("lit").alias("term"), F.lit("literal").alias("kind"), F.col("score").cast("long").alias("score"))
    terms = preds.unionByName(lits).withColumns({"term_id": F.xxhash64("kind", "term"), "term_len": F.length("term")})
    residual = scores.join(top.select("lit"), "lit", "left_anti").withColumn("lit_len", F.length("lit"))
    return terms.select("term_id", "term", "kind", "term_len", "score"), residual.select("lit", F.col("score").cast("long").alias("score"), "lit_len")


def build_suffix_table(terms: DataFrame) -> DataFrame:
    """Every suffix of every term, folded: a term that contains a text has a suffix that starts with it."""
    folded = terms.withColumn("f", fold(F.col("term")))
    return folded.select("term_id", F.posexplode(F.transform(F.sequence(F.lit(1), F.length("f")), lambda i: F.substring("f", i, MAX_LEN + 1))).alias("pos", "suffix")).select("suffix", "term_id", "pos")


def build_cache(g: Graph, m: int = 40_000, mode: str = "exact", scores: DataFrame | None = None) -> Cache:
    """Scores are read three times, so they are written once before."""
    terms, residual = split_terms(g, written(scores if scores is not None else significance(g, mode)), m)
    return Cache(terms, build_suffix_table(terms), residual)


def store(c: Cache, path: str, rows_per_file: int = 2_000_000) -> Cache:
    """The cache on disk: suffixes range-sorted, so that a prefix reads few row groups; residual in one folder a length, dealt by balanced slices."""
    terms = written(c.terms)
    terms.write.mode("overwrite").parquet(f"{path}/terms")
    build_suffix_table(terms).repartitionByRange("suffix").sortWithinPartitions("suffix", "term_id", "pos").write.mode("overwrite").parquet(f"{path}/suffixes")
    residual = written(c.residual)
    tasks, placed = place(residual, rows_per_file)
    save(placed.withColumn("folded", fold(F.col("lit"))).repartition(tasks, "lit_len", "slice").drop("slice"), f"{path}/residual", ("lit_len",), rows_per_file)
    return open_cache(c.spark, path)


def place(residual: DataFrame, rows_per_slice: int) -> tuple[int, DataFrame]:
    """(tasks, residual with its slice): the bins as assign_slices() cuts them for so many tasks. A bin that reaches into n tasks is dealt into n
    slices by its literals' hash, so a long bin is written, and later scanned, by as many tasks as its share of all literals asks for."""
    sizes = residual.groupBy("lit_len").agg(F.count("*").alias("n"))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    tasks = max(1, -(-total // rows_per_slice))
    cut = assign_slices(sizes, tasks).groupBy("lit_len").agg(F.count("*").alias("slices"))  # a row a length
    return tasks, residual.join(F.broadcast(cut), "lit_len").withColumn("slice", F.pmod(F.xxhash64("lit"), F.col("slices"))).select("lit", "score", "lit_len", "slice")


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of a stored cache's files."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()


def open_cache(spark: SparkSession, path: str) -> Cache:
    return Cache(spark.read.parquet(f"{path}/terms"), spark.read.parquet(f"{path}/suffixes"), spark.read.schema("lit string, score long, folded string, lit_len int").parquet(f"{path}/residual"))


def suffix_lookup(c: Cache, text: str) -> DataFrame:
    """(term_id, term, kind, term_len, score) of indexed terms that contain text, whatever the case."""
    hits = c.suffixes.where(F.col("suffix").startswith(text.lower())).select("term_id").distinct()
    return c.terms.join(hits, "term_id", "left_semi")


def scan_bins(c: Cache, lo: int, hi: int) -> DataFrame:
    """Residual literals of lo to hi characters: other bins' folders are not read."""
    return c.residual.where(F.col("lit_len").between(lo, hi))


def bin_sizes(c: Cache) -> DataFrame:
    return c.residual.groupBy("lit_len").agg(F.count("*").alias("n"))


def assign_slices(sizes: DataFrame, tasks: int) -> DataFrame:
    """(task, lit_len, start, stop): which rows of which bins each task takes.

    Literals are numbered through the bins in order of length; task i takes the numbers from i * n / tasks
    to (i + 1) * n / tasks, rounded down, so shares differ by one at most. start and stop count within the bin.
    """
    order = Window.orderBy("lit_len").rowsBetween(Window.unboundedPreceding, 0)  # a row for each length
    placed = sizes.withColumn("top", F.sum("n").over(order)).withColumn("base", F.col("top") - F.col("n"))
    total = sizes.agg(F.sum("n").alias("total"))
    each = placed.crossJoin(total).withColumn("task", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))))  # one total row
    share = each.withColumns({"lo": F.expr(f"task * total div {tasks}"), "hi": F.expr(f"(task + 1) * total div {tasks}")})
    cut = share.where("lo < top AND hi > base")
    return cut.select("task", "lit_len", (F.greatest("lo", "base") - F.col("base")).alias("start"), (F.least("hi", "top") - F.col("base")).alias("stop"))


def balance(slices: DataFrame) -> DataFrame:
    """(tasks, most, least, total) of the literals of a task."""
    sums = slices.groupBy("task").agg(F.sum(F.col("stop") - F.col("start")).alias("n"))
    return sums.agg(F.count("*").alias("tasks"), F.max("n").alias("most"), F.min("n").alias("least"), F.sum("n").alias("total"))


def index_stats(c: Cache) -> DataFrame:
    """One row: predicates, literals, suffix rows, characters and bytes of suffixes, residual literals, bins."""
    kinds = c.terms.agg(F.count(F.when(F.col("kind") == "predicate", 1)).alias("predicates"), F.count(F.when(F.col("kind") == "literal", 1)).alias("literals"))
    rows = c.suffixes.agg(F.count("*").alias("suffix_rows"), F.sum(F.length("suffix")).alias("suffix_chars"), F.sum(F.octet_length("suffix")).alias("suffix_bytes"))
    rest = c.residual.agg(F.count("*").alias("residual"), F.countDistinct("lit_len").alias("bins"))
    return kinds.crossJoin(rows).crossJoin(rest)  # one row each


def build_ngrams(literals: DataFrame, n: int = 3) -> DataFrame:
    """(gram, lit) postings: a gram index for residual literals where a scan would be too long."""
    folded = literals.select("lit", fold(F.col("lit")).alias("f")).where(F.length("f") >= n)
    grams = F.array_distinct(F.transform(F.sequence(F.lit(1), F.length("f") - n + 1), lambda i: F.substring("f", i, n)))
    return folded.select("lit", F.explode(grams).alias("gram"))


def ngram_lookup(postings: DataFrame, text: str, n: int = 3) -> DataFrame:
    """(lit) that contain text: literals with all its grams, checked again. text needs n characters."""
    t = text.lower()
    grams = sorted({t[i : i + n] for i in range(len(t) - n + 1)})
    if not grams:
        raise ValueError(f"text needs at least {n} characters")
    found = postings.where(F.col("gram").isin(grams)).groupBy("lit").agg(F.count("*").alias("k")).where(F.col("k") == len(grams))
    return found.where(F.contains(fold(F.col("lit")), F.lit(t))).select("lit")


def ntile_slices(literals: DataFrame, tasks: int) -> DataFrame:
    """(task, n): literals in order of length and text, cut by ntile; a check on assign_slices()."""
    order = Window.orderBy("lit_len", "lit")
    return literals.withColumn("task", F.ntile(tasks).over(order) - 1).groupBy("task").agg(F.count("*").alias("n"))
