"""Cost and accuracy measures as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

# The two-sided 95 % quantile of Student's t by degrees of freedom.
T95 = {1: 12.706, 2: 4.303, 3: 3.182, 4: 2.776, 5: 2.571, 6: 2.447, 7: 2.365, 8: 2.306, 9: 2.262, 10: 2.228, 11: 2.201, 12: 2.179, 13: 2.16, 14: 2.145, 15: 2.131, 16: 2.12, 17: 2.11, 18: 2.101, 19: 2.093, 20: 2.086, 25: 2.06, 30: 2.042, 40: 2.021, 60: 2.0, 120: 1.98}

# Published counts of a 50-question comparison, as (system, processed, right, partial).
PUBLISHED = [
    ("competition entrant 1", 42, 26, 7), ("competition entrant 2", 26, 8, 5), ("competition entrant 3", 37, 9, 4), ("competition entrant 4", 31, 7, 3), ("competition entrant 5", 33, 8, 2),
    ("NL-QA comparator", 40, 14, 9), ("factoid QA", 8, 8, 0), ("summary-graph rewriter", 26, 16, 5), ("query-by-example learner", 7, 4, 0), ("the studied tool", 43, 43, 0),
]


def answers(df: DataFrame, by: list[str], column: str) -> DataFrame:
    """(by, answers): the sorted distinct answers of each run."""
    return df.groupBy(*by).agg(F.sort_array(F.collect_set(column)).alias("answers"))


def judge(runs: DataFrame, gold: DataFrame) -> DataFrame:
    """(system, qid, processed, right, partial): runs(system, qid, answers) against gold(qid, gold)."""
    both = gold.join(runs, "qid")
    got, want = F.coalesce("answers", F.array()), F.col("gold")
    same = (F.size(F.array_except(got, want)) == 0) & (F.size(F.array_except(want, got)) == 0) & (F.size(got) > 0)
    return both.select("system", "qid", (F.size(got) > 0).alias("processed"), same.alias("right"), (F.arrays_overlap(got, want) & ~same).alias("partial"))


def judge_rows(runs: DataFrame, gold: DataFrame) -> DataFrame:
    """(system, qid, processed, right, partial): runs(system, qid, answer) against gold(qid, answer), as rows and not as lists, so answers may be any number."""
    runs, gold = runs.distinct(), gold.distinct()
    n_gold = gold.groupBy("qid").agg(F.count("*").alias("n_gold"))
    held = runs.join(gold.withColumn("hit", F.lit(1)), ["qid", "answer"], "left").groupBy("system", "qid").agg(F.count("*").alias("n"), F.count("hit").alias("hits"))
    right = (F.col("hits") == F.col("n")) & (F.col("hits") == F.col("n_gold"))
    return held.join(n_gold, "qid", "left").withColumn("n_gold", F.coalesce("n_gold", F.lit(0))).select("system", "qid", F.lit(True).alias("processed"), right.alias("right"), ((F.col("hits") > 0) & ~right).alias("partial"))


def _ratio(a, b):
    return F.round(F.try_divide(a, b), 6)


def _f1(r, p):
    return F.round(F.try_divide(2 * r * p, r + p), 6)


def scores_of(counts: DataFrame, total: int) -> DataFrame:
    """Recall, precision and F1 with their partial forms, from (system, processed, n_right, n_partial)."""
    right, part, done = F.col("n_right"), F.col("n_right") + F.col("n_partial"), F.col("processed")
    out = counts.withColumns({"share": _ratio(done, F.lit(total)), "r": right / total, "r_star": part / total, "p": F.try_divide(right, done), "p_star": F.try_divide(part, done)})
    out = out.withColumns({"f1": _f1(F.col("r"), F.col("p")), "f1_star": _f1(F.col("r_star"), F.col("p_star"))})
    return out.withColumns({c: F.round(c, 6) for c in ("r", "r_star", "p", "p_star")})


def tallied(verdicts: DataFrame) -> DataFrame:
    return verdicts.groupBy("system").agg(F.count_if("processed").alias("processed"), F.count_if("right").alias("n_right"), F.count_if("partial").alias("n_partial"))


def scores(verdicts: DataFrame, total: int) -> DataFrame:
    return scores_of(tallied(verdicts), total)


def factoid_recall(verdicts: DataFrame, factoid: DataFrame) -> DataFrame:
    """(system, n_right, total, r): recall over factoid questions (qid) alone."""
    total = factoid.agg(F.count("*").alias("total"))  # one row
    right = verdicts.join(F.broadcast(factoid), "qid", "left_semi").groupBy("system").agg(F.count_if("right").alias("n_right"))
    return right.join(F.broadcast(total)).select("system", "n_right", "total", _ratio(F.col("n_right"), F.col("total")).alias("r"))


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(PUBLISHED, "system string, processed long, n_right long, n_partial long")


# ---------------------------------------------------------------- study log: system, participant, qid, category, event_id, ts, click, outcome, seconds


def episodes(log: DataFrame) -> DataFrame:
    """A row for each (system, participant, qid): answered, attempts up to the first success (or all), seconds."""
    order = Window.partitionBy("system", "participant", "qid").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = log.withColumn("over", F.coalesce(F.max(F.when(F.col("outcome") == "success", 1)).over(order), F.lit(0)))
    held = seen.where("over = 0")
    return held.groupBy("system", "participant", "qid", "category").agg(
        F.coalesce(F.bool_or(F.col("outcome") == "success"), F.lit(False)).alias("answered"), F.count_if(F.col("click")).alias("attempts"), F.round(F.sum("seconds"), 6).alias("seconds"))


def per_participant(log: DataFrame) -> DataFrame:
    return episodes(log).groupBy("system", "category", "participant").agg(F.avg(F.col("answered").cast("double")).alias("rate"))


def with_ci(rates: DataFrame) -> DataFrame:
    """Mean over participants with its 95 % interval's half width."""
    t = F.create_map(*[F.lit(x) for kv in T95.items() for x in kv])
    df = F.greatest(F.col("n") - 1, F.lit(1)).cast("int")
    near = F.element_at(t, F.array_max(F.filter(F.array(*[F.lit(d) for d in T95]), lambda d: d <= df)))
    out = rates.groupBy("system", "category").agg(F.avg("rate").alias("mean"), F.stddev_samp("rate").alias("sd"), F.count("*").alias("n"))
    return out.select("system", "category", F.round("mean", 6).alias("mean"), "n", F.round(near * F.col("sd") / F.sqrt("n"), 6).alias("half_width"))


def success_rate(log: DataFrame) -> DataFrame:
    """Share of questions answered, per participant and then averaged."""
    return with_ci(per_participant(log))


def answered_by_any(log: DataFrame) -> DataFrame:
    by_question = episodes(log).groupBy("system", "category", "qid").agg(F.bool_or("answered").alias("any"))
    return by_question.groupBy("system", "category").agg(F.round(F.avg(F.col("any").cast("double")), 6).alias("share"))


def attempts_to_success(log: DataFrame) -> DataFrame:
    return episodes(log).where("answered").groupBy("system", "category").agg(F.round(F.avg("attempts"), 6).alias("attempts"))


def attempts_to_giveup(log: DataFrame) -> DataFrame:
    return episodes(log).where("NOT answered").groupBy("system", "category").agg(F.min("attempts").alias("least"), F.max("attempts").alias("most"), F.round(F.avg("attempts"), 6).alias("mean"))


def time_on_answered(log: DataFrame) -> DataFrame:
    return episodes(log).where("answered").groupBy("system", "category").agg(F.round(F.avg("seconds"), 6).alias("seconds"))


def differences(log: DataFrame) -> DataFrame:
    """(participant, d): rate with system 0 less rate with system 1."""
    rates = episodes(log).groupBy("participant").agg(F.avg(F.when(F.col("system") == 0, F.col("answered").cast("double"))).alias("a"), F.avg(F.when(F.col("system") == 1, F.col("answered").cast("double"))).alias("b"))
    return rates.where("a IS NOT NULL AND b IS NOT NULL").select("participant", F.round(F.col("a") - F.col("b"), 9).alias("d"))


def sign_flip_p(diffs: DataFrame, most: int = 20) -> DataFrame:
    """(n, mean, p): the exact share of sign patterns whose sum is at least as extreme; n is at most `most` participants."""
    packed = diffs.agg(F.sort_array(F.collect_list("d")).alias("ds"))  # one value for each participant
    spark = diffs.sparkSession
    n = packed.select(F.size("ds")).first()[0]
    if n > most:
        raise ValueError("too many participants for all sign patterns")
    patterns = spark.range(1 << n).crossJoin(F.broadcast(packed))  # one row
    flipped = F.aggregate(F.transform("ds", lambda d, i: F.when(F.getbit("id", i) == 1, -d).otherwise(d)), F.lit(0.0), lambda a, x: a + x)
    plain = F.aggregate("ds", F.lit(0.0), lambda a, x: a + x)
    return patterns.select(flipped.alias("f"), plain.alias("s"), F.size("ds").alias("n")).agg(F.first("n").cast("long").alias("n"), F.round(F.first("s") / F.first("n"), 6).alias("mean"), F.round(F.avg((F.abs("f") >= F.abs("s") - 1e-9).cast("double")), 6).alias("p"))


def suggestion_usage(log: DataFrame) -> DataFrame:
    """Share of questions with any accepted suggestion, and by kind: log(qid, accepted) with kinds predicate, literal, structure or null."""
    per = log.groupBy("system", "participant", "qid").agg(*[F.bool_or(F.coalesce(F.col("accepted") == k, F.lit(False))).alias(k) for k in ("predicate", "literal", "structure")])
    out = per.agg(*[F.round(F.avg(F.col(k).cast("double")), 6).alias(k) for k in ("predicate", "literal", "structure")], F.round(F.avg((F.col("predicate") | F.col("literal") | F.col("structure")).cast("double")), 6).alias("any_kind"))
    return out


def harvest_cost(log: DataFrame) -> DataFrame:
    """Queries, pages and rows by status, by predicate, and in all."""
    log.createOrReplaceTempView("_harvest_log")
    return log.sparkSession.sql("""
        SELECT status, p, count(*) AS queries, sum(pages) AS pages, sum(CASE WHEN status = 'ok' THEN n_rows ELSE 0 END) AS n_rows
        FROM _harvest_log GROUP BY GROUPING SETS ((status), (p), ())""")


def cube_report(docs: DataFrame) -> DataFrame:
    """Documents and characters by language and source, with all margins."""
    return docs.cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def latency(events: DataFrame) -> DataFrame:
    """By event type: median, 95th percentile, and the event of the largest and smallest value."""
    return events.groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.95), 6).alias("p95"), F.max_by("event_id", F.struct("value", "event_id")).alias("largest"), F.min_by("event_id", F.struct("value", "event_id")).alias("smallest"))


def missing(wanted: DataFrame, got: DataFrame) -> DataFrame:
    return wanted.subtract(got)


def expansion_cost(ledgers: DataFrame) -> DataFrame:
    """(strategy, searches, expansions, refused, cost) of searches, a ledger row (relax.ledger) each."""
    return ledgers.groupBy("strategy").agg(F.count("*").alias("searches"), F.sum("expansions").alias("expansions"), F.sum("refused").alias("refused"), F.sum("cost").alias("cost"))


def steiner_bound(seeds: int) -> float:
    """The ratio of a tree's cost to the least possible that the approximation keeps."""
    return 2 - 2 / seeds
