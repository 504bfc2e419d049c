"""The experiment workloads as one report: python experiments.py [sf_dir] [questions].

Prints a JSON line for each: harvest under limits, significance, index size, hit ratio against index size, length
filter, completion by number of cores, suggestions, relaxation by strategy and weights, the comparison, the study measures.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)


def session(cores: int):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(max(2, cores))).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def tell(name: str, value) -> None:
    print(json.dumps({"experiment": name, "result": value}, default=str), flush=True)


def rows(df) -> list:
    return [r.asDict() for r in df.collect()]


def scan_seconds(cores: int, sf_dir: str) -> None:
    """Called in a process of its own: the scan of residual bins with so many cores. The literals are the words of documents, of which there are more than of names."""
    import statistics

    from pyspark.sql import functions as F

    from rdf_assist.operators.complete import residual_search
    from rdf_assist.operators.index import Cache
    from rdf_assist.sources.tables import load

    spark = session(cores)
    words = load(spark, sf_dir, "documents").select(F.explode(F.split("text", "[ \n]")).alias("lit")).where("length(lit) BETWEEN 1 AND 80")
    held = words.select("lit", F.lit(0).cast("long").alias("score"), F.length("lit").alias("lit_len")).repartition(4 * 8).cache()
    held.count()
    c = Cache(held.limit(0), held.limit(0), held)
    took = []
    for t in ("thion", "eredst", "ouand", "inwh", "tionre"):
        start = time.perf_counter()
        residual_search(c, t).collect()
        took.append(time.perf_counter() - start)
    print(statistics.median(took[1:]))


def main(sf_dir: str, n_questions: int) -> None:
    from rdf_assist import queries
    from rdf_assist.operators import complete, harvest, measures, relax, workloads
    from rdf_assist.operators.mapping import Graph
    from rdf_assist.plans.parse import parse
    from rdf_assist.sources.tables import written

    for cores in (1, 2, 4, 8):
        done = subprocess.run([sys.executable, __file__, "--scan", str(cores), sf_dir], capture_output=True, text=True, timeout=600)
        tell("residual scan, seconds by cores", {"cores": cores, "seconds": done.stdout.strip().splitlines()[-1] if done.stdout.strip() else done.stderr[-200:]})
    spark = session(8)
    g = workloads.star(spark, sf_dir)
    for limit in (100, 1000, 10_000):
        log = harvest.plan_harvest(g, harvest.EndpointCost(limit))
        tell("harvest by timeout", {"timeout_rows": limit, "by_status": rows(log.groupBy("status").count()), "coverage": rows(harvest.coverage(g, log))})
    tell("harvest without a hierarchy", rows(harvest.plan_harvest_flat(Graph(spark, sf_dir, ("log", "vec"), False), harvest.EndpointCost(2500)).groupBy("status").count()))
    tell("most significant literals", rows(queries.top_significant(spark, sf_dir).limit(10)))
    tell("index", rows(queries.index_stats(spark, sf_dir)))
    tell("hit ratio by indexed literals", rows(queries.index_hit_ratio_by_size(spark, sf_dir)))
    held = queries.cache(spark, sf_dir)
    for gamma in (10, 80):
        start = time.perf_counter()
        for t in ("r#0000", "mach", "plate"):
            complete.residual_search(held, t, gamma=gamma).collect()
        tell("bins with and without the length filter", {"gamma": gamma, "seconds": round((time.perf_counter() - start) / 3, 3)})
    tell("literals skipped by the length filter", rows(queries.bins_elimination(spark, sf_dir)))
    for name in ("suggest_terms_misspelled", "suggest_terms_plural"):
        start = time.perf_counter()
        found = rows(queries.ALL[name](spark, sf_dir))
        tell(name, {"seconds": round(time.perf_counter() - start, 2), "first": found[:1], "n": len(found)})
    q = parse('SELECT * WHERE { ?x name "Customer#000000008" . ?y name "Supplier#000000003" }')
    for kw in ({}, {"strategy": "single", "budget": 1000}, {"w_query": 1, "w_default": 1}, {"budget": 5}):
        start = time.perf_counter()
        made, _ = relax.relax(g, q, ["customer", "supplier"], **kw)
        tell("relaxation", {**kw, "found": made.found, "cost": made.cost, "trees": len(made.trees), "expanded": len(made.expanded), "refused": made.refused, "seconds": round(time.perf_counter() - start, 2)})
    qs = workloads.questions(50)[:: max(1, 50 // n_questions)]
    verdicts = written(measures.judge_rows(*queries.comparison_runs(spark, sf_dir, qs)))
    tell("comparison", {"questions": len(qs), "scores": rows(measures.scores(verdicts, len(qs)))})
    tell("recall over factoid questions", rows(measures.factoid_recall(verdicts, queries._factoid(spark, qs))))
    for name in ("study_success_ci", "study_answered_any", "study_attempts", "study_giveup", "study_time", "study_permutation_p", "study_suggestion_usage"):
        tell(name, rows(queries.ALL[name](spark, sf_dir)))
    spark.stop()


if __name__ == "__main__":
    if sys.argv[1:2] == ["--scan"]:
        scan_seconds(int(sys.argv[2]), sys.argv[3])
    else:
        main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", int(sys.argv[2]) if len(sys.argv) > 2 else 50)
