"""Streams of keystrokes and events: windows, sessions, joins in time, state, and their batch twins."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.complete import complete_batch
from ..operators.index import Cache


def with_time(events: DataFrame) -> DataFrame:
    """ts as a timestamp, which watermarks need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def with_lateness(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return with_time(events).withWatermark("ts", delay)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedupe(events: DataFrame, key: str = "event_id", delay: str = "1 hour") -> DataFrame:
    """Each key once, as long as its repeats come within the delay."""
    return with_lateness(events, delay).dropDuplicatesWithinWatermark([key])


def gaps(events: DataFrame) -> DataFrame:
    """(user_id, event_id, gap): seconds since the user's event before."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("user_id", "event_id", (F.unix_micros("ts") - F.unix_micros(F.lag("ts").over(order))).alias("gap"))


def recent(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """(event_id, n): the user's events in the time up to each event."""
    order = Window.partitionBy("user_id").orderBy(F.unix_seconds("ts")).rangeBetween(-seconds, 0)
    return events.select("event_id", F.count("*").over(order).alias("n"))


def asof(left: DataFrame, right: DataFrame, by: str, ts: str, value: str) -> DataFrame:
    """left with the last `value` of right at or before each row's time, by key: one sorted pass over both sides, no range join."""
    both = left.select(by, ts, F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side")).unionByName(
        right.select(by, ts, F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("_row"), F.col(value).alias("_v"), F.lit(0).alias("_side")))
    order = Window.partitionBy(by).orderBy(ts, "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(order)).where("_side = 1").select("_row.*", f"last_{value}")


def within(left: DataFrame, right: DataFrame, by: str, seconds: int) -> DataFrame:
    """Pairs of a key whose right time follows the left within `seconds`; keyed by time slots too, so a busy key is cut into slots."""
    slot = lambda c: F.floor(F.unix_seconds(c) / seconds)
    a = left.select(by, F.col("event_id").alias("left_id"), F.col("ts").alias("left_ts")).withColumn("slot", F.explode(F.array(slot(F.col("left_ts")), slot(F.col("left_ts")) + 1)))
    b = right.select(by, F.col("event_id").alias("right_id"), F.col("ts").alias("right_ts")).withColumn("slot", slot(F.col("right_ts")))
    near = (F.col("right_ts") > F.col("left_ts")) & (F.unix_micros("right_ts") - F.unix_micros("left_ts") <= seconds * 1_000_000)
    return a.join(b, [by, "slot"]).where(near).select(by, "left_id", "right_id")


def sink(df: DataFrame, out: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what there is, into the Parquet folder out: append adds each batch, complete replaces what was there. Gives the folder's rows.

    A batch that is run again after a failure writes its own folder again and adds nothing twice.
    """

    def run(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/all" if mode == "complete" else f"{out}/batch={n}")

    df.writeStream.foreachBatch(run).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    spark = df.sparkSession
    return spark.read.schema(df.schema).parquet(f"{out}/all") if mode == "complete" else spark.read.schema(f"{ddl(df)}, batch long").option("basePath", out).parquet(out).select(df.columns)


def ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)


def each_batch(df: DataFrame, f: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    df.writeStream.foreachBatch(f).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def complete_stream(c: Cache, typed: DataFrame, out: str, checkpoint: str, k: int = 10) -> None:
    """Completions of a stream of typed texts (column t), appended to the Parquet folder out; each batch is a batch completion."""

    def run(batch: DataFrame, n: int) -> None:
        complete_batch(c, batch, k).withColumn("batch", F.lit(n)).write.mode("append").parquet(out)

    each_batch(typed, run, checkpoint)


ATTEMPTS = "user_id long, attempts long, outcome string"


def attempts(events: DataFrame) -> DataFrame:
    """(user_id, attempts, outcome): clicks until a purchase or an error, for each such end; state is one count a user.

    A user's rows of a batch may come in several frames in any order, so what counts of them is put together before it is sorted.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        count = state.get[0] if state.exists else 0
        rows = []
        for kind in pd.concat(list(frames)).sort_values(["ts", "event_id"])["event_type"]:
            if kind == "click":
                count += 1
            else:
                rows.append((key[0], count, "success" if kind == "purchase" else "gave_up"))
                count = 0
        state.update((count,))
        yield pd.DataFrame(rows, columns=["user_id", "attempts", "outcome"])

    told = with_time(events).where(F.col("event_type").isin("click", "purchase", "error")).select("user_id", "ts", "event_id", "event_type")
    return told.groupBy("user_id").applyInPandasWithState(step, ATTEMPTS, "count long", "append", "NoTimeout")


def attempts_batch(events: DataFrame) -> DataFrame:
    """The batch twin of attempts(): clicks between ends, by windows."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    ends = F.col("event_type").isin("purchase", "error")
    part = events.withColumn("run", F.coalesce(F.sum(ends.cast("int")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return part.groupBy("user_id", "run").agg(F.count_if(F.col("event_type") == "click").alias("attempts"), F.max(F.when(F.col("event_type") == "purchase", "success").when(F.col("event_type") == "error", "gave_up")).alias("outcome")).where("outcome IS NOT NULL").select("user_id", "attempts", "outcome")


def register_udtf(spark: SparkSession, terms: list[tuple[str, int]]) -> None:
    """complete_terms(text, k) for SQL, over a bounded list of (term, score)."""
    held = sorted(terms, key=lambda t: (-t[1], len(t[0]), t[0]))

    @F.udtf(returnType="rank int, term string")
    class CompleteTerms:
        def eval(self, text: str, k: int):
            found = (t for t, _ in held if text and not text.startswith("?") and text.lower() in t.lower())
            for i, t in enumerate(found):
                if i == k:
                    return
                yield i + 1, t

    spark.udtf.register("complete_terms", CompleteTerms)
