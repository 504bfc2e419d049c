"""Reading the given tables, flat files, triple files and streams, and writing them."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table with its declared schema; nothing is inferred."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def _place(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def shared_folder(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir, removed when the application ends if not before.

    A local master without that setting (tests) gets a temporary folder; a cluster must name one.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "rdf_assist_shared")
    path = f"{base.rstrip('/')}/{uuid.uuid4().hex}"
    fs, at = _place(spark, path)
    fs.deleteOnExit(at)
    return path


def remove_folder(spark: SparkSession, path: str) -> None:
    fs, at = _place(spark, path)
    fs.delete(at, True)


def written(df: DataFrame) -> DataFrame:
    """df written once to a shared folder and read again: its lineage ends there."""
    path = f"{shared_folder(df.sparkSession)}/t"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_flat(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """CSV (with header) or JSON lines; rows that do not fit go whole to the column _bad."""
    reader = spark.read.schema(f"{schema}, _bad string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad")
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


_LINE = r'^<([^>]*)> <([^>]*)> (?:<([^>]*)>|"((?:[^"\\]|\\.)*)"(?:@([A-Za-z-]+)|\^\^<([^>]*)>)?) \.$'


def write_ntriples(triples: DataFrame, path: str) -> None:
    """One line a triple; literals escape backslash, quote, line feed, carriage return and tab."""
    body = F.col("o")
    for mark, code in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        body = F.replace(body, F.lit(mark), F.lit(code))
    literal = F.concat(F.lit('"'), body, F.lit('"'), F.when(F.col("o_lang").isNotNull(), F.concat(F.lit("@"), F.col("o_lang"))).when(F.col("o_dtype") != "string", F.concat(F.lit("^^<"), F.col("o_dtype"), F.lit(">"))).otherwise(""))
    target = F.when(F.col("o_kind") == "iri", F.concat(F.lit("<"), F.col("o"), F.lit(">"))).otherwise(literal)
    triples.select(F.concat(F.lit("<"), F.col("s"), F.lit("> <"), F.col("p"), F.lit("> "), target, F.lit(" .")).alias("value")).write.text(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o, o_kind, o_dtype, o_lang) of each line that is a triple; other lines are left out."""
    lines = spark.read.text(path).where(F.col("value").rlike(_LINE))
    part = [F.regexp_extract("value", _LINE, i) for i in range(7)]
    iri = part[3] != ""
    plain = F.regexp_replace(part[4], r"\\\\", "\u0001")
    for code, mark in ((r"\\n", "\n"), (r"\\r", "\r"), (r"\\t", "\t"), (r'\\"', '"')):
        plain = F.regexp_replace(plain, code, mark)
    return lines.select(
        part[1].alias("s"), part[2].alias("p"),
        F.when(iri, part[3]).otherwise(F.replace(plain, F.lit("\u0001"), F.lit("\\"))).alias("o"),
        F.when(iri, "iri").otherwise("literal").alias("o_kind"),
        F.when(iri, None).when(part[6] != "", part[6]).otherwise("string").alias("o_dtype"),
        F.when(part[5] != "", part[5]).alias("o_lang"),
    )


def save(df: DataFrame, path: str, by: tuple[str, ...] = (), rows_per_file: int = 0) -> None:
    """Parquet in one folder for each value of `by`; the rows of a value may fill several files."""
    writer = df.write.mode("overwrite").option("compression", "zstd")
    if rows_per_file:
        writer = writer.option("maxRecordsPerFile", rows_per_file)
    (writer.partitionBy(*by) if by else writer).parquet(path)


def save_bucketed(df: DataFrame, table: str, by: str, buckets: int) -> None:
    """A table whose rows of one key lie in one bucket, so joins on the key do not shuffle it."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table as a file stream, with its time column as a UTC timestamp that watermarks accept."""
    found = spark.readStream.schema(SCHEMAS[name]).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return found.withColumn("ts", F.col("ts").cast("timestamp")) if name == "events" else found
