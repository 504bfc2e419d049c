"""What the operators of this subpackage share: input columns, worker code, durable tables."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows of an Arrow batch: a text may be long, and each batch is held by Spark and by Python at once.
BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's rows per Arrow batch to BATCH_ROWS; a smaller setting stays."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def texts(docs: DataFrame) -> DataFrame:
    """(doc_id long, text string) of documents; other columns, whatever their names, stay behind."""
    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def remote(module: str, name: str, **kw):
    """Worker code by name: the worker finds this package even if only the driver had it on its path."""
    root = ROOT

    def call(batches):
        import importlib
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        try:
            yield from getattr(importlib.import_module(module), name)(batches, **kw)
        finally:  # workers live on between tasks; what Arrow holds back would stay with them
            import pyarrow

            pyarrow.default_memory_pool().release_unused()

    return call


def remote_group(module: str, name: str, **kw):
    """As remote(), for applyInPandas."""
    root = ROOT

    def call(frame):
        import importlib
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        return getattr(importlib.import_module(module), name)(frame, **kw)

    return call


def remote_pair(module: str, name: str, **kw):
    """As remote(), for applyInPandas of cogrouped frames."""
    root = ROOT

    def call(left, right):
        import importlib
        import sys

        if root not in sys.path:
            sys.path.insert(0, root)
        return getattr(importlib.import_module(module), name)(left, right, **kw)

    return call


def shared_dir(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir, removed when the application ends.

    A local master without that setting (tests) gets a temporary folder; a cluster must name one.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "rdf_assist_shared")
    path = f"{base.rstrip('/')}/{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    fs = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    fs.mkdirs(at)
    fs.deleteOnExit(at)
    return path


def durable(df: DataFrame) -> DataFrame:
    """df written once to the shared folder and read again: a cut in the lineage that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/t"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def text_bytes(docs: DataFrame) -> int:
    """Bytes of all texts; sizes buckets so that each holds a like amount at any scale."""
    return docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0


def mixed(x):
    """Well-spread 64-bit values of an integer array."""
    import numpy as np

    with np.errstate(over="ignore"):
        x = x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        return x ^ (x >> np.uint64(32))


def pack_columns(columns, level: int = 1) -> bytes:
    """Arrays of any lengths as one compressed value."""
    import numpy as np
    import zstandard

    pack = zstandard.ZstdCompressor(level=level).compress
    pieces = [pack(np.ascontiguousarray(c).tobytes()) for c in columns]
    head = " ".join(f"{c.dtype.str}:{len(p)}" for c, p in zip(columns, pieces, strict=True)).encode()
    return len(head).to_bytes(4, "little") + head + b"".join(pieces)


def unpack_columns(blob: bytes) -> list:
    import numpy as np
    import zstandard

    unpack = zstandard.ZstdDecompressor().decompress
    n = int.from_bytes(blob[:4], "little")
    out, at = [], 4 + n
    for spec in blob[4 : 4 + n].decode().split(" "):
        kind, _, size = spec.rpartition(":")
        out.append(np.frombuffer(unpack(blob[at : at + int(size)]), np.dtype(kind)))
        at += int(size)
    return out


def blobs(part, columns):
    """Record batches (part int, blob binary): the rows of each part as packed column arrays.

    One shuffle row then carries thousands of values, without a row's overhead for each.
    """
    import numpy as np
    import pyarrow as pa

    if not len(part):
        return
    order = np.argsort(part, kind="stable")
    columns = [c[order] for c in columns]
    part = part[order]
    begin = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
    out = [pack_columns([c[lo:hi] for c in columns]) for lo, hi in zip(begin, np.r_[begin[1:], len(part)], strict=True)]
    yield pa.RecordBatch.from_arrays([pa.array(part[begin], pa.int32()), pa.array(out, pa.binary())], ["part", "blob"])


def unblob(found):
    """The column arrays of blobs, one after the other; an empty list of blobs gives no columns."""
    import numpy as np

    return [np.concatenate(x) for x in zip(*map(unpack_columns, found), strict=True)]
