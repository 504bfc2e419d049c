"""Rows counted by keys, and the counts met with the literals of these keys: what is shuffled are sorted keys as gaps, and not the rows."""

from __future__ import annotations

import pickle
import sys
import zlib
from collections.abc import Callable, Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # workers may not have this package on their path

#: Keys that differ in their lower bits alone share a bucket, so their gaps are small; of buckets there are two to the second number.
BLOCK_BITS, BUCKET_BITS = 12, 10
#: Bytes of rows that a task holds and sorts at once.
HELD = 100_000_000

PACKETS = pa.schema([("link", pa.int32()), ("bucket", pa.int32()), ("lits", pa.bool_()), ("data", pa.binary())])
SPEC = "link int, bucket int, lits boolean, data binary"


def bucket_of(keys: np.ndarray) -> np.ndarray:
    return ((keys >> BLOCK_BITS).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)


def small(values: np.ndarray) -> np.ndarray:
    """Values from zero on, in as few bytes each as the largest needs."""
    return values.astype(np.min_scalar_type(int(values.max(initial=0))))


def pack(keys: np.ndarray, values: np.ndarray, names: pa.Array | None = None) -> Iterator[tuple[int, bytes]]:
    """(bucket, data) of sorted keys, each with a value from zero on. With names, a value stands for the name at its place."""
    bucket = bucket_of(keys)
    order = np.argsort(bucket, kind="stable")
    bucket, keys, values = bucket[order], keys[order], values[order]
    starts = np.flatnonzero(np.diff(bucket, prepend=-1))
    for a, b in zip(starts, [*starts[1:], len(keys)], strict=True):
        own, held = values[a:b], None
        if names is not None:
            met, own = np.unique(own, return_inverse=True)
            held = names.take(pa.array(met)).to_pylist()
        gaps = np.diff(keys[a:b].astype(np.uint64))
        yield int(bucket[a]), zlib.compress(pickle.dumps((int(keys[a]), small(gaps), small(own), held)), 6)


def unpack(data: bytes) -> tuple[np.ndarray, np.ndarray, list[str] | None]:
    """(keys, values, names) of a packet."""
    base, gaps, values, names = pickle.loads(zlib.decompress(data))
    return np.int64(base) + np.concatenate([[0], np.cumsum(gaps.astype(np.int64))]).astype(np.int64), values.astype(np.int64), names


def _sent(rows: Iterable[tuple[int, int, bool, bytes]]) -> pa.RecordBatch:
    found = list(zip(*rows, strict=True)) or [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(found, PACKETS, strict=True)], schema=PACKETS)


def _held(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.Table]:
    kept, size = [], 0
    for b in batches:
        if b.num_rows:
            kept.append(b)
            size += b.nbytes
        if size >= HELD:
            yield pa.Table.from_batches(kept)
            kept, size = [], 0
    if kept:
        yield pa.Table.from_batches(kept)


def _counting(links: list[int]) -> Callable:
    def counted(batches):
        for rows in _held(batches):
            for i, column in zip(links, rows.columns, strict=True):
                keys, n = np.unique(column.drop_null().to_numpy(), return_counts=True)
                if len(keys):
                    yield _sent((i, bucket, False, data) for bucket, data in pack(keys, n))

    return counted


def _naming(link: int) -> Callable:
    def named(batches):
        for rows in _held(batches):
            rows = rows.drop_null()
            if rows.num_rows:
                keys, lits = rows.column(0).to_numpy(), rows.column(1).combine_chunks().dictionary_encode()
                order = np.argsort(keys, kind="stable")
                yield _sent((link, bucket, True, data) for bucket, data in pack(keys[order], lits.indices.to_numpy()[order], lits.dictionary))

    return named


def _met(packets: pa.Table) -> pa.Table:
    """(lit, score) of a bucket: of each literal, the rows counted at the keys that carry it. A key that carries a literal twice counts once."""
    own = [unpack(d) for d, lits in zip(packets.column("data").to_pylist(), packets.column("lits").to_pylist(), strict=True) if not lits]
    held = [unpack(d) for d, lits in zip(packets.column("data").to_pylist(), packets.column("lits").to_pylist(), strict=True) if lits]
    out, sums = [], np.zeros(0, np.int64)
    if own and held:
        keys, n = (np.concatenate([p[i] for p in own]) for i in (0, 1))
        order = np.argsort(keys, kind="stable")
        keys, n = keys[order], n[order]
        starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        keys, n = keys[starts], np.add.reduceat(n, starts)
        places: dict[str, int] = {}
        at = np.concatenate([k for k, _, _ in held])
        lit = np.concatenate([np.array([places.setdefault(x, len(places)) for x in names], np.int64)[values] for _, values, names in held])
        order = np.lexsort((at, lit))
        at, lit = at[order], lit[order]
        place = np.minimum(np.searchsorted(keys, at), len(keys) - 1)
        keep = (keys[place] == at) & np.r_[True, (at[1:] != at[:-1]) | (lit[1:] != lit[:-1])]
        place, lit = place[keep], lit[keep]
        if len(lit):
            starts = np.flatnonzero(np.r_[True, lit[1:] != lit[:-1]])
            texts = list(places)
            out, sums = [texts[i] for i in lit[starts].tolist()], np.add.reduceat(n[place], starts)
    return pa.table({"lit": pa.array(out, pa.string()), "score": pa.array(sums, pa.int64())})


def counts(rows: DataFrame, columns: dict[int, str]) -> DataFrame:
    """Packets of how often each key occurs in a column of whole numbers, for each link's column, by one scan."""
    return rows.select(*[F.col(c).cast("long").alias(f"k{i}") for i, c in columns.items()]).mapInArrow(_counting(list(columns)), SPEC)


def names(held: DataFrame, link: int) -> DataFrame:
    """Packets of (key, literal) rows, of the keys that a link points at."""
    key, lit = held.columns
    return held.select(F.col(key).cast("long").alias("k"), F.col(lit).cast("string").alias("lit")).mapInArrow(_naming(link), SPEC)


def met(packets: list[DataFrame]) -> DataFrame:
    """(lit, score) by link and bucket: a literal may come from several."""
    return reduce(DataFrame.unionByName, packets).groupBy("link", "bucket").applyInArrow(_met, "lit string, score long")
