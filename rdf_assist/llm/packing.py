"""Packing documents into sequences of a fixed capacity, shortest pack first over the length histogram.

Documents are cut at multiples of the capacity. The histogram of piece lengths (at most one entry for
each length) is packed on the driver: lengths go longest first, each to the packs that are filled least,
as counts of whole packing patterns, never piece by piece. Patterns then meet pieces by rank within
their length.
"""

from __future__ import annotations

import heapq
import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, remote, texts
from .tokens import encoder, runs_of

HERE = __name__
PIECES = "doc_id long, start long, length int, ids_crc32 long, doc_tokens long"


def piece_batches(batches, path: str, end: int, capacity: int):
    enc = encoder(path)
    tail = end.to_bytes(4, "little")
    step = 4 * capacity
    for b in batches:
        doc, start, length, crc, total = [], [], [], [], []
        found = (ids for run in runs_of(b.column("text").to_pylist()) for ids in enc.encode_all([t or "" for t in run]))
        for d, ids in zip(b.column("doc_id").to_pylist(), found, strict=True):
            ids += tail
            view = memoryview(ids)
            for at in range(0, len(ids), step):
                part = view[at : at + step]
                doc.append(d)
                start.append(at // 4)
                length.append(len(part) // 4)
                crc.append(zlib.crc32(part))
                total.append(len(ids) // 4)
        yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(length, pa.int32()), pa.array(crc, pa.int64()), pa.array(total, pa.int64())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])


def shortest_pack_first(histogram: dict[int, int], capacity: int) -> list[tuple[int, list[int]]]:
    """(count, piece lengths) of each packing pattern; pieces stand longest first in a pattern.

    Packs are kept as counts by pattern in a heap ordered by free space, so a step costs the number of
    patterns it touches. Each length splits at most one pattern, which bounds the patterns by about twice the lengths.
    """
    packs: list[tuple[int, int, int, tuple]] = []  # (-free, order, count, lengths linked back)
    done, order = [], 0
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        put = []
        while left:
            if packs and -packs[0][0] >= length:
                free, _, count, lengths = heapq.heappop(packs)
                take = min(left, count)
                if take < count:
                    order += 1
                    put.append((free, order, count - take, lengths))
                order += 1
                grown = (free + length, order, take, (length, lengths))
                heapq.heappush(packs, grown)
                left -= take
                for p in put:
                    heapq.heappush(packs, p)
                put = []
            else:
                order += 1
                heapq.heappush(packs, (length - capacity, order, left, (length, ())))
                left = 0
    for _, _, count, lengths in packs:
        flat = []
        while lengths:
            flat.append(lengths[0])
            lengths = lengths[1]
        done.append((count, flat[::-1]))
    return sorted(done, key=lambda p: (-sum(p[1]), p[1]))


def slots(patterns: list[tuple[int, list[int]]]) -> dict[str, np.ndarray]:
    """Runs of ranks of each length, by (length, first rank), and where they go: sequence of the first and offset."""
    next_rank: dict[int, int] = {}
    rows, base = [], 0
    for count, lengths in patterns:
        offset = 0
        for n in lengths:
            rank = next_rank.get(n, 0)
            rows.append((n, rank, base, offset))
            next_rank[n] = rank + count
            offset += n
        base += count
    rows.sort()
    return {k: np.array([r[i] for r in rows], np.int64) for i, k in enumerate(("length", "rank", "sequence", "offset"))}


def place_batches(batches, runs: dict):
    first = {int(n): int(i) for i, n in reversed(list(enumerate(runs["length"])))}
    counts = {int(n): int(c) for n, c in zip(*np.unique(runs["length"], return_counts=True), strict=True)}
    for b in batches:
        length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
        at = np.zeros(len(length), np.int64)
        for n in np.unique(length).tolist():
            lo = first[n]
            own = length == n
            at[own] = lo + np.searchsorted(runs["rank"][lo : lo + counts[n]], rank[own], "right") - 1
        sequence = runs["sequence"][at] + rank - runs["rank"][at]
        keep = [i for i, c in enumerate(b.schema.names) if c != "rank"]
        yield pa.RecordBatch.from_arrays([b.column(i) for i in keep] + [pa.array(sequence), pa.array(runs["offset"][at])], [b.schema.names[i] for i in keep] + ["sequence_id", "offset"])


def place(pieces: DataFrame, capacity: int = 2048, per_group: int = 50_000) -> DataFrame:
    """pieces (durable; with doc_id, start, length, ids_crc32) with sequence_id and offset.

    A piece's rank within its length is the number of that length in groups before its own, plus its rank
    in the group; groups are equal shares by hash, so a length that holds a third of all pieces spreads.
    """
    found = pieces.groupBy("length").count().collect()  # at most `capacity` rows
    histogram = {r["length"]: r["count"] for r in found}
    runs = slots(shortest_pack_first(histogram, capacity))
    groups = max(1, math.ceil(sum(histogram.values()) / per_group))
    held = pieces.withColumn("g", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(groups)))
    sizes = held.groupBy("length", "g").count()
    before = Window.partitionBy("length").orderBy("g").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("length", "g", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"))
    inside = Window.partitionBy("g", "length").orderBy("doc_id", "start", "ids_crc32")
    ranked = held.withColumn("n", F.row_number().over(inside)).join(offsets, ["g", "length"]).withColumn("rank", F.col("n") - 1 + F.col("before"))
    ranked = ranked.select(*pieces.columns, "rank")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"
    return ranked.mapInArrow(remote(HERE, "place_batches", runs=runs), schema)


def pack(docs: DataFrame, path: str, end: int = 1, capacity: int = 2048) -> DataFrame:
    """A row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Each id of a document, and the end id after it, lies in one piece. Null and empty texts hold the end
    id alone. Repeated rows are packed each. Sequence ids are dense from 0; a sequence is filled from
    offset 0 without gaps and padded at its end (see padding()). No rows give no rows.
    """
    pieces = durable(texts(docs).mapInArrow(remote(HERE, "piece_batches", path=path, end=end, capacity=capacity), PIECES))
    return place(pieces, capacity).withColumn("length", F.col("length").cast("long"))


def padding(packed: DataFrame, capacity: int = 2048) -> DataFrame:
    """One row: sequences, tokens, pad tokens (none for a sequence whose fill is a power of two), share of pad."""
    fill = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count("n") == 1, 0).otherwise(F.lit(capacity) - F.col("n"))
    out = fill.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("pad"))
    return out.withColumn("share", F.col("pad") / (F.col("pad") + F.col("tokens")))


def sequence_batches(batches, path: str, end: int):
    """Rows (sequence_id, offset, ids) of pieces given with their document's text."""
    enc = encoder(path)
    for b in batches:
        out = []
        for t, start, length in zip(b.column("text").to_pylist(), b.column("start").to_pylist(), b.column("length").to_pylist(), strict=True):
            ids = np.frombuffer(enc.encode(t or "") + end.to_bytes(4, "little"), "<u4")
            out.append(ids[start : start + length].astype(np.int64).tolist())
        yield pa.RecordBatch.from_arrays([b.column("sequence_id"), b.column("offset"), pa.array(out, pa.list_(pa.int64()))], ["sequence_id", "offset", "ids"])


def sequences(docs: DataFrame, packed: DataFrame, path: str, end: int = 1) -> DataFrame:
    """(sequence_id, ids): the packed sequences themselves, without padding. doc_id must be unique in docs."""
    both = packed.join(texts(docs), "doc_id").select("text", "start", "length", "sequence_id", "offset")
    ids = both.mapInArrow(remote(HERE, "sequence_batches", path=path, end=end), "sequence_id long, offset long, ids array<long>")
    return ids.groupBy("sequence_id").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("offset", "ids"))), lambda x: x["ids"])).alias("ids"))
