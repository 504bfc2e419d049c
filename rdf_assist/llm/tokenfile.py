"""Token-id files: patched frame-of-reference blocks.

A block holds 256 ids. Its minimum is subtracted; what remains is packed at the width that the chosen
percentile of the block needs, and ids that need more go whole into an exception list. Blocks are
written in segments; the footer indexes where each block's bits and exceptions start, and lists the
documents with their lengths, so that a range of ids is read from its blocks alone.

Layout: magic, then for each segment the bits of its blocks, exception positions (u8) and exception
values (u32); then a zstd-compressed footer, its length (u64) and the magic again.
"""

from __future__ import annotations

import io
import os
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, remote, shared_dir, text_bytes, texts
from .tokens import encoder, runs_of

HERE = __name__
MAGIC = b"PFORIDS1"
BLOCK = 256
SEGMENT = 2048 * BLOCK


def _bit_lengths(x: np.ndarray) -> np.ndarray:
    return np.frexp(x.astype(np.float64))[1].astype(np.uint8)


def pack_blocks(ids: np.ndarray, percentile: float = 90.0) -> dict[str, np.ndarray]:
    """mins, widths, counts of exceptions, bits, positions and values of the blocks of ids (u32); the last block is filled up with its first id."""
    n = len(ids)
    blocks = -(-n // BLOCK)
    x = np.empty(blocks * BLOCK, np.uint32)
    x[:n] = ids
    if n % BLOCK:
        x[n:] = ids[(blocks - 1) * BLOCK]
    x = x.reshape(blocks, BLOCK)
    low = x.min(axis=1) if blocks else np.zeros(0, np.uint32)
    rest = x - low[:, None]
    need = _bit_lengths(rest)
    k = min(BLOCK - 1, int(np.ceil(percentile / 100 * BLOCK)) - 1)
    width = np.partition(need, k, axis=1)[:, k] if blocks else np.zeros(0, np.uint8)
    over = need > width[:, None]
    row, col = np.nonzero(over)
    values = rest[row, col]
    rest[over] = 0
    size = width.astype(np.int64) * (BLOCK // 8)
    start = np.r_[0, np.cumsum(size)]
    bits = np.zeros(int(start[-1]), np.uint8)
    for w in np.unique(width).tolist():
        if w:
            own = np.flatnonzero(width == w)
            flat = ((rest[own][:, :, None] >> np.arange(w, dtype=np.uint32)) & 1).astype(np.uint8)
            bits[(start[own][:, None] + np.arange(w * BLOCK // 8)).ravel()] = np.packbits(flat.reshape(len(own), -1), axis=1, bitorder="little").ravel()
    return {"low": low, "width": width, "over": np.bincount(row, minlength=blocks).astype(np.uint16), "bits": bits, "pos": col.astype(np.uint8), "value": values.astype(np.uint32)}


def unpack_blocks(low, width, over, bits, pos, value) -> np.ndarray:
    """The ids of whole blocks, from the arrays of pack_blocks()."""
    blocks = len(low)
    out = np.zeros((blocks, BLOCK), np.uint32)
    start = np.r_[0, np.cumsum(width.astype(np.int64) * (BLOCK // 8))]
    for w in np.unique(width).tolist():
        if w:
            own = np.flatnonzero(width == w)
            packed = bits[(start[own][:, None] + np.arange(w * BLOCK // 8)).ravel()].reshape(len(own), -1)
            flat = np.unpackbits(packed, axis=1, bitorder="little").reshape(len(own), BLOCK, w)
            acc = np.zeros((len(own), BLOCK), np.uint32)
            for i in range(w):
                acc |= flat[:, :, i].astype(np.uint32) << np.uint32(i)
            out[own] = acc
    out[np.repeat(np.arange(blocks), over), pos] = value
    return (out + low[:, None]).ravel()


class Writer:
    """Streams ids of documents into a file object."""

    def __init__(self, sink, percentile: float = 90.0):
        self.sink, self.percentile = sink, percentile
        self.docs: list[tuple[int | None, int]] = []
        self.pending: list[np.ndarray] = []
        self.held = self.total = 0
        self.index: list[tuple[int, dict]] = []
        self.at = len(MAGIC)
        sink.write(MAGIC)

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.docs.append((doc_id, len(ids)))
        self.pending.append(ids)
        self.held += len(ids)
        self.total += len(ids)
        if self.held >= SEGMENT:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.pending) if self.pending else np.zeros(0, np.uint32)
        while len(ids) >= SEGMENT or last and len(ids):
            x = pack_blocks(ids[:SEGMENT], self.percentile)
            ids = ids[SEGMENT:]
            data = x["bits"].tobytes() + x["pos"].tobytes() + x["value"].astype("<u4").tobytes()
            self.sink.write(data)
            self.index.append((self.at, {k: x[k] for k in ("low", "width", "over")}))
            self.at += len(data)
        self.pending, self.held = [ids], len(ids)

    def close(self) -> None:
        self._flush(True)
        out = io.BytesIO()
        out.write(struct.pack("<QQQ", self.total, len(self.docs), len(self.index)))
        out.write(np.array([d is None for d, _ in self.docs], np.uint8).tobytes())
        out.write(np.array([d or 0 for d, _ in self.docs], "<i8").tobytes())
        out.write(np.array([n for _, n in self.docs], "<i8").tobytes())
        for at, x in self.index:
            out.write(struct.pack("<QQ", at, len(x["low"])))
            out.write(x["low"].astype("<u4").tobytes() + x["width"].tobytes() + x["over"].astype("<u2").tobytes())
        footer = zstandard.ZstdCompressor(level=3).compress(out.getvalue())
        self.sink.write(footer + struct.pack("<Q", len(footer)) + MAGIC)


class Reader:
    """Documents and id ranges of a file's bytes."""

    def __init__(self, content: bytes):
        if content[: len(MAGIC)] != MAGIC or content[-len(MAGIC) :] != MAGIC:
            raise ValueError("not a token-id file, or cut short")
        self.content = memoryview(content)
        (n,) = struct.unpack("<Q", content[-16:-8])
        raw = zstandard.ZstdDecompressor().decompress(content[-16 - n : -16])
        self.total, docs, segments = struct.unpack_from("<QQQ", raw)
        at = 24
        self.null = np.frombuffer(raw, np.uint8, docs, at)
        self.doc_id = np.frombuffer(raw, "<i8", docs, at + docs)
        self.length = np.frombuffer(raw, "<i8", docs, at + 9 * docs)
        at += 17 * docs
        self.segments = []
        for _ in range(segments):
            begin, blocks = struct.unpack_from("<QQ", raw, at)
            low = np.frombuffer(raw, "<u4", blocks, at + 16)
            width = np.frombuffer(raw, np.uint8, blocks, at + 16 + 4 * blocks)
            over = np.frombuffer(raw, "<u2", blocks, at + 16 + 5 * blocks)
            self.segments.append((begin, low, width, over))
            at += 16 + 7 * blocks

    def read(self, start: int, stop: int) -> np.ndarray:
        """Ids start to stop, from the blocks that hold them."""
        start, stop = max(0, start), min(stop, self.total)
        out = []
        while start < stop:
            s, first = divmod(start, SEGMENT)
            begin, low, width, over = self.segments[s]
            last = min(stop - s * SEGMENT, SEGMENT)
            lo, hi = first // BLOCK, -(-last // BLOCK)
            size = np.r_[0, np.cumsum(width.astype(np.int64) * (BLOCK // 8))]
            listed = np.r_[0, np.cumsum(over.astype(np.int64))]
            bits = np.frombuffer(self.content, np.uint8, int(size[hi] - size[lo]), begin + int(size[lo]))
            pos = np.frombuffer(self.content, np.uint8, int(listed[hi] - listed[lo]), begin + int(size[-1] + listed[lo]))
            value = np.frombuffer(self.content, "<u4", int(listed[hi] - listed[lo]), begin + int(size[-1] + listed[-1] + 4 * listed[lo]))
            ids = unpack_blocks(low[lo:hi], width[lo:hi], over[lo:hi], bits, pos, value)
            out.append(ids[first - lo * BLOCK : last - lo * BLOCK])
            start = s * SEGMENT + last
        return np.concatenate(out) if out else np.zeros(0, np.uint32)

    def documents(self):
        """(doc_id, ids) of each document in file order, a segment at a time."""
        at, held, base = 0, np.zeros(0, np.uint32), 0
        for d, null, n in zip(self.doc_id.tolist(), self.null.tolist(), self.length.tolist(), strict=True):
            while base + len(held) < at + n:
                more = self.read(base + len(held), base + len(held) + SEGMENT)
                held, base = np.concatenate([held[at - base :], more]), at
            yield None if null else d, held[at - base : at - base + n]
            at += n


def write_batches(batches, path: str, end: int, folder: str, percentile: float):
    """One file for the task's rows, in their order. It gets its name when complete, so a repeated task replaces it whole."""
    from pyarrow import fs
    from pyspark import TaskContext

    enc = encoder(path)
    tail = end.to_bytes(4, "little")
    store, root = fs.FileSystem.from_uri(folder)
    name = f"{root}/part-{TaskContext.get().partitionId():08d}.pfor"
    draft = f"{root}/_{uuid.uuid4().hex}"
    with store.open_output_stream(draft) as sink:
        out = Writer(sink, percentile)
        for b in batches:
            found = (ids for run in runs_of(b.column("text").to_pylist()) for ids in enc.encode_all([t or "" for t in run]))
            for d, ids in zip(b.column("doc_id").to_pylist(), found, strict=True):
                out.add(d, np.frombuffer(ids + tail, "<u4"))
        out.close()
    store.move(draft, name)
    yield pa.RecordBatch.from_arrays([pa.array([os.path.basename(name)]), pa.array([len(out.docs)], pa.int64()), pa.array([out.total], pa.int64())], ["file", "n_docs", "n_tokens"])


def write(docs: DataFrame, path: str, folder: str, end: int = 1, percentile: float = 90.0, file_bytes: int = 24 << 20) -> DataFrame:
    """(file, n_docs, n_tokens) of files written to folder: ids of all texts and an end id each, in ascending doc_id order.

    Files hold ranges of doc_id of about file_bytes of text each and their names sort as their ranges do.
    Null ids come first; ties of doc_id are ordered by text. Null and empty texts hold the end id alone.
    """
    files = max(1, -(-text_bytes(docs) // file_bytes))
    ordered = texts(docs).repartitionByRange(files, "doc_id").sortWithinPartitions("doc_id", "text")
    return durable(ordered.mapInArrow(remote(HERE, "write_batches", path=path, end=end, folder=folder, percentile=percentile), "file string, n_docs long, n_tokens long"))


def digest_batches(batches, before: dict):
    for b in batches:
        for path, content in zip(b.column("path").to_pylist(), b.column("content"), strict=True):
            at = before[os.path.basename(path)]
            reader = Reader(content.as_py())
            rows = []
            for d, ids in reader.documents():
                rows.append((d, at, len(ids), zlib.crc32(np.ascontiguousarray(ids, "<u4"))))
                at += len(ids)
            columns = list(zip(*rows, strict=True)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in columns], ["doc_id", "start", "n_tokens", "ids_crc32"])


def read_back(folder: str, written: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of each document, decoded from the files in folder."""
    spark = written.sparkSession
    before, total = {}, 0
    for r in sorted(written.collect(), key=lambda r: r["file"]):  # a row for each file
        before[r["file"]] = total
        total += r["n_tokens"]
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.pfor").load(folder).select("path", "content")
    return files.mapInArrow(remote(HERE, "digest_batches", before=before), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, path: str, end: int = 1) -> DataFrame:
    folder = shared_dir(docs.sparkSession)
    return read_back(folder, write(docs, path, folder, end))
