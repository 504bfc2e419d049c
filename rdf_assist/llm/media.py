"""Media columns: payloads stored as lossless WebP in a binary column, and read back as pixels."""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import webp
from .common import remote, texts

HERE = __name__


def payload_of(text: str | None) -> tuple[bytes, int]:
    """(UTF-8 bytes filled up with zeros to a positive multiple of 64, bytes before that)."""
    raw = (text or "").encode("utf-8")
    return raw + bytes(-len(raw) % 64 if raw else 64), len(raw)


def store_batches(batches):
    for b in batches:
        for at in range(0, b.num_rows, 1024):
            part = b.slice(at, 1024)
            payloads = [payload_of(t) for t in part.column("text").to_pylist()]
            media = webp.encode_many([p for p, _ in payloads])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([n for _, n in payloads], pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])


def store(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media binary) of every row. Null and empty texts store 64 zero bytes."""
    return texts(docs).mapInArrow(remote(HERE, "store_batches"), "doc_id long, n_bytes long, media binary")


def feature(pixels: np.ndarray) -> str:
    """Shares of the sample values by 32s in thousandths, and their mean: equal samples, equal feature."""
    counts = np.bincount(pixels >> 5, minlength=8)
    shares = (1000 * counts + len(pixels) // 2) // len(pixels)
    return "-".join(map(str, shares.tolist())) + f"/{int(pixels.sum(dtype=np.int64)) * 100 // len(pixels)}"


def feature_batches(batches):
    for b in batches:
        rows = []
        for media in b.column("media").to_pylist():
            back = webp.decode_bytes(media)
            rows.append((len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature(np.frombuffer(back, np.uint8))))
        cols = list(zip(*rows, strict=True)) or [[]] * 6
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("n_bytes"), *[pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)]], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])


def features(stored: DataFrame) -> DataFrame:
    """What reading each stored medium back gives: sizes, digests and a feature of its samples."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return stored.select("doc_id", "n_bytes", "media").mapInArrow(remote(HERE, "feature_batches"), schema)


def pixel_batches(batches):
    for b in batches:
        ids, h, w, flat = [], [], [], []
        for d, media in zip(b.column("doc_id").to_pylist(), b.column("media").to_pylist(), strict=True):
            while media:
                _, n = webp.unframe(media)
                p = webp.decode(media[:n])
                ids.append(d)
                h.append(p.shape[0])
                w.append(p.shape[1])
                flat.append(p.tobytes())
                media = media[n:]
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(h, pa.int32()), pa.array(w, pa.int32()), pa.array(flat, pa.binary())], ["doc_id", "height", "width", "argb"])


def pixels(stored: DataFrame) -> DataFrame:
    """(doc_id, height, width, argb binary): a row for each image of each stored medium, by the full decoder."""
    return stored.select("doc_id", "media").mapInArrow(remote(HERE, "pixel_batches"), "doc_id long, height int, width int, argb binary")
