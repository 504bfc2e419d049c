"""Keys that occur more than once, found by fingerprints: what is shuffled is two to three bytes a row and not the rows."""

from __future__ import annotations

import sys
import zlib
from collections.abc import Callable, Iterable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # workers may not have this package on their path

#: Bits of a fingerprint where the number of rows is not known.
BITS = 48
#: Where it is known: as many more than the number's own, so one key in a thousand shares its fingerprint with another.
SPARE = 10
#: A fingerprint's upper bits name its bucket.
BUCKET_BITS = 10
#: Fingerprints that a task holds and sorts at once.
HELD = 4_000_000

PACKETS = pa.schema([("bucket", pa.int32()), ("base", pa.int64()), ("width", pa.int32()), ("n", pa.int32()), ("gaps", pa.binary())])


def bits_for(n: int) -> int:
    """Bits of the fingerprints of n rows: the fewer, the smaller are the gaps."""
    return min(62, max(36, n.bit_length() + SPARE))


def mark(kind: str, keys: Iterable[str], bits: int = BITS) -> Column:
    """The fingerprint of a row's key."""
    return F.xxhash64(F.lit(kind), *keys).bitwiseAND(F.lit((1 << bits) - 1))


def pack(h: np.ndarray, bits: int = BITS) -> list[tuple[int, int, int, bytes]]:
    """(bucket, base, width, gaps) of fingerprints: sorted, each bucket's first one and the gaps that follow, in as many bytes each as the widest needs."""
    h = np.sort(h)
    bucket = h >> (bits - BUCKET_BITS)
    starts = np.flatnonzero(np.diff(bucket, prepend=-1))
    out = []
    for a, b in zip(starts, [*starts[1:], len(h)], strict=True):
        gaps = np.diff(h[a:b])
        width = max(1, -(-int(gaps.max(initial=0)).bit_length() // 8))
        out.append((int(bucket[a]), int(h[a]), width, gaps.astype("<i8").view(np.uint8).reshape(-1, 8)[:, :width].tobytes()))
    return out


def unpack(base: int, width: int, gaps: bytes) -> np.ndarray:
    wide = np.zeros((len(gaps) // width, 8), np.uint8)
    wide[:, :width] = np.frombuffer(gaps, np.uint8).reshape(-1, width)
    return base + np.concatenate([[0], np.cumsum(wide.view("<i8")[:, 0])]).astype(np.int64)


def squeezed(width: int, gaps: bytes) -> bytes:
    """Gaps byte by byte: the lower bytes of all as they are, then the highest, which are mostly alike, compressed."""
    planes = np.frombuffer(gaps, np.uint8).reshape(-1, width).T
    return planes[:-1].tobytes() + zlib.compress(planes[-1].tobytes())


def widened(width: int, n: int, squeezed: bytes) -> bytes:
    """The gaps, n of them, that squeezed() was given."""
    low = (width - 1) * n
    return np.frombuffer(squeezed[:low] + zlib.decompress(squeezed[low:]), np.uint8).reshape(width, n).T.tobytes()


def _packed(bits: int) -> Callable:
    def packed(batches):
        def sent() -> pa.RecordBatch:
            rows = [(bucket, base, width, len(gaps) // width, squeezed(width, gaps)) for bucket, base, width, gaps in pack(np.concatenate(held), bits)]
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), PACKETS, strict=True)], schema=PACKETS)

        held, n = [], 0
        for b in batches:
            if b.num_rows:
                held.append(b.column(0).to_numpy(zero_copy_only=False))
                n += b.num_rows
            if n >= HELD:
                yield sent()
                held, n = [], 0
        if held:
            yield sent()

    return packed


def _doubled(packets: pa.Table) -> pa.Table:
    h = np.sort(np.concatenate([unpack(r["base"], r["width"], widened(r["width"], r["n"], r["gaps"])) for r in packets.to_pylist()]))
    return pa.table({"h": pa.array(np.unique(h[1:][h[1:] == h[:-1]]), pa.int64())})


def repeated(marks: list[DataFrame], bits: int = BITS) -> DataFrame:
    """(h) of the fingerprints of so many bits, column h of the frames, that occur more than once. Keys that occur more than once are among them; a few others may be."""
    packets = reduce(DataFrame.unionByName, marks).mapInArrow(_packed(bits), "bucket int, base long, width int, n int, gaps binary")
    return packets.groupBy("bucket").applyInArrow(_doubled, "h long")
