"""SimHash near-duplicates: fingerprints from word shingles, linked by multi-index hashing.

A fingerprint is cut into segments. Two fingerprints that differ in few bits differ in at most
a known number of bits within some segment, so every fingerprint looks up a small Hamming ball
around its own segment values in a table keyed by (segment, value), and complete distances
are then compared.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, mixed, pack_columns, remote, remote_group, texts, unpack_columns
from .graph import components

HERE = __name__
#: Tasks that the members of one component are dealt to where they are joined with what is known of it.
SALTS = 32
#: Members up to which a bucket's candidates are paired by a join; larger buckets go the exact linear way.
HOT = 32


def fingerprint(text: str | None, shingle: int = 3, lanes: int = 1) -> bytes:
    """8 * lanes bytes. Null, empty or blank text: all zero bits."""
    words = text.encode("utf-8", "surrogatepass").translate(_LOWER).split() if text else []
    n = max(1, len(words) - shingle + 1)
    digest, join = xxhash.xxh64_intdigest, b" ".join
    return bits_of(np.fromiter((digest(join(words[i : i + shingle]), 42) for i in range(n)), np.uint64, n) if words else np.zeros(0, np.uint64), lanes)


def bits_of(h: np.ndarray, lanes: int) -> bytes:
    """The majority of each bit over shingle hashes, 64 bits a lane; no hashes give zero bits."""
    n = len(h)
    if not n:
        return bytes(8 * lanes)
    out = []
    for lane in range(lanes):
        x = h
        if lane:
            with np.errstate(over="ignore"):
                x = (h + np.uint64(lane)) * np.uint64(0x9E3779B97F4A7C15)
                x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
                x = x ^ (x >> np.uint64(32))
        counts = np.zeros(64, np.int64)
        for i in range(0, n, 65536):
            part = np.unpackbits(x[i : i + 65536].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            counts += part.sum(axis=0, dtype=np.uint32)
        out.append(np.packbits(counts * 2 > n).tobytes())
    return b"".join(out)


_LOWER = bytes(x + 32 if 65 <= x <= 90 else x for x in range(256))


def fingerprint_batches(batches, shingle: int, lanes: int):
    for b in batches:
        found = [fingerprint(t, shingle, lanes) for t in b.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(found, pa.binary())], ["doc_id", "fp"])


def fingerprints(docs: DataFrame, shingle: int = 3, lanes: int = 1) -> DataFrame:
    """(doc_id, fp binary) of every row of docs."""
    return texts(docs).mapInArrow(remote(HERE, "fingerprint_batches", shingle=shingle, lanes=lanes), "doc_id long, fp binary")


def links_within_two(found: DataFrame) -> DataFrame:
    """Edges (a, b) that connect all 64-bit fingerprints (column f, long, distinct) at distance 1 or 2.

    Segments are the upper and lower 32 bits. Distance 2 or less leaves: upper halves equal,
    lower halves equal, or one bit of difference in each. The first two look up the segment value
    itself; the third looks up the upper value with one of its set bits cleared (of two values one
    bit apart, one has that bit set), so no pair is met from both ends. Buckets of more than HOT
    members skip pairing: their members, and the fingerprints that would look them up, emit the
    64-bit points within one bit instead. Two fingerprints at distance 2 or less share such a
    point, and a point has at most 65 fingerprints, so this way is exact and linear whatever the bucket.
    """
    upper, lower = F.shiftrightunsigned("f", 32), F.col("f").bitwiseAND(0xFFFFFFFF)
    keyed = durable(found.select("f", F.explode(F.array(F.struct(F.lit(0).alias("seg"), upper.alias("key")), F.struct(F.lit(1).alias("seg"), lower.alias("key")))).alias("s")).select("f", "s.seg", "s.key"))
    sizes = keyed.groupBy("seg", "key").count()
    hot = sizes.where(F.col("count") > HOT).select("seg", "key", F.lit(True).alias("hot"))
    cold = keyed.join(hot, ["seg", "key"], "left_anti")
    bits = F.expr("filter(transform(sequence(0, 31), i -> shiftleft(1L, i)), b -> (shiftrightunsigned(f, 32) & b) <> 0)")
    cleared = found.select("f", F.explode(bits).alias("bit")).select("f", F.lit(0).alias("seg"), (F.shiftrightunsigned("f", 32) - F.col("bit")).alias("key"))
    table = cold.select(F.col("f").alias("g"), "seg", "key")
    far = F.bit_count(F.col("f").bitwiseXOR(F.col("g"))) <= 2
    same = cold.join(table, ["seg", "key"]).where("f < g").where(far)
    near = cleared.join(table, ["seg", "key"]).where(far)
    pairs = same.select("f", "g").unionByName(near.select("f", "g"))

    in_hot = keyed.join(hot, ["seg", "key"], "left_semi")
    seek_hot = cleared.join(hot, ["seg", "key"], "left_semi")
    around = in_hot.unionByName(seek_hot).select("f").distinct()
    points = around.select("f", F.explode(F.expr("concat(array(f), transform(sequence(0, 63), i -> f ^ shiftleft(1L, i)))")).alias("p"))
    met = points.groupBy("p").agg(F.collect_set("f").alias("fs")).where("size(fs) > 1")
    chained = met.select(F.array_min("fs").alias("f"), F.explode("fs").alias("g")).where("f <> g")
    return pairs.unionByName(chained).select(F.col("f").alias("a"), F.col("g").alias("b")).distinct()


def carried(found: DataFrame, named: DataFrame, key: str) -> DataFrame:
    """found with the columns that named(key, n, ...) has for its key. Keys of more than a thousandth of all rows (n), of which there are fewer than a
    thousand, go to every task; the rows of the others meet theirs by a shuffle."""
    often = F.col("n") * 1000 > found.count()
    hot = named.where(often).drop("n")
    rest = found.join(F.broadcast(hot.select(key)), key, "left_anti").join(named.where(~often).drop("n"), key, "left")
    return found.join(F.broadcast(hot), key).unionByName(rest)


def near_duplicates(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fingerprint hex, component_id) of every row; links at 2 or fewer differing bits.

    A row without words has fingerprint zero and links like any other. component_id is the smallest
    doc_id in reach; null ids count as no candidate, so a component of null ids alone has null.
    Repeated rows each keep their row. No rows give no rows.
    """
    found = durable(fingerprints(docs, shingle).select("doc_id", F.conv(F.hex("fp"), 16, -10).cast("long").alias("f")))
    firsts = found.groupBy("f").agg(F.min("doc_id").alias("first"), F.count("*").alias("n"))
    group = components(links_within_two(firsts.select("f")))
    members = firsts.join(group.withColumnRenamed("node", "f"), "f")
    least = members.groupBy("root").agg(F.min("first").alias("least")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    linked = members.withColumn("salt", F.pmod(F.xxhash64("f"), F.lit(SALTS))).join(least, ["root", "salt"]).select("f", "least")
    named = firsts.join(linked, "f", "left").select("f", "n", F.coalesce("least", "first").alias("component_id"))
    return carried(found, durable(named), "f").select("doc_id", F.lower(F.lpad(F.hex("f"), 16, "0")).alias("fingerprint"), "component_id")


def bits_apart(similarity: float, bits: int) -> int:
    """Expected differing bits of two fingerprints whose shingle sets have this Jaccard similarity."""
    return round(bits * math.acos(2 * similarity / (1 + similarity)) / math.pi)


def shingle_set(text: str | None, shingle: int) -> np.ndarray:
    """The distinct 64-bit hashes of a text's word shingles, in order; no words give none."""
    words = text.encode("utf-8", "surrogatepass").translate(_LOWER).split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    digest, join = xxhash.xxh64_intdigest, b" ".join
    n = max(1, len(words) - shingle + 1)
    return np.unique(np.fromiter((digest(join(words[i : i + shingle]), 42) for i in range(n)), np.uint64, n))


def set_name(found: np.ndarray) -> bytes:
    """16 bytes that name a shingle set."""
    return xxhash.xxh3_128_digest(found.astype("<u8").tobytes())


def set_batches(batches, shingle: int, lanes: int):
    for b in batches:
        sets = [shingle_set(t, shingle) for t in b.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("print"), pa.array([set_name(x) for x in sets], pa.binary()), pa.array([bits_of(x, lanes) for x in sets], pa.binary())], ["doc_id", "print", "id", "fp"])


def segment_blobs(batches, lanes: int, width: int, orders: int, parts: int):
    """Rows (part, blob) of the lookups of each fingerprint: arrays of key, place, and the ids and words the places point to.

    A key holds segment and value. Segments are cut from the bits in `orders` fixed orders. A fingerprint's id
    and words travel once for each part, however many of its rows go there.
    """
    count = 64 * lanes // width
    one = 1 << np.arange(width, dtype=np.int64)
    mixes = [np.random.default_rng(o).permutation(64 * lanes)[: count * width] for o in range(orders)]
    for b in batches:
        fps = b.column("fp").to_pylist()
        if not fps:
            continue
        mat = np.frombuffer(b"".join(fps), np.uint8).reshape(len(fps), -1)
        bits = np.unpackbits(mat, axis=1)
        found = [bits[:, m].reshape(len(fps), count, width) @ one + ((np.arange(count) + o * count) << 40) for o, m in enumerate(mixes)]
        key = np.concatenate(found, axis=1).ravel()
        ids = np.frombuffer(b"".join(b.column("id").to_pylist()), "V16")
        yield from packed_lookups(ids, mat, np.repeat(np.arange(len(fps)), count * orders), key, parts)


def packed_lookups(ids: np.ndarray, mat: np.ndarray, row: np.ndarray, key: np.ndarray, parts: int):
    part = (mixed(key) % np.uint64(parts)).astype(np.int64)
    order = np.argsort(part, kind="stable")
    part, row, key = part[order], row[order], key[order]
    begin = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
    out = []
    for lo, hi in zip(begin, np.r_[begin[1:], len(part)], strict=True):
        used, place = np.unique(row[lo:hi], return_inverse=True)
        words = np.ascontiguousarray(mat[used]).view(np.uint64).ravel()
        out.append(pack_columns([key[lo:hi], place.astype(np.uint32), ids[used], words]))
    yield pa.RecordBatch.from_arrays([pa.array(part[begin], pa.int32()), pa.array(out, pa.binary())], ["part", "blob"])


def joined_buckets(frame, most: int, small: int = 16):
    """Edges (a, b) of ids in each key's bucket whose complete fingerprints are within `most` bits.

    Buckets of up to `small` members compare each pair. Larger ones are searched breadth first: what
    is connected already is only compared with what is not, so a bucket that holds one group of
    copies costs about one comparison a member. Every edge is verified before any is left away,
    so the spanning forest that goes out connects all that the edges connect.
    """
    import pandas as pd

    key, at, ids, words = [], [], [], []
    held = 0
    for blob in frame["blob"]:
        k, p, i, w = unpack_columns(blob)
        key.append(k)
        at.append(p.astype(np.int64) + held)
        ids.append(i)
        words.append(w.reshape(len(i), -1))
        held += len(i)
    key, at, ids, words = map(np.concatenate, (key, at, ids, words))
    order = np.argsort(key, kind="stable")
    key = key[order]
    start = np.r_[True, key[1:] != key[:-1]]
    bucket = np.cumsum(start) - 1
    size = np.bincount(bucket)
    keep = size[bucket] > 1
    order, bucket = order[keep], bucket[keep]
    at = at[order]
    begin = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]) if len(bucket) else np.zeros(0, int)
    length = np.diff(np.r_[begin, len(bucket)])
    left, right = [], []
    few = np.repeat(length <= small, length)

    def near(x, y):
        d = np.zeros(np.broadcast(x, y).shape, np.int64)
        for w in range(words.shape[1]):
            d += np.bitwise_count(words[x, w] ^ words[y, w])
        return d <= most

    for step in range(1, small):
        i = np.flatnonzero(few[:-step] & (bucket[step:] == bucket[:-step])) if len(bucket) > step else np.zeros(0, int)
        i = i[near(at[i], at[i + step])]
        left.append(at[i])
        right.append(at[i + step])
    for lo, n in zip(begin[length > small], length[length > small], strict=True):
        rest = at[lo : lo + n]
        while len(rest) > 1:
            queue, rest = [rest[0]], rest[1:]
            while queue and len(rest):
                x = queue.pop()
                hit = near(x, rest)
                if hit.any():
                    left.append(np.full(hit.sum(), x))
                    right.append(rest[hit])
                    queue += list(rest[hit])
                    rest = rest[~hit]
    a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (left, right))
    _, name = np.unique(ids, return_inverse=True)
    first = np.zeros(len(ids), np.int64)
    first[name[::-1]] = np.arange(len(ids))[::-1]
    edges = forest(first[name[a]], first[name[b]])
    return pd.DataFrame([(ids[x].tobytes(), ids[y].tobytes()) for x, y in edges], columns=["a", "b"])


def forest(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Of verified edges, those of one spanning forest: it connects what all of them connect."""
    _, where = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right = where[: len(a)].tolist(), where[len(a) :].tolist()
    up, out = list(range(len(where))), []
    for i, (x, y) in enumerate(zip(left, right, strict=True)):
        while up[x] != x:
            up[x] = x = up[up[x]]
        while up[y] != y:
            up[y] = y = up[up[y]]
        if x != y:
            up[x] = y
            out.append((int(a[i]), int(b[i])))
    return out


def grouped_sets(batches, shingle: int):
    """(part, root, block, id, hashes) of the texts whose shingle set is the one asked for."""
    for b in batches:
        rows = []
        for text, name, root, block, part in zip(*(b.column(c).to_pylist() for c in ("text", "id", "root", "block", "part")), strict=True):
            found = shingle_set(text, shingle)
            if set_name(found) == name:
                rows.append((part, root, block, name, found.tobytes()))
        cols = list(zip(*rows, strict=True)) or [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, (pa.int32(), pa.binary(), pa.int64(), pa.binary(), pa.binary()), strict=True)], ["part", "root", "block", "id", "hashes"])


class Sets:
    """Shingle sets side by side, each of which can be compared with all that are still in."""

    def __init__(self, hashes, similarity: float):
        self.sets = [np.frombuffer(x, np.uint64) for x in hashes]
        self.size = np.array([len(x) for x in self.sets], np.int64)
        self.flat = np.concatenate(self.sets) if self.sets else np.zeros(0, np.uint64)
        self.owner = np.repeat(np.arange(len(self.sets)), self.size)
        self.inside = np.ones(len(self.sets), bool)
        self.similarity = similarity

    def leave(self, out) -> None:
        self.inside[out] = False
        keep = self.inside[self.owner]
        self.flat, self.owner = self.flat[keep], self.owner[keep]

    def near(self, own: np.ndarray) -> np.ndarray:
        """The sets still in that have the similarity or more to one; a set without hashes is near none."""
        if not len(own) or not len(self.flat):
            return np.zeros(0, np.int64)
        place = np.minimum(np.searchsorted(own, self.flat), len(own) - 1)
        common = np.bincount(self.owner[own[place] == self.flat], minlength=len(self.sets))
        return np.flatnonzero(self.inside & (common >= self.similarity * (self.size + len(own) - common) - 1e-9))


def exact_groups(frame, similarity: float):
    """(id, seed): within each block of a loose group, what pairs at an exact Jaccard of `similarity` or more connect.

    Breadth first: what is connected already is only compared with what is not, so no pair that could
    join two groups is left out.
    """
    import pandas as pd

    out = []
    for _, part in frame.groupby(["root", "block"], sort=False):
        part = part.drop_duplicates("id").sort_values("id")
        ids = part["id"].tolist()
        sets = Sets(part["hashes"], similarity)
        for seed in range(len(ids)):
            if not sets.inside[seed]:
                continue
            sets.leave([seed])
            queue = [seed]
            out.append((ids[seed], ids[seed]))
            while queue and sets.inside.any():
                hit = sets.near(sets.sets[queue.pop()])
                if len(hit):
                    out += [(ids[i], ids[seed]) for i in hit.tolist()]
                    queue += hit.tolist()
                    sets.leave(hit)
    return pd.DataFrame(out, columns=["id", "seed"])


def near_pivot(batches, similarity: float):
    """(a, b): seeds that are near the pivot of their loose group."""
    for b in batches:
        rows = [(i, p) for i, h, p, ph in zip(*(b.column(c).to_pylist() for c in ("id", "hashes", "pivot", "pivot_hashes")), strict=True) if i == p or len(Sets([h], similarity).near(np.frombuffer(ph, np.uint64)))]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.binary()) for i in (0, 1)], ["a", "b"])


def cross_links(frame, similarity: float):
    """(a, b): seeds of members outside the core, and of members of one block that are near them."""
    import pandas as pd

    out = set()
    asked, held = frame[frame["asked"]], frame[~frame["asked"]]
    sets, seeds = Sets(held["hashes"], similarity), held["seed"].tolist()
    for seed, own in zip(asked["seed"], asked["hashes"], strict=True):
        out |= {(seed, seeds[i]) for i in sets.near(np.frombuffer(own, np.uint64)).tolist()}
    return pd.DataFrame(sorted(x for x in out if x[0] != x[1]), columns=["a", "b"])


def joined_blocks(sets: DataFrame, local: DataFrame, similarity: float, chunk: int) -> DataFrame:
    """(a, b): edges between the seeds of the blocks of loose groups that no single task holds; sets and local are those groups' alone.

    The seeds near a group's pivot, its least seed, are its core. A pair of members in two blocks is either in the core, and connected so, or has a
    member outside it: these are compared with every block of their group, some at a time. So no link is lost, and
    a group of copies, whose seeds are nearly all in the core, costs one comparison a member.
    """
    members = sets.select("root", "block", "id", "hashes").join(local, "id")
    seeds = members.where("id = seed").select("root", "id", "hashes")
    pivot = seeds.groupBy("root").agg(F.min("id").alias("pivot"), F.min_by("hashes", "id").alias("pivot_hashes")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    met = seeds.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS))).join(pivot, ["root", "salt"])
    star = durable(met.select("id", "hashes", "pivot", "pivot_hashes").mapInArrow(remote(HERE, "near_pivot", similarity=similarity), "a binary, b binary"))
    outside = durable(members.join(star.select(F.col("a").alias("seed")), "seed", "left_anti"))
    chunks = outside.groupBy("root").agg(F.ceil(F.count("*") / chunk).alias("chunks"))
    blocks = sets.select("root", "block").distinct()
    asked = outside.join(chunks, "root").withColumn("chunk", F.pmod(F.xxhash64("id"), F.col("chunks"))).drop("block").join(blocks, "root")
    held = members.join(chunks, "root").withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)))
    columns = ["root", "block", "chunk", "seed", "hashes"]
    both = asked.select(*columns, F.lit(True).alias("asked")).unionByName(held.select(*columns, F.lit(False).alias("asked")))
    return star.unionByName(both.groupBy("root", "block", "chunk").applyInPandas(remote_group(HERE, "cross_links", similarity=similarity), "a binary, b binary"))


def text_print():
    """What tells texts of one doc_id apart; null counts as empty."""
    return F.md5(F.coalesce("text", F.lit("")).cast("binary"))


def named_rows(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, lanes: int = 4, width: int = 18, orders: int = 10, per_bucket: int = 1_000_000, block_sets: int = 20_000) -> DataFrame:
    """(doc_id, print, first_id, first_print) of every row: the row's component is named by its least doc_id, and by the least print under that id."""
    bits = 64 * lanes
    printed = texts(docs).withColumn("print", text_print())
    found = durable(printed.mapInArrow(remote(HERE, "set_batches", shingle=shingle, lanes=lanes), "doc_id long, print string, id binary, fp binary"))
    least = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "print")))
    firsts = durable(found.groupBy("id", "fp").agg(least.alias("first"), F.count("*").alias("n")))
    parts = max(1, math.ceil(firsts.count() * orders * (bits // width) / per_bucket))
    blob = firsts.select("id", "fp").mapInArrow(remote(HERE, "segment_blobs", lanes=lanes, width=width, orders=orders, parts=parts), "part int, blob binary")
    most = bits_apart(similarity, bits)
    most += round(3 * math.sqrt(most * (1 - most / bits)))
    edges = blob.groupBy("part").applyInPandas(remote_group(HERE, "joined_buckets", most=most), "a binary, b binary")
    loose = durable(components(edges))
    shares = max(1, math.ceil(loose.count() / 5000))
    large = durable(loose.groupBy("root").agg(F.ceil(F.count("*") / block_sets).alias("blocks")).where("blocks > 1"))
    # one doc_id may have several rows, so the set itself is checked again
    asked = firsts.where("first is not null").join(loose.withColumnRenamed("node", "id"), "id").join(large, "root", "left").select(F.col("first.doc_id").alias("doc_id"), "id", "root", F.pmod(F.xxhash64("id"), F.coalesce("blocks", F.lit(1))).alias("block"))
    asked = asked.withColumn("part", F.pmod(F.xxhash64("root", "block"), F.lit(shares)).cast("int"))
    sets = texts(docs).join(asked, "doc_id").select("text", "id", "root", "block", "part").mapInArrow(remote(HERE, "grouped_sets", shingle=shingle), "part int, root binary, block long, id binary, hashes binary")
    some = not large.isEmpty()
    if some:
        sets = durable(sets)
    group = durable(sets.groupBy("part").applyInPandas(remote_group(HERE, "exact_groups", similarity=similarity), "id binary, seed binary"))
    if some:
        wide = sets.join(large, "root", "left_semi").dropDuplicates(["id"])
        linked = components(joined_blocks(wide, group.join(wide.select("id"), "id", "left_semi"), similarity, block_sets)).withColumnRenamed("node", "seed")
        group = group.join(linked, "seed", "left").select("id", F.coalesce("root", "seed").alias("seed"))
    members = group.withColumnRenamed("seed", "root").join(firsts.select("id", "first"), "id")
    salt = F.pmod(F.xxhash64("id"), F.lit(SALTS))
    best = members.groupBy("root").agg(F.min("first").alias("best")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    named = members.withColumn("salt", salt).join(best, ["root", "salt"]).select("id", "best")
    every = durable(firsts.join(named, "id", "left").select("id", "n", F.coalesce("best", "first").alias("best")))
    return carried(found, every, "id").select("doc_id", "print", F.col("best.doc_id").alias("first_id"), F.col("best.print").alias("first_print"))


def similar_groups(docs: DataFrame, **kw) -> DataFrame:
    """(doc_id, component_id): groups that pairs at an exact shingle Jaccard of `similarity` (0.8) or more connect.

    Candidates come from fingerprints of the distinct shingles, 256 bits, cut into segments of 18 bits in ten orders
    of the bits. Fingerprints that share a segment and differ by no more than the similarity's expected
    distance and three standard deviations make loose groups. Within a loose group every text's shingle
    set is at hand and exact Jaccard decides; only how candidates are found is an estimate. Loose groups of more than block_sets
    sets are dealt out to blocks (joined_blocks()), so none has to fit a task.
    Rows without words never group here with others than rows without words. Rows without an id do not link others.
    """
    return named_rows(docs, **kw).select("doc_id", F.col("first_id").alias("component_id"))


def keep_first(docs: DataFrame, **kw) -> DataFrame:
    """docs without near-duplicates: of each group the row with the smallest doc_id stays, with its own columns.

    Rows are told apart by doc_id and text: different texts under one doc_id both stay unless they are alike, and then the
    one whose digest is smaller does. Of rows equal in both one stays. Rows with a null doc_id belong to no group and all stay.
    """
    ids = docs.where("doc_id is not null")
    gone = named_rows(ids, **kw).where("doc_id <> first_id OR print <> first_print").select(F.col("doc_id").alias("d"), F.col("print").alias("p")).distinct()
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r")
    held = ids.select(row, F.col("doc_id").cast("long").alias("d"), text_print().alias("p")).dropDuplicates(["d", "p"])
    return held.join(gone, ["d", "p"], "left_anti").select([F.col("r").getField(c).alias(c) for c in docs.columns]).unionByName(docs.where("doc_id is null"))
