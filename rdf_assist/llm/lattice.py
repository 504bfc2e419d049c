"""Subword lattice likelihood: the marginal probability of a text over all its segmentations.

The pieces of an existing vocabulary (word pieces, bytes for letters outside it, and an end mark) have the weights
that the vocabulary's own scores give them; no weight is fitted. A word is the piece sequence's text after a word mark,
so words are independent and a text's probability is the product of its words' and the end's. A word's
probability sums over every segmentation by a forward recursion in log space.

What is learned from the training texts are their words: each is one more arc of the lattice, from a word's first
place to its last, with the share of its count that an absolute discount leaves. The discounts' sum
is the share of the pieces, so all arcs and pieces together have at most the weight one.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, mixed, remote, small_batches

HERE = __name__
MARK = "▁"
END = "</text>"
HOT_BYTES = 64
_LOWER = bytes(x + 32 if 65 <= x <= 90 else x for x in range(256))


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_LOWER).split() if text else []


def vocabulary(path: str) -> dict[str, float]:
    """piece → log probability, from a sentencepiece file: ordinary pieces, bytes and the end mark.

    Scores that fall by one from piece to piece are ranks; the chance of a rank falls as its inverse.
    """
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    weight: dict[str, float] = {END: 1e-3}
    for i in range(sp.get_piece_size()):
        piece = sp.id_to_piece(i)
        if sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i):
            continue
        if MARK not in piece[1:]:
            weight[piece] = 1.0 / (100.0 - sp.get_score(i))
    for b in range(256):
        weight[f"<{b:02X}>"] = 1e-6
    total = sum(weight.values())
    return {p: math.log(w / total) for p, w in weight.items()}


class PieceTable:
    """Pieces by a hash of their code points, four to a bucket, for lookups of whole arrays at once."""

    def __init__(self, pieces: list[str], longest: int):
        self.power = np.array([pow(0x9E3779B97F4A7C15, k, 1 << 64) for k in range(longest)], np.uint64)
        keys = np.array([self._key(p) for p in pieces], np.uint64)
        bits = max(8, int(len(pieces)).bit_length() + 2)
        while True:
            self.shift = np.uint64(64 - bits)
            at = (mixed(keys) >> self.shift).astype(np.int64)
            if np.bincount(at, minlength=1).max(initial=0) <= 4:
                break
            bits += 1
        self.keys = np.zeros((1 << bits, 4), np.uint64)
        self.ids = np.full((1 << bits, 4), -1, np.int32)
        used = np.zeros(1 << bits, np.int64)
        for i, (k, slot) in enumerate(zip(keys, at.tolist(), strict=True)):
            self.keys[slot, used[slot]], self.ids[slot, used[slot]] = k, i
            used[slot] += 1

    def _key(self, piece: str) -> int:
        return (sum(ord(c) * int(self.power[k]) for k, c in enumerate(piece)) + len(piece)) & 0xFFFFFFFFFFFFFFFF

    def find(self, keys: np.ndarray) -> np.ndarray:
        slot = (mixed(keys) >> self.shift).astype(np.int64)
        out = np.full(keys.shape, -1, np.int32)
        for c in range(4):
            same = self.keys[slot, c] == keys
            out[same] = self.ids[slot, c][same]
        return out


#: Words up to this many letters are worked on as arrays; longer ones one by one, so many letters at once.
WIDE, CHUNK = 40, 1 << 14


class Lattice:
    """Forward sums over all segmentations of words."""

    def __init__(self, logp: dict[str, float]):
        self.logp = logp
        self.byte = np.array([logp[f"<{b:02X}>"] for b in range(256)])
        bytes_ = {f"<{b:02X}>" for b in range(256)}
        self.names = [p for p in logp if p != END and p not in bytes_]
        self.value = np.array([logp[p] for p in self.names])
        self.index = {p: i for i, p in enumerate(self.names)}
        self.longest = max(map(len, self.names), default=1)
        self.table = PieceTable(self.names, self.longest)
        heads: dict[str, int] = {}
        for p in self.names:
            if len(p) > 3:
                heads[p[:3]] = max(heads.get(p[:3], 0), len(p))
        self.heads = PieceTable(list(heads), 3)
        self.reach = np.array([*heads.values(), 0], np.int64)  # the longest piece that begins with three letters; last: none

    def _spell(self, c: int) -> bytes:
        return chr(c).encode("utf-8", "surrogatepass")

    def run(self, words: list[str]) -> np.ndarray:
        """log P of each word."""
        out = np.zeros(len(words))
        size = np.array([len(w) + 1 for w in words], np.int64)
        order = np.argsort(size, kind="stable")
        short = order[size[order] <= WIDE]
        for at in range(0, len(short), 2048):
            own = short[at : at + 2048]
            out[own] = self._block([words[i] for i in own.tolist()], size[own])
        for i in order[size[order] > WIDE].tolist():
            out[i] = self._long(words[i])
        return out

    def _found(self, code: np.ndarray, inside: np.ndarray, first: bool) -> list[np.ndarray]:
        """For each piece length from one, the piece that begins at each place of rows of letters, or -1."""
        rows, width = code.shape
        out = []
        key = np.zeros((rows, width), np.uint64)
        barred = code == ord(MARK)
        if first:
            barred[:, 0] = False
        with np.errstate(over="ignore"):
            for n in range(1, min(self.longest, width) + 1):
                m = width - n + 1
                key = key[:, :m] + code[:, n - 1 :] * self.table.power[n - 1]
                if n <= 3:
                    found = self.table.find(key + np.uint64(n))
                    if n == 3:
                        far = self.reach[self.heads.find(key + np.uint64(3))]
                else:
                    found = np.full((rows, m), -1, np.int32)
                    row, col = np.nonzero(far[:, :m] >= n)
                    found[row, col] = self.table.find(key[row, col] + np.uint64(n))
                found[barred[:, :m] | ~inside[:, n - 1 :]] = -1
                out.append(found)
        return out

    def _block(self, words: list[str], size: np.ndarray) -> np.ndarray:
        rows, width = len(words), int(size.max())
        flat = np.frombuffer("".join([MARK + w for w in words]).encode("utf-32-le", "surrogatepass"), "<u4")
        code = np.zeros((rows, width), np.uint64)
        inside = np.arange(width)[None, :] < size[:, None]
        code[inside] = flat
        by_byte = np.full((rows, width), -np.inf)
        by_byte[inside] = self._by_byte(flat)
        ids = self._found(code, inside, True)
        lp = [np.where(found >= 0, self.value[found], -np.inf) for found in ids]
        alive = [(i >= 0).any(axis=0).tolist() for i in ids]  # places where any word of the block has a piece of a length
        a = np.full((rows, width + 1), -np.inf)
        a[:, 0] = 0.0
        with np.errstate(divide="ignore", invalid="ignore"):
            for j in range(1, width + 1):
                terms = np.stack([a[:, j - n] + lp[n - 1][:, j - n] for n in range(1, min(len(lp), j) + 1) if alive[n - 1][j - n]] + [a[:, j - 1] + by_byte[:, j - 1]])
                a[:, j] = _log_sum(terms)
        return a[np.arange(rows), size]

    def _by_byte(self, flat: np.ndarray) -> np.ndarray:
        """log P of each letter spelled in bytes."""
        letters, which = np.unique(flat, return_inverse=True)
        return np.array([sum(self.byte[b] for b in self._spell(int(c))) for c in letters])[which]

    def _long(self, word: str) -> float:
        """log P of a word of any length: the sums to the next places alone are held, scaled so that they stay numbers."""
        ahead = [0.0] * self.longest  # sums of the segmentations up to the next places
        now, scale = 1.0, 0.0
        for lo in range(0, len(word) + 1, CHUNK):
            part = (MARK + word[: CHUNK + self.longest]) if lo == 0 else word[lo - 1 : lo - 1 + CHUNK + self.longest]
            own = min(CHUNK, len(word) + 1 - lo)
            flat = np.frombuffer(part.encode("utf-32-le", "surrogatepass"), "<u4")
            code = flat.astype(np.uint64)[None, :]
            steps: list[list[tuple[int, float]]] = [[(1, p)] for p in np.exp(self._by_byte(flat[:own])).tolist()]
            for n, found in enumerate(self._found(code, np.ones(code.shape, bool), lo == 0), 1):
                at = np.flatnonzero(found[0, :own] >= 0)
                for i, p in zip(at.tolist(), np.exp(self.value[found[0, at]]).tolist(), strict=True):
                    steps[i].append((n, p))
            for reach in steps:
                for n, p in reach:
                    ahead[n - 1] += now * p
                now = ahead.pop(0)
                ahead.append(0.0)
                if now < 1e-100:
                    scale += math.log(now)
                    ahead = [x / now for x in ahead]
                    now = 1.0
        return scale + math.log(now)

    def forward(self, word: str) -> float:
        return float(self.run([word])[0])


def _log_sum(terms: np.ndarray) -> np.ndarray:
    top = terms.max(axis=0)
    safe = np.where(np.isfinite(top), top, 0.0)
    return safe + np.log(np.exp(terms - safe).sum(axis=0))


def slices(batches, rows: int = 500):
    """Batches in small runs of rows, so that few texts are held as Python objects."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def count_batches(batches, most: int = 150_000):
    """(word, n_train, n_all) partial counts over runs of texts."""
    train: Counter = Counter()
    every: Counter = Counter()
    for b in slices(batches):
        for t, held in zip(b.column("text").to_pylist(), b.column("held_out").to_pylist(), strict=True):
            words = words_of(t)
            every.update(words)
            if not held:
                train.update(words)
        if len(every) > most:
            yield _counted(train, every)
            train, every = Counter(), Counter()
    yield _counted(train, every)


def _counted(train: Counter, every: Counter):
    return pa.RecordBatch.from_arrays([pa.array([w.decode("utf-8", "replace") for w in every], pa.string()), pa.array([train[w] for w in every], pa.int64()), pa.array(list(every.values()), pa.int64())], ["word", "n_train", "n_all"])


def gathered(batches, rows: int = 16_384):
    """Batches of short rows put together, so that lattices work on long arrays whatever the session's batch size."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held).combine_chunks()
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held).combine_chunks()


class Arcs:
    """Shares of whole-word arcs and of the pieces: (count - discount) / total, and what the discounts leave."""

    def __init__(self, total: int, distinct: int, once: int, twice: int):
        self.total = total
        self.discount = once / (once + 2 * twice) if once else 0.5
        self.rest = self.discount * distinct / total if total else 1.0

    def log_add(self, count: int, pieces: float) -> float:
        """log of the arc's share plus the pieces' share times exp(pieces)."""
        own = max(count - self.discount, 0.0) / self.total if self.total else 0.0
        rest = math.log(self.rest) + pieces
        if not own:
            return rest
        own = math.log(own)
        return max(own, rest) + math.log1p(math.exp(-abs(own - rest)))

    def column(self, count, pieces):
        """log_add() of columns."""
        own = F.log(F.greatest(count - F.lit(self.discount), F.lit(0.0)) / F.lit(float(max(1, self.total))))  # null without a count
        rest = F.lit(math.log(self.rest)) + pieces
        return F.coalesce(F.greatest(own, rest) + F.log1p(F.exp(-F.abs(own - rest))), rest)


def word_batches(batches, logp: dict):
    lattice = Lattice(logp)
    for b in gathered(batches):
        found = lattice.run(b.column("word").to_pylist())
        yield from b.append_column("pieces", pa.array(found, pa.float64())).to_batches(10_000)


def hot_key(word: bytes) -> bytes:
    """A word, or where it is long 17 bytes that stand for it: hot words of any length take bounded room."""
    return word if len(word) <= HOT_BYTES else b"\0" + xxhash.xxh3_128_digest(word)


def long_keys(batches):
    for b in batches:
        keys = [hot_key(w.encode("utf-8")) for w in b.column("word").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), b.column("n_train"), b.column("pieces")], ["key", "n_train", "pieces"])


def tally_batches(batches, hot: dict, base: tuple[float, float]):
    """A row for each text with the sums of its hot words and its end, and a row for each rare word in it.

    A text's own row carries a key with a space, which no word has, so the join below leaves it alone.
    """
    from pyspark import TaskContext

    uid = TaskContext.get().partitionId() << 33
    log10 = math.log(10)
    for b in slices(batches):
        out: list[tuple] = []
        for d, t, held in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), b.column("held_out").to_pylist(), strict=True):
            uid += 1
            tf = Counter(words_of(t))
            n = sum(tf.values())
            known, plain, score = (1 if base[1] else 0), base[0], hot[b""][1] / log10
            for w, k in tf.items():
                got = hot.get(w) if len(w) <= HOT_BYTES else hot.get(hot_key(w))
                if got is None:
                    out.append((uid, w.decode("utf-8", "replace"), k, None, None, None, None, None, None))
                else:
                    known += k if got[2] else 0
                    plain += k * got[0]
                    score += k * got[1] / log10
            out.append((uid, f" {uid}", 0, d, held, n + 1, known, plain, score))
            if len(out) > 50_000:
                yield _rows(out)
                out = []
        if out:
            yield _rows(out)


_TALLY = [("uid", pa.int64()), ("word", pa.string()), ("tf", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("hot_known", pa.int64()), ("hot_base", pa.float64()), ("hot_score", pa.float64())]


def _rows(out: list[tuple]):
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, (_, k) in zip(zip(*out, strict=True), _TALLY, strict=True)], [n for n, _ in _TALLY])


def held_out(docs: DataFrame) -> DataFrame:
    """(doc_id, text, held_out): crc32 of the id as text, modulo 7, is 2. A null id reads as empty text and trains."""
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), (F.crc32(key.cast("binary")) % 7 == 2).alias("held_out"))


def score(docs: DataFrame, path: str, hot_words: int = 65_536) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row.

    Word counts come from all training texts, and each distinct word goes through the lattice once. At most `hot_words`
    words, those met most (a bounded table), go to the tasks; every other word of a text joins
    the word table by a shuffle, so no size of vocabulary has to fit anywhere. Null and empty texts are
    the end alone. Repeated rows each count and keep their row. Without training texts the base is 1 over 1.
    """
    small_batches(docs.sparkSession)
    rows = held_out(docs)
    counted = rows.select("text", "held_out").mapInArrow(remote(HERE, "count_batches"), "word string, n_train long, n_all long")
    words = counted.groupBy("word").agg(F.sum("n_train").alias("n_train"), F.sum("n_all").alias("n_all"))
    logp = vocabulary(path)
    scored = durable(words.mapInArrow(remote(HERE, "word_batches", logp=logp), "word string, n_train long, n_all long, pieces double"))
    ends = rows.where(~F.col("held_out")).count()
    got = scored.agg(F.sum("n_train"), F.count(F.when(F.col("n_train") > 0, 1)), F.count(F.when(F.col("n_train") == 1, 1)), F.count(F.when(F.col("n_train") == 2, 1))).first()
    total, distinct = (got[0] or 0) + ends, got[1] + (1 if ends else 0)
    arcs = Arcs(total, distinct, got[2], got[3])
    floor = math.log10(total + distinct + 1)
    eighth = F.floor(F.log2("n_all") * 8).cast("int")
    least, room = 1 << 30, hot_words
    for r in sorted(scored.groupBy(eighth.alias("e")).count().collect(), key=lambda r: -r["e"]):  # a row an eighth of a doubling
        if r["count"] > room:
            break
        least, room = r["e"], room - r["count"]
    named = F.when(F.octet_length("word") <= HOT_BYTES, F.col("word"))
    long = scored.where(eighth >= least).where(F.octet_length("word") > HOT_BYTES).select("word", "n_train", "pieces").mapInArrow(remote(HERE, "long_keys"), "key binary, n_train long, pieces double")
    top = scored.where(eighth >= least).where(named.isNotNull()).select(F.col("word").cast("binary").alias("key"), "n_train", "pieces").unionByName(long).collect()  # at most hot_words of bounded size
    hot = {bytes(r["key"]): (math.log10(r["n_train"] + 1) - floor, arcs.log_add(r["n_train"], r["pieces"]), r["n_train"]) for r in top} | {b"": (0.0, arcs.log_add(ends, logp[END]), 0)}
    tally = rows.mapInArrow(remote(HERE, "tally_batches", hot=hot, base=(math.log10(ends + 1) - floor, ends)), "uid long, word string, tf long, doc_id long, held_out boolean, n_tokens long, hot_known long, hot_base double, hot_score double")
    joined = tally.join(scored.select("word", "n_train", arcs.column(F.col("n_train"), F.col("pieces")).alias("logp")), "word", "left")
    plain = F.col("tf") * (F.log10(F.coalesce("n_train", F.lit(0)) + 1) - F.lit(floor))
    out = joined.groupBy("uid").agg(
        F.max("doc_id").alias("doc_id"), F.max("held_out").alias("held_out"), F.max("n_tokens").alias("n_tokens"),
        (F.sum(F.when(F.col("n_train") > 0, F.col("tf")).otherwise(0)) + F.max("hot_known")).alias("n_known"),
        (F.sum(plain) + F.max("hot_base")).alias("base_score"),
        (F.sum(F.coalesce(F.col("tf") * F.col("logp"), F.lit(0.0))) / math.log(10) + F.max("hot_score")).alias("score"),
    )
    return out.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score")
