"""Removal of long repeated byte strings across documents, by prefix-free parsing.

Parsing. A rolling hash over `gram` bytes triggers phrases: each string of `span` bytes belongs to the
leftmost smallest hash within it, so equal strings belong to equal triggers at equal places, and
consecutive strings of one trigger make a phrase. Phrases overlap by span - 1 bytes, so no string that is asked about
leaves its phrase. Every document is a sequence of phrases (its parse), and what repeats between documents repeats as phrases.

Dictionary. Documents are taken in units of some hundred rows. Each unit sends each of its distinct phrases once, with the least
document that has it; equal phrases meet and the least document of all is known. However often a
phrase occurs, its group has one row a unit. Phrases that are alone with their trigger are in corpus order as they are.

Suffix order. Where a trigger has several phrases, the bytes of each distinct one are fetched once. The suffix array of that part of the
dictionary, all suffixes by their first `span` bytes and then by the least document of their phrase, shows which strings of a phrase a
smaller document holds too. Triggers with very many phrases are dealt out string by string, so none has to fit a task.

Combining. The units are parsed again and what is known of a phrase, or of some of its strings, is carried to each place
where the parse has it: it goes if the least document there is smaller than its own. As comparisons end within a phrase,
the order of what follows a phrase, which a suffix array of the parse would give, is never asked for.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import blobs, durable, mixed, pack_columns, remote, remote_group, remote_pair, text_bytes, texts, unblob, unpack_columns

HERE = __name__
SPAN, GRAM = 50, 20
CHUNK = 1 << 20
#: A unit has 2 ** UNIT rows at most.
UNIT = 8
#: Phrases of one trigger beyond which its strings are dealt out.
HOT = 50_000
BASE = 0x9E3779B97F4A7C15 | 1
# Base and byte values of a second hash of phrases, independent of the first.
BASE2 = 0xD1342543DE82EF95
VALUES2 = np.random.default_rng(50).integers(0, 1 << 64, 256, np.uint64)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int, base: int = BASE) -> tuple[np.ndarray, np.ndarray]:
    """base and its inverse to the powers 0 to n - 1, modulo 2 ** 64."""
    if len(_POWERS.get(base, ((),))[0]) < n:
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            x = np.full(n, b, np.uint64)
            x[0] = 1
            both.append(np.multiply.accumulate(x))
        _POWERS[base] = both[0], both[1]
    up, down = _POWERS[base]
    return up[:n], down[:n]


def phrases(data: np.ndarray, bounds: np.ndarray, span: int = SPAN, gram: int = GRAM) -> dict[str, np.ndarray]:
    """The phrases of a buffer that holds pieces one after the other, piece i from bounds[i] to bounds[i + 1].

    piece; lo: start of its first string, counted from the piece's; more: further strings; off: where the trigger
    stands from lo; trigger: its hash; whole, second: two independent hashes of the phrase, of 64 and 32 bits. Phrases of one
    trigger are taken for equal if all 96 bits are: with D of them the expected wrong coverings are D^2 / 2^97.
    """
    n = len(data)
    names = ("piece", "lo", "more", "off", "trigger", "whole", "second")
    if n < span:
        return dict.fromkeys(names, np.zeros(0, np.int64))
    up, down = _powers(n + 1)
    with np.errstate(over="ignore"):
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n], out=total[1:])
        grams = mixed((total[gram:] - total[:-gram]) * down[: n - gram + 1])
    place = np.uint64((1 << 27) - 1)
    key = (grams & ~place) | np.arange(len(grams), dtype=np.uint64)
    width = span - gram + 1
    have, low = 1, key
    while have < width:
        step = min(have, width - have)
        low = np.minimum(low[: len(low) - step], low[step:])
        have += step
    owner = (low & place).astype(np.int64)  # of the string that starts at each place
    room = np.diff(bounds)
    piece = np.repeat(np.arange(len(room)), room)[: len(owner)]
    start = np.arange(len(owner))
    fits = start + span <= bounds[1:][piece]
    start, piece, owner = start[fits], piece[fits], owner[fits]
    if not len(start):
        return dict.fromkeys(names, np.zeros(0, np.int64))
    first = np.flatnonzero(np.r_[True, (owner[1:] != owner[:-1]) | (piece[1:] != piece[:-1])])
    last = np.r_[first[1:], len(start)] - 1
    lo, hi, owner, piece = start[first], start[last], owner[first], piece[first]
    with np.errstate(over="ignore"):
        up2, down2 = _powers(n + 1, BASE2)
        total2 = np.zeros(n + 1, np.uint64)
        np.cumsum(VALUES2[data] * up2[:n], out=total2[1:])
        second = mixed((total2[hi + span] - total2[lo]) * down2[lo] + (hi - lo + 64 * (owner - lo)).astype(np.uint64))
        whole = mixed((total[hi + span] - total[lo]) * down[lo] + (hi - lo + 64 * (owner - lo)).astype(np.uint64))
    return {"piece": piece, "lo": lo - bounds[piece], "more": (hi - lo).astype(np.uint8), "off": (owner - lo).astype(np.uint8), "trigger": grams[owner], "whole": whole, "second": (second >> np.uint64(32)).astype(np.uint32)}


def pieces(rows, span: int):
    """Buffers of about CHUNK bytes: (data, bounds, row, base) of (row, bytes); long texts go in pieces that overlap by span - 1."""
    held, meta, size = [], [], 0
    for row, raw in rows:
        for base in range(0, max(1, len(raw) - span + 1), CHUNK):
            part = raw[base : base + CHUNK + span - 1]
            held.append(part)
            meta.append((row, base))
            size += len(part)
            if size >= CHUNK:
                yield _buffer(held, meta)
                held, meta, size = [], [], 0
    if held:
        yield _buffer(held, meta)


def _buffer(held, meta):
    bounds = np.r_[0, np.cumsum([len(p) for p in held])]
    row, base = (np.array(c, np.int64) for c in zip(*meta, strict=True))
    return np.frombuffer(b"".join(held), np.uint8), bounds, row, base


def parse(raws: list[bytes], span: int, gram: int) -> dict[str, np.ndarray]:
    """The phrases of texts: row (place of the text in the list), lo, more, off, trigger, whole, second."""
    found = []
    for data, bounds, row, base in pieces(enumerate(raws), span):
        p = phrases(data, bounds, span, gram)
        at = p["piece"].astype(np.int64)
        found.append([row[at], p["lo"] + base[at], p["more"].astype(np.uint8), p["off"].astype(np.uint8), p["trigger"].astype(np.uint64), p["whole"].astype(np.uint64), p["second"].astype(np.uint32)])
    names = ("row", "lo", "more", "off", "trigger", "whole", "second")
    kinds = (np.int64, np.int64, np.uint8, np.uint8, np.uint64, np.uint64, np.uint32)
    if not found:
        return {n: np.zeros(0, k) for n, k in zip(names, kinds, strict=True)}
    return dict(zip(names, (np.concatenate(x) for x in zip(*found, strict=True)), strict=True))


def starts(*columns: np.ndarray) -> np.ndarray:
    """Whether each row of sorted columns differs from the one before."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return new


def part_of(unit: np.ndarray, parts: int) -> np.ndarray:
    return (mixed(unit) % np.uint64(parts)).astype(np.int64)


def _units(batches):
    """(unit, doc, tag, raws) for each run of rows of one unit."""
    for b in batches:
        unit, doc, tag = (b.column(c).to_numpy() for c in ("unit", "doc_id", "tag"))
        first = np.flatnonzero(starts(unit))
        for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(unit)], strict=True):
            raws = [(t or "").encode("utf-8", "surrogatepass") for t in b.column("text").slice(lo, hi - lo).to_pylist()]
            yield int(unit[lo]), doc[lo:hi], tag[lo:hi], raws


def dictionary_blobs(batches, parts: int, span: int, gram: int):
    """Each unit's distinct phrases as blobs by trigger, with a place, the least document that has them and how far the greatest is beyond it."""
    found: list[list[np.ndarray]] = []
    size = 0
    for unit, doc, tag, raws in _units(batches):
        p = parse(raws, span, gram)
        own = doc[p["row"]]
        order = np.lexsort((own, p["second"], p["whole"], p["trigger"]))
        key = [p[c][order] for c in ("trigger", "whole", "second")]
        first = np.flatnonzero(starts(*key))
        if not len(first):
            continue
        at = order[first]
        last = order[np.r_[first[1:], len(order)] - 1]
        read = np.argsort(at)  # as the texts have them: documents and places then rise, and take little room
        at, last, first = at[read], last[read], first[read]
        found.append([*[k[first] for k in key], np.full(len(at), unit), own[at], tag[p["row"][at]].astype(np.uint32), p["lo"][at].astype(np.uint32), p["more"][at], p["off"][at], own[last] - own[at]])
        size += len(at)
        if size > 400_000:
            yield from _dealt(found, parts)
            found, size = [], 0
    if found:
        yield from _dealt(found, parts)


def _dealt(found, parts: int):
    columns = [np.concatenate(x) for x in zip(*found, strict=True)]
    yield from blobs((columns[0] % np.uint64(parts)).astype(np.int64), columns)


def _rows_of(kind: int, part: np.ndarray, columns) -> list[tuple]:
    out = []
    for batch in blobs(part, columns):
        for p, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            out.append((kind, p, int((part == p).sum()), blob))
    return out


def ordered_phrases(frame, dparts: int, span: int, hot: int):
    """(kind, part, n, blob). Kind 0: phrases of a unit that a smaller document has too, which goes with them. Kind 1: phrases to fetch."""
    trigger, whole, second, unit, doc, tag, lo, more, off, beyond = unblob(frame["blob"])
    most = doc + beyond
    order = np.lexsort((doc, second, whole, trigger))
    trigger, whole, second, unit, doc, tag, lo, more, off, most = (x[order] for x in (trigger, whole, second, unit, doc, tag, lo, more, off, most))
    new_trigger = starts(trigger)
    new_phrase = starts(trigger, whole, second)
    least = doc[new_phrase][np.cumsum(new_phrase) - 1]
    held = most > least
    nothing = np.zeros(len(doc), np.uint8)
    out = _rows_of(0, part_of(unit[held], dparts), [unit[held], doc[held], tag[held], lo[held], nothing[held], more[held], least[held]])
    group = np.cumsum(new_trigger) - 1
    begin = np.flatnonzero(new_trigger)
    low, high = np.minimum.reduceat(least, begin), np.maximum.reduceat(least, begin)
    many = np.bincount(group[new_phrase])
    ask = new_phrase & (low < high)[group]  # a phrase's first row: its least document is there
    out += _rows_of(1, part_of(unit[ask], dparts), [unit[ask], doc[ask], tag[ask], lo[ask], more[ask], off[ask], trigger[ask], (many > hot)[group[ask]]])
    return pd.DataFrame(out, columns=["kind", "part", "n", "blob"])


def text_blobs(batches, dparts: int):
    """Documents by part, compressed, so that texts move at a third of their size."""
    for b in batches:
        held: dict[int, list] = {}
        for unit, doc, tag, raws in _units([b]):
            part = int(part_of(np.array([unit]), dparts)[0])
            held.setdefault(part, []).extend(zip([unit] * len(raws), doc.tolist(), tag.tolist(), raws, strict=True))
        out = []
        for own in held.values():
            unit, doc, tag, raw = zip(*own, strict=True)
            out.append(pack_columns([np.array(unit, np.int64), np.array(doc, np.int64), np.array(tag, np.uint32), np.array([len(x) for x in raw], np.int64), np.frombuffer(b"".join(raw), np.uint8)], level=3))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array(out, pa.binary())], ["part", "blob"])


def _documents(frame) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """(unit, doc, tag, raws) of a part's documents, unit by unit."""
    unit, doc, tag, raws = [], [], [], []
    for blob in frame["blob"]:
        u, d, g, size, data = unpack_columns(blob)
        at = np.r_[0, np.cumsum(size)].tolist()
        raw = data.tobytes()
        unit.append(u)
        doc.append(d)
        tag.append(g)
        raws += [raw[lo:hi] for lo, hi in zip(at[:-1], at[1:], strict=True)]
    unit, doc, tag = (np.concatenate(x) for x in (unit, doc, tag))
    order = np.argsort(unit, kind="stable")
    return unit[order], doc[order], tag[order], [raws[i] for i in order.tolist()]


def _places(doc: np.ndarray, tag: np.ndarray) -> dict[tuple[int, int], int]:
    return {k: i for i, k in enumerate(zip(doc.tolist(), tag.tolist(), strict=True))}


def fetch_bytes(docs, asked, eparts: int, span: int, gram: int):
    """(part, blob) by trigger: the bytes of the phrases asked for, filled up to one width; of hot triggers each string by itself."""
    out = []
    if len(asked) and len(docs):
        _, held_doc, held_tag, raws = _documents(docs)
        at = _places(held_doc, held_tag)
        unit, doc, tag, lo, more, off, trigger, hot = unblob(asked["blob"])
        width = 2 * span - gram
        raw = b"".join([raws[at[d, g]][s : s + width].ljust(width, b"\0") for d, g, s in zip(doc.tolist(), tag.tolist(), lo.tolist(), strict=True)])
        mat = np.frombuffer(raw, np.uint8).reshape(-1, width)
        start = np.zeros(len(doc), np.uint8)
        columns = [trigger, unit, doc, tag, lo, start, more, off, mat]
        if hot.any():
            own = np.flatnonzero(hot)
            row = np.repeat(own, more[own].astype(np.int64) + 1)
            begin = np.cumsum(more[own].astype(np.int64) + 1) - more[own] - 1
            j = np.arange(len(row)) - np.repeat(begin, more[own].astype(np.int64) + 1)
            string = np.zeros((len(row), width), np.uint8)
            string[:, :span] = mat[row[:, None], j[:, None] + np.arange(span)]
            name = np.array([xxhash.xxh3_64_intdigest(x) for x in string[:, :span].copy().view(f"V{span}").ravel().tolist()], np.uint64)
            none = np.zeros(len(row), np.uint8)
            single = [name, unit[row], doc[row], tag[row], lo[row], j.astype(np.uint8), none, none, string]
            columns = [np.concatenate([a[~hot], b]) for a, b in zip(columns, single, strict=True)]
        *columns, mat = columns
        part = (mixed(columns[0]) % np.uint64(eparts)).astype(np.int64)
        for batch in blobs(part, [*columns, np.ascontiguousarray(mat).view(f"V{width}").ravel()]):
            out += list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
    return pd.DataFrame(out, columns=["part", "blob"])


def suffix_array(trigger: np.ndarray, doc: np.ndarray, more: np.ndarray, off: np.ndarray, mat: np.ndarray, span: int, gram: int):
    """The dictionary's suffixes in order, one array for each distance `before` from a suffix to its trigger: yields (before, rows, equal).

    Rows are in the order of trigger, the suffix's first span bytes, and the phrase's least document; equal marks rows whose
    trigger and bytes are those of the row before. Equal suffixes have equal distances, so arrays need not be merged.
    """
    words = -(-span // 8)
    for before in range(span - gram + 1):
        at = off - before  # place of the string that starts `before` bytes ahead of the trigger
        own = np.flatnonzero((at >= 0) & (at <= more))
        if len(own) < 2:
            continue
        text = np.zeros((len(own), 8 * words), np.uint8)
        text[:, :span] = mat[own[:, None], at[own][:, None] + np.arange(span)]
        cols = text.view(">u8").astype(np.uint64)
        order = np.lexsort((doc[own], *[cols[:, i] for i in reversed(range(words))], trigger[own]))
        own, cols = own[order], cols[order]
        equal = np.zeros(len(own), bool)
        equal[1:] = (trigger[own[1:]] == trigger[own[:-1]]) & (cols[1:] == cols[:-1]).all(axis=1)
        yield before, own, equal


def ordered_suffixes(frame, dparts: int, span: int, gram: int):
    """(kind 0, part, n, blob): strings of phrases that a smaller document has too, in runs of one least document, from suffix order."""
    trigger, unit, doc, tag, lo, start, more, off, ctx = unblob(frame["blob"])
    mat = np.ascontiguousarray(ctx).view(np.uint8).reshape(len(trigger), -1)
    kept: list[list[np.ndarray]] = []
    off, more = off.astype(np.int64), more.astype(np.int64)
    for before, own, equal in suffix_array(trigger, doc, more, off, mat, span, gram):
        least = doc[own][~equal][np.cumsum(~equal) - 1]
        hit = doc[own] > least
        kept.append([own[hit], off[own[hit]] - before, least[hit]])
    row, j, least = (np.concatenate(x) for x in zip(*kept, strict=True)) if kept else (np.zeros(0, np.int64),) * 3
    order = np.lexsort((j, row))
    row, j, least = row[order], j[order], least[order]
    first = np.flatnonzero(starts(row, j - np.arange(len(j)), least)) if len(row) else np.zeros(0, int)
    last = np.r_[first[1:], len(row)] - 1 if len(row) else first
    own = row[first]
    begin = (start[own] + j[first]).astype(np.uint8)
    columns = [unit[own], doc[own], tag[own], lo[own], begin, (j[last] - j[first]).astype(np.uint8), least[first]]
    return pd.DataFrame(_rows_of(0, part_of(unit[own], dparts), columns), columns=["kind", "part", "n", "blob"])


def spans_of(lo: np.ndarray, hi: np.ndarray) -> list[tuple[int, int]]:
    """The union of intervals, as maximal runs in order."""
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    first = np.flatnonzero(np.r_[True, lo[1:] > hi[:-1]])
    return list(zip(lo[first].tolist(), hi[np.r_[first[1:] - 1, len(hi) - 1]].tolist(), strict=True))


def carried(unit: np.ndarray, doc: np.ndarray, tag: np.ndarray, raws: list[bytes], found, span: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, from, to): the intervals of a part's documents that go, for all places of the phrases found."""
    r_unit, r_doc, r_tag, r_lo, r_begin, r_more, r_least = unblob(found["blob"])
    named = np.isin(unit, np.unique(r_unit))
    own = np.flatnonzero(named)
    p = parse([raws[i] for i in own.tolist()], span, gram)
    row, lo = own[p["row"]], p["lo"]
    order = np.lexsort((p["second"], p["whole"], p["trigger"], unit[row]))
    new = starts(unit[row][order], *[p[c][order] for c in ("trigger", "whole", "second")])
    phrase = np.empty(len(order), np.int64)
    phrase[order] = np.cumsum(new) - 1
    begin = np.flatnonzero(new)
    count = np.diff(np.r_[begin, len(order)])
    at = _places(doc, tag)
    place = np.array([at[k] for k in zip(r_doc.tolist(), r_tag.tolist(), strict=True)], np.int64) << 32 | r_lo.astype(np.int64)
    key = row << 32 | lo
    by = np.argsort(key, kind="stable")
    which = phrase[by[np.searchsorted(key[by], place)]]
    each = count[which]
    result = np.repeat(np.arange(len(which)), each)
    step = np.arange(len(result)) - np.repeat(np.cumsum(each) - each, each)
    there = order[begin[which][result] + step]
    hit = doc[row[there]] > r_least[result]
    there, result = there[hit], result[hit]
    lo = lo[there] + r_begin[result].astype(np.int64)
    return row[there], lo, lo + r_more[result].astype(np.int64) + span


def cut_out(docs, found, span: int, gram: int, digest: bool):
    """A row for each document: what its spans leave."""
    rows = []
    if len(docs):
        unit, doc, tag, raws = _documents(docs)
        at: dict[int, list[tuple[int, int]]] = {}
        if len(found):
            row, lo, hi = carried(unit, doc, tag, raws, found, span, gram)
            order = np.lexsort((lo, row))
            row, lo, hi = row[order], lo[order], hi[order]
            first = np.flatnonzero(starts(row))
            for a, b in zip(first.tolist(), [*first[1:].tolist(), len(row)], strict=True):
                at[int(row[a])] = spans_of(lo[a:b], hi[a:b])
        for i, (d, raw) in enumerate(zip(doc.tolist(), raws, strict=True)):
            spans = at.get(i, [])
            kept, place = [], 0
            for a, b in spans:
                kept.append(raw[place:a])
                place = b
            left = b"".join([*kept, raw[place:]]) if spans else raw
            if digest:
                rows.append((d, len(raw), len(raw) - len(left), len(spans), hashlib.sha256(left).hexdigest()))
            else:
                rows.append((d, int(tag[i]), left.decode("utf-8", "ignore"), len(raw) - len(left), [v for s in spans for v in s]))
    return pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] if digest else ["doc_id", "tag", "kept", "n_removed", "spans"])


DIGEST = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
KEPT = "doc_id long, tag int, kept string, n_removed long, spans array<long>"
ROWS = "doc_id long, tag int, text string, unit long"


def tagged(docs: DataFrame) -> DataFrame:
    """(doc_id, tag, text) of rows with an id; tag tells rows of one doc_id apart (0 for all if ids are unique)."""
    rows = texts(docs).where("doc_id is not null")
    twice = rows.groupBy("doc_id").count().where("count > 1").select("doc_id")
    if twice.isEmpty():
        return rows.select("doc_id", F.lit(0).alias("tag"), "text")
    number = F.row_number().over(Window.partitionBy("doc_id").orderBy("text")) - 1
    again = rows.join(twice, "doc_id", "left_semi").select("doc_id", number.cast("int").alias("tag"), "text")
    return rows.join(twice, "doc_id", "left_anti").select("doc_id", F.lit(0).alias("tag"), "text").unionByName(again)


def remove_repeats(docs: DataFrame, digest: bool = False, span: int = SPAN, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """A row for each row of docs with an id: KEPT (text without the repeats, spans as flat start and end bytes) or DIGEST.

    A byte goes if a string of `span` bytes over it also starts in a document with a smaller doc_id; matches
    do not cross documents and are judged on the input. Rows with one doc_id do not take bytes from each other; tag numbers them by text.
    Null and empty texts, and texts shorter than span, keep all. In KEPT, letters cut in the middle go whole.
    Rows with a null doc_id have no order: they are not part of the result.
    """
    size = max(1, text_bytes(docs))
    tasks = max(1, math.ceil(size / (16 << 20)))
    parts, dparts = 8 * tasks, max(1, math.ceil(size / (8 << 20)))
    unit = F.shiftright(F.monotonically_increasing_id(), UNIT)
    rows = durable(tagged(docs).select("doc_id", "tag", "text", unit.alias("unit")))
    kw = {"span": span, "gram": gram}
    spread = rows.mapInArrow(remote(HERE, "dictionary_blobs", parts=parts, **kw), "part int, blob binary").repartition(tasks, "part")
    ordered = durable(spread.groupBy("part").applyInPandas(remote_group(HERE, "ordered_phrases", dparts=dparts, span=span, hot=hot), "kind int, part int, n long, blob binary"))
    asked = ordered.where("kind = 1")
    eparts = max(1, math.ceil((asked.agg(F.sum("n")).first()[0] or 0) / 300_000))
    packed = rows.mapInArrow(remote(HERE, "text_blobs", dparts=dparts), "part int, blob binary")
    fetched = packed.groupBy("part").cogroup(asked.select("part", "blob").groupBy("part")).applyInPandas(remote_pair(HERE, "fetch_bytes", eparts=eparts, **kw), "part int, blob binary")
    ends = fetched.groupBy("part").applyInPandas(remote_group(HERE, "ordered_suffixes", dparts=dparts, **kw), "kind int, part int, n long, blob binary")
    found = ordered.where("kind = 0").unionByName(ends).select("part", "blob")
    return packed.groupBy("part").cogroup(found.groupBy("part")).applyInPandas(remote_pair(HERE, "cut_out", digest=digest, **kw), DIGEST if digest else KEPT)


def digests(docs: DataFrame) -> DataFrame:
    """DIGEST rows of documents with an id, and those of rows without one, which keep all bytes."""
    bare = texts(docs).where("doc_id is null").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    whole = bare.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), F.sha2("text", 256).alias("kept_sha256"))
    return remove_repeats(docs, digest=True).unionByName(whole)


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs with text replaced by what remove_repeats() leaves and, where the column exists, n_chars to match.

    Rows that lose nothing keep their text as it is, null or not. Rows of one doc_id each keep their row: which of them a
    text belongs to is told by their order of text. Rows without an id pass as they are, as do all other columns, whatever their names.
    """
    cut = durable(remove_repeats(docs).where("n_removed > 0").select(F.col("doc_id").alias("d"), F.col("tag").alias("t"), "kept"))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r")
    held = docs.where("doc_id is not null").select(row, F.col("doc_id").cast("long").alias("d"))
    twice = docs.select(F.col("doc_id").cast("long").alias("d")).where("d is not null").groupBy("d").count().where("count > 1").select("d")
    if twice.isEmpty():
        changed = held.join(cut.drop("t"), "d", "left").select("r", "kept")
    else:
        number = F.row_number().over(Window.partitionBy("d").orderBy(F.col("r.text").cast("string"))) - 1
        again = held.join(twice, "d", "left_semi").select("r", "d", number.alias("t"))
        single = held.join(twice, "d", "left_anti").select("r", "d", F.lit(0).alias("t"))
        changed = single.unionByName(again).join(cut, ["d", "t"], "left").select("r", "kept")
    out = []
    for c in docs.columns:
        own = F.col("r").getField(c)
        if c == "text":
            own = F.coalesce(F.col("kept"), own)
        if c == "n_chars":
            own = F.when(F.col("kept").isNotNull(), F.length("kept").cast(docs.schema["n_chars"].dataType)).otherwise(own)
        out.append(own.alias(c))
    return changed.select(out).unionByName(docs.where("doc_id is null"))
