"""Lossless WebP in numpy: a complete decoder, and an encoder that can use each feature.

Pixels are uint8 arrays of shape (height, width, 4) in the order alpha, red, green, blue. The decoder
reads prefix codes, meta prefix groups, back-references and the colour cache, and inverts the
predictor, cross-colour, subtract-green and palette transforms.

A prefix code can only be read from where the last one ended. So that this need not be a walk through
every field, a block of the stream is looked at from each of its bit positions at once: tables say how
long the pixel that would start there is. The walk then only hops from pixel to pixel, and the fields of the
places it met are read as arrays. Copies and cache hits become pointers to earlier pixels,
which are followed by doubling.
"""

from __future__ import annotations

import functools
import struct

import numpy as np

SIDE = 16384

# Fixed values of the format: the order in which code length codes are stored, and the cache's multiplier.
CODE_ORDER = [17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15]
CACHE_MULTIPLIER = 0x1E35A7BD

#: Bits of a stream that are looked at together, and the longest pixel or copy that may run over the end.
BLOCK, SLACK = 1 << 18, 128
#: Images of fewer pixels are read one by one.
FEW = 48


@functools.cache
def near_offsets() -> list[tuple[int, int]]:
    """(dx, dy) of the 120 short distance codes: pixels above or left, by distance, then |dx|, right side first."""
    found = [(x, y) for y in range(8) for x in range(-7, 9) if y or x > 0]
    return sorted(found, key=lambda p: (p[0] ** 2 + p[1] ** 2, abs(p[0]), p[0] < 0))


@functools.cache
def near_distances(width: int) -> np.ndarray:
    """The distance in pixels of each short code, at an image width."""
    return np.array([max(1, dx + dy * width) for dx, dy in near_offsets()], np.int64)


@functools.cache
def near_codes(width: int) -> np.ndarray:
    """distance → its smallest short code, 0 where there is none."""
    out = np.zeros(int(near_distances(width).max()) + 1, np.int64)
    out[near_distances(width)[::-1]] = np.arange(120, 0, -1)
    return out


# ---------------------------------------------------------------- bits


class BitReader:
    def __init__(self, data: bytes, pos: int = 0):
        self.data, self.pos, self.end = bytes(data) + bytes(SLACK), pos, 8 * len(data)

    def peek(self, n: int) -> int:
        at = self.pos >> 3
        return (int.from_bytes(self.data[at : at + 8], "little") >> (self.pos & 7)) & ((1 << n) - 1)

    def read(self, n: int) -> int:
        out = self.peek(n)
        self.pos += n
        if self.pos > self.end:
            raise ValueError("the image data ends too early")
        return out


class BitWriter:
    def __init__(self):
        self.value, self.size = 0, 0

    def put(self, value: int, n: int) -> None:
        self.value |= value << self.size
        self.size += n

    def bytes(self) -> bytes:
        return self.value.to_bytes((self.size + 7) // 8, "little")


def packed_words(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The bits of values, each in its number of places (at most 63), lowest first, as 64-bit words from bit 0 on."""
    stop = np.cumsum(sizes)
    begin = stop - sizes
    out = np.zeros((int(stop[-1]) >> 6) + 2 if len(stop) else 1, np.uint64)
    word, shift = begin >> 6, (begin & 63).astype(np.uint64)
    if len(word):
        starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
        out[word[starts]] = np.bitwise_or.reduceat(values << shift, starts)
        last = np.r_[starts[1:], len(word)] - 1  # of the values that begin in a word only the last can reach into the next
        last = last[stop[last] > (word[last] + 1) << 6]
        out[word[last] + 1] |= values[last] >> (np.uint64(64) - shift[last])
    return out


# ---------------------------------------------------------------- prefix codes


@functools.cache
def mirrored(width: int) -> np.ndarray:
    """Every number of so many bits read backwards."""
    out = np.zeros(1 << width, np.int64)
    for i in range(width):
        out |= ((np.arange(1 << width) >> i) & 1) << (width - 1 - i)
    return out


class PrefixCode:
    """A code by the lengths of its symbols. Codes are stored as written: first bit in the lowest place. A lone symbol takes no bits."""

    def __init__(self, lengths):
        self.lengths = np.asarray(lengths, np.uint8)
        own = np.flatnonzero(self.lengths)
        if len(own) < 2:
            self.width, self.order, self.codes = 0, np.array([own[0] if len(own) else 0]), np.zeros(1, np.int64)
        else:
            size = self.lengths[own]
            self.width = int(size.max())
            by = np.argsort(size, kind="stable")
            self.order, size = own[by], size[by]
            room = 1 << (self.width - size.astype(np.int64))
            if room.sum() != 1 << self.width:
                raise ValueError("a prefix code is not complete")
            back = mirrored(self.width)
            self.codes = back[np.cumsum(room) - room]
            self._room, self._size = room, size
        self.mask = (1 << self.width) - 1
        self._pairs = self._listed = None

    @functools.cached_property
    def symbols(self) -> np.ndarray:
        """The symbol that each `width` bits begin with."""
        return np.repeat(self.order, self._room)[mirrored(self.width)] if self.width else self.order

    @functools.cached_property
    def sizes(self) -> np.ndarray:
        """How many of each `width` bits it takes."""
        return np.repeat(self._size, self._room)[mirrored(self.width)] if self.width else np.zeros(1, np.uint8)

    def read(self, bits: BitReader) -> int:
        if not self.width:
            return int(self.symbols[0])
        symbols, sizes = self.pairs()
        at = bits.peek(self.width)
        bits.pos += sizes[at]
        return symbols[at]

    def pairs(self) -> tuple[list[int], list[int]]:
        if self._pairs is None:
            self._pairs = self.symbols.tolist(), self.sizes.tolist()
        return self._pairs

    def written(self) -> tuple[np.ndarray, np.ndarray]:
        """(code, bits) of each symbol of the alphabet."""
        code = np.zeros(len(self.lengths), np.uint64)
        code[self.order] = self.codes
        return code, (self.lengths if self.width else np.zeros_like(self.lengths)).astype(np.int64)

    def listed(self) -> tuple[list[int], list[int]]:
        if self._listed is None:
            self._listed = tuple(x.tolist() for x in self.written())
        return self._listed


@functools.lru_cache(256)
def code_of(lengths: bytes) -> PrefixCode:
    """The code of these lengths; channels often share one, and so do images."""
    return PrefixCode(np.frombuffer(lengths, np.uint8))


def read_code(bits: BitReader, alphabet: int) -> PrefixCode:
    lengths = bytearray(alphabet)
    if bits.read(1):
        two, wide = bits.read(1), bits.read(1)
        lengths[bits.read(8 if wide else 1)] = 1
        if two:
            lengths[bits.read(8)] = 1
        return code_of(bytes(lengths))
    own = bytearray(19)
    many = 4 + bits.read(4)
    held = bits.read(3 * many)
    for i in CODE_ORDER[:many]:
        own[i] = held & 7
        held >>= 3
    code = code_of(bytes(own))
    left = alphabet
    if bits.read(1):
        left = 2 + bits.read(2 + 2 * bits.read(3))
    (symbols, sizes), mask = code.pairs(), code.mask
    at, previous = 0, 8
    begin, used = bits.pos >> 3, bits.pos & 7
    held = int.from_bytes(bits.data[begin : begin + 64], "little")
    while at < alphabet and left:
        left -= 1
        if used > 480:
            begin, used = begin + (used >> 3), used & 7
            held = int.from_bytes(bits.data[begin : begin + 64], "little")
        i = held >> used & mask
        s = symbols[i]
        used += sizes[i]
        if s < 16:
            lengths[at] = s
            previous = s or previous
            at += 1
            continue
        n, value, least = ((2, previous, 3), (3, 0, 3), (7, 0, 11))[s - 16]
        run = (held >> used & ((1 << n) - 1)) + least
        used += n
        if at + run > alphabet:
            raise ValueError("code lengths run over the alphabet")
        if value:
            lengths[at : at + run] = bytes([value]) * run
        at += run
    bits.pos = 8 * begin + used
    if bits.pos > bits.end:
        raise ValueError("the image data ends too early")
    return code_of(bytes(lengths))


def starts_of(values: np.ndarray) -> np.ndarray:
    """Where runs of equal values begin, and the end."""
    new = np.ones(len(values) + 1, bool)
    np.not_equal(values[1:], values[:-1], out=new[1:-1])
    return np.flatnonzero(new)


def _tokens_of(value: int, run: int):
    """(symbol, extra value, extra bits) of the tokens that spell so many equal code lengths."""
    if value:
        yield value, 0, 0
        run -= 1
    while run:
        if value == 0 and run >= 11:
            n = min(run, 138)
            yield 18, n - 11, 7
        elif value == 0 and run >= 3:
            n = min(run, 10)
            yield 17, n - 3, 3
        elif value and run >= 3:
            n = min(run, 6)
            yield 16, n - 3, 2
        else:
            n = 1
            yield value, 0, 0
        run -= n


class _Runs(dict):
    """(code length, run) → the bits of its tokens, first bit first, as text: made when first met, at most once for each length and run of an alphabet."""

    def __missing__(self, key: tuple[int, int]) -> str:
        codes, sizes = code_of(LENGTH_CODE).listed()
        self[key] = "".join(format(codes[s] | extra << sizes[s], f"0{sizes[s] + n}b")[::-1] for s, extra, n in _tokens_of(*key))
        return self[key]


RUNS = _Runs()


#: Lengths of the code in which this encoder writes code lengths: what a Huffman code of those of text images gives.
LENGTH_CODE = bytes([2, 7, 7, 5, 4, 4, 4, 4, 4, 4, 4, 5, 6, 7, 7, 7, 7, 3, 4])


@functools.lru_cache(64)
def code_bits(lengths: bytes) -> tuple[int, int]:
    """How code lengths are written: the bits as a number, and how many."""
    out = BitWriter()
    used = [s for s, n in enumerate(lengths) if n]
    if len(used) <= 2 and all(s < 256 for s in used):
        used = used or [0]
        out.put(1, 1)
        out.put(len(used) - 1, 1)
        out.put(1, 1)
        for s in used:
            out.put(s, 8)
        return out.value, out.size
    of = np.frombuffer(lengths, np.uint8)
    cut = starts_of(of)
    bits = "".join(map(RUNS.__getitem__, zip(of[cut[:-1]].tolist(), (cut[1:] - cut[:-1]).tolist(), strict=True)))
    head, n = _length_code_bits()
    return head | int(bits[::-1], 2) << n, n + len(bits)


@functools.cache
def _length_code_bits() -> tuple[int, int]:
    """How LENGTH_CODE is written before code lengths."""
    out = BitWriter()
    out.put(0, 1)
    out.put(15, 4)
    for s in CODE_ORDER:
        out.put(LENGTH_CODE[s], 3)
    out.put(0, 1)
    return out.value, out.size


def huffman(counts: np.ndarray, limit: int = 15) -> np.ndarray:
    """Code lengths of at most `limit` bits: counts are flattened until the tree is low enough."""
    used = np.flatnonzero(counts)
    lengths = np.zeros(len(counts), np.uint8)
    n = len(used)
    if n < 2:
        lengths[used] = 1
        return lengths
    floor = 1
    while True:
        weight = np.maximum(counts[used], floor)
        order = np.argsort(weight, kind="stable")
        single = weight[order].tolist()  # leaves and inner nodes both come up in order of weight
        single += [1 << 62, 1 << 62]
        joined = [1 << 62] * (n + 1)
        above = [0] * (2 * n - 1)
        i = j = 0
        for k in range(n, 2 * n - 1):
            x, y = single[i], joined[j]
            if x <= y:
                total = x
                above[i] = k
                i += 1
                x = single[i]
            else:
                total = y
                above[n + j] = k
                j += 1
                y = joined[j]
            if x <= y:
                joined[k - n] = total + x
                above[i] = k
                i += 1
            else:
                joined[k - n] = total + y
                above[n + j] = k
                j += 1
        depth = [0] * (2 * n - 1)
        for node in range(2 * n - 3, -1, -1):
            depth[node] = depth[above[node]] + 1
        if max(depth[:n]) <= limit:
            lengths[used[order]] = depth[:n]
            return lengths
        floor *= 2


def _value(prefix: int, bits: BitReader) -> int:
    if prefix < 4:
        return prefix + 1
    extra = (prefix - 2) >> 1
    return ((2 + (prefix & 1)) << extra) + bits.read(extra) + 1


def _prefixes(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(prefixes, extra values, extra bits) of lengths or distance codes."""
    v = values.astype(np.int64) - 1
    top = np.frexp(np.maximum(v, 1).astype(float))[1] - 1
    extra = np.where(v < 4, 0, top - 1)
    prefix = np.where(v < 4, v, 2 * top + ((v >> np.maximum(extra, 0)) & 1))
    return prefix, v & ((1 << extra) - 1) * (v >= 4), extra


# Extra bits and first value of each prefix of a length or distance.
EXTRA = np.array([0, 0, 0, 0, *[(p - 2) >> 1 for p in range(4, 40)]], np.int64)
LEAST = np.array([1, 2, 3, 4, *[((2 + (p & 1)) << ((p - 2) >> 1)) + 1 for p in range(4, 40)]], np.int64)


# ---------------------------------------------------------------- entropy-coded images


def _read_groups(bits: BitReader, count: int, cache_bits: int) -> list[list[PrefixCode]]:
    first = 280 + ((1 << cache_bits) if cache_bits else 0)
    return [[read_code(bits, n) for n in (first, 256, 256, 256, 40)] for _ in range(count)]


def _read_image(bits: BitReader, width: int, height: int, main: bool) -> np.ndarray:
    """Pixels as packed uint32 (alpha highest), row by row."""
    cache_bits = 0
    if bits.read(1):
        cache_bits = bits.read(4)
        if not 1 <= cache_bits <= 11:
            raise ValueError("colour cache size out of range")
    meta, shift, across = None, 0, 0
    count = 1
    if main and bits.read(1):
        shift = bits.read(3) + 2
        across = -(-width >> shift)
        meta = ((_read_image(bits, across, -(-height >> shift), False) >> 8) & 0xFFFF).tolist()
        count = max(meta) + 1
    groups = _read_groups(bits, count, cache_bits)
    total = width * height
    widths = [c.width for c in groups[0]]
    if count == 1 and total >= FEW and (widths[0] or groups[0][0].symbols[0] < 256 and sum(widths[1:4])):
        return _read_blocks(bits, width, total, groups[0], cache_bits)
    out = [0] * total
    cache = [0] * (1 << cache_bits) if cache_bits else None
    near = near_distances(width).tolist()
    at = cached = 0
    green, red, blue, alpha, dist = groups[0]
    while at < total:
        if meta is not None:
            y, x = divmod(at, width)
            green, red, blue, alpha, dist = groups[meta[(y >> shift) * across + (x >> shift)]]
        s = green.read(bits)
        if s < 256:
            r = red.read(bits)
            b = blue.read(bits)
            out[at] = alpha.read(bits) << 24 | r << 16 | s << 8 | b
            at += 1
        elif s < 280:
            length = _value(s - 256, bits)
            d = _value(dist.read(bits), bits)
            d = d - 120 if d > 120 else near[d - 1]
            if d > at or at + length > total:
                raise ValueError("a back-reference leaves the image")
            for _ in range(length):
                out[at] = out[at - d]
                at += 1
        else:
            if cache is None:
                raise ValueError("a colour cache code without a cache")
            while cached < at:
                cache[_slot(out[cached], cache_bits)] = out[cached]
                cached += 1
            out[at] = cache[s - 280]
            at += 1
        if bits.pos > bits.end:
            raise ValueError("the image data ends too early")
    return np.array(out, np.uint32)


def _windows(data: np.ndarray, lo: int, n: int) -> np.ndarray:
    """The 16 bits that begin at each of n bit positions from lo, a multiple of 8."""
    b = data[lo >> 3 : (lo + n >> 3) + 3].astype(np.uint32)
    whole = b[:-2] | b[1:-1] << 8 | b[2:] << 16
    return ((whole[:, None] >> np.arange(8, dtype=np.uint32)) & 0xFFFF).ravel()[:n].astype(np.int64)


def _bits_at(data: np.ndarray, place: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers of so many bits (at most 24) at bit positions."""
    at = place >> 3
    whole = data[at].astype(np.int64) | data[at + 1].astype(np.int64) << 8 | data[at + 2].astype(np.int64) << 16 | data[at + 3].astype(np.int64) << 24
    return (whole >> (place & 7)) & ((1 << sizes) - 1)


def _read_blocks(bits: BitReader, width: int, total: int, group: list[PrefixCode], cache_bits: int) -> np.ndarray:
    """_read_image() for one group of codes, by blocks of bit positions."""
    green, *others, dist = group
    data = np.frombuffer(bits.data, np.uint8)
    kinds, literals, counts, back = [], [], [], []
    at, done, top = bits.pos, 0, 280 + ((1 << cache_bits) if cache_bits else 0)
    while done < total:
        if at >= bits.end:
            raise ValueError("the image data ends too early")
        lo = at & ~7
        n = min(BLOCK, bits.end - lo) + SLACK
        window = _windows(data, lo, n)
        n = len(window) - SLACK  # what starts before ends before len(window)
        code = window[:n] & green.mask
        symbol, ends = green.symbols.take(code), green.sizes.take(code) + np.arange(n)
        long = np.flatnonzero(symbol >= 256)
        after = ends[long]
        for i, c in enumerate(others):
            if c.width:
                if i == 0 or c is not others[i - 1]:
                    steps = c.sizes.take(window & c.mask)
                ends += steps.take(ends)
        copy = symbol[long] < 280
        own = after[copy] + EXTRA[symbol[long][copy] - 256]
        code = window[own] & dist.mask
        after[copy] = own + dist.sizes[code] + EXTRA[dist.symbols[code]]
        ends[long] = after
        hop, p, stop, met = memoryview(np.ascontiguousarray(ends, np.int64)), at - lo, min(n, bits.end - lo), []
        while p < stop:
            met.append(p)
            p = hop[p]
        met = np.array(met, np.int64)
        kind = symbol[met]
        if kind.max(initial=0) >= top:
            raise ValueError("a colour cache code without a cache")
        count, far, value = np.ones(len(met), np.int64), np.zeros(len(met), np.int64), np.zeros(len(met), np.uint32)
        plain = np.flatnonzero(kind < 256)
        q = met.take(plain)
        q = q + green.sizes.take(window.take(q) & green.mask)
        word = kind.take(plain) << 8
        for c, shift in zip(others, (16, 0, 24), strict=True):
            w = window.take(q) & c.mask
            word |= c.symbols.take(w) << shift
            q = q + c.sizes.take(w)
        value[plain] = word
        ref = np.flatnonzero((kind >= 256) & (kind < 280))
        if len(ref):
            prefix = kind[ref] - 256
            q = met[ref] + green.sizes[window[met[ref]] & green.mask]
            count[ref] = LEAST[prefix] + _bits_at(data, lo + q, EXTRA[prefix])
            q = q + EXTRA[prefix]
            prefix = dist.symbols[window[q] & dist.mask]
            q = q + dist.sizes[window[q] & dist.mask]
            d = LEAST[prefix] + _bits_at(data, lo + q, EXTRA[prefix])
            far[ref] = np.where(d > 120, d - 120, near_distances(width)[np.minimum(d, 120) - 1])
        kinds.append(kind)
        literals.append(value)
        counts.append(count)
        back.append(far)
        sums = done + np.cumsum(count)
        if sums[-1] >= total:
            last = int(np.searchsorted(sums, total))
            if sums[last] != total:
                raise ValueError("a back-reference leaves the image")
            for x in (kinds, literals, counts, back):
                x[-1] = x[-1][: last + 1]
            at = lo + int(ends[met[last]])
            if at > bits.end:
                raise ValueError("the image data ends too early")
            bits.pos = at
            break
        done, at = int(sums[-1]), lo + p
    kind, value, count, far = (np.concatenate(x) for x in (kinds, literals, counts, back))
    return _resolved(kind, value, count, far, cache_bits)


def _resolved(kind: np.ndarray, value: np.ndarray, count: np.ndarray, far: np.ndarray, cache_bits: int) -> np.ndarray:
    """The pixels of literals, copies and cache hits."""
    plain = len(count) == int(count.sum())
    here = np.arange(len(count)) if plain else np.repeat(np.arange(len(count)), count)
    total = len(here)
    source = np.arange(total) - far[here]
    if source.min(initial=0) < 0:
        raise ValueError("a back-reference leaves the image")
    if (far > 0).any():
        source = _followed(source)
    if cache_bits and (kind >= 280).any():
        kind_here, value_here = (kind, value) if plain else (kind.take(here), value.take(here))
        kinds, value_of = (kind_here.take(source), value_here.take(source)) if (far > 0).any() else (kind_here, value_here)
        slot = np.where(kinds >= 280, kinds - 280, _slots(value_of, cache_bits))
        order = np.argsort(slot.astype(np.uint16), kind="stable")  # a cache has at most 2,048 places
        before = np.full(total + 1, total)
        sorted_slot = slot.take(order)
        same = np.flatnonzero(sorted_slot[1:] == sorted_slot[:-1])
        before[order[same + 1]] = order[same]
        hit = kind_here >= 280
        before[:-1][~hit] = source[~hit]  # the place after the last is the empty cache
        return np.append(value_here, np.uint32(0)).take(_followed(before))[:-1]
    return value[here][source]


def _followed(source: np.ndarray) -> np.ndarray:
    while True:
        further = source.take(source)
        if (further == source).all():
            return source
        source = further


def _slot(argb: int, cache_bits: int) -> int:
    return ((CACHE_MULTIPLIER * argb) & 0xFFFFFFFF) >> (32 - cache_bits)


def _slots(argb: np.ndarray, cache_bits) -> np.ndarray:
    """Cache places, for one size or a size for each pixel."""
    return ((argb.astype(np.int64) * CACHE_MULTIPLIER) & 0xFFFFFFFF) >> (32 - cache_bits)


# ---------------------------------------------------------------- transforms


def _planes(argb: np.ndarray, height: int, width: int) -> np.ndarray:
    return argb.astype(">u4").view(np.uint8).reshape(height, width, 4)


def _argb(planes: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(planes).view(">u4").ravel().astype(np.uint32)


def predict(mode: int, left: np.ndarray, top: np.ndarray, top_left: np.ndarray, top_right: np.ndarray) -> np.ndarray:
    """The predictions of a mode from neighbours, int arrays of shape (n, 4)."""
    if mode in (0, 14, 15):
        return np.tile(np.array([255, 0, 0, 0]), (len(left), 1))
    if mode <= 4:
        return (left, top, top_right, top_left)[mode - 1]
    if mode <= 10:
        pairs = {6: (left, top_left), 7: (left, top), 8: (top_left, top), 9: (top, top_right)}
        if mode in pairs:
            return sum(pairs[mode]) >> 1
        if mode == 5:
            return (((left + top_right) >> 1) + top) >> 1
        return (((left + top_left) >> 1) + ((top + top_right) >> 1)) >> 1
    if mode == 11:
        nearer = np.abs(top - top_left).sum(axis=1) < np.abs(left - top_left).sum(axis=1)
        return np.where(nearer[:, None], left, top)
    if mode == 12:
        return np.clip(left + top - top_left, 0, 255)
    mid = (left + top) >> 1
    return np.clip(mid + np.fix((mid - top_left) / 2).astype(np.int64), 0, 255)


def _predictions(known: np.ndarray, modes: np.ndarray, y: np.ndarray, x: np.ndarray) -> np.ndarray:
    """What places with a row above and a pixel to the left are predicted to be."""
    width = known.shape[1]
    last = x == width - 1
    around = known[y, x - 1], known[y - 1, x], known[y - 1, x - 1], known[np.where(last, y, y - 1), np.where(last, 0, (x + 1) % width)]
    out = np.zeros((len(y), 4), np.int64)
    for m in np.unique(modes):
        own = modes == m
        out[own] = predict(int(m), *(a[own] for a in around))
    return out


def predictor(planes: np.ndarray, modes: np.ndarray, shift: int, undo: bool) -> np.ndarray:
    """Adds (undo) or subtracts each pixel's prediction; modes has a row for each block row.

    Undone in waves: a pixel needs its left neighbour and the row above up to one place further right, so all
    pixels with the same x + 2 y follow from earlier waves. If all blocks take the left or the upper pixel, sums do it.
    """
    height, width, _ = planes.shape
    src = planes.astype(np.int64)
    uniform = int(modes.min()) if modes.min() == modes.max() else 0
    if not undo:
        out = src.copy()
        if uniform in (1, 2):
            out[:, 1:] -= src[:, :-1]
            out[1:, 0] -= src[:-1, 0]
            if uniform == 2:
                out[1:, 1:] = src[1:, 1:] - src[:-1, 1:]
            out[0, 0] -= (255, 0, 0, 0)
            return (out & 255).astype(np.uint8)
        out[0, 0] -= (255, 0, 0, 0)
        out[0, 1:] -= src[0, :-1]
        out[1:, 0] -= src[:-1, 0]
        y, x = (a.ravel() for a in np.mgrid[1:height, 1:width])
        out[y, x] -= _predictions(src, modes[y >> shift, x >> shift], y, x)
        return (out & 255).astype(np.uint8)
    src[0, 0] += (255, 0, 0, 0)
    if uniform in (1, 2):
        first, then = (0, 1) if uniform == 1 else (1, 0)
        edge = (slice(None), 0) if first == 0 else (0,)
        src[edge] = np.cumsum(src[edge], axis=0)
        return (np.cumsum(src, axis=then) & 255).astype(np.uint8)
    src[0] = np.cumsum(src[0], axis=0) & 255
    src[:, 0] = np.cumsum(src[:, 0], axis=0) & 255
    for wave in range(3, width + 2 * height - 2):
        y = np.arange(max(1, (wave - width + 2) // 2), min(height - 1, (wave - 1) // 2) + 1)
        x = wave - 2 * y
        src[y, x] = (src[y, x] + _predictions(src, modes[y >> shift, x >> shift], y, x)) & 255
    return src.astype(np.uint8)


def cross_colour(planes: np.ndarray, table: np.ndarray, shift: int, undo: bool) -> np.ndarray:
    """Adds or subtracts what green and red tell of red and blue; table: (rows, columns, 3) of red-to-blue, green-to-blue, green-to-red."""
    height, width, _ = planes.shape
    at = table.astype(np.int8).astype(np.int32)[np.arange(height)[:, None] >> shift, np.arange(width)[None, :] >> shift]
    red, green, blue = (planes[:, :, i].astype(np.int32) for i in (1, 2, 3))
    signed = lambda v: v.astype(np.uint8).astype(np.int8).astype(np.int32)
    sign = 1 if undo else -1
    new_red = (red + sign * (at[:, :, 2] * signed(green) >> 5)) & 255
    seen = new_red if undo else red
    new_blue = (blue + sign * ((at[:, :, 1] * signed(green) >> 5) + (at[:, :, 0] * signed(seen) >> 5))) & 255
    out = planes.copy()
    out[:, :, 1], out[:, :, 3] = new_red, new_blue
    return out


def green_shift(planes: np.ndarray, undo: bool) -> np.ndarray:
    out = planes.copy()
    for c in (1, 3):
        out[:, :, c] = planes[:, :, c] + planes[:, :, 2] if undo else planes[:, :, c] - planes[:, :, 2]
    return out


def _pack_shift(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def unpalette(planes: np.ndarray, palette: np.ndarray, width: int) -> np.ndarray:
    """Palette indices (several to a green value for small palettes) to colours; indices beyond it are transparent black."""
    shift = _pack_shift(len(palette))
    index = planes[:, :, 2]
    if shift:
        each = 8 >> shift
        index = (index[:, :, None] >> (np.arange(1 << shift) * each)) & ((1 << each) - 1)
        index = index.reshape(len(planes), -1)
    colours = np.zeros((256, 4), np.uint8)
    colours[: len(palette)] = palette
    return colours[index[:, :width]]


def to_palette(planes: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """(index image, palette) of an image of at most 256 colours."""
    height, width, _ = planes.shape
    found, index = np.unique(_argb(planes), return_inverse=True)
    if len(found) > 256:
        return None
    shift = _pack_shift(len(found))
    index = index.reshape(height, width).astype(np.uint8)
    if shift:
        each = 8 >> shift
        full = np.zeros((height, -(-width >> shift) << shift), np.uint8)
        full[:, :width] = index
        index = (full.reshape(height, -1, 1 << shift) << (np.arange(1 << shift) * each).astype(np.uint8)).sum(axis=2).astype(np.uint8)
    out = np.zeros((*index.shape, 4), np.uint8)
    out[:, :, 0], out[:, :, 2] = 255, index
    return out, _planes(found, 1, len(found))[0]


# ---------------------------------------------------------------- files


def frame(stream: bytes) -> bytes:
    pad = len(stream) & 1
    return b"RIFF" + struct.pack("<I", 12 + len(stream) + pad) + b"WEBPVP8L" + struct.pack("<I", len(stream)) + stream + bytes(pad)


def unframe(data: bytes) -> tuple[bytes, int]:
    """(the image's stream, bytes of the whole file) of the file that data begins with."""
    if data[:4] != b"RIFF" or data[8:16] != b"WEBPVP8L":
        raise ValueError("not a lossless WebP file")
    (size,) = struct.unpack("<I", data[4:8])
    (n,) = struct.unpack("<I", data[16:20])
    if 20 + n > len(data) or data[20:21] != b"/":
        raise ValueError("the file is cut short")
    return bytes(data[20 : 20 + n]), 8 + size


def decode(data: bytes) -> np.ndarray:
    stream, _ = unframe(data)
    bits = BitReader(stream, 8)
    width, height = bits.read(14) + 1, bits.read(14) + 1
    bits.read(1)
    if bits.read(3):
        raise ValueError("unknown version")
    undo = []
    now = width
    while bits.read(1):
        kind = bits.read(2)
        if any(k == kind for k, *_ in undo):
            raise ValueError("a transform is given twice")
        if kind < 2:
            shift = bits.read(3) + 2
            w, h = -(-now >> shift), -(-height >> shift)
            undo.append((kind, now, shift, _planes(_read_image(bits, w, h, False), h, w)))
        elif kind == 2:
            undo.append((kind, now))
        else:
            n = bits.read(8) + 1
            steps = _planes(_read_image(bits, n, 1, False), 1, n)[0]
            undo.append((kind, now, np.cumsum(steps, axis=0, dtype=np.uint8)))
            now = -(-now >> _pack_shift(n))
    planes = _planes(_read_image(bits, now, height, True), height, now)
    for kind, w, *rest in reversed(undo):
        if kind == 0:
            planes = predictor(planes, rest[1][:, :, 2] & 15, rest[0], True)
        elif kind == 1:
            planes = cross_colour(planes, rest[1][:, :, 1:4], rest[0], True)
        elif kind == 2:
            planes = green_shift(planes, True)
        else:
            planes = unpalette(planes, rest[0], w)
    return planes


def _by_image(values: np.ndarray, image: np.ndarray) -> np.ndarray:
    """The order of pixels by image, then by value, then by place: sorted by 16 bits at a time, for which counting does."""
    parts = np.ascontiguousarray(values).astype(values.dtype.newbyteorder("<"), copy=False).view("<u2").reshape(len(values), -1)
    order = np.argsort(parts[:, 0], kind="stable")
    for i in range(1, parts.shape[1]):
        order = order.take(np.argsort(parts[:, i].take(order), kind="stable"))
    return order.take(np.argsort(image.take(order), kind="stable"))


def _tokens(argb: np.ndarray, image: np.ndarray, cache_bits: np.ndarray, search: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(place, kind, length, distance) of the tokens of images that lie one after the other; kind 0: literal, 1: copy, 2: cache hit.

    A place's candidate is the last earlier one of its image with the same two pixels. Where neighbouring places have
    candidates at one distance the copy runs on, so lengths follow from runs. Copies take three pixels or more, from the left.
    """
    total = len(argb)
    kind = np.zeros(total, np.int64)
    length, far = np.ones(total, np.int64), np.zeros(total, np.int64)
    keep = np.ones(total, bool)
    if search and total > 3:
        pair = argb[:-1].astype(np.uint64) << np.uint64(32) | argb[1:]
        order = _by_image(pair, image[:-1])
        order = order[image[order] == image[order + 1]]
        same = np.flatnonzero((pair[order][1:] == pair[order][:-1]) & (image[order][1:] == image[order][:-1]))
        d = np.zeros(total, np.int64)
        d[order[same + 1]] = order[same + 1] - order[same]
        cut = starts_of(d)  # an image's last pixel begins no pair, so runs end with it
        ends = np.repeat(cut[1:], np.diff(cut))
        run = np.where(d > 0, ends - np.arange(total) + 1, 0)
        places = np.flatnonzero(run >= 3)
        at, begin = 0, []
        for p, n in zip(places.tolist(), run[places].tolist(), strict=True):
            if p >= at:
                begin.append(p)
                at = p + min(n, 4096)
        begin = np.array(begin, np.int64)
        kind[begin], far[begin], length[begin] = 1, d[begin], np.minimum(run[begin], 4096)
        step = np.zeros(total + 2, np.int64)
        step[begin + 1] += 1
        step[begin + length[begin]] -= 1
        keep = np.cumsum(step[:total]) == 0
    if cache_bits.any():
        slot = _slots(argb, cache_bits[image])
        order = _by_image(slot.astype(np.uint16), image)
        order = order[cache_bits[image[order]] > 0]
        last, now = order[:-1], order[1:]
        hit = now[(slot[now] == slot[last]) & (argb[now] == argb[last]) & (image[now] == image[last])]
        kind[hit] = np.where(kind[hit] == 0, 2, kind[hit])
    place = np.flatnonzero(keep)
    return place, kind[place], length[place], far[place]


def joint(counts: list[np.ndarray]) -> np.ndarray:
    """Of each image (a row of counts for each channel), whether its channels are alike enough for one code: then only one has to be made, here and by the reader.

    A code of their own is worth it if it saves a thirtieth of the bits, with about five for each symbol's place in a code.
    """
    every = np.stack([*counts, sum(counts)])
    total, used = every.sum(axis=2), np.count_nonzero(every, axis=2)
    bits = total * np.log2(np.maximum(total, 1)) - (every * np.log2(np.maximum(every, 1))).sum(axis=2)
    own, one = (bits[:-1] + 5 * used[:-1]).sum(axis=0), bits[-1] + 5 * len(counts) * used[-1]
    return (used[-1] > 2) & (own > 0.97 * one)


def _written(sizes: np.ndarray, begins: tuple[int, ...]) -> np.ndarray:
    """The codes of code lengths, as PrefixCode.written() has them, of all images (rows) and channels (which begin at these columns) together. A lone
    symbol's length becomes 0."""
    row, column = np.nonzero(sizes)
    own = row * len(begins) + np.searchsorted(begins, column, side="right") - 1
    size = sizes[row, column]
    lone = np.bincount(own, minlength=len(sizes) * len(begins))[own] == 1
    sizes[row[lone], column[lone]] = 0
    row, column, own, size = row[~lone], column[~lone], own[~lone], size[~lone].astype(np.int64)
    order = np.argsort(size.astype(np.uint16), kind="stable")
    order = order[np.argsort(own[order], kind="stable")]
    room = (1 << (15 - size)).take(order)
    left = np.cumsum(room) - room  # a complete code takes 2 ** 15 places, so each begins anew
    codes = np.zeros(sizes.shape, np.uint64)
    codes[row.take(order), column.take(order)] = mirrored(15)[left & 32767]
    return codes


def _coded(images: list[np.ndarray], width: int, cache_bits: list[int], search: bool) -> list[tuple[list[tuple[int, int]], int, int]]:
    """For each of some images of one width: its codes, as written, the bits of its tokens as a number, and how many. All images go through each step together."""
    many = len(images)
    argb = np.concatenate(images)
    image = np.repeat(np.arange(many, dtype=np.uint16), [len(x) for x in images])
    caches = np.array(cache_bits, np.int64)
    place, kind, length, far = _tokens(argb, image, caches, search)
    own = image[place].astype(np.int64)
    plain, copy, hit = (np.flatnonzero(kind == k) for k in range(3))
    samples = argb[place[plain]].astype("<u4").view(np.uint8).reshape(-1, 4)
    blue, green, red, alpha = (samples[:, i] for i in range(4))
    n, n_extra, n_bits = _prefixes(length[copy])
    near = near_codes(width)
    short = np.where(far[copy] < len(near), near[np.minimum(far[copy], len(near) - 1)], 0)
    d, d_extra, d_bits = _prefixes(np.where(short > 0, short, far[copy] + 120))
    slot = _slots(argb[place[hit]], caches[own[hit]])
    room = 280 + (1 << int(caches.max()) if caches.any() else 0)

    def counted(which, symbol, size):
        return np.bincount(which * size + symbol, minlength=many * size).reshape(many, size)

    first = counted(np.concatenate([own[plain], own[copy], own[hit]]), np.concatenate([green.astype(np.int64), 256 + n, 280 + slot]), room)
    channels = [counted(own[plain], x.astype(np.int64), 256) for x in (red, blue, alpha)]
    back = counted(own[copy], d, 40)
    alike = joint(channels)
    heads, sizes = [], np.zeros((many, room + 768 + 40), np.uint8)
    begins = (0, room, room + 256, room + 512, room + 768)
    for i in range(many):
        top = 280 + (1 << cache_bits[i] if cache_bits[i] else 0)
        if alike[i]:
            others = [huffman(sum(c[i] for c in channels))] * 3
        else:
            others = [huffman(c[i]) for c in channels]
        lengths = [huffman(first[i, :top]), *others, huffman(back[i])]
        heads.append([code_bits(x.tobytes()) for x in lengths])
        for at, x in zip(begins, lengths, strict=True):
            sizes[i, at : at + len(x)] = x
    codes = _written(sizes, begins)
    values, places = np.zeros(len(place), np.uint64), np.zeros(len(place), np.int64)  # a token's fields make one number: four codes of at most 15 bits, or two with their extra bits
    codes, sizes = codes.ravel(), sizes.ravel().astype(np.int64)
    base = own * (room + 768 + 40)
    at = base[plain] + green
    v, n_v = codes.take(at), sizes.take(at)
    for i, x in enumerate((red, blue, alpha)):
        at = base[plain] + x + (room + 256 * i)
        v |= codes.take(at) << n_v.astype(np.uint64)
        n_v += sizes.take(at)
    values[plain], places[plain] = v, n_v
    v, n_v = np.zeros(len(copy), np.uint64), np.zeros(len(copy), np.int64)
    for at, extra, bits in ((base[copy] + 256 + n, n_extra, n_bits), (base[copy] + room + 768 + d, d_extra, d_bits)):
        v |= (codes[at] | extra.astype(np.uint64) << sizes[at].astype(np.uint64)) << n_v.astype(np.uint64)
        n_v += sizes[at] + bits
    values[copy], places[copy] = v, n_v
    at = base[hit] + 280 + slot
    values[hit], places[hit] = codes[at], sizes[at]
    ends = np.searchsorted(own, np.arange(many + 1))
    out = []
    for i, head in enumerate(heads):
        n_v = places[ends[i] : ends[i + 1]]
        out.append((head, int.from_bytes(packed_words(values[ends[i] : ends[i + 1]], n_v).tobytes(), "little"), int(n_v.sum())))
    return out


def _put_image(out: BitWriter, coded, main: bool, cache_bits: int) -> None:
    out.put(1 if cache_bits else 0, 1)
    if cache_bits:
        out.put(cache_bits, 4)
    if main:
        out.put(0, 1)
    heads, stream, n = coded
    for head in heads:
        out.put(*head)
    out.put(stream, n)


def _write_image(out: BitWriter, argb: np.ndarray, width: int, main: bool, cache_bits: int = 0, search: bool = False) -> None:
    _put_image(out, _coded([argb], width, [cache_bits], search)[0], main, cache_bits)


def _begun(height: int, width: int) -> BitWriter:
    out = BitWriter()
    out.put(0x2F | (width - 1) << 8 | (height - 1) << 22 | 1 << 36, 40)
    return out


def _file(out: BitWriter) -> bytes:
    return frame(out.bytes())


def encode(planes: np.ndarray, transforms: tuple[str, ...] = (), cache_bits: int = 0, search: bool = False, shift: int = 3, modes: np.ndarray | None = None) -> bytes:
    """A file of the pixels. transforms: any of 'palette', 'predictor', 'cross', 'green', applied in this order.

    modes: the predictor's mode of each block; without it all modes take turns.
    """
    height, width, _ = planes.shape
    out = _begun(height, width)
    for name in transforms:
        w = planes.shape[1]
        across, down = -(-w >> shift), -(-height >> shift)
        if name == "palette":
            made = to_palette(planes)
            if made is None:
                continue
            planes, palette = made
            out.put(1, 1)
            out.put(3, 2)
            out.put(len(palette) - 1, 8)
            _write_image(out, _argb(np.diff(palette, axis=0, prepend=np.zeros((1, 4), np.uint8))), len(palette), False)
        elif name == "predictor":
            own = modes if modes is not None else (np.arange(across * down) % 14).reshape(down, across)
            planes = predictor(planes, own, shift, False)
            out.put(1, 1)
            out.put(0, 2)
            out.put(shift - 2, 3)
            _write_image(out, (own.ravel() << 8).astype(np.uint32), across, False)
        elif name == "cross":
            table = np.tile(cross_steps(planes)[0], (down, across, 1))
            planes = cross_colour(planes, table, shift, False)
            out.put(1, 1)
            out.put(1, 2)
            out.put(shift - 2, 3)
            _write_image(out, _argb(np.concatenate([np.full((down, across, 1), 255, np.uint8), table], axis=2)), across, False)
        else:
            planes = green_shift(planes, False)
            out.put(1, 1)
            out.put(2, 2)
    out.put(0, 1)
    _write_image(out, _argb(planes), planes.shape[1], True, cache_bits, search)
    return _file(out)


def cross_steps(planes: np.ndarray, begin: np.ndarray | None = None) -> np.ndarray:
    """(red to blue, green to blue, green to red) in 32nds: least squares of the channels' signed values, for the rows from each of `begin`."""
    red, green, blue = (planes[:, :, i].astype(np.int8).astype(float) for i in (1, 2, 3))
    begin = np.zeros(1, np.int64) if begin is None else begin

    def total(a, b):
        return np.add.reduceat((a * b).sum(axis=1), begin)

    gg, rr = np.maximum(1.0, total(green, green)), np.maximum(1.0, total(red, red))
    to_red, to_blue = np.rint(32 * total(green, red) / gg), np.rint(32 * total(green, blue) / gg)
    across = np.rint(32 * (total(red, blue) - to_blue * total(red, green) / 32) / rr)
    return np.clip(np.stack([across, to_blue, to_red], axis=1), -128, 127).astype(np.int8).view(np.uint8)


# ---------------------------------------------------------------- bytes as images


def costs(planes: np.ndarray, image: np.ndarray, many: int) -> np.ndarray:
    """For each of `many` images, whose rows lie one after the other: bits of its channels as literals, with about five for each symbol's place in a code."""
    lane = (1024 * image)[:, None] + np.tile(256 * np.arange(4), planes.shape[1])
    counts = np.bincount((planes.reshape(len(planes), -1) + lane).ravel(), minlength=1024 * many).reshape(many, 4, 256)
    own = (counts * np.log2(np.maximum(counts, 1))).sum(axis=2)
    n = counts[:, 0].sum(axis=1)[:, None]
    return (n * np.log2(np.maximum(n, 1)) - own + 5 * np.count_nonzero(counts, axis=2)).sum(axis=1)


#: What encode_many() chooses from: the name of a transform, and the predictor's mode.
OPTIONS = [("", 0), ("cross", 0), ("predictor", 1), ("predictor", 2)]


def chosen(planes: np.ndarray, image: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """The place in OPTIONS, for each of some images, of what makes its samples cheapest as literals."""
    many = len(begin)
    steps = np.broadcast_to(cross_steps(planes, begin)[image][:, None], (*planes.shape[:2], 3))
    left = planes.copy()
    left[:, 1:] -= planes[:, :-1]
    left[1:, 0] -= planes[:-1, 0]
    above = planes.copy()
    above[1:] -= planes[:-1]
    above[begin] = left[begin]
    for made in (left, above):
        made[begin, 0] = planes[begin, 0] - np.array([255, 0, 0, 0], np.uint8)
    cost = [costs(planes, image, many), costs(cross_colour(planes, steps, 0, False), image, many)]
    for made in (left, above):  # a predictor that seldom hits is not worth its cost's counting
        hits = np.add.reduceat(np.count_nonzero(made.reshape(len(made), -1) == 0, axis=1), begin)
        own = np.flatnonzero(4 * hits > np.bincount(image, minlength=many) * made[0].size)
        rows = np.isin(image, own)
        cost.append(np.full(many, np.inf))
        if len(own):
            cost[-1][own] = costs(made[rows], np.searchsorted(own, image[rows]), len(own))
    cost = np.stack(cost) + np.array([0, 64, 64, 64])[:, None]  # of the transform's own image
    return cost.argmin(axis=0)


def encode_many(payloads: list[bytes], together: int = 1 << 16) -> list[bytes]:
    """Of each payload, bytes (a positive multiple of 64), one or more files: 16 pixels a row, bytes in the order green, red, blue, alpha.

    Each file has prefix codes of its own counts, back-references, a colour cache where pixels come again, and the transform that
    makes the samples cheapest; few different pixels go through a palette if that is shorter.
    A file has at most 16,384 rows (1 MiB); more bytes continue in the next file. Files of about `together` pixels are made at once,
    which does not change them.
    """
    out: list[list[bytes]] = [[] for _ in payloads]
    held, size = [], 0
    for i, payload in enumerate(payloads):
        for at in range(0, len(payload), 64 * SIDE):
            part = np.frombuffer(payload, np.uint8, min(64 * SIDE, len(payload) - at), at)
            held.append((i, part.reshape(-1, 16, 4)))
            size += len(part) // 4
            if size >= together:
                _made(held, out)
                held, size = [], 0
    if held:
        _made(held, out)
    return [b"".join(x) for x in out]


def _made(held: list, out: list[list[bytes]]) -> None:
    many = len(held)
    rows = np.array([len(x) for _, x in held])
    begin = np.cumsum(rows) - rows
    planes = np.ascontiguousarray(np.concatenate([x for _, x in held])[:, :, [3, 1, 0, 2]])
    image = np.repeat(np.arange(many), rows)
    option = chosen(planes, image, begin)
    argb, pixel_image = _argb(planes), np.repeat(image, 16).astype(np.uint16)
    order = _by_image(argb, pixel_image)
    new = np.ones(len(order), bool)
    new[1:] = (argb[order][1:] != argb[order][:-1]) | (pixel_image[order][1:] != pixel_image[order][:-1])
    different = np.bincount(pixel_image[order[new]], minlength=many).tolist()
    caches = [int(np.clip((16 * n).bit_length() - 2, 1, 10)) if k < 0.9 * 16 * n else 0 for k, n in zip(different, rows.tolist(), strict=True)]
    plain = [i for i in range(many) if option[i] == 0]
    coded = dict(zip(plain, _coded([argb[16 * begin[i] : 16 * (begin[i] + rows[i])] for i in plain], 16, [caches[i] for i in plain], True), strict=True)) if plain else {}
    for i, (payload, _) in enumerate(held):
        own = planes[begin[i] : begin[i] + rows[i]]
        if i in coded:
            writer = _begun(len(own), 16)
            writer.put(0, 1)
            _put_image(writer, coded[i], True, caches[i])
            files = [_file(writer)]
        else:
            name, mode = OPTIONS[option[i]]
            files = [encode(own, (name,), caches[i], True, 9, np.full((-(-len(own) >> 9), 1), mode))]
        if different[i] <= 256 and 3 * different[i] <= 16 * len(own):
            files.append(encode(own, ("palette",), 0, True))
        out[payload].append(min(files, key=len))


def encode_bytes(payload: bytes) -> bytes:
    return encode_many([payload])[0]


def decode_bytes(data: bytes) -> bytes:
    """The bytes of encode_bytes(), from its files or any others: each file's pixels as green, red, blue, alpha."""
    out = []
    while data:
        _, n = unframe(data)
        out.append(decode(data[:n])[:, :, [2, 1, 3, 0]].tobytes())
        data = data[n:]
    return b"".join(out)
