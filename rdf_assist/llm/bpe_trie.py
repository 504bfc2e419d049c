"""BPE encoding over a trie of distinct words, and decoding.

The BPE encoding of a string ends in a certain token; what stands before that token is encoded as if
it stood alone. So the last token of every prefix is all the state there is: the distinct words of a batch
form a trie, a depth-first walk gives each node the last token of its prefix, and prefixes that words share
are worked out once. A token may end a prefix if it and the last token of what stands before it do not
merge differently when put together; exactly one token does.

Words of one spelling end in another symbol than they go on with (word-end files), so a node has one
state for going on and one for ending.
"""

from __future__ import annotations

import hashlib
import json

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import remote, texts
from .tokens import encoder, runs_of

HERE = __name__


def byte_letters() -> list[str]:
    """The letter that stands for each byte in byte-level vocabularies: printable bytes for themselves, the others from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in plain)}
    return [chr(rest.get(b, b)) for b in range(256)]


class TrieEncoder:
    """Encodes words (as strings of byte letters) with a BPE file's vocabulary and merges."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.text = {i: t for t, i in self.vocab.items()}
        self.suffix: str = model.get("end_of_word_suffix") or ""
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        ids = self.vocab
        self.rank = {(ids[a], ids[b]): (r, ids[a + b]) for r, (a, b) in enumerate(pairs) if a in ids and b in ids and a + b in ids}
        self.letters = byte_letters()
        self.symbols: dict[int, tuple[int, ...]] = {}
        self.fits: dict[tuple[int, int], bool] = {}
        #: Tokens that encoding can give: their own symbols merge to them. By spelling: going on, and ending.
        self.inner: dict[str, int] = {}
        self.final: dict[str, int] = {}
        for t, i in ids.items():
            end = bool(self.suffix) and t.endswith(self.suffix) and len(t) > len(self.suffix)
            bare = t[: -len(self.suffix)] if end else t
            parts = self._letters(bare, end)
            if parts is not None and self.merge(list(parts)) == [i]:
                self.symbols[i] = parts
                (self.final if end or not self.suffix else self.inner)[bare] = i
                if not self.suffix:
                    self.inner[bare] = i
        self.longest = max(map(len, [*self.inner, *self.final]), default=1)

    def _letters(self, bare: str, end: bool) -> tuple[int, ...] | None:
        out = [self.vocab.get(c) for c in bare]
        if end and out:
            out[-1] = self.vocab.get(bare[-1] + self.suffix)
        return None if None in out or not out else tuple(out)

    def merge(self, parts: list[int]) -> list[int]:
        """The plain procedure: merge the pair of the lowest rank, leftmost first, until none is left."""
        rank = self.rank
        while len(parts) > 1:
            best = min(((rank[p][0], k) for k, p in enumerate(zip(parts, parts[1:], strict=False)) if p in rank), default=None)
            if best is None:
                break
            k = best[1]
            parts[k : k + 2] = [rank[parts[k], parts[k + 1]][1]]
        return parts

    def compatible(self, a: int, b: int) -> bool:
        key = (a, b)
        got = self.fits.get(key)
        if got is None:
            if len(self.fits) > 2_000_000:
                self.fits.clear()
            got = self.fits[key] = self.merge([*self.symbols[a], *self.symbols[b]]) == [a, b]
        return got

    def last(self, word: str, n: int, table: dict[str, int], before: list[int]) -> int:
        """The last token of word[:n], from the last tokens of its shorter prefixes; -1 if letters are unknown."""
        for size in range(min(n, self.longest), 0, -1):
            t = table.get(word[n - size : n])
            if t is not None:
                if size == n:
                    return t
                held = before[n - size]
                if held >= 0 and self.compatible(held, t):
                    return t
        return -1

    def encode_all(self, words) -> dict[str, list[int]]:
        """Ids of each distinct word. The walk visits words in sorted order and keeps the states of the
        path to the current node, which is the depth-first walk of their trie."""
        out: dict[str, list[int]] = {}
        path: list[int] = [-1]
        previous = ""
        size_of = self.symbols
        for word in sorted(words):
            shared = 0
            top = min(len(word), len(previous), len(path) - 1)
            while shared < top and word[shared] == previous[shared]:
                shared += 1
            del path[shared + 1 :]
            inner, final = self.inner, self.final
            for n in range(shared + 1, len(word)):
                path.append(self.last(word, n, inner, path))
            n = len(word)
            ids: list[int] = []
            t = self.last(word, n, final, path) if n else -1
            while n > 0 and t >= 0:
                ids.append(t)
                n -= len(size_of[t])
                t = path[n] if n else -1
            if n:
                ids = self.plain(word)[::-1]
            out[word] = ids[::-1]
            previous = word
        return out

    def plain(self, word: str) -> list[int]:
        """For words with letters outside the vocabulary: such letters are left out, as the library does without an unknown token."""
        parts = self._letters(word, bool(self.suffix)) or [i for i in (self.vocab.get(c + self.suffix * (k == len(word) - 1)) for k, c in enumerate(word)) if i is not None]
        return self.merge(list(parts))


class Codec:
    """Texts to (ids, decoded) with a bounded table of the words met so far."""

    def __init__(self, path: str, limit: int = 400_000):
        self.cut = encoder(path)
        self.trie = TrieEncoder(path)
        self.limit = limit
        self.known: dict[str, tuple[bytes, str, int]] = {}
        self.joiner = self.cut.tokenizer.decoder is None

    def learn(self, words: set[str]) -> None:
        letters = self.trie.letters
        spelled = {w: "".join([letters[b] for b in w.encode("utf-8")]) if not w.isascii() or " " in w or not w.isprintable() else w for w in words}
        ids = self.trie.encode_all(set(spelled.values()))
        text = self.trie.text
        for w in words:
            own = ids[spelled[w]]
            self.known[w] = (b"".join([i.to_bytes(4, "little") for i in own]), " ".join([text[i] for i in own]), len(own))

    def run(self, found: list[str | None]) -> list[tuple[bytes, str]]:
        """(ids as little-endian unsigned 32-bit bytes, decoded text) of each text; None reads as empty."""
        cut = [self.cut.split(t or "") for t in found]
        new = set().union(*[w for w in cut if w]).difference(self.known)
        if len(self.known) + len(new) > self.limit:
            self.known.clear()
            new = set().union(*[w for w in cut if w])
        self.learn(new)
        out = []
        for t, words in zip(found, cut, strict=True):
            if words is None:
                ids = self.cut.whole(t)
                out.append((b"".join([i.to_bytes(4, "little") for i in ids]), self.cut.tokenizer.decode(ids, skip_special_tokens=False)))
                continue
            got = [self.known[w] for w in words]
            ids = b"".join([g[0] for g in got])
            if self.joiner:
                decoded = " ".join([g[1] for g in got if g[2]])
            else:
                decoded = self.cut.tokenizer.decode(list(memoryview(ids).cast("I")), skip_special_tokens=False)
            out.append((ids, decoded))
        return out


_CODECS: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _CODECS:
        _CODECS[path] = Codec(path)
    return _CODECS[path]


def encode_batches(batches, path: str):
    c = codec(path)
    for b in batches:
        got = [x for run in runs_of(b.column("text").to_pylist()) for x in c.run(run)]
        ids = [memoryview(i).cast("I").tolist() for i, _ in got]
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(ids, pa.list_(pa.int64())), pa.array([d for _, d in got])], ["doc_id", "ids", "decoded"])


def digest_batches(batches, path: str):
    c = codec(path)
    for b in batches:
        n, ids, text = [], [], []
        for run in runs_of(b.column("text").to_pylist()):
            for i, d in c.run(run):
                n.append(len(i) // 4)
                ids.append(hashlib.sha256(i).hexdigest())
                text.append(hashlib.sha256(d.encode("utf-8")).hexdigest())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids), pa.array(text)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def encode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids, decoded) of every row; null and empty texts have no ids and an empty decoding. Repeated rows each keep theirs."""
    return texts(docs).mapInArrow(remote(HERE, "encode_batches", path=path), "doc_id long, ids array<long>, decoded string")


def digests(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every row."""
    return texts(docs).mapInArrow(remote(HERE, "digest_batches", path=path), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
