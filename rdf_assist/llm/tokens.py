"""Token ids by the tokenizers library, with words that were met before taken from a bounded table.

Both tokenizers cut a text into words by a pattern and encode each word on its own, so a text's ids
are its words' ids in a row. Words are cut with the same pattern here and new ones go to the library
in batches. A text that holds an added token's string, or a character for which pattern engines could
differ, goes to the library whole; so does every text where the file's steps are not the known ones.
"""

from __future__ import annotations

import json
import os
import re
import unicodedata
from array import array

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

# The word patterns of the two kinds of tokenizer file.
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
WORD_END = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

#: Outside these ranges Unicode versions, white space or case rules of two libraries may differ.
_SAFE = [(0x00, 0x1B), (0x20, 0x36F), (0x400, 0x52F), (0x2010, 0x2027), (0x2030, 0x205E), (0x20A0, 0x20BF), (0x2122, 0x2122)]
_ODD = re.compile("[^" + "".join(f"{chr(a)}-{chr(b)}" for a, b in _SAFE) + "]")


def _class(kind: str) -> str:
    """The safe characters of a Unicode category (L or N) as ranges for a character class."""
    found = [c for a, b in _SAFE for c in range(a, b + 1) if unicodedata.category(chr(c))[0] == kind]
    runs: list[list[int]] = []
    for c in found:
        if runs and runs[-1][1] == c - 1:
            runs[-1][1] = c
        else:
            runs.append([c, c])
    return "".join(f"{chr(a)}-{chr(b)}" for a, b in runs)


def _cutter(pattern: str):
    """findall of a word pattern for safe characters, where classes can be spelled out."""
    return re.compile(pattern.replace(r"[\p{L}]", r"\p{L}").replace(r"[\p{N}]", r"\p{N}").replace(r"[^\s\p{L}\p{N}]", "[^\\s" + _class("L") + _class("N") + "]").replace(r"\p{L}", "[" + _class("L") + "]").replace(r"\p{N}", "[" + _class("N") + "]")).findall


def public_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """encode(text) gives the ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str, limit: int = 1_200_000):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        self.limit, self.known = limit, {}
        added = [x["content"] for x in spec.get("added_tokens") or []]
        self.added = re.compile("|".join(map(re.escape, added))) if added else None
        before, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        self.words, self.normal = None, False
        if norm is None and before.get("type") == "ByteLevel" and before.get("use_regex") and not before.get("add_prefix_space"):
            self.words = _cutter(BYTE_LEVEL)
        elif norm and [x["type"] for x in norm.get("normalizers", [])] == ["NFC", "Replace", "Lowercase"] and before.get("pretokenizers", [{}])[0].get("pattern", {}).get("Regex") == WORD_END:
            self.words, self.normal = _cutter(WORD_END), True

    def split(self, text: str) -> list[str] | None:
        """The words of a text, or None if the library has to take it whole."""
        if self.words is None or not text.isascii() and _ODD.search(text) or text.isascii() and any(c in text for c in "\x1c\x1d\x1e\x1f") or self.added and self.added.search(text):
            return None
        if self.normal:
            if not text.isascii():  # normalising and lower-casing may leave the safe characters
                text = unicodedata.normalize("NFC", text).lower()
                if _ODD.search(text) or not unicodedata.is_normalized("NFC", text):
                    return None
            else:
                text = text.lower()
        return self.words(text)

    def whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def learn(self, words: list[str]) -> None:
        """Takes up the ids of words. Plain words of letters go to the library many to a text, cut where its word
        numbers change; a call for each would cost more than encoding them."""
        known, lead = self.known, "" if self.normal else " "
        plain = [w for w in words if w[: len(lead)] == lead and w[len(lead) :].isalpha()]
        alone = [w for w in words if not (w[: len(lead)] == lead and w[len(lead) :].isalpha())]
        for at in range(0, len(plain), 4096):
            run = plain[at : at + 4096]
            e = self.tokenizer.encode((" " if self.normal else "").join(run), add_special_tokens=False)
            number = np.array(e.word_ids)
            cut = np.flatnonzero(np.diff(number, prepend=-1)).tolist()
            if len(cut) != len(run):
                alone += run
                continue
            raw = array("I", e.ids).tobytes()
            for w, lo, hi in zip(run, cut, [*cut[1:], len(number)], strict=True):
                known[w] = raw[4 * lo : 4 * hi]
        for w, e in zip(alone, self.tokenizer.encode_batch_fast(alone, add_special_tokens=False), strict=True):
            known[w] = array("I", e.ids).tobytes()

    def encode(self, text: str) -> bytes:
        return self.encode_all([text])[0]

    def encode_all(self, found: list[str]) -> list[bytes]:
        """The ids of each text; words that are new go to the library together."""
        cut = [self.split(t) for t in found]
        known = self.known
        new = set().union(*[w for w in cut if w]).difference(known)
        if len(known) + len(new) > self.limit:
            known.clear()
            new = set().union(*[w for w in cut if w])
        self.learn(list(new))
        get, join = known.__getitem__, b"".join
        return [join(map(get, w)) if w is not None else array("I", self.whole(t)).tobytes() for t, w in zip(found, cut, strict=True)]


def runs_of(found: list, size: int = 4 << 20):
    """A list of texts in runs of about `size` characters."""
    run, held = [], 0
    for t in found:
        run.append(t)
        held += len(t or "")
        if held >= size:
            yield run
            run, held = [], 0
    if run:
        yield run


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One for each path and worker process."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]
