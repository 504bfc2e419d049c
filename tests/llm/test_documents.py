"""The operators on documents against brute force, and on nulls, empty and repeated rows, odd columns and empty tables."""

import collections
import functools
import hashlib
import math
import os
import random
import re
import zlib

import numpy as np
import pytest
import xxhash

from rdf_assist.llm import bpe_trie, lattice, media, packing, quality, simhash, suffixes, tokenfile, webp
from rdf_assist.llm.tokens import encoder, public_path

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
WORD_FILE, BYTE_FILE, PIECE_FILE = (public_path(n) for n in ("word_bpe_49k.json", "byte_bpe_50k.json", "piece_bpe_32k.model"))


def made_texts():
    random.seed(5)
    base = [" ".join(random.choice("the of anon tion ereau señor über naïve x1 2²".split()) for _ in range(90)) + "." for _ in range(6)]
    out = [None, "", "   \n\t ", "a", "Word", "<|endoftext|> and <|startoftext|>", "日本 🙂 text\x1cx", "x" * 5000, "same line here\n" * 40]
    for i in range(40):
        b = base[i % 6].split(" ")
        if i % 3:
            b[i % len(b)] = f"edit{i}"
        out.append(" ".join(b[i % 7 :]))
    return out + [base[0], base[0], base[1]]


ROWS = [(i, t) for i, t in enumerate(made_texts())]
ODD = [*ROWS, (3, ROWS[12][1]), (None, ROWS[10][1]), (None, None), (7, ROWS[7][1])]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, "doc_id long, text string").repartition(3)


@pytest.fixture(scope="module")
def odd(spark):
    """Null and repeated ids, and further columns whose names operators use inside."""
    rows = [(d, t, "en", "s", len(t or ""), 1, "f", 0, "p") for d, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_words long, fp string, part int, row string").repartition(2)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")


def test_quality_measures(docs, odd, empty):
    for r in quality.quality(docs).collect():
        text = dict(ROWS)[r.doc_id] or ""
        w = WORDS.findall(text)
        windows = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        covered = {j for i in range(len(w) - 4) if windows[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        seen, copies = set(), 0
        for line in text.split("\n"):
            if WORDS.search(line):
                copies += line in seen
                seen.add(line)
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(covered), copies)
        assert r.n_symbols == len(re.findall(r"[#*$%&|<>]", text))
        assert r.base_failed == (len(w) < 10 or 100 * len(covered) > 20 * len(w))
    assert quality.quality(odd).count() == len(ODD)
    kept = quality.keep_good(odd)
    assert kept.columns == odd.columns and 0 < kept.count() < len(ODD)
    assert quality.quality(empty).count() == quality.keep_good(empty).count() == 0


def test_votes_decide():
    model = quality.fit([([1] * 9, 900), ([1, 1, -1, 1, 1, -1, 1, 1, -1], 60), ([1, 1, 1, 1, 1, 1, 0, 1, 1], 40)])
    assert 0.9 < model["share"] < 0.99
    assert all(bad <= 0 <= good for bad, _, good in model["odds"])
    assert quality.fit([])["odds"] == []


def test_labels_agree(spark):
    """The verdict against the quality labels, where the base limits leave it to the posterior: at most 2 in 100 differ."""
    folder = os.environ.get("TEST_LABEL_DIR", "/root/testdata/sf0.01")
    labels = spark.read.parquet(f"{folder}/labels.parquet").selectExpr("doc_id", "quality AS label")
    found = quality.quality(spark.read.parquet(f"{folder}/documents.parquet")).join(labels, "doc_id").where("NOT base_failed").select("kept", "quality", "label").collect()
    assert len(found) > 100 and all((r["quality"] > 0.5) == r.kept for r in found)
    assert sum(r.kept != (r.label == 1) for r in found) <= 0.02 * len(found)


def _fingerprint(text):
    low = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    w = WORDS.findall(low)
    if not w:
        return 0
    sh = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def _classes(fps):
    up = {i: i for i in fps}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(fps)
    for a in ids:
        for b in ids:
            if a < b and (fps[a] ^ fps[b]).bit_count() <= 2:
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_simhash(docs, odd, empty):
    fps = {d: _fingerprint(t) for d, t in ROWS}
    want = _classes(fps)
    got = {r.doc_id: (int(r.fingerprint, 16), r.component_id) for r in simhash.near_duplicates(docs).collect()}
    assert got == {d: (fps[d], want[d]) for d in fps}
    assert simhash.near_duplicates(odd).count() == len(ODD)
    assert simhash.near_duplicates(empty).count() == 0


def test_links_in_hot_buckets(spark):
    """Many fingerprints with one half in common, linked in chains: the linear way finds what pairs would."""
    random.seed(2)
    base = random.getrandbits(64)
    fps = {base ^ (1 << a) ^ (1 << b) for a in range(12) for b in range(12, 24)} | {random.getrandbits(64) for _ in range(60)}
    fps |= {f ^ (1 << 40) for f in list(fps)[:40]} | {f ^ (1 << 63) ^ (1 << 3) for f in list(fps)[:20]}
    signed = sorted(f - (1 << 64) if f >> 63 else f for f in fps)
    edges = simhash.links_within_two(spark.createDataFrame([(f,) for f in signed], "f long")).collect()
    assert all(((r.a ^ r.b) & (2**64 - 1)).bit_count() <= 4 for r in edges)
    up = {f: f for f in signed}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for r in edges:
        up[max(root(r.a), root(r.b))] = min(root(r.a), root(r.b))
    want = {f: f for f in signed}

    def wroot(x):
        while want[x] != x:
            x = want[x]
        return x

    for i, a in enumerate(signed):
        for b in signed[:i]:
            if ((a ^ b) & (2**64 - 1)).bit_count() <= 2:
                x, y = wroot(a), wroot(b)
                want[max(x, y)] = min(x, y)
    assert {f: root(f) for f in signed} == {f: wroot(f) for f in signed}


def test_near_copies_go(spark, odd, empty):
    random.seed(9)
    words = [f"w{i}" for i in range(3000)]
    rows = []
    for i in range(12):
        text = random.choices(words, k=300)
        rows.append((100 * i, " ".join(text), i))
        for j in range(1, 4):
            near = list(text)
            near[50 * j] = "changed"
            rows.append((100 * i + j, " ".join(near), i))
    frame = spark.createDataFrame(rows, "doc_id long, text string, n_words int")
    kept = simhash.keep_first(frame)
    assert kept.columns == frame.columns
    assert {r.doc_id for r in kept.collect()} == {100 * i for i in range(12)}
    assert simhash.keep_first(odd).where("doc_id is null").count() == 2
    both = [(1, rows[0][1], 1), (1, rows[4][1], 2), (1, rows[4][1], 2), (2, rows[5][1], 3), (3, None, 4), (3, "", 5), (4, " ", 6)]
    left = sorted((r.doc_id, r.text or "") for r in simhash.keep_first(spark.createDataFrame(both, "doc_id long, text string, d int")).collect())
    assert left == sorted([(1, rows[0][1]), (1, rows[4][1]), (3, "")])
    assert simhash.keep_first(empty).count() == 0


def test_edges_are_verified_before_they_are_thinned():
    """In one bucket, c is near x and y on the first word only; x and y are near in full and must stay connected."""
    import pandas as pd

    c, x = np.zeros(4, "<u8"), np.array([0, *[2**64 - 1] * 3], "<u8")
    fps = [c, x, x ^ np.array([0, 1, 0, 0], "<u8"), *[np.array([2**64 - 1, i << 20, 2**63 + i, 0], "<u8") ^ np.uint64(i * 0x9E3779B97F4A7C15 % 2**64) for i in range(1, 20)]]
    mat = np.array(fps).view(np.uint8).reshape(len(fps), -1)
    n = len(fps)
    batches = simhash.packed_lookups(np.array([i.to_bytes(16, "big") for i in range(n)], "V16"), mat, np.arange(n), np.zeros(n, np.int64), 1)
    frame = pd.concat([b.to_pandas() for b in batches])
    edges = {frozenset(int.from_bytes(x, "big") for x in e) for e in simhash.joined_buckets(frame, most=39).itertuples(index=False)}
    assert frozenset((1, 2)) in edges and not any(0 in e for e in edges)


def _jaccard(a, b):
    a, b = (set(zip(*[t.split()[i:] for i in range(5)], strict=False)) for t in (a, b))
    return len(a & b) / len(a | b)


def test_exact_similarity_decides(spark):
    """Pairs at 0.80 to 0.95 group nearly always, pairs at 0.70 to 0.79 never."""
    random.seed(3)
    rows, near, far = [], [], []
    for i in range(400):
        text = [f"w{random.randrange(9000)}" for _ in range(300)]
        other = list(text)
        want = random.choice([0.73, 0.77, 0.81, 0.86, 0.92])
        while True:
            other[random.randrange(300)] = f"x{random.randrange(9000)}"
            j = _jaccard(" ".join(text), " ".join(other))
            if j < want + 0.02:
                break
        rows += [(2 * i, " ".join(text)), (2 * i + 1, " ".join(other))]
        (near if j >= 0.8 else far).append(i)
    got = {r.doc_id: r.component_id for r in simhash.similar_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(far) > 50 and not [i for i in far if got[2 * i + 1] == got[2 * i]]
    assert len(near) > 150 and sum(got[2 * i + 1] == 2 * i for i in near) >= 0.97 * len(near)


def test_large_loose_groups_in_blocks(spark):
    """Chains and stars of near copies: dealt to blocks of a few sets they give the groups that one task gives."""
    random.seed(11)
    rows = []
    for base in range(3):
        text = [f"b{base}w{i}" for i in range(120)]
        for i in range(30):  # a chain: each differs a little from the one before, its ends by much
            text = list(text)
            text[(7 * i) % 120] = f"c{base}x{i}"
            rows.append((1000 * base + i, " ".join(text)))
    hub = [f"h{i}" for i in range(150)]
    for i in range(40):  # a star around one text that is there too
        own = list(hub)
        if i:
            own[(3 * i) % 150] = f"s{i}"
        rows.append((9000 + i, " ".join(own)))
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = sorted(map(tuple, simhash.similar_groups(frame).collect()))
    assert len({c for _, c in want}) < 10
    assert sorted(map(tuple, simhash.similar_groups(frame, block_sets=4).collect())) == want


def _cut(rows, span=50):
    least = {}
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - span + 1):
            k = b[i : i + span]
            least[k] = min(d, least.get(k, d))
    out = []
    for d, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - span + 1):
            if least[b[i : i + span]] < d:
                gone[i : i + span] = b"\1" * span
        left = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        spans = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        out.append((d, len(b), len(b) - len(left), spans, hashlib.sha256(left).hexdigest()))
    return sorted(out)


def test_repeats(spark, docs, odd, empty):
    rows = [*ROWS, (60, "ab" * 300), (61, "ab" * 200), (62, "z" * 49), (63, "z" * 120), (64, "z" * 90), (60, "é" * 60), (65, "é" * 60)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert sorted(map(tuple, suffixes.digests(frame).collect())) == _cut(rows)
    assert suffixes.digests(odd).count() == len(ODD)
    assert suffixes.digests(empty).count() == 0
    for hot in (0, 3):  # strings of hot triggers are dealt out
        assert sorted(map(tuple, suffixes.remove_repeats(frame, digest=True, hot=hot).collect())) == _cut(rows)
    kept = suffixes.without_repeats(odd)
    assert kept.columns == odd.columns and kept.count() == len(ODD)
    left = sorted((r.doc_id, r.text or "") for r in kept.collect() if r.doc_id is not None)
    whole = {r[0]: r for r in odd.select("doc_id", "text").collect()}
    assert [d for d, _ in left] == sorted(d for d, _ in ODD if d is not None)
    assert sum(len(t.encode()) for _, t in left) == sum(n - gone for _, n, gone, _, _ in _cut([r for r in ODD if r[0] is not None]))
    assert all(r.text == whole[r.doc_id].text for r in kept.where("doc_id = 0 or doc_id = 2").collect())


def test_repeated_ids_keep_their_rows(spark):
    """Rows of one doc_id, also equal ones, and columns that the operator uses inside."""
    long = " ".join(f"w{i}" for i in range(40))
    rows = [(1, long, 1, 2, 3), (2, long + " x", 1, 2, 3), (2, "y " + long, 4, 5, 6), (2, "short", 7, 8, 9), (3, None, 1, 1, 1), (3, None, 1, 1, 2)]
    out = suffixes.without_repeats(spark.createDataFrame(rows, "doc_id int, text string, _id int, tag int, d int"))
    assert sorted(map(tuple, out.collect()), key=str) == sorted([(1, long, 1, 2, 3), (2, " x", 1, 2, 3), (2, "y ", 4, 5, 6), (2, "short", 7, 8, 9), (3, None, 1, 1, 1), (3, None, 1, 1, 2)], key=str)


def _one_trigger(n, seed=8):
    """n texts around one 20-byte string that is the least of its surroundings."""
    rng = np.random.default_rng(seed)
    data = rng.integers(97, 123, 1 << 21).astype(np.uint8)
    p = suffixes.phrases(data, np.array([0, len(data)]))
    at = int((p["lo"] + p["off"])[p["trigger"].argmin()])
    rows = rng.integers(97, 123, (n, 80)).astype(np.uint8)
    rows[:, 30:50] = data[at : at + 20]
    return rows


def test_many_surroundings_of_one_trigger(spark):
    """200,000 different phrases of one frequent trigger: none is taken for another."""
    import pandas as pd
    import pyarrow as pa

    n = 200_000
    rows = _one_trigger(n)
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(n)), "tag": [0] * n, "text": [x.tobytes().decode() for x in rows], "unit": [i >> 8 for i in range(n)]})
    frame = pd.concat([b.to_pandas() for b in suffixes.dictionary_blobs([batch], 1, 50, 20)])
    found = suffixes.ordered_phrases(frame, 1, 50, 50_000)
    assert found[found["kind"] == 1]["n"].sum() > 0.9 * n and not len(found[found["kind"] == 0])


def test_hot_trigger_with_shared_ends(spark):
    """Thousands of surroundings of one trigger, some shared on one side: equal to brute force, with and without dealing out."""
    rows = _one_trigger(3000, 5)
    rows[::7, 40:] = rows[3, 40:]
    rows[1::11, :45] = rows[4, :45]
    texts = [(i, x.tobytes().decode()) for i, x in enumerate(rows)]
    frame = spark.createDataFrame(texts, "doc_id long, text string")
    for hot in (100, 50_000):
        assert sorted(map(tuple, suffixes.remove_repeats(frame, digest=True, hot=hot).collect())) == _cut(texts)


def test_a_phrase_of_many_documents_is_one_row_a_unit():
    """However many copies a unit has of a passage, its dictionary has each phrase once."""
    import pandas as pd
    import pyarrow as pa

    sizes = []
    for n in (10, 1000):
        text = " ".join(f"word{i}" for i in range(200))
        batch = pa.RecordBatch.from_pydict({"doc_id": list(range(n)), "tag": [0] * n, "text": [text] * n, "unit": [0] * n})
        frame = pd.concat([b.to_pandas() for b in suffixes.dictionary_blobs([batch], 1, 50, 20)])
        sizes.append(len(suffixes.unblob(frame["blob"])[0]))
    assert sizes[0] == sizes[1]


def test_long_texts_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffixes, "CHUNK", 300)
    random.seed(1)
    long = "".join(random.choice("abcdef ") for _ in range(2500))
    raws = [long.encode(), (long[500:1700] + "zz" + long[100:400]).encode()]
    p = suffixes.parse(raws, 50, 20)
    found = {0: set(), 1: set()}
    for row, lo, more in zip(p["row"].tolist(), p["lo"].tolist(), p["more"].tolist(), strict=True):
        found[row] |= set(range(lo, lo + more + 1))
    assert found == {i: set(range(len(raws[i]) - 49)) for i in (0, 1)}


def test_packing(docs, odd, empty):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(BYTE_FILE)
    ids = {d: np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4") for d, x in ROWS}
    packed = packing.pack(docs, BYTE_FILE)
    got = packed.collect()
    total, fill = collections.Counter(), collections.defaultdict(list)
    for r in got:
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert (len(part), zlib.crc32(part.tobytes()), len(ids[r.doc_id])) == (r.length, r.ids_crc32, r.doc_tokens)
        total[r.doc_id] += r.length
        fill[r.sequence_id].append((r.offset, r.length))
    assert total == {d: len(x) for d, x in ids.items()}
    for v in fill.values():
        at = 0
        for offset, n in sorted(v):
            assert offset == at
            at += n
        assert at <= 2048
    assert sorted(fill) == list(range(len(fill)))
    back = {r.sequence_id: r.ids for r in packing.sequences(docs, packed, BYTE_FILE).collect()}
    assert sum(map(len, back.values())) == sum(total.values())
    assert packing.padding(packed).first().tokens == sum(total.values())
    assert packing.pack(odd, BYTE_FILE).select("sequence_id").distinct().count() > 0
    assert packing.pack(empty, BYTE_FILE).count() == 0


@pytest.mark.parametrize("seed", range(4))
def test_shortest_pack_first(seed):
    random.seed(seed)
    hist = collections.Counter(random.randint(1, 64) for _ in range(2000))
    patterns = packing.shortest_pack_first(dict(hist), 64)
    used = collections.Counter()
    for count, lengths in patterns:
        assert sum(lengths) <= 64 and count > 0
        for n in lengths:
            used[n] += count
    assert used == hist
    assert sum(c for c, _ in patterns) * 64 < 1.1 * sum(n * c for n, c in hist.items()) + 64
    assert len(patterns) <= 130


def brute_lattice(la, logp, word):
    """P of a word by listing every segmentation."""
    s, total = lattice.MARK + word, 0.0
    for cuts in range(1 << (len(s) - 1)):
        p, at = 1.0, 0
        for i in range(1, len(s) + 1):
            if i == len(s) or cuts >> (i - 1) & 1:
                g = s[at:i]
                q = math.exp(logp[g]) if g in la.index and (at == 0 or g[0] != lattice.MARK) else 0.0
                if len(g) == 1:
                    q += math.exp(sum(logp[f"<{b:02X}>"] for b in g.encode()))
                p *= q
                at = i
        total += p
    return total


def test_lattice_sums(monkeypatch):
    logp = lattice.vocabulary(PIECE_FILE)
    la = lattice.Lattice(logp)
    assert abs(sum(map(math.exp, logp.values())) - 1) < 1e-9
    words = ["", "a", "the", "onthhe", "é日x", "a▁b", "x<0A>", "anly."]
    want = [math.log(brute_lattice(la, logp, w)) for w in words]
    assert np.allclose(la.run(words), want, atol=1e-9)
    more = [*words, "zq" * 60, "international" * 9, "é日🙂▁" * 30]
    plain = la.run(more)
    monkeypatch.setattr(lattice, "WIDE", 0)
    for chunk in (1, 5, 1 << 14):  # the way of long words, over ends of chunks too
        monkeypatch.setattr(lattice, "CHUNK", chunk)
        assert np.allclose(la.run(more), plain, atol=1e-7)
    monkeypatch.setattr(lattice, "WIDE", 1 << 20)
    assert np.allclose(la.run(more), plain, atol=1e-7)


def test_lattice_scores(docs, odd, empty):
    rows = lattice.score(docs, PIECE_FILE).collect()
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    tok = {d: [*WORDS.findall((t or "").translate(low)), None] for d, t in ROWS}
    train = collections.Counter(w for d in tok if zlib.crc32(str(d).encode()) % 7 != 2 for w in tok[d])
    n, v = sum(train.values()), len(train)
    logp = lattice.vocabulary(PIECE_FILE)
    la = lattice.Lattice(logp)
    counts = collections.Counter(c for w, c in train.items() if w is not None)
    discount = counts[1] / (counts[1] + 2 * counts[2])

    @functools.cache
    def log10_p(w):
        pieces = math.exp(logp[lattice.END]) if w is None else brute_lattice(la, logp, w) if len(w) < 14 else math.exp(max(-700, la.forward(w)))
        own = max(train[w] - discount, 0) / n + discount * v / n * pieces
        return math.log10(own) if own > 1e-290 else (math.log(discount * v / n) + la.forward(w)) / math.log(10)

    assert len(rows) == len(ROWS)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(tok[r.doc_id]), sum(train[w] > 0 for w in tok[r.doc_id]), n)
        assert abs(r.base_score - sum(math.log10((train[w] + 1) / (n + v + 1)) for w in tok[r.doc_id])) < 1e-6 * max(1, abs(r.base_score))
        assert abs(r.score - sum(map(log10_p, tok[r.doc_id]))) < 1e-6 * max(1, abs(r.score))
    few = {r.doc_id: r.score for r in lattice.score(docs, PIECE_FILE, hot_words=3).collect()}
    assert all(abs(few[r.doc_id] - r.score) < 1e-6 * abs(r.score) for r in rows)
    assert lattice.score(odd, PIECE_FILE, hot_words=3).count() == len(ODD)
    assert lattice.score(empty, PIECE_FILE).count() == 0


def test_token_files(docs, odd, empty):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORD_FILE)
    at = 0
    got = {r.doc_id: r for r in tokenfile.round_trip(docs, WORD_FILE).collect()}
    for d, x in ROWS:
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4")
        assert (got[d].start, got[d].n_tokens, got[d].ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert tokenfile.round_trip(odd, WORD_FILE).count() == len(ODD)
    assert tokenfile.round_trip(empty, WORD_FILE).count() == 0


@pytest.mark.parametrize("n", [0, 1, 255, 256, 257, 5000])
def test_blocks(n):
    import io

    rng = np.random.default_rng(n)
    ids = rng.integers(0, 300, n).astype(np.uint32)
    ids[rng.random(n) < 0.05] = rng.integers(0, 2**32, int((rng.random(n) < 0.05).sum()) or 1, dtype=np.uint32)[0]
    out = io.BytesIO()
    w = tokenfile.Writer(out)
    w.add(5, ids)
    w.add(None, ids[: n // 2])
    w.close()
    r = tokenfile.Reader(out.getvalue())
    assert [(d, x.tolist()) for d, x in r.documents()] == [(5, ids.tolist()), (None, ids[: n // 2].tolist())]
    both = np.concatenate([ids, ids[: n // 2]])
    for lo, hi in ((0, 1), (n // 3, n // 2 + 7), (255, 257), (n - 3, n + 9)):
        assert r.read(lo, hi).tolist() == both[max(0, lo) : hi].tolist()
    with pytest.raises(ValueError):
        tokenfile.Reader(out.getvalue()[:-1])


def test_trie_equals_library(docs, odd, empty):
    from tokenizers import Tokenizer

    random.seed(3)
    more = ["".join(random.choice("abcdeézñ \n\t.,!?'0123ABC$#<|>") for _ in range(random.randint(0, 60))) for _ in range(400)]
    for path in (WORD_FILE, BYTE_FILE):
        t = Tokenizer.from_file(path)
        texts = [x or "" for _, x in ROWS] + more
        for x, (ids, decoded), plain in zip(texts, bpe_trie.codec(path).run(texts), encoder(path).encode_all(texts), strict=True):
            want = t.encode(x, add_special_tokens=False).ids
            assert memoryview(ids).cast("I").tolist() == want == memoryview(plain).cast("I").tolist()
            assert decoded == t.decode(want, skip_special_tokens=False)
    assert bpe_trie.digests(odd, WORD_FILE).count() == len(ODD)
    assert bpe_trie.digests(empty, WORD_FILE).count() == 0
    assert bpe_trie.encode(docs, WORD_FILE).where("doc_id = 0").first().ids == []


def test_webp_round_trips():
    rng = np.random.default_rng(0)
    for shape in ((1, 1), (3, 5), (17, 9)):
        for colours in (1, 2, 3, 9, 60):
            im = rng.integers(0, 256, (colours, 4), dtype=np.uint8)[rng.integers(0, colours, shape)]
            for steps in ((), ("palette",), ("predictor",), ("cross",), ("green",), ("predictor", "cross", "green"), ("palette", "predictor")):
                for cache, search in ((0, False), (4, True), (10, False)):
                    assert np.array_equal(webp.decode(webp.encode(im, steps, cache, search)), im)
    for shape in ((40, 33), (300, 16)):  # large enough for the reader by blocks
        im = np.repeat(rng.integers(0, 256, (900, 4), dtype=np.uint8)[rng.integers(0, 900, shape[0] * 4)], shape[1] // 4 + 1, axis=0)[: shape[0] * shape[1]].reshape(*shape, 4)
        for steps in ((), ("predictor",), ("cross", "green")):
            for cache, search in ((0, True), (1, False), (11, True), (6, False)):
                assert np.array_equal(webp.decode(webp.encode(im, steps, cache, search)), im)
        for mode in range(14):
            modes = np.full((-(-shape[0] >> 3), -(-shape[1] >> 3)), mode)
            assert np.array_equal(webp.decode(webp.encode(im, ("predictor",), modes=modes)), im)
    assert webp.near_offsets()[:6] == [(0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0)] and len(webp.near_offsets()) == 120
    with pytest.raises(ValueError):
        webp.decode(b"RIFF1234WEBPVP8X")


def test_webp_of_another_encoder():
    """Two files of one pixel that browsers are commonly probed with, made by the format's own tool."""
    import base64

    assert webp.decode(base64.b64decode("UklGRhoAAABXRUJQVlA4TA0AAAAvAAAAEAcQERGIiP4HAA==")).tolist() == [[[0, 0, 0, 0]]]
    assert webp.decode(base64.b64decode("UklGRh4AAABXRUJQVlA4TBEAAAAvAAAAAAfQ//73v/+BiOh/AAA=")).tolist() == [[[255, 255, 255, 255]]]


def test_blocks_and_single_steps_read_alike(monkeypatch):
    """The reader by blocks of bits against the one that reads field by field, also over block ends and past the stream's end."""
    random.seed(6)
    words = [bytes(random.choices(b"abcdefghij kl", k=random.randint(1, 9))) for _ in range(300)]
    payload = b" ".join(random.choices(words, k=4000))
    payload += bytes(-len(payload) % 64)
    stored = webp.encode_bytes(payload)
    monkeypatch.setattr(webp, "BLOCK", 1 << 9)
    assert webp.decode_bytes(stored) == payload
    monkeypatch.setattr(webp, "FEW", 1 << 40)
    assert webp.decode_bytes(stored) == payload
    monkeypatch.undo()
    for cut in (40, len(stored) // 2, len(stored) - 9):
        short = stored[:16] + (cut - 20).to_bytes(4, "little") + stored[20:cut]
        with pytest.raises(ValueError):
            webp.decode_bytes(short)


def test_payloads_use_the_format():
    """Copies, cache hits and palettes occur in what texts are stored as, and gradients choose a predictor."""
    seen = []

    def noted(name, f):
        def call(*args):
            seen.append((name, args))
            return f(*args)

        return call

    with pytest.MonkeyPatch.context() as m:
        for name in ("_resolved", "unpalette", "predictor"):
            m.setattr(webp, name, noted(name, getattr(webp, name)))
        texts = [(x or "").encode() for _, x in ROWS] + [bytes((3 * i + i // 64) % 256 for i in range(6400))]
        for t in texts:
            payload = t + bytes(-len(t) % 64 if t else 64)
            assert webp.decode_bytes(webp.encode_bytes(payload)) == payload
    kinds = np.concatenate([a[0] for n, a in seen if n == "_resolved"])
    assert ((kinds >= 256) & (kinds < 280)).any() and (kinds >= 280).any()
    assert {"unpalette", "predictor"} <= {n for n, a in seen}


def test_media(docs, odd, empty):
    for r in media.features(media.store(docs)).collect():
        raw = (dict(ROWS)[r.doc_id] or "").encode()
        payload = raw + bytes(-len(raw) % 64 if raw else 64)
        stored = webp.encode_bytes(payload)
        assert (r.n_bytes, r.payload_bytes, r.media_bytes) == (len(raw), len(payload), len(stored))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.media_sha256 == hashlib.sha256(stored).hexdigest()
        assert r.tail_crc32 == zlib.crc32(payload[-64:])
        shares = [int(1000 * sum(b // 32 == i for b in payload) / len(payload) + 0.5) for i in range(8)]
        assert r.feature == "-".join(map(str, shares)) + f"/{100 * sum(payload) // len(payload)}"
    big = bytes(range(256)) * 5000
    assert webp.decode_bytes(webp.encode_bytes(big)) == big
    first = media.pixels(media.store(docs)).where("doc_id = 7").first()
    assert (first.width, first.height) == (16, -(-5000 // 64))
    assert media.features(media.store(odd)).count() == len(ODD)
    assert media.features(media.store(empty)).count() == 0


def test_letters_that_compose_outside_the_safe_ranges():
    """Decomposed Vietnamese composes to letters of other ranges: such texts go to the library whole."""
    from tokenizers import Tokenizer

    from rdf_assist.llm.tokens import Encoder

    t = Tokenizer.from_file(WORD_FILE)
    found = ["ha\u0323nh", "HA\u0323NH phu\u0301c", "cafe\u0301 plain", "\u0130\u0327x", "vie\u0323\u0302t nam 12"]
    e = Encoder(WORD_FILE)
    assert e.split("ha\u0323nh") is None and e.split("cafe\u0301 plain") is not None
    got = [np.frombuffer(x, "<u4").tolist() for x in e.encode_all(found)]
    assert got == [t.encode(x, add_special_tokens=False).ids for x in found]


def test_webp_codes_and_bits_of_many_images_together():
    """op10: codes made for many images at once are those of each alone, a lone symbol takes no bits, and packed words hold the bits of their values."""
    rng = np.random.default_rng(3)
    begins, rows = (0, 300, 556), []
    for i in range(20):
        counts = [rng.integers(0, 1 + 9 ** (i % 4), n) * (rng.random(n) < 0.3) for n in (300, 256, 40)]
        if i % 5 == 0:
            counts[2] = np.eye(1, 40, i, dtype=int)[0]
        rows.append([webp.huffman(c) for c in counts])
    sizes = np.stack([np.concatenate(r) for r in rows])
    codes = webp._written(sizes, begins)
    for i, r in enumerate(rows):
        for at, x in zip(begins, r, strict=True):
            code, size = webp.PrefixCode(x).written()
            assert (codes[i, at : at + len(x)] == code).all() and (sizes[i, at : at + len(x)] == size).all()
    n = rng.integers(0, 61, 5000)
    v = rng.integers(0, 1 << 60, 5000).astype(np.uint64) & ((np.uint64(1) << n.astype(np.uint64)) - np.uint64(1))
    want = "".join(format(int(x), f"0{k}b")[::-1] for x, k in zip(v, n, strict=True) if k)
    assert int.from_bytes(webp.packed_words(v, n).tobytes(), "little") == int(want[::-1], 2)
