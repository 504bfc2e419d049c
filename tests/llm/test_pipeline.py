"""The pipeline, stage by stage, on documents with planted cases."""

import collections
import random
import string
import zlib

import numpy as np

import corpus_pipeline
from rdf_assist.llm import packing, quality, simhash, suffixes
from rdf_assist.llm.common import durable

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def planted(spark):
    random.seed(4)
    words = ["the", "of", "and", *["".join(random.choices(["th", "an", "er", "on", "in", "re", "ly"], k=random.randint(2, 4))) for _ in range(800)]]

    def prose(n):
        return "\n".join(" ".join(random.choices(words, k=11)).capitalize() + " the of." for _ in range(n))

    passage = " ".join(random.choices(words, k=70))
    rows = [(i, prose(12)) for i in range(40)]
    rows += [(100 + i, rows[i][1]) for i in range(5)]
    rows += [(200 + i, rows[10 + i][1].replace("the of.", "the of.", 1).replace(rows[10 + i][1].split()[40], "otherword", 1)) for i in range(5)]
    rows += [(300 + i, prose(6) + "\n" + passage + "\n" + prose(6)) for i in range(4)]
    rows += [(400, "$$$ ### | && " * 60), (401, "buy now\n" * 80), (402, ""), (403, "short")]
    return spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long"), passage


def test_stages(spark):
    docs, passage = planted(spark)
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "near_duplicates", "repeated_passages", "packing"]
    steps = dict(corpus_pipeline.STAGES)
    good = durable(steps["quality_rules"](spark, docs, ""))
    assert good.columns == COLUMNS
    kept = {r.doc_id for r in good.collect()}
    assert kept == {r.doc_id for r in docs.collect()} - {400, 401, 402, 403}
    single = durable(steps["near_duplicates"](spark, good, ""))
    assert {r.doc_id for r in single.collect()} == kept - set(range(100, 105)) - set(range(200, 205))
    bare = durable(steps["repeated_passages"](spark, single, ""))
    assert bare.columns == COLUMNS
    holders = [r.doc_id for r in bare.collect() if passage in r.text]
    assert holders == [300]
    texts = {r.doc_id: r.text for r in single.collect()}
    assert all(r.text == texts[r.doc_id] for r in bare.collect() if r.doc_id < 40)
    packed = steps["packing"](spark, bare, "")
    total = collections.Counter()
    for r in packed.collect():
        total[r.doc_id] += r.length
        assert r.doc_tokens >= total[r.doc_id]
    assert set(total) == {r.doc_id for r in bare.collect()}


def test_run_is_its_stages(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = durable(stage(spark, docs, tiny))
    key = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    want = sorted(map(tuple, packing.pack(docs, corpus_pipeline.public_path("byte_bpe_50k.json")).select(key).collect()))
    assert sorted(map(tuple, corpus_pipeline.run(spark, tiny).select(key).collect())) == want


def _plain(rows, similarity=0.8, span=50):
    """doc_id → text after near-duplicates and repeated passages, by comparing everything with everything."""
    shingles = {}
    for d, t in rows:
        words = t.translate(str.maketrans(string.ascii_uppercase, string.ascii_lowercase)).split()
        shingles[d] = {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))}
    group = {d: d for d in shingles}
    for a in sorted(shingles):
        for b in sorted(shingles):
            if a < b and len(shingles[a] & shingles[b]) >= similarity * len(shingles[a] | shingles[b]):
                old, new = max(group[a], group[b]), min(group[a], group[b])
                group = {d: new if g == old else g for d, g in group.items()}
    left = sorted((d, t.encode()) for d, t in rows if group[d] == d)
    least = {}
    for d, b in left:
        for i in range(len(b) - span + 1):
            least.setdefault(b[i : i + span], d)
    out = {}
    for d, b in left:
        gone = bytearray(len(b))
        for i in range(len(b) - span + 1):
            if least[b[i : i + span]] < d:
                gone[i : i + span] = b"\1" * span
        out[d] = bytes(x for x, g in zip(b, gone, strict=True) if not g).decode("utf-8", "ignore")
    return out


def test_run_against_brute_force(spark, tmp_path):
    from tokenizers import Tokenizer

    docs, _ = planted(spark)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect() if r.doc_id < 400]  # what test_stages() knows the quality rules to keep
    want = _plain(rows)
    t = Tokenizer.from_file(corpus_pipeline.public_path("byte_bpe_50k.json"))
    ids = {d: np.array([*t.encode(x, add_special_tokens=False).ids, 1], "<u4") for d, x in want.items()}
    total = collections.Counter()
    for r in corpus_pipeline.run(spark, str(tmp_path)).collect():
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert (len(part), zlib.crc32(part.tobytes()), len(ids[r.doc_id])) == (r.length, r.ids_crc32, r.doc_tokens)
        total[r.doc_id] += r.length
    assert total == {d: len(x) for d, x in ids.items()}


def test_stages_take_odd_rows(spark):
    rows = [(None, None, None, None, None, 1), (1, None, "en", "s", 0, 2), (1, "", "en", "s", 0, 3), (2, "the of and " * 30, "en", "s", 330, 4)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_words int")
    for f in (quality.keep_good, simhash.keep_first, suffixes.without_repeats):
        out = f(frame)
        assert out.columns == frame.columns
        out.collect()
        assert f(frame.limit(0)).count() == 0
