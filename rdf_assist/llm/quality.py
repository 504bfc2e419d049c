"""Quality rules under weak supervision: rules vote or abstain, and a posterior decides.

Each rule votes good (1), bad (-1) or abstains (0). How often votes go together tells how accurate
each rule is: expectation-maximisation over the counts of vote patterns (at most 3 ** rules rows,
whatever the corpus) estimates each rule's accuracy and the share of good documents. A document is
kept by its posterior, so one odd measure does not reject it, as all-must-pass filters would.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import durable, remote, texts

HERE = __name__
MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, n_letters long, n_ended long, n_upper long, n_common long"
NAMES = [x.split()[0] for x in MEASURES.split(", ")]

# The symbols counted, white space between words, and marks that end a sentence.
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\r\x0b\x0c"
ENDS = tuple(x.encode() for x in (".", "!", "?", '"', "”", "…", ":", ";"))

# Frequent function words of English, German, French and Spanish.
COMMON = frozenset(w.encode() for w in (
    "the of and to in is that it for on with as was are be this or at from by an have not you "
    "der die das und ist nicht ein eine zu den von mit sich auf im des dem für "
    "le la les de des et un une est que qui pour dans sur pas avec au "
    "el los las y en una por con del se su para es como al"
).split())

_CAPITAL = bytes(i for i in range(256) if not 65 <= i <= 90)
_NO_LETTER = bytes(i for i in range(128) if not (65 <= i <= 90 or 97 <= i <= 122))


def repeated_words(words: list, n: int = 5) -> int:
    """Positions covered by the n-word windows that occur twice or more."""
    count = len(words) - n + 1
    if count < 2:
        return 0
    h = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)
    with np.errstate(over="ignore"):
        key = h[:count].copy()
        for i in range(1, n):
            key = key * np.uint64(0x9E3779B97F4A7C15) + h[i : count + i]
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    if not same.any():
        return 0
    suspects = np.union1d(order[1:][same], order[:-1][same])  # windows alone with their hash are alone
    seen: dict = {}
    for i in suspects.tolist():
        seen.setdefault(tuple(words[i : i + n]), []).append(i)
    covered = np.zeros(len(words) + 1, np.int64)
    for at in seen.values():
        if len(at) > 1:
            np.add.at(covered, at, 1)
            np.add.at(covered, np.asarray(at) + n, -1)
    return int((np.cumsum(covered) > 0).sum())


def measure(text: str | None) -> tuple[int, ...]:
    """The values of MEASURES; all zero without text."""
    if not text:
        return (0,) * len(NAMES)
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    seen: set[bytes] = set()
    lines = repeats = ended = 0
    for line in raw.split(b"\n"):
        if line and (bare := line.strip()):
            lines += 1
            ended += bare.endswith(ENDS)
            if line in seen:
                repeats += 1
            else:
                seen.add(line)
    return (
        len(words),
        len(text) - sum(map(text.count, SPACES)),
        sum(map(text.count, SYMBOLS)),
        repeats,
        repeated_words(words),
        lines,
        len(raw.translate(None, _NO_LETTER).decode("utf-8", "replace")),
        ended,
        len(raw.translate(None, _CAPITAL)),
        sum(map(COMMON.__contains__, words)),
    )


def measure_batches(batches, inside: str | None = None):
    """Adds the measures of each text: of the column text, which goes, or of the field text of the struct `inside`, which stays."""
    for b in batches:
        found = b.column(inside).field("text") if inside else b.column("text")
        rows = np.array([measure(t) for t in found.to_pylist()], np.int64).reshape(-1, len(NAMES))
        keep = [i for i, n in enumerate(b.schema.names) if n != "text"]
        yield pa.RecordBatch.from_arrays([b.column(i) for i in keep] + [pa.array(rows[:, i]) for i in range(len(NAMES))], [b.schema.names[i] for i in keep] + NAMES)


def _vote(good: Column, bad: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0).cast("int")


def rules() -> dict[str, Column]:
    """Name → vote, from the measures."""
    words, lines = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("n_lines"), F.lit(1))
    chars = F.greatest(F.col("word_chars"), F.lit(1))
    mean, symbols = F.col("word_chars") / words, F.col("n_symbols") / words
    copies, again = F.col("n_dup_lines") / lines, F.col("n_repeat_words") / words
    letters, ended, upper, common = F.col("n_letters") / chars, F.col("n_ended") / lines, F.col("n_upper") / chars, F.col("n_common") / words
    return {
        "long_enough": _vote(F.col("n_words") >= 50, F.col("n_words") < 20),
        "word_length": _vote((mean >= 3) & (mean <= 8), (mean < 2) | (mean > 14)),
        "few_symbols": _vote(symbols <= 0.02, symbols > 0.1),
        "few_copied_lines": _vote((copies <= 0.05) & (F.col("n_lines") > 1), copies > 0.3),
        "few_repeats": _vote(again <= 0.03, again > 0.1),
        "letters": _vote(letters >= 0.93, letters < 0.9),
        "sentences": _vote(ended >= 0.5, (ended < 0.1) & (F.col("n_lines") > 2)),
        "lower_case": _vote(upper <= 0.1, upper > 0.4),
        "function_words": _vote(common >= 0.1, (common < 0.03) & (F.col("n_words") >= 20)),
    }


#: Starting chances of a bad vote, an abstention and a good vote, for bad and for good documents.
START = {False: (0.35, 0.25, 0.4), True: (0.02, 0.18, 0.8)}


def fit(patterns: list[tuple[list[int], int]], rounds: int = 100) -> dict:
    """share of good documents, and for each rule the log odds that its votes -1, 0, 1 lend to good.

    Expectation-maximisation over (votes, count): a rule's accuracy is its chance of each vote given good
    and given bad. The share stays between 0.5 and 0.995, and no vote's odds turn against its sign (an
    abstention has none), so the classes cannot swap. Without patterns: the starting values, no rules.
    """
    share = 0.9
    if not patterns:
        return {"share": share, "odds": []}
    votes = np.array([v for v, _ in patterns], np.int64)
    count = np.array([c for _, c in patterns], np.float64)
    hot = (votes[:, :, None] == np.array([-1, 0, 1])).astype(np.float64)
    width = votes.shape[1]
    chance = {c: np.tile(np.array(START[c]), (width, 1)) for c in START}

    def odds() -> np.ndarray:
        o = np.log(chance[True] / chance[False])
        return np.stack([np.minimum(o[:, 0], 0), np.zeros(width), np.maximum(o[:, 2], 0)], axis=1)

    for _ in range(rounds):
        x = (hot * odds()).sum((1, 2)) + math.log(share / (1 - share))
        good = 1 / (1 + np.exp(-np.clip(x, -50, 50)))
        for c, weight in ((True, count * good), (False, count * (1 - good))):
            mass = (weight[:, None, None] * hot).sum(0) + 20 * np.array(START[c])
            chance[c] = mass / mass.sum(axis=1, keepdims=True)
        share = float(np.clip((count * good).sum() / count.sum(), 0.5, 0.995))
    return {"share": share, "odds": odds().tolist()}


def posterior(votes: list[Column], model: dict) -> Column:
    share = model["share"]
    total = F.lit(math.log(share / (1 - share)))
    for vote, (bad, _, good) in zip(votes, model["odds"], strict=bool(model["odds"])):
        total = total + F.when(vote < 0, bad).when(vote > 0, good).otherwise(0.0)
    return 1 / (1 + F.exp(-total))


def base_failed() -> Column:
    """The plain limits, which hold before any vote: fewer than 10 words, or over 20 % in repeated windows."""
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def learn(measured: DataFrame) -> dict:
    votes = F.array(*rules().values())
    counted = measured.where(~base_failed()).groupBy(votes.alias("v")).count().collect()  # at most 3 ** rules rows
    return fit([(list(r["v"]), r["count"]) for r in sorted(counted, key=lambda r: list(r["v"]))])


def judge(measured: DataFrame, model: dict) -> DataFrame:
    quality = posterior(list(rules().values()), model)
    return measured.withColumns({"base_failed": base_failed(), "quality": quality}).withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= 0.5))


def quality(docs: DataFrame) -> DataFrame:
    """doc_id, the measures, base_failed, quality (posterior) and kept of every row.

    Null and empty texts measure 0 and fail the base limits. Repeated rows count each. No rows give no rows.
    """
    measured = durable(texts(docs).mapInArrow(remote(HERE, "measure_batches"), f"doc_id long, {MEASURES}"))
    return judge(measured, learn(measured))


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows of docs that quality() keeps, with all their columns, whatever these are called.

    Measuring is repeated rather than joined back: texts are not shuffled.
    """
    model = learn(texts(docs).mapInArrow(remote(HERE, "measure_batches"), f"doc_id long, {MEASURES}"))
    row = F.struct(*[F.col(f"`{c}`").cast("string").alias(c) if c == "text" else F.col(f"`{c}`") for c in docs.columns]).alias("row")
    held = docs.select(row)
    schema = T.StructType([held.schema["row"], *[T.StructField(n, T.LongType()) for n in NAMES]])
    return judge(held.mapInArrow(remote(HERE, "measure_batches", inside="row"), schema), model).where("kept").select("row.*")
