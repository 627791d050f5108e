"""Toxicity by compression distance.

The zstandard trainer makes one dictionary from toxic and one from ordinary text.
Invented or rare wording is scarce in both, so each class is trained on its telling
words: those that its documents hold far more often than the other's, of which
most short pieces do so too. Near copies among the training documents count once,
else a copied text would pass for a wording. A trained dictionary is cut to whole
words, as broken ones would save bytes in any text, and laid before the same
ordinary windows for both classes, so that only the class's own words differ.

A document is read in overlapping windows of whole words, each compressed with
either dictionary; the difference of the lengths is the window's margin. A logistic
curve over a document's margins, fitted on labelled rows, calibrates the score.

Fitting uses at most ``MOST_TOXIC`` and ``MOST_ORDINARY`` labelled rows, those of the
smallest seeded hash among those of at most ``FIT_BYTES`` bytes, each whole. Scoring
reads every document whole.
"""

from __future__ import annotations

import random
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.work import load

MOST_TOXIC = 1_500
MOST_ORDINARY = 3_000
FIT_BYTES = 20_000
WINDOW_WORDS = 8
STEP_WORDS = 6
BASE_BYTES = 32_000
#: Size of a trained dictionary, the trainer's segment and match lengths, and how often a document's words are laid out anew.
TRAINED_BYTES, SEGMENT, MATCH, REPEATS = 2_048, 24, 6, 10
LEVEL = 6
LIMIT = 0.3
SEED = 5


def windows(text: str | None, words: int = WINDOW_WORDS, step: int = STEP_WORDS) -> list[bytes]:
    """Lower-cased windows of whole words that together cover the text; none if it has no words."""
    found = (text or "").lower().encode("utf-8", "replace").split()
    if len(found) <= words:
        return [b" ".join(found)] if found else []
    return [b" ".join(found[s : s + words]) for s in [*range(0, len(found) - words, step), len(found) - words]]


def pieces(word: bytes) -> set[bytes]:
    """Byte strings of ``MATCH`` bytes inside the spaced word."""
    spaced = b" " + word + b" "
    return {spaced[i : i + MATCH] for i in range(max(1, len(spaced) - MATCH + 1))}


def uncopied(bags: list[set[bytes]], hashes: int = 6, most: int = 3) -> list[set[bytes]]:
    """Word sets without those that share over ``most`` of ``hashes`` minima with earlier ones."""
    seen: set[tuple[int, int]] = set()
    kept = []
    for bag in bags:
        minima = {(j, min((zlib.crc32(w, j) for w in bag), default=0)) for j in range(hashes)}
        if len(minima & seen) <= most:
            kept.append(bag)
        seen |= minima
    return kept


def telling(bags: list[set[bytes]], others: list[set[bytes]], times: float = 20.0, most_pieces: float = 0.75) -> list[list[bytes]]:
    """The telling words of each set, ``times`` as common here as there; so are ``most_pieces`` of their pieces."""
    share = lambda n, of: (n + 0.5) / (of + 1)
    split = {w: pieces(w) for bag in bags for w in bag} | {w: pieces(w) for bag in others for w in bag}
    words, parts = [], []
    for side in (bags, others):
        words.append(Counter(w for bag in side for w in bag))
        parts.append(Counter(p for bag in side for p in {p for w in bag for p in split[w]}))
    often = lambda counts, x: share(counts[0][x], len(bags)) >= times * share(counts[1][x], len(others))
    least = max(4, len(bags) // 100)
    good = {w for w, n in words[0].items() if n >= least and often(words, w)}
    good = {w for w in good if np.mean([often(parts, p) for p in split[w]]) >= most_pieces}
    return [sorted(bag & good) for bag in bags]


def dictionary(bags: list[set[bytes]], others: list[set[bytes]], rng: random.Random) -> bytes:
    """What the zstandard trainer takes from the telling words of ``bags``, cut to whole words; empty if there are too few."""
    found = [words for words in telling(bags, others) if words]
    samples = [(b" " + b" ".join(rng.sample(words, len(words))) + b" ").ljust(2 * MATCH) for words in found for _ in range(REPEATS)]
    try:
        trained = zstandard.train_dictionary(TRAINED_BYTES, samples, k=SEGMENT, d=MATCH).as_bytes()
    except zstandard.ZstdError:  # the trainer refuses so little text
        trained = b"".join(dict.fromkeys(samples))[-TRAINED_BYTES:]
    known = {w for words in found for w in words}
    return b" ".join(dict.fromkeys(w for w in trained.split() if w in known))


@dataclass(frozen=True)
class Model:
    """Both dictionaries, the centre and scale of the features, and the logistic weights."""

    toxic: bytes
    ordinary: bytes
    centre: tuple[float, ...]
    scale: tuple[float, ...]
    weights: tuple[float, ...]

    def compressors(self) -> tuple[zstandard.ZstdCompressor, zstandard.ZstdCompressor]:
        made = []
        for content in (self.toxic, self.ordinary):
            held = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            held.precompute_compress(level=LEVEL)
            made.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=held, write_content_size=False, write_checksum=False, write_dict_id=False))
        return made[0], made[1]

    def score(self, features: np.ndarray) -> np.ndarray:
        z = (features - np.array(self.centre)) / np.array(self.scale) @ np.array(self.weights[1:]) + self.weights[0]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def features(texts: Iterable[str | None], toxic: zstandard.ZstdCompressor, ordinary: zstandard.ZstdCompressor) -> np.ndarray:
    """Largest margin, sum of the three largest, damped sum of those over 2, and log count of windows."""
    rows = []
    for text in texts:
        found = windows(text)
        margins = sorted((len(ordinary.compress(w)) - len(toxic.compress(w)) for w in found), reverse=True) if found else [0]
        rows.append((margins[0], sum(margins[:3]), np.log1p(sum(m - 2 for m in margins if m > 2)), np.log1p(len(found))))
    return np.array(rows, float).reshape(-1, 4)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Newton steps for ridge-penalised logistic regression; the first weight is the constant."""
    x = np.column_stack([np.ones(len(x)), x])
    w, penalty = np.zeros(x.shape[1]), ridge * np.eye(x.shape[1])
    penalty[0, 0] = 1e-6
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + penalty, x.T @ (y - p) - penalty @ w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def train(toxic: list[str], ordinary: list[str], share: float) -> Model:
    """Dictionaries from one half of each class, calibration on the other; ``share``: toxic rows of all labelled."""
    rng = random.Random(SEED)
    halves = toxic[::2] or toxic, ordinary[::2] or ordinary
    bags = [[set(t.lower().encode("utf-8", "replace").split()) for t in texts] for texts in halves]
    own = [dictionary(uncopied(bags[k]), uncopied(bags[1 - k]), rng) for k in (0, 1)]
    sample = [w for t in halves[1] for w in (lambda ws: rng.sample(ws, min(3, len(ws))))(windows(t))]
    rng.shuffle(sample)
    base = b" " + b" ".join(sample)[:BASE_BYTES].ljust(64, b" ")
    wide = max(64, *map(len, own))
    blank = Model(own[0].rjust(wide) + base, own[1].rjust(wide) + base, (0.0,) * 4, (1.0,) * 4, (0.0,) * 5)
    bad, good = toxic[1::2], ordinary[1::2]
    if not bad or not good:
        share = min(max(share, 1e-3), 1 - 1e-3)
        return Model(blank.toxic, blank.ordinary, blank.centre, blank.scale, (float(np.log(share / (1 - share))), 0.0, 0.0, 0.0, 0.0))
    x = features([*bad, *good], *blank.compressors())
    y = np.r_[np.ones(len(bad)), np.zeros(len(good))]
    centre, scale = x.mean(0), x.std(0) + 1e-9
    weights = logistic((x - centre) / scale, y)
    # back from the sample's share of toxic rows to that of all labelled rows
    weights[0] += np.log(share / (1 - share)) - np.log(len(bad) / len(good)) if 0 < share < 1 else 0.0
    return Model(blank.toxic, blank.ordinary, tuple(centre), tuple(scale), tuple(float(w) for w in weights))


def held_out(doc_id: Column) -> Column:
    """Whether crc32 of the id as text leaves 2 by 4; a row without an id isn't held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def labelled(docs: DataFrame, labels: DataFrame) -> tuple[list[str], list[str], float]:
    """Bounded training texts of both classes, and the share of toxic rows among all labelled ones."""
    known = labels.select("doc_id", "toxic").where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    counts = {r[0]: r[1] for r in known.groupBy("toxic").count().collect()}
    short = docs.where(F.octet_length("text").between(1, FIT_BYTES)).select("doc_id", "text")
    texts: dict[int, list[str]] = {}
    for value, most in ((1, MOST_TOXIC), (0, MOST_ORDINARY)):
        ids = known.where(F.col("toxic") == value).select("doc_id", F.xxhash64(F.lit(SEED), "doc_id").alias("h"))
        picked = short.select("doc_id").join(ids, "doc_id").orderBy("h", "doc_id").limit(most).distinct()
        rows = short.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select(F.xxhash64(F.lit(SEED), "doc_id").alias("h"), "doc_id", "text")
        # repeated ids could bring more rows than ids
        texts[value] = [r[2] for r in rows.orderBy("h", "doc_id", "text").limit(most).collect()]
    total = sum(counts.values())
    return texts[1], texts[0], counts.get(1, 0) / total if total else 0.0


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    return train(*labelled(docs, labels))


def score_documents(docs: DataFrame, model: Model, name: str = "toxicity") -> DataFrame:
    """The input's rows and columns with ``name``, a score from 0 to 1.

    Null and empty texts get the score of a document without windows; repeated rows
    are scored alike; rows without an id are scored as any; an empty table gives an
    empty result. An input column called ``name`` is replaced.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)  # two dictionaries of fixed size

    @F.pandas_udf("double")
    def toxicity(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        toxic, ordinary = held.value.compressors()
        for batch in texts:
            yield pd.Series(held.value.score(features(batch, toxic, ordinary)))

    return docs.withColumn(name, toxicity(F.col("text")))


def kept(docs: DataFrame, labels: DataFrame, limit: float = LIMIT) -> DataFrame:
    """The documents whose score stays under ``limit``, with the columns they came with."""
    return score_documents(docs, fit(docs, labels), "_toxicity_score").where(F.col("_toxicity_score") < limit).select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    scored = score_documents(docs.select("doc_id", "text"), fit(docs, load(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= LIMIT).cast("int").alias("predicted"))
