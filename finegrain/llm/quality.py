"""Quality classifier by positive-unlabelled learning with the non-negative risk estimator.

Texts labelled good are the trusted positives; all other texts are unlabelled, whatever they are. Labels of bad texts are
not used at all, and of held-out rows neither label nor text enters the fit. A first logistic model, positives against unlabelled,
gives the class prior; the second minimises

    prior * E_p[loss(f, +)] + max(0, E_u[loss(f, -)] - prior * E_p[loss(f, -)])

by gradient descent, reversing the step on the second part while it is negative. The score is the logistic function of ``f``.

Inputs of a score are counts over the whole text only: bytes by class, words, repeats, lines.

Defined results: null counts as empty; an empty text has all-zero counts and gets the model's score for them. Without any
trusted positive every score is the prior 0.5. Rows with the same id are scored each on its own text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.llm.batches import in_batches
from finegrain.llm.rows import column
from finegrain.llm.textkernel import ALNUM, blocks, words_of
from finegrain.sources.staging import staged

#: The most labelled positives and the most unlabelled rows that the fit reads, chosen by a hash of the id.
MOST_POSITIVE, MOST_UNLABELLED = 20_000, 20_000
THRESHOLD = 0.7
PAD_BYTES, PAD_WORDS = 60, 10

#: Byte classes of the counts.
_CLASSES = {
    "upper": lambda b: 65 <= b <= 90,
    "lower": lambda b: 97 <= b <= 122,
    "digit": lambda b: 48 <= b <= 57,
    "space": lambda b: b == 32,
    "line": lambda b: b == 10,
    "high": lambda b: b >= 128,
    "stop": lambda b: b in b".",
    "comma": lambda b: b in b",;:",
    "shout": lambda b: b in b"!?",
    "bar": lambda b: b in b"|<>{}[]=/\\_",
    "sign": lambda b: b in b"#$%&*@^~+",
    "other": lambda b: b in b"\"'()`-",
}
_CODE = np.full(256, len(_CLASSES), dtype=np.int64)
for _k, _f in enumerate(_CLASSES.values()):
    for _b in range(256):
        if _f(_b):
            _CODE[_b] = _k
_RATIOS = [*_CLASSES, "repeat", "repeat2", "distinct", "word_length", "long_words", "capital_run", "line_repeat", "size"]
WIDTH = 2 * len(_RATIOS)


def features_of(column: pa.Array) -> np.ndarray:
    """One row of features for each text."""
    out = np.zeros((len(column), WIDTH), dtype=np.float64)
    for row, data, offsets in blocks(column):
        out[row : row + len(offsets) - 1] = _block_features(data, offsets)
    return out


def _per_text(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of ``values`` over the ranges that ``first`` bounds."""
    running = np.concatenate([[0.0], np.cumsum(values, dtype=np.float64)])
    return running[first[1:]] - running[first[:-1]]


def _block_features(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    n = len(offsets) - 1
    size = np.diff(offsets).astype(np.float64)
    text = np.repeat(np.arange(n), np.diff(offsets))
    classes = len(_CLASSES) + 1
    counts = np.bincount(text * classes + _CODE[data], minlength=n * classes).reshape(n, classes)[:, :-1]
    words = words_of(data, offsets, ALNUM)
    number = words.counts.astype(np.float64)
    # a few neutral bytes and words are added, so that a short text's counts weigh little
    safe, safe_words = size + PAD_BYTES, number + PAD_WORDS
    of = words.text_of_words()
    h = words.hashes
    same = np.zeros(len(h))
    same[1:] = (h[1:] == h[:-1]) & (of[1:] == of[:-1])
    second = np.zeros(len(h))
    if len(h) > 5:
        for back in range(2, 6):
            second[back:] = np.maximum(second[back:], (h[back:] == h[:-back]) & (of[back:] == of[:-back]))
    lengths = (words.ends - words.starts).astype(np.float64)
    order = np.lexsort((h, of))
    ho, oo = h[order], of[order]
    new = np.ones(len(h))
    new[1:] = (ho[1:] != ho[:-1]) | (oo[1:] != oo[:-1])
    capital = np.zeros(len(h))
    if len(h):
        up = lambda at: (data[np.minimum(at, len(data) - 1)] >= 65) & (data[np.minimum(at, len(data) - 1)] <= 90)
        capital = (up(words.starts) & up(words.starts + 1) & (lengths >= 2)).astype(np.float64)
    lines = words_of(data, offsets, _NOT_LINE, None)
    lo = lines.text_of_words()
    again = np.lexsort((lines.hashes, lo))
    hl, ol = lines.hashes[again], lo[again]
    fresh = np.ones(len(hl))
    fresh[1:] = (hl[1:] != hl[:-1]) | (ol[1:] != ol[:-1])
    line_count = np.maximum(lines.counts, 1)
    ratios = np.column_stack(
        [
            counts / safe[:, None],
            _per_text(same, words.first) / safe_words,
            _per_text(second, words.first) / safe_words,
            np.bincount(oo, new, minlength=n) / np.sqrt(safe_words) / 10,
            _per_text(lengths, words.first) / safe_words / 10,
            _per_text((lengths > 20).astype(np.float64), words.first) / safe_words,
            _per_text(capital, words.first) / safe_words,
            1 - np.bincount(ol, fresh, minlength=n) / line_count,
            np.log1p(size) / 10,
        ]
    )
    ratios[size == 0] = 0
    return np.hstack([ratios, np.sqrt(np.maximum(ratios, 0))])


_NOT_LINE = np.array([b != 10 for b in range(256)])


@dataclass
class QualityModel:
    """A standardised linear model; ``prior`` is the estimated share of positives among unlabelled texts."""

    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray
    bias: float
    prior: float

    def score(self, features: np.ndarray) -> np.ndarray:
        z = ((features - self.mean) / self.scale) @ self.weight + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _descend(gradient, width: int, steps: int, rate: float) -> tuple[np.ndarray, float]:
    """Adam over weight and bias."""
    w, m, v = np.zeros(width + 1), np.zeros(width + 1), np.zeros(width + 1)
    for t in range(1, steps + 1):
        g = gradient(w[:-1], w[-1])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = w - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w[:-1], float(w[-1])


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, steps: int = 400) -> float:
    """Share of positives among the unlabelled, between 0.05 and 0.97: the lesser of two estimates.

    ``g`` is a classifier of three quarters of the positives against the unlabelled, ``c`` its mean over the other quarter. A sure
    positive has the odds ``c / (1 - c)`` = positives over unlabelled positives, which gives the first estimate. It is too high where
    the classes are not apart; the second is the share of the unlabelled that look at least half as positive as a positive does.
    """
    hold = np.arange(len(positive)) % 4 == 0
    train, test = positive[~hold], positive[hold]
    if not len(train) or not len(test) or not len(unlabelled):
        return 0.5
    x = np.vstack([train, unlabelled])
    y = np.concatenate([np.ones(len(train)), np.zeros(len(unlabelled))])

    def gradient(w, b):
        d = (_sigmoid(x @ w + b) - y) / len(y)
        return np.append(x.T @ d + 1e-3 * w / len(y), d.sum())

    w, b = _descend(gradient, x.shape[1], steps, 0.05)
    g = np.clip(_sigmoid(unlabelled @ w + b), 1e-6, 1 - 1e-6)
    c = np.clip(_sigmoid(test @ w + b).mean(), 1e-3, 1 - 1e-3)
    # with g fitted on n_p + n_u rows, the odds of "labelled" at a sure positive are n_p / (prior * n_u)
    prior = (len(train) / len(unlabelled)) * (1 - c) / c
    return float(np.clip(min(prior, (g > 0.5 * c).mean()), 0.05, 0.97))


def fit_nnpu(positive: np.ndarray, unlabelled: np.ndarray, steps: int = 1500, rate: float = 0.02, penalty: float = 1e-4) -> QualityModel:
    """Fit the non-negative positive-unlabelled risk with the logistic loss."""
    if not len(positive) or not len(unlabelled):
        return QualityModel(np.zeros(WIDTH), np.ones(WIDTH), np.zeros(WIDTH), 0.0, 0.5)
    both = np.vstack([positive, unlabelled])
    mean, scale = both.mean(0), both.std(0) + 1e-6
    p, u = np.clip((positive - mean) / scale, -20, 20), np.clip((unlabelled - mean) / scale, -20, 20)
    prior = estimate_prior(p, u)

    def gradient(w, b):
        fp, fu = p @ w + b, u @ w + b
        # logistic loss: l(f,+) = log(1 + e^-f), l(f,-) = log(1 + e^f)
        negative_part = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
        d_positive = -prior * _sigmoid(-fp) / len(fp)
        d_up, d_pn = _sigmoid(fu) / len(fu), -prior * _sigmoid(fp) / len(fp)
        if negative_part >= 0:
            dp, du = d_positive + d_pn, d_up
        else:  # the estimate cannot be negative: step back on that part alone
            dp, du = -d_pn, -d_up
        return np.append(p.T @ dp + u.T @ du + penalty * w, dp.sum() + du.sum())

    w, b = _descend(gradient, WIDTH, steps, rate)
    return QualityModel(mean, scale, w, b, prior)


def _feature_rows(docs: DataFrame, id_col: str, text: str) -> DataFrame:
    id_type = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            f = features_of(batch.column(1)).astype(np.float32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.FixedSizeListArray.from_arrays(pa.array(f.ravel()), WIDTH).cast(pa.list_(pa.float32()))], names=["id", "features"])

    return docs.select(column(id_col).alias("id"), column(text).alias("text")).transform(in_batches, run, f"id {id_type}, features array<float>")


def train_quality(features: DataFrame, labels: DataFrame, learn_from, most_positive: int = MOST_POSITIVE, most_unlabelled: int = MOST_UNLABELLED) -> QualityModel:
    """Fit on feature rows; ``labels`` holds id and quality, ``learn_from`` is a condition on ``id`` (null: not held out)."""
    learn_from = F.coalesce(learn_from, F.lit(True))
    features = features.filter(learn_from)
    good = labels.filter(learn_from).groupBy("id").agg(F.max("quality").alias("quality"))
    known = features.join(good, "id", "left").withColumn("_h", F.xxhash64(F.col("id").cast("string"), F.lit(7)))
    # bounded samples: the smallest hashes of the id
    positive = known.filter("quality = 1").orderBy("_h").limit(most_positive).select("features").toArrow()
    rest = features.join(good.filter("quality = 1"), "id", "left_anti").withColumn("_h", F.xxhash64(F.col("id").cast("string"), F.lit(11)))
    unlabelled = rest.orderBy("_h").limit(most_unlabelled).select("features").toArrow()
    stack = lambda table: table["features"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, WIDTH)
    return fit_nnpu(stack(positive), stack(unlabelled))


def learnable(id_col: str = "id"):
    """Rows whose labels may be learnt from: the checksum of the id as text, modulo 4, is not 2."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4)) != 2


def quality_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Id, ``held_out``, ``score`` and ``predicted`` of every row of ``docs``."""
    features = staged(_feature_rows(docs, id_col, text), "features")
    marks = labels.select(F.col(id_col).alias("id"), F.col("quality").cast("int").alias("quality"))
    model = train_quality(features, marks, learnable())
    id_type = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, WIDTH)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(x), pa.float64())], names=["id", "score"])

    scored = features.transform(in_batches, run, f"id {id_type}, score double")
    held = F.coalesce(~learnable(), F.lit(False))
    return scored.select(F.col("id").alias(id_col), held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` whose predicted quality is 1, with their columns: the texts are scored where they lie."""
    features = staged(_feature_rows(docs, id_col, text), "features")
    marks = labels.select(F.col(id_col).alias("id"), F.col("quality").cast("int").alias("quality"))
    model = train_quality(features, marks, learnable())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(model.score(features_of(batch.column(batch.schema.get_field_index(text)))) >= THRESHOLD))

    return docs.transform(in_batches, run, docs.schema)
