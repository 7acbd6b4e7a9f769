"""Quality rules: countable text measures, and a calibrated logistic regression against a fixed threshold.

The regression reads square roots of hashed word and character n-gram frequencies, learns from a bounded sample of
labelled quality rows, and is calibrated on a fifth of them that it has not seen. Documents are scored where
they lie, in Arrow batches.

Edge cases: a null text has no words; a text without words scores the calibrated base rate; without labels of both
kinds the score is that one kind (or 1 without any), so nothing is rejected for want of labels; ties and repeated rows
score alike; a text of any length is counted whole, in a piece of its own; an empty table gives no rows; other columns pass
through unless they bear a result's name.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpgrid.llm import features
from dpgrid.llm.arrow import SPACES, chunks, column, out

#: Labelled rows that are learnt from, at most; probability below which a document goes.
SAMPLE, THRESHOLD = 3000, 0.5
#: A document fails below so many words, or with more than this percentage of words in repeated windows.
LEAST_WORDS, MOST_REPEATED = 50, 50
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
_SYMBOLS, _SPACES = b"#*$%&|<>", SPACES.encode()


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a three-word window which occurs twice or more in the text."""
    n = len(words)
    if n < 4:
        return 0
    names: dict[bytes, int] = {}
    at = np.fromiter((names.setdefault(w, len(names)) for w in words), np.int64, n)
    pair = at[:-1] * len(names) + at[1:]
    if n > 2_000_000:  # else the three numbers fit into 63 bits
        pair = np.unique(pair, return_inverse=True)[1]
    window = pair[:-1] * len(names) + at[2:]
    order = np.argsort(window, kind="stable")
    same = window[order[1:]] == window[order[:-1]]
    if not same.any():
        return 0
    twice = np.zeros(n - 2, bool)
    twice[order[1:][same]] = twice[order[:-1][same]] = True
    covered = np.zeros(n, bool)
    for k in range(3):
        covered[k : n - 2 + k] |= twice
    return int(covered.sum())


def base_counts(text: bytes, words: list[bytes]) -> tuple[int, int, int, int, int]:
    """The five counts of a text, in the order of ``COUNTS``."""
    lines = [x for x in text.split(b"\n") if x.strip(_SPACES)]
    points = len(text) if text.isascii() else len(text.decode("utf-8", "replace"))
    chars = points - (len(text) - len(text.translate(None, _SPACES)))
    return len(words), chars, len(text) - len(text.translate(None, _SYMBOLS)), len(lines) - len(set(lines)), repeated_words(words)


@dataclass
class Logistic:
    """Linear score of the roots of frequencies, then the calibration line, then the logistic function."""

    weights: np.ndarray
    offset: float
    slope: float
    shift: float

    def __call__(self, x: np.ndarray) -> np.ndarray:
        z = (np.sqrt(x) @ self.weights + self.offset) * self.slope + self.shift
        return 1 / (1 + np.exp(-np.clip(z, -50, 50).astype(np.float64)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def calibrate(z: np.ndarray, y: np.ndarray, steps: int = 50) -> tuple[float, float]:
    """Slope and shift that fit probabilities to unseen rows, by Newton steps with softened targets."""
    pos, neg = y.sum(), len(y) - y.sum()
    if not pos or not neg:
        return 1.0, 0.0
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a = np.stack([z, np.ones_like(z)], 1).astype(np.float64)
    line, pull = np.array([1.0, 0.0]), 1e-3

    def loss(at: np.ndarray) -> float:
        s = a @ at
        return float((np.logaddexp(0, s) - target * s).sum() + pull / 2 * ((at - [1.0, 0.0]) ** 2).sum())

    for _ in range(steps):
        p = _sigmoid(a @ line)
        g = a.T @ (p - target) + pull * (line - [1.0, 0.0])
        step, size = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + pull * np.eye(2), g), 1.0
        while loss(line - size * step) > loss(line) and size > 1e-6:
            size /= 2
        line = line - size * step
    return (float(line[0]), float(line[1])) if np.isfinite(line).all() and line[0] > 0 else (1.0, 0.0)


def fit(x: np.ndarray, y: np.ndarray, l2: float = 1e-3, steps: int = 300) -> Logistic:
    """Logistic regression by accelerated gradient steps on scaled roots of frequencies, four fifths to fit and a fifth to calibrate."""
    x = np.sqrt(x)
    if not len(y) or y.min() == y.max():
        return Logistic(np.zeros(features.WIDTH, np.float32), 0.0, 1.0, 50.0 if not len(y) or y[0] else -50.0)
    unseen = np.arange(len(y)) % 5 == 4
    if y[~unseen].min() == y[~unseen].max():
        unseen[:] = False
    a, b = x[~unseen], y[~unseen]
    scale = 1 / (a.std(0) + 1e-4)
    mean = a.mean(0)
    s = ((a - mean) * scale).astype(np.float32)
    rate = 1 / (0.25 * _largest_eigenvalue(s) + l2)
    w = np.zeros(s.shape[1], np.float32)
    bias = float(np.log(b.mean() / (1 - b.mean())))
    v, vb = w.copy(), bias
    for t in range(steps):
        g = _sigmoid(s @ v + vb) - b
        new = v - rate * (s.T @ g.astype(np.float32) / len(b) + l2 * v)
        new_bias = vb - rate * float(g.mean())
        pull = t / (t + 3)
        v, vb = new + np.float32(pull) * (new - w), new_bias + pull * (new_bias - bias)
        w, bias = new.astype(np.float32), new_bias
    weights = (w * scale).astype(np.float32)
    offset = float(bias - mean @ weights)
    slope, shift = calibrate(x[unseen] @ weights + offset, y[unseen]) if unseen.any() else (1.0, 0.0)
    return Logistic(weights, offset, slope, shift)


def _largest_eigenvalue(s: np.ndarray, steps: int = 30) -> float:
    """Of the mean outer product of rows, by power steps, with one for the constant."""
    v = np.random.default_rng(0).standard_normal(s.shape[1]).astype(np.float32)
    size = 1.0
    for _ in range(steps):
        v = s.T @ (s @ v) / len(s)
        size = float(np.linalg.norm(v))
        v /= size + 1e-12
    return size * 1.05 + 1


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Logistic:
    """Fit on at most ``sample`` labelled rows."""
    return fit(*features.labelled_vectors(docs, labels, sample, id_col, text_col, label_col))


def apply_rules(docs: DataFrame, model: Logistic, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """``docs`` with the five counts, ``base_failed``, ``probability`` (of good quality) and ``kept``."""
    new = [*COUNTS, "base_failed", "probability", "kept"]
    passed = [f for f in docs.schema.fields if f.name not in new]
    kinds = [T.LongType()] * 5 + [T.BooleanType(), T.DoubleType(), T.BooleanType()]
    schema = T.StructType(passed + [T.StructField(n, k) for n, k in zip(new, kinds, strict=True)])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in chunks(batches, text_col):
            texts = features.texts_of(piece, text_col)
            words = [t.split() for t in texts]
            counts = np.array([base_counts(t, w) for t, w in zip(texts, words, strict=True)], np.int64).reshape(-1, 5)
            p = features.scored(model, texts, words)
            failed = (counts[:, 0] < LEAST_WORDS) | (100 * counts[:, 4] > MOST_REPEATED * counts[:, 0])
            yield out([*piece.schema.names, *new], *piece.columns, *counts.T.copy(), failed, p, ~failed & (p >= threshold))

    return docs.select(*[f.name for f in passed]).mapInArrow(score, schema)
