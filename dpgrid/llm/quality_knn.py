"""Quality by the nearest labelled neighbours in a latent-semantic space.

Hashed n-gram frequencies of labelled texts are damped by a square root, centred by the region scale and reduced by a
truncated singular value decomposition. The labelled latent vectors, a bounded sample, go to every task; each document
is projected and compared with all of them, as exact cosine products of blocks, and its nearest neighbours vote with
weights that rise with similarity.

Edge cases: a null or wordless text, or any text that no labelled vector resembles, scores the label's base rate;
without labelled rows that rate is 1 and every document is kept; ties of computed similarity go to the earlier labelled row (by
id, label, hash of the text); repeated rows score alike; a null id is never held out; a text of any length is one vector, made in
a piece of its own; an empty table gives no rows; other columns pass through unless they bear a result's name.
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
from dpgrid.llm.arrow import chunks, out

#: Labelled rows at most, latent dimensions, neighbours that vote, power of similarity in a vote.
SAMPLE, LATENT, NEIGHBOURS, POWER = 3000, 64, 25, 8


def nearest(near: np.ndarray, k: int) -> np.ndarray:
    """Places of each row's ``k`` largest values; of equal ones at the border the earliest."""
    at = np.argpartition(-near, k - 1, axis=1)[:, :k]
    found = np.take_along_axis(near, at, 1)
    least = found.min(1, keepdims=True)
    for i in np.flatnonzero((near == least).sum(1) > (found == least).sum(1)):  # the border value also lies outside
        at[i] = np.argsort(-near[i], kind="stable")[:k]
    return at


@dataclass
class Neighbours:
    mean: np.ndarray
    basis: np.ndarray
    latent: np.ndarray
    labels: np.ndarray
    base: float

    def project(self, x: np.ndarray) -> np.ndarray:
        """Latent vectors of unit length; the zero vector stays zero."""
        z = (np.sqrt(x) - self.mean) @ self.basis
        z[~x.any(1)] = 0
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        """Scores from 0 to 1 of a block of vectors."""
        if not len(self.labels) or not len(x):
            return np.full(len(x), self.base)
        near = self.project(x) @ self.latent.T
        k = min(NEIGHBOURS, near.shape[1])
        at = nearest(near, k)
        weight = np.maximum(np.take_along_axis(near, at, 1).astype(np.float64), 0) ** POWER
        total = weight.sum(1)
        # A neighbour's worth of the base rate keeps unlike texts near it.
        return np.clip(((weight * self.labels[at]).sum(1) + 1e-6 * self.base) / (total + 1e-6), 0, 1)


def fit(x: np.ndarray, y: np.ndarray, latent: int = LATENT, seed: int = 7) -> Neighbours:
    """Truncated singular vectors by randomised subspace steps, then the sample's latent vectors."""
    if not len(y):
        return Neighbours(np.zeros(features.WIDTH, np.float32), np.zeros((features.WIDTH, 1), np.float32), np.zeros((0, 1), np.float32), y, 1.0)
    root = np.sqrt(x)
    mean = root.mean(0)
    a = root - mean
    r = min(latent, *a.shape)
    q = np.random.default_rng(seed).standard_normal((a.shape[1], min(r + 16, *a.shape))).astype(np.float32)
    for _ in range(4):
        q, _ = np.linalg.qr(a.T @ (a @ q))
    _, _, v = np.linalg.svd(a @ q, full_matrices=False)
    basis = (q @ v.T[:, :r]).astype(np.float32)
    model = Neighbours(mean, basis, np.zeros((0, r), np.float32), y[:0], float(y.mean()))
    some = x.any(1)
    model.latent, model.labels = model.project(x[some]), y[some]
    return model


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Neighbours:
    """Fit on at most ``sample`` labelled rows."""
    return fit(*features.labelled_vectors(docs, labels, sample, id_col, text_col, label_col))


def held_out(id_col: str = "doc_id"):
    """Rows that never train: CRC-32 of the id as text leaves 1 when divided by 3. False for a null id, which no label has."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def score(docs: DataFrame, model: Neighbours, text_col: str = "text") -> DataFrame:
    """``docs`` with ``score`` (0 to 1, higher: better) and ``predicted`` (1 from a score of one half)."""
    passed = [f for f in docs.schema.fields if f.name not in ("score", "predicted")]
    schema = T.StructType([*passed, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by SAMPLE and LATENT, not by the data

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in chunks(batches, text_col):
            s = features.scored(sent.value, features.texts_of(piece, text_col))
            yield out([*piece.schema.names, "score", "predicted"], *piece.columns, s, (s >= 0.5).astype(np.int32))

    return docs.select(*[f.name for f in passed]).mapInArrow(run, schema)
