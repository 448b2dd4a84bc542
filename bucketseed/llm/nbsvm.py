"""Quality classifier: naive Bayes log-count ratios scale n-gram indicators of a linear SVM.

Indicators are hashed words, word pairs and byte 4-grams of the lower-cased text. Each is scaled
by its class log-count ratio, each text's vector is brought to length one, and a linear hinge-loss
model is fitted by dual coordinate descent. A sigmoid fitted on a fifth of the sample that the SVM
doesn't see turns margins into scores. Only the fit uses a bounded sample (``most``); every text
is scored whole, row by row, with no shuffle.

Defined results: null, empty and very long texts get a score, the last read whole; without labels
of both classes the score is the smoothed share of label 1; ids may be of any type; repeated rows
give a row each; a score of exactly one half predicts 1; other columns are ignored; an empty table
gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.hashing import LOWER, mix, pieces, word_hashes
from bucketseed.llm.labelled import crc_fold, labelled_sample

BITS = 18


def indicators(data: np.ndarray, offs: np.ndarray) -> Iterator[np.ndarray]:
    """For each text, the distinct hashed n-grams it holds, sorted."""
    words, first = word_hashes(data, offs)
    shift = np.uint64(64 - BITS)
    ones = (words >> shift).astype(np.int32)
    pairs = (mix(words[:-1] * np.uint64(3) + words[1:]) >> shift).astype(np.int32)
    low = LOWER[data].astype(np.uint32)
    n = max(len(low) - 3, 0)
    code = low[:n] | (low[1 : n + 1] << 8) | (low[2 : n + 2] << 16) | (low[3 : n + 3] << 24)
    quads = ((code * np.uint32(2654435761)) >> np.uint32(32 - BITS)).astype(np.int32)
    for i in range(len(offs) - 1):
        a, b = first[i], first[i + 1]
        yield np.unique(
            np.concatenate(
                [ones[a:b], pairs[a : max(b - 1, a)], quads[offs[i] : max(offs[i + 1] - 3, offs[i])]]
            )
        )


@dataclass
class Model:
    """Weight and squared scale by hashed n-gram; ``slope`` and ``shift`` of the sigmoid."""

    weight: np.ndarray
    scale2: np.ndarray
    slope: float
    shift: float

    def margin(self, x: np.ndarray) -> float:
        norm = float(self.scale2[x].sum())
        return float(self.weight[x].sum()) / norm**0.5 if norm > 0 else 0.0

    def score(self, margins: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * margins + self.shift, -40, 40)))


def dual_descent(
    rows: list[np.ndarray], y: np.ndarray, scale: np.ndarray, cost: float, epochs: int
) -> np.ndarray:
    """Weights over scaled, normalised indicators; classes weigh the same in the loss."""
    w = np.zeros(len(scale))
    values = [scale[x] / max(float(np.sqrt((scale[x] ** 2).sum())), 1e-12) for x in rows]
    share = max(float((y > 0).mean()), 1e-9)
    most = np.where(y > 0, cost * 0.5 / share, cost * 0.5 / max(1 - share, 1e-9))
    alpha, order = np.zeros(len(rows)), np.random.default_rng(7)
    for _ in range(epochs):
        for i in order.permutation(len(rows)):
            x, v = rows[i], values[i]
            if len(x):
                new = min(max(alpha[i] + 1 - y[i] * float(w[x] @ v), 0.0), most[i])
                if new != alpha[i]:
                    w[x] += (new - alpha[i]) * y[i] * v
                    alpha[i] = new
    return w


def _sigmoid(m: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift by damped Newton steps on smoothed targets."""
    pos, neg = float((y > 0).sum()), float((y < 0).sum())
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    beta = np.array([1.0, 0.0])
    design = np.stack([m, np.ones_like(m)], 1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(design @ beta, -40, 40)))
        grad = design.T @ (p - target) + 1e-3 * beta
        hess = (design * (p * (1 - p))[:, None]).T @ design + 1e-3 * np.eye(2)
        beta -= np.clip(np.linalg.solve(hess, grad), -2, 2)
    return float(max(beta[0], 1e-3)), float(beta[1])


def fit(
    docs: DataFrame,
    labels: DataFrame,
    train: Column,
    label: str = "quality",
    most: int = 6000,
    cost: float = 4.0,
    epochs: int = 12,
) -> Model:
    """Fit on at most ``most`` labelled texts (see ``labelled_sample``)."""

    def features(batches):
        for batch, data, offs in pieces(batches):
            found = [x.astype(np.int32).tobytes() for x in indicators(data, offs)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("h"), batch.column("y"), pa.array(found, pa.binary())],
                ["h", "y", "x"],
            )

    table = (
        labelled_sample(docs, labels, label, train, most)
        .mapInArrow(features, "h bigint, y int, x binary")
        .toArrow()
    )
    cells = table["x"].to_pylist()
    hashes = table["h"].to_numpy()
    order = sorted(range(len(cells)), key=lambda i: (hashes[i], cells[i]))
    y = np.where(table["y"].to_numpy() == 1, 1.0, -1.0)[order]
    rows = [np.frombuffer(cells[i], np.int32) for i in order]
    size = 1 << BITS
    if not len(y) or y.min() == y.max():
        prior = (float((y > 0).sum()) + 1) / (len(y) + 2)
        return Model(np.zeros(size, np.float32), np.zeros(size, np.float32), 1.0, float(np.log(prior / (1 - prior))))
    counts = {c: np.ones(size) for c in (-1.0, 1.0)}
    for x, c in zip(rows, y, strict=True):
        counts[c][x] += 1
    ratio = np.log(counts[1.0] / counts[1.0].sum()) - np.log(counts[-1.0] / counts[-1.0].sum())
    held = np.arange(len(y)) % 5 == 4
    if len(set(y[~held])) < 2 or len(set(y[held])) < 2:
        held[:] = False
    fitted = [i for i in range(len(y)) if not held[i]]
    w = dual_descent([rows[i] for i in fitted], y[fitted], ratio, cost, epochs)
    model = Model((w * ratio).astype(np.float32), (ratio**2).astype(np.float32), 1.0, 0.0)
    seen = np.flatnonzero(held) if held.any() else np.arange(len(y))
    model.slope, model.shift = _sigmoid(np.array([model.margin(rows[i]) for i in seen]), y[seen])
    return model


def score(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """(doc_id, score) for every row."""

    def scored(batches):
        for batch, data, offs in pieces(batches):
            margins = np.array([model.margin(x) for x in indicators(data, offs)])
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(model.score(margins))], ["doc_id", "score"]
            )

    rows = docs.select("doc_id", F.col(text).alias("text"))
    return rows.mapInArrow(scored, f"doc_id {dict(rows.dtypes)['doc_id']}, score double")


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    docs = load(spark, sf_dir, "documents")
    fold = crc_fold("doc_id", 3)
    model = fit(docs, load(spark, sf_dir, "labels"), fold != 1)
    return score(docs, model).select(
        "doc_id",
        (fold == 1).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
    )
