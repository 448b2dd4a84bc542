"""Toxicity: a factorization machine over hashed terms.

Terms are lower-cased alphanumeric words and their beginnings of 4 to 8 bytes, as 64-bit hashes, so
that inflected forms share a term. From a bounded sample of labelled texts (``most``), of near copies
one each, Spark counts each term's texts by class and chooses the terms that go with a class beyond
chance (at most ``terms``). Terms that say nothing alone are let in by pair: over the ``pair_terms``
most frequent terms of the sample, the classes of the texts that hold both terms are held against
what the two give by themselves. A second-order factorization machine over the indicators is fitted
by Adam on the logistic loss, so pairs of terms count beyond the sum of their weights. Every text
is scored whole.

Defined results: null and empty texts score the model's bias; without labels of both classes every
score is the smoothed share of label 1; ids may be of any type; repeated rows give a row each; a
score of exactly one half predicts 1; very long texts are read whole, one at a time; other columns
are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.hashing import NOT_ALNUM, list_array, pieces, shingle_hashes, uniques, word_hashes
from bucketseed.llm.labelled import crc_fold, labelled_sample
from bucketseed.staging import staged

BEGINNINGS = (4, 5, 6, 7, 8)
#: A pair of terms is judged if so many texts of the sample hold both.
PAIR_TEXTS = 12
#: Columns whose pairs are judged at once on the driver.
BLOCK = 128


def term_hashes(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's terms, repeats included, and where each text's begin."""
    return word_hashes(data, offs, NOT_ALNUM, beginnings=BEGINNINGS)


@dataclass
class Model:
    """Sorted term hashes with their weights and factors."""

    terms: np.ndarray
    weight: np.ndarray
    factors: np.ndarray
    bias: float

    def hits(self, words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (text, term) places of the model's terms."""
        if not len(self.terms) or not len(words):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        at = np.minimum(np.searchsorted(self.terms, words), len(self.terms) - 1)
        found = np.flatnonzero(self.terms[at] == words)
        text = np.searchsorted(first, found, side="right") - 1
        both = np.unique(text * len(self.terms) + at[found])
        return both // len(self.terms), both % len(self.terms)

    def score(self, words: np.ndarray, first: np.ndarray) -> np.ndarray:
        n = len(first) - 1
        text, term = self.hits(words, first)
        raw = self.bias + np.bincount(text, self.weight[term], n)
        for f in range(self.factors.shape[1]):
            v = self.factors[term, f]
            raw = raw + 0.5 * (np.bincount(text, v, n) ** 2 - np.bincount(text, v * v, n))
        return 1 / (1 + np.exp(-np.clip(raw, -40, 40)))


def term_counts(features: DataFrame) -> DataFrame:
    """(t, a, texts): each term's texts, and those of class 1."""
    return (
        features.select("y", F.explode("terms").alias("t"))
        .groupBy("t")
        .agg(F.sum("y").alias("a"), F.count("*").alias("texts"))
    )


def choose_terms(counts: DataFrame, n: int, pos: int, most: int, least_z: float, least_texts: int) -> DataFrame:
    """(t) the terms whose texts' classes differ from chance by the largest standard scores."""
    a, texts = F.col("a"), F.col("texts")
    spread = texts * (pos / n) * (1 - pos / n) * (n - texts) / max(n - 1, 1)
    return (
        counts.filter((texts >= least_texts) & (texts < n))
        .withColumn("z", F.abs(a - texts * (pos / n)) / F.sqrt(spread))
        .filter(F.col("z") >= least_z)
        .orderBy(F.desc("z"), "t")
        .limit(most)
        .select("t")
    )


def paired(x: np.ndarray, y: np.ndarray, least_z: float, most: int) -> np.ndarray:
    """Columns of the 0/1 matrix ``x`` that go with a class only together with another column.

    A pair's texts of class 1 are held against the sum of what either column adds to the base rate.
    The columns of the ``most`` strongest pairs beyond ``least_z`` come back.
    """
    n, base, positive = len(y), float((y > 0).mean()), x[y > 0]
    size = x.sum(0, dtype=np.float64)
    alone = positive.sum(0, dtype=np.float64) / np.maximum(size, 1)
    floor, found = 1 / (n + 2), []
    for at in range(0, x.shape[1], BLOCK):
        own = slice(at, at + BLOCK)
        both, both_hit = x[:, own].T @ x, positive[:, own].T @ positive
        expected = np.clip(alone[own, None] + alone[None] - base, floor, 1 - floor)
        # a rate known from few texts is no firm expectation: the spread has at least the base rate's
        spread = both * np.maximum(expected * (1 - expected), base * (1 - base))
        z = np.abs(both_hit - both * expected) / np.sqrt(np.maximum(spread, 1e-9))
        z[both < PAIR_TEXTS] = 0
        # columns that (nearly) always come together are one term to the classes
        z[both > 0.9 * np.minimum(size[own, None], size[None])] = 0
        first, second = np.nonzero(np.triu(z >= least_z, at + 1))
        found.append((z[first, second], first + at, second))
    z, first, second = (np.concatenate(parts) for parts in zip(*found, strict=True))
    best = np.argsort(-z, kind="stable")[:most]
    return np.unique(np.concatenate([first[best], second[best]]))


def descend(x: np.ndarray, y: np.ndarray, rank: int, epochs: int, decay: float) -> tuple:
    """Adam on the mean logistic loss over all rows; x holds 0/1 indicators."""
    rng = np.random.default_rng(11)
    parts = [np.zeros(1), np.zeros(x.shape[1]), rng.normal(0, 0.05, (x.shape[1], rank))]
    first, second = [np.zeros_like(p) for p in parts], [np.zeros_like(p) for p in parts]
    target = (y > 0).astype(float)
    single = lambda a: a.astype(x.dtype)  # noqa: E731  else numpy makes a double copy of x each time
    for step in range(1, epochs + 1):
        bias, w, v = parts
        s = (x @ single(v)).astype(float)
        raw = bias[0] + x @ single(w) + 0.5 * ((s**2).sum(1) - x @ single((v**2).sum(1)))
        err = (1 / (1 + np.exp(-np.clip(raw, -40, 40))) - target) / len(y)
        grads = [
            np.array([err.sum()]),
            x.T @ single(err) + decay * w,
            x.T @ single(err[:, None] * s) - (x.T @ single(err))[:, None] * v + decay * v,
        ]
        for i, g in enumerate(grads):
            first[i] = 0.9 * first[i] + 0.1 * g
            second[i] = 0.999 * second[i] + 0.001 * g * g
            parts[i] = parts[i] - 0.05 * (first[i] / (1 - 0.9**step)) / (
                np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8
            )
    return parts


def fit(
    docs: DataFrame,
    labels: DataFrame,
    train: Column,
    label: str = "toxic",
    most: int = 8000,
    terms: int = 1024,
    least_z: float = 6.0,
    least_texts: int = 4,
    rank: int = 4,
    epochs: int = 300,
    decay: float = 1e-4,
    pair_terms: int = 2048,
    pairs: int = 128,
    pair_z: float = 8.0,
) -> Model:
    def features(batches):
        for batch, data, offs in pieces(batches):
            found, first = uniques(*term_hashes(data, offs))
            shingles, at = shingle_hashes(*word_hashes(data, offs))
            sketch = [int(shingles[a:b].min() >> np.uint64(1)) if b > a else -1 for a, b in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("h"), batch.column("y"), pa.array(sketch, pa.int64()), list_array(found, first)],
                ["h", "y", "sketch", "terms"],
            )

    sample = staged(
        labelled_sample(docs, labels, label, train, most)
        .mapInArrow(features, "h bigint, y int, sketch bigint, terms array<bigint>")
        .groupBy("sketch", "y")
        .agg(F.min(F.struct("h", "terms")).alias("f"))
        .select("f.h", "y", "f.terms"),
        "terms",
    )
    count = {r["y"]: r["count"] for r in sample.groupBy("y").count().collect()}
    prior = (count.get(1, 0) + 1) / (sum(count.values()) + 2)
    empty = Model(np.zeros(0, np.uint64), np.zeros(0), np.zeros((0, rank)), float(np.log(prior / (1 - prior))))
    if len(count) < 2:
        return empty
    n, pos = sum(count.values()), count.get(1, 0)
    counts = staged(term_counts(sample).filter(F.col("texts") >= least_texts), "term-counts")
    single = choose_terms(counts, n, pos, terms, least_z, least_texts).toArrow()["t"].to_numpy()
    frequent = (
        counts.filter((F.col("texts") >= PAIR_TEXTS) & (F.col("texts") < n))
        .orderBy(F.desc("texts"), "t")
        .limit(pair_terms)
        .toArrow()["t"]
        .to_numpy()
    )
    chosen = np.unique(np.concatenate([single, frequent]).astype(np.int64).view(np.uint64))
    if not len(chosen):
        return empty

    def marked(batches):
        for batch in batches:
            cells = batch.column("terms").to_pylist()
            at = [np.flatnonzero(np.isin(chosen, np.array(c, np.int64).view(np.uint64))).tolist() for c in cells]
            yield pa.RecordBatch.from_arrays(
                [batch.column("h"), batch.column("y"), pa.array(at, pa.list_(pa.int64()))], ["h", "y", "x"]
            )

    # at most ``most`` rows of at most ``terms`` + ``pair_terms`` cells
    table = sample.mapInArrow(marked, "h bigint, y int, x array<bigint>").toArrow().sort_by("h")
    y = np.where(table["y"].to_numpy() == 1, 1.0, -1.0)
    cells = table["x"].combine_chunks()
    row, col = np.repeat(np.arange(len(y)), np.diff(cells.offsets.to_numpy())), cells.flatten().to_numpy()
    del table, cells

    def matrix(columns: np.ndarray) -> np.ndarray:
        place = np.full(len(chosen), -1)
        place[columns] = np.arange(len(columns))
        there = place[col] >= 0
        x = np.zeros((len(y), len(columns)), np.float32)
        x[row[there], place[col[there]]] = 1
        return x

    alone = np.isin(chosen, single.astype(np.int64).view(np.uint64))
    often = np.flatnonzero(np.isin(chosen, frequent.astype(np.int64).view(np.uint64)))
    alone[often[paired(matrix(often), y, pair_z, pairs)]] = True
    kept = np.flatnonzero(alone)
    if not len(kept):
        return empty
    chosen, x = chosen[kept], matrix(kept)
    bias, w, v = descend(x, y, rank, epochs, decay)
    return Model(chosen, w, v, float(bias[0]))


def score(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """(doc_id, score) for every row."""

    def scored(batches):
        for batch, data, offs in pieces(batches):
            values = model.score(*term_hashes(data, offs))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(values)], ["doc_id", "score"]
            )

    rows = docs.select("doc_id", F.col(text).alias("text"))
    return rows.mapInArrow(scored, f"doc_id {dict(rows.dtypes)['doc_id']}, score double")


def without_toxic(docs: DataFrame, model: Model, least: float = 0.5, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that score below ``least``, with all their columns, in one pass."""

    def kept(batches):
        for batch, data, offs in pieces(batches, text):
            yield batch.filter(pa.array(model.score(*term_hashes(data, offs)) < least))

    return docs.mapInArrow(kept, docs.schema)


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    docs = load(spark, sf_dir, "documents")
    fold = crc_fold("doc_id", 5)
    model = fit(docs, load(spark, sf_dir, "labels"), fold != 0)
    return score(docs, model).select(
        "doc_id",
        (fold == 0).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
    )
