"""Toxicity scores by FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Every coordinate has its own learning rate, and an L1 term keeps a weight at zero until its gradients insist. What is
left is a short list of hashed features and weights that goes with the scoring tasks.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import prepare_workers
from .grams import mix, pairs, word_hashes


def features(text: str, bits: int = 20, skips: int = 2) -> np.ndarray:
    """Distinct hashed words (lower half of the index space), word pairs and pairs with up to ``skips`` words between them."""
    h = word_hashes(text)
    if not len(h):
        return np.zeros(0, dtype=np.int64)
    every = np.concatenate([mix(h + np.uint64(1)), *(pairs(h, g, 1 + g) for g in range(1, skips + 2))])
    at = (every >> np.uint64(65 - bits)).astype(np.int64)
    at[len(h) :] += 1 << (bits - 1)
    return np.unique(at)


def ftrl(rows: Iterable[tuple[np.ndarray, int]], bits: int, alpha: float, beta: float, l1: np.ndarray, l2: float, epochs: int) -> tuple[np.ndarray, np.ndarray, float]:
    """Indexes and values of the weights that aren't zero, and the intercept; ``l1`` is given for every coordinate."""
    z, n = np.zeros(1 << bits), np.zeros(1 << bits)
    z0 = n0 = 0.0
    rows = list(rows)
    for _ in range(epochs):
        for f, y in rows:
            zf, root, cut = z[f], np.sqrt(n[f]), l1[f]
            w = np.where(np.abs(zf) <= cut, 0.0, -(zf - np.sign(zf) * cut) / ((beta + root) / alpha + l2))
            b = -z0 / ((beta + n0**0.5) / alpha)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum() + b, -35, 35))) - y
            z[f] = zf + g - (np.sqrt(root * root + g * g) - root) / alpha * w
            n[f] += g * g
            z0 += g - ((n0 + g * g) ** 0.5 - n0**0.5) / alpha * b
            n0 += g * g
    at = np.flatnonzero(np.abs(z) > l1)
    return at, -(z[at] - np.sign(z[at]) * l1[at]) / ((beta + np.sqrt(n[at])) / alpha + l2), float(-z0 / ((beta + n0**0.5) / alpha))


def fit(rows: DataFrame, text_col: str = "text", label_col: str = "toxic", bits: int = 20, skips: int = 2, alpha: float = 3.0, beta: float = 1.0, l1: float = 2.0, pair_l1: float = 6.0, l2: float = 0.0, epochs: int = 3, sample: int = 16_000) -> tuple[np.ndarray, np.ndarray, float]:
    """Weights learned from the rows with a label (0 or 1) and text; null texts count as empty.

    The learner is sequential, so at most about ``sample`` rows (documented bound; those with the smallest hashes of
    text) reach the one task that runs it, as features; they are taken in the order of their hashes, so that the result
    doesn't depend on the partitions. Pairs far outnumber words and most are seen once or twice, so they have a greater
    L1 term. Without rows the model scores 0.5 everywhere.
    """
    prepare_workers(rows.sparkSession)
    known = rows.filter(F.col(label_col).isin(0, 1)).select(F.coalesce(F.col(text_col), F.lit("")).alias("text"), F.col(label_col).cast("int").alias("y"))
    share = min(1.0, sample / max(1, known.select("y").count()))
    penalty = np.repeat([l1, pair_l1], 1 << (bits - 1))
    order = F.xxhash64("text")
    taken = known.withColumn("at", order).filter(F.pmod("at", F.lit(1 << 20)) < int(share * (1 << 20)) + 1)

    def featurise(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(1), b.column(2), pa.array([features(t, bits, skips).astype("<i4").tobytes() for t in b.column(0).to_pylist()], pa.binary())], names=["y", "at", "f"])

    def learn(table: pa.Table) -> pa.Table:
        table = table.sort_by([("at", "ascending"), ("y", "ascending")])
        at, w, b = ftrl(((np.frombuffer(f, dtype="<i4"), y) for f, y in zip(table["f"].to_pylist(), table["y"].to_pylist(), strict=True)), bits, alpha, beta, penalty, l2, epochs)
        return pa.table({"at": pa.array(np.concatenate((at, [-1])), pa.int64()), "w": pa.array(np.concatenate((w, [b])), pa.float64())})

    got = taken.mapInArrow(featurise, "y int, at long, f binary").withColumn("one", F.lit(1)).groupBy("one").applyInArrow(learn, "at long, w double").collect()
    at = np.array([r["at"] for r in got if r["at"] >= 0], dtype=np.int64)
    return at, np.array([r["w"] for r in got if r["at"] >= 0]), float(sum(r["w"] for r in got if r["at"] < 0))


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray, float], id_col: str = "doc_id", text_col: str = "text", bits: int = 20, skips: int = 2) -> DataFrame:
    """One row per row: (id_col, score, predicted). Null and empty texts get the intercept's score; nothing else is read."""
    prepare_workers(docs.sparkSession)
    at, w, b0 = model

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = np.zeros(1 << bits)
        weights[at] = w
        for b in batches:
            raw = np.array([weights[features(t or "", bits, skips)].sum() + b0 for t in b.column(1).to_pylist()])
            s = 1.0 / (1.0 + np.exp(-np.clip(raw, -35, 35)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32), pa.int32())], names=[id_col, "score", "predicted"])

    src = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("strata_text"))
    return src.mapInArrow(work, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, score double, predicted int")
