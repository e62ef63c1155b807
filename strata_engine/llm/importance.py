"""Quality selection by importance resampling.

Two generative models over hashed word n-grams, one of target text and one of the raw corpus, give each document a log
ratio of likelihoods; adding Gumbel noise and taking the greatest keys samples without replacement in proportion to
the ratios.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import prepare_workers, stage
from .grams import mix, pairs, word_hashes


def buckets_of(text: str, buckets: int) -> np.ndarray:
    h = word_hashes(text)
    return (np.concatenate((mix(h + np.uint64(1)), pairs(h, 1, 2))) % np.uint64(buckets)).astype(np.int64)


def counts(docs: DataFrame, text_col: str, buckets: int) -> np.ndarray:
    """Occurrences of each hashed n-gram over all rows: fixed-size partial sums, added up by bucket."""
    prepare_workers(docs.sparkSession)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(buckets, dtype=np.int64)
        for b in batches:
            for t in b.column(0).to_pylist():
                if t:
                    total += np.bincount(buckets_of(t, buckets), minlength=buckets)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(total[at], pa.int64())], names=["i", "c"])

    out = np.zeros(buckets, dtype=np.int64)
    for r in docs.select(F.col(text_col).cast("string").alias("t")).mapInArrow(work, "i int, c long").groupBy("i").agg(F.sum("c").alias("c")).collect():
        out[r["i"]] = r["c"]
    return out


def log_ratios(docs: DataFrame, target: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int = 10_000) -> DataFrame:
    """(id_col, n_grams, log_weight) for every row: log-likelihood ratio of target to raw, summed over the text's n-grams.

    Both models count all their rows and are smoothed by one. A null or empty text has ratio 0.
    """
    t, r = counts(target, text_col, buckets) + 1.0, counts(docs, text_col, buckets) + 1.0
    ratio = np.log(t / t.sum()) - np.log(r / r.sum())

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [buckets_of(x or "", buckets) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(f) for f in found], pa.int64()), pa.array([float(ratio[f].sum()) for f in found], pa.float64())], names=[id_col, "n_grams", "log_weight"])

    src = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("strata_text"))
    return src.mapInArrow(work, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, n_grams long, log_weight double")


def greatest(df: DataFrame, key: str, tie: str, k: int, bins: int = 1000, small: int = 10_000) -> DataFrame:
    """The ``k`` rows with the greatest ``key``; equal keys by the smallest ``tie``. Exact, without a global sort.

    Histograms close in on the k-th key; only rows of the last bin, at most ``small`` unless keys tie, are ranked.
    """
    lo, hi, n = df.agg(F.min(key), F.max(key), F.count("*")).first()
    if k >= n:
        return df
    if k <= 0:
        return df.limit(0)
    above = 0  # rows over hi
    inside = n
    while inside > small and hi > lo:
        width = (hi - lo) / bins
        if width <= 0 or lo + width == lo:
            break
        at = F.least(F.floor((F.col(key) - lo) / width), F.lit(bins - 1)).cast("int")
        hist = {r["at"]: (r["n"], r["lo"], r["hi"]) for r in df.filter(F.col(key).between(lo, hi)).groupBy(at.alias("at")).agg(F.count("*").alias("n"), F.min(key).alias("lo"), F.max(key).alias("hi")).collect()}
        for b in sorted(hist, reverse=True):
            if above + hist[b][0] >= k:
                shrunk = hist[b][0] < inside
                inside, lo, hi = hist[b]
                break
            above += hist[b][0]
        if not shrunk:
            break
    edge = df.filter(F.col(key).between(lo, hi)).withColumn("strata_rank", F.row_number().over(Window.orderBy(F.col(key).desc(), F.col(tie).asc_nulls_last())))
    return df.filter(F.col(key) > hi).unionByName(edge.filter(F.col("strata_rank") <= k - above).drop("strata_rank"))


def resample(docs: DataFrame, target: DataFrame, share: float, id_col: str = "doc_id", text_col: str = "text", buckets: int = 10_000, seed: int = 11) -> DataFrame:
    """The sampled rows: (id_col, n_grams, log_weight, gumbel_key); their number is ``share`` of all rows, rounded.

    The noise follows from the id and the seed, so the sample is the same on every run and for every partitioning; rows
    with equal ids get equal noise, and a null id is a value like others. An empty table gives an empty result.
    """
    weighed = log_ratios(docs, target, id_col, text_col, buckets)
    u = (F.pmod(F.xxhash64(F.lit(seed), F.col(id_col)), F.lit(1 << 52)) + F.lit(0.5)) / F.lit(float(1 << 52))
    keyed, _ = stage(weighed.withColumn("gumbel_key", F.col("log_weight") - F.log(-F.log(u))), "weights")
    return greatest(keyed, "gumbel_key", id_col, round(share * keyed.count()))
