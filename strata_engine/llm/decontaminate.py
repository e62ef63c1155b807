"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment over words.

A first pass counts in how many documents each word n-gram of the test items occurs. An item's seeds are its rarer
n-grams; what occurs far more often than its rarest ones says little and is left out. A second pass finds seeds in each
document and aligns the item with the words around them, so that edited and paraphrased copies score high too. Texts
stay in their rows: only counts are shuffled.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import prepare_workers
from .grams import WORDS


class Items:
    """Test items as word ids over their own vocabulary, and the distinct n-grams of all of them."""

    def __init__(self, rows: list[tuple[int, str]], n: int):
        self.n, self.ids = n, [r[0] for r in rows]
        self.vocab: dict[str, int] = {}
        self.words = [np.array([self.vocab.setdefault(w, len(self.vocab)) for w in WORDS(t.lower())], dtype=np.int64) for _, t in rows]
        self.sizes = [min(n, len(w)) for w in self.words]
        grams = [self.grams(w) for w in self.words]
        self.all = np.unique(np.concatenate(grams)) if grams else np.zeros(0, dtype=np.uint64)

    def grams(self, words: np.ndarray) -> np.ndarray:
        """Packed n-grams of word ids; those with a word that no item has are 0."""
        if len(words) < self.n:
            return np.zeros(0, dtype=np.uint64)
        windows = np.lib.stride_tricks.sliding_window_view(words, self.n)
        out = np.zeros(len(windows), dtype=np.uint64)
        for k in range(self.n):
            out = out * np.uint64(len(self.vocab) + 1) + (windows[:, k] + 1).astype(np.uint64)
        out[(windows < 0).any(axis=1)] = 0
        return out

    def text(self, text: str) -> np.ndarray:
        get = self.vocab.get
        return np.array([get(w, -1) for w in WORDS(text.lower())], dtype=np.int64)

    def find(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in ``words`` where an item's n-gram starts, and its index in ``all``."""
        g = self.grams(words)
        if not len(g) or not len(self.all):
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        at = np.flatnonzero(g)
        k = np.minimum(np.searchsorted(self.all, g[at]), len(self.all) - 1)
        ok = self.all[k] == g[at]
        return at[ok], k[ok]


def align(item: np.ndarray, words: np.ndarray, match: float = 1.0, mismatch: float = -0.5, gap: float = -0.5) -> tuple[float, int, int]:
    """Best local alignment of ``item`` within ``words``: (score, first word, word after the last)."""
    m = len(words)
    h, start = np.zeros(m + 1), np.arange(m + 1)
    best = (0.0, 0, 0)
    place = np.arange(m + 1)
    for w in item:
        diag = h[:-1] + np.where(words == w, match, mismatch)
        up = h[1:] + gap
        new = np.concatenate(([0.0], np.maximum(np.maximum(diag, up), 0.0)))
        origin = np.concatenate(([0], np.where(diag >= up, start[:-1], start[1:])))
        origin = np.where(new > 0, origin, place)
        # A run of gaps along the words: the greatest of earlier scores less the gaps since.
        lifted = new - gap * place
        top = np.maximum.accumulate(lifted)
        src = np.maximum.accumulate(np.where(lifted >= top, place, 0))
        run = top + gap * place
        use = run > new
        h, start = np.where(use, run, new), np.where(use, origin[src], origin)
        k = int(h.argmax())
        if h[k] > best[0]:
            best = (float(h[k]), int(start[k]), k)
    return best


def contaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", n: int = 3, threshold: float = 0.5, rarity: float = 4.0, block_mb: float = 32.0) -> DataFrame:
    """One row per document and test item that it has a copy of: (id_col, item_id, similarity, first_word, end_word).

    ``similarity`` is the alignment's score divided by the item's words: 1 for an exact passage, ``threshold`` at least.
    An item's seeds are its n-grams in no more than ``rarity`` times as many documents as its median one, so each item
    has at least half of its n-grams. Items with fewer than ``n`` words, null or empty items and texts match nothing.
    Items go to all tasks in blocks of at most ``block_mb`` MB of text, each block against all documents. Repeated rows
    each give their own result; extra columns are not read.
    """
    spark = docs.sparkSession
    prepare_workers(spark)
    wanted = items.filter(F.col(item_text).isNotNull()).select(F.col(item_col).cast("long").alias("i"), F.col(item_text).alias("t"))
    size = wanted.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    blocks = max(1, int(np.ceil(size / (block_mb * 1e6))))
    out = None
    for b in range(blocks):
        some = wanted.filter(F.pmod(F.xxhash64("i"), F.lit(blocks)) == b) if blocks > 1 else wanted
        part = _block(docs, Items([(r["i"], r["t"]) for r in some.orderBy("i", "t").collect()], n), id_col, text_col, threshold, rarity)
        out = part if out is None else out.unionByName(part)
    return out


def _block(docs: DataFrame, items: Items, id_col: str, text_col: str, threshold: float, rarity: float) -> DataFrame:
    src = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("strata_text"))

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(items.all), dtype=np.int64)
        for batch in batches:
            for t in batch.column(0).to_pylist():
                if t:
                    total[np.unique(items.find(items.text(t))[1])] += 1
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["g", "df"])

    df = np.zeros(len(items.all), dtype=np.int64)
    if len(items.all):
        for r in src.select("strata_text").mapInArrow(count, "g long, df long").groupBy("g").agg(F.sum("df").alias("df")).collect():
            df[r["g"]] = r["df"]
    owners: dict[int, list[tuple[int, int]]] = {}
    for k, words in enumerate(items.words):
        g = items.grams(words)
        if len(g):
            own = np.searchsorted(items.all, g)
            for place in np.flatnonzero(df[own] <= rarity * max(1.0, float(np.median(df[own])))):
                owners.setdefault(int(own[place]), []).append((k, int(place)))
    rare = np.zeros(len(items.all), dtype=bool)
    rare[list(owners)] = True

    def search(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for key, t in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                if not t:
                    continue
                words = items.text(t)
                at, found = items.find(words)
                keep = rare[found]
                hits: dict[int, list[int]] = {}
                for p, g in zip(at[keep].tolist(), found[keep].tolist(), strict=True):
                    for k, place in owners[g]:
                        hits.setdefault(k, []).append(p - place)
                for k, diagonals in hits.items():
                    size = len(items.words[k])
                    slack, best = max(4, size // 2), (0.0, 0, 0)
                    reach = -1
                    for d in sorted(set(diagonals)):  # one window for seeds that lie close together
                        if d <= reach:
                            continue
                        lo, hi = max(0, d - slack), min(len(words), d + size + 2 * slack)
                        reach = d + slack
                        score, a, z = align(items.words[k], words[lo:hi])
                        if score > best[0]:
                            best = (score, a + lo, z + lo)
                    if best[0] >= threshold * size:
                        rows.append((key.as_py(), items.ids[k], best[0] / size, best[1], best[2]))
            cols = list(zip(*rows, strict=True)) or [()] * 5
            kinds = [batch.schema.field(0).type, pa.int64(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=[id_col, "item_id", "similarity", "first_word", "end_word"])

    return src.mapInArrow(search, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, item_id long, similarity double, first_word long, end_word long")
