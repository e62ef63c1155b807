"""Language identification by hyperdimensional profiles.

Every letter has a random +1/-1 vector, drawn from its code point. An n-gram's vector binds its letters' vectors, each
rotated by its place, by products; a text's vector bundles (sums) those of its n-grams, and so does a language's
prototype. Texts go to the language whose prototype has the greatest cosine with theirs.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import prepare_workers

GAP = 0x20
_letters: dict = {}


def _fold() -> np.ndarray:
    """Code point to the lower-case letter it counts as; all that is not a letter is a gap."""
    if "fold" not in _letters:
        out = np.full(0x110000, GAP, dtype=np.uint32)
        for i in range(0x110000):
            c = chr(i)
            if c.isalpha():
                low = c.lower()
                out[i] = ord(low) if len(low) == 1 else i
        _letters["fold"] = out
    return _letters["fold"]


def _letter(code: int, dims: int, seed: int) -> np.ndarray:
    key = (code, dims, seed)
    if key not in _letters:
        _letters[key] = np.random.default_rng([seed, code]).integers(0, 2, dims, dtype=np.int8) * 2 - 1
    return _letters[key]


def _gram(code: int, n: int, dims: int, seed: int) -> np.ndarray:
    """The bound vector of a packed n-gram: 21 bits a letter, the last one lowest."""
    out = np.ones(dims, dtype=np.int8)
    for place in range(n):
        out = out * np.roll(_letter(code >> (21 * place) & 0x1FFFFF, dims, seed), place)
    return out


def grams(text: str, n: int = 3) -> tuple[np.ndarray, np.ndarray] | None:
    """Distinct packed n-grams over letters and single gaps, and their counts; None without a letter."""
    codes = _fold()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    if not (codes != GAP).any():
        return None
    codes = np.concatenate((np.full(n - 2, GAP, dtype=np.uint32), [GAP], codes, [GAP])).astype(np.uint64)
    codes = codes[np.concatenate(([True], (codes[1:] != GAP) | (codes[:-1] != GAP)))]
    codes = np.concatenate((np.full(max(0, n - len(codes)), GAP, dtype=np.uint64), codes))
    packed = np.zeros(len(codes) - n + 1, dtype=np.uint64)
    for k in range(n):
        packed = (packed << np.uint64(21)) | codes[k : len(codes) - n + 1 + k]
    return np.unique(packed, return_counts=True)


class Encoder:
    """Vectors of texts; n-gram vectors are remembered, at most ``limit`` of them."""

    def __init__(self, n: int, dims: int, seed: int, limit: int = 30_000):
        self.n, self.dims, self.seed, self.limit = n, dims, seed, limit
        self.keys = np.zeros(0, dtype=np.uint64)
        self.table = np.zeros((0, dims), dtype=np.float32)

    def _rows(self, need: np.ndarray) -> np.ndarray:
        new = np.setdiff1d(need, self.keys, assume_unique=True)
        if len(self.keys) + len(new) > self.limit:
            self.keys, self.table, new = np.zeros(0, dtype=np.uint64), self.table[:0], need
        if len(new):
            made = np.stack([_gram(int(c), self.n, self.dims, self.seed) for c in new]).astype(np.float32)
            keys = np.concatenate((self.keys, new))
            order = np.argsort(keys)
            self.keys, self.table = keys[order], np.concatenate((self.table, made))[order]
        return self.table[np.searchsorted(self.keys, need)]

    def vectors(self, texts: list[str], step: int = 8192) -> tuple[np.ndarray, np.ndarray]:
        """(texts x dims bundled vectors, whether each text has a letter)."""
        out, found = np.zeros((len(texts), self.dims), dtype=np.float32), [grams(t, self.n) for t in texts]
        need = np.unique(np.concatenate([f[0] for f in found if f] or [np.zeros(0, dtype=np.uint64)]))
        for s in range(0, len(need), step):
            some = need[s : s + step]
            counts = np.zeros((len(texts), len(some)), dtype=np.float32)
            for i, f in enumerate(found):
                if f:
                    lo, hi = np.searchsorted(f[0], some[0]), np.searchsorted(f[0], some[-1], side="right")
                    counts[i, np.searchsorted(some, f[0][lo:hi])] = f[1][lo:hi]
            out += counts @ self._rows(some)
        return out, np.array([f is not None for f in found], dtype=bool)


def fit(rows: DataFrame, text_col: str = "text", lang_col: str = "lang", n: int = 3, dims: int = 512, seed: int = 7, sample: int = 20_000) -> tuple[list[str], np.ndarray]:
    """Languages and their unit prototypes, learned from the rows with a language and text.

    At most about ``sample`` rows are used (documented bound): those with the smallest hashes of text. Each text weighs
    the same. Prototypes are dims numbers a language, so what reaches the driver is languages x dims.
    """
    prepare_workers(rows.sparkSession)
    known = rows.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    total = known.select("lang").count()
    share = min(1.0, sample / max(1, total))
    taken = known.filter(F.pmod(F.xxhash64("text"), F.lit(1 << 20)) < int(share * (1 << 20)) + 1)

    def partial(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, sums = Encoder(n, dims, seed), {}
        for b in batches:
            langs, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            for s in range(0, len(texts), 128):
                vecs, has = enc.vectors(texts[s : s + 128])
                for lang, v in zip(langs[s : s + 128], vecs / np.maximum(np.linalg.norm(vecs, axis=1, keepdims=True), 1e-9), strict=True):
                    sums[lang] = sums.get(lang, 0) + v
        at = np.arange(dims)
        for lang, v in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([lang] * dims), pa.array(at, pa.int32()), pa.array(np.asarray(v, dtype=np.float64))], names=["lang", "i", "v"])

    got = taken.mapInArrow(partial, "lang string, i int, v double").groupBy("lang", "i").agg(F.sum("v").alias("v")).collect()
    langs = sorted({r["lang"] for r in got})
    out = np.zeros((len(langs), dims))
    for r in got:
        out[langs.index(r["lang"]), r["i"]] = r["v"]
    return langs, out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], id_col: str = "doc_id", text_col: str = "text", n: int = 3, dims: int = 512, seed: int = 7) -> DataFrame:
    """One row per row: (id_col, lang_pred, score): the nearest prototype and the cosine, cut at 0.

    ``und`` with score 0 for a null text, one without a letter, or a model without languages; equal cosines go to the
    language that sorts first. Whole texts are used; ids may be null or repeated, other columns are not read.
    """
    prepare_workers(docs.sparkSession)
    langs, protos = model[0], model[1].astype(np.float32)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(n, dims, seed)
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            preds, scores = [], []
            for s in range(0, len(texts), 128):
                vecs, has = enc.vectors(texts[s : s + 128])
                cos = (vecs @ protos.T) / np.maximum(np.linalg.norm(vecs, axis=1, keepdims=True), 1e-9) if langs else np.zeros((len(vecs), 0))
                for row, ok in zip(cos, has, strict=True):
                    k = int(row.argmax()) if ok and langs else -1
                    preds.append(langs[k] if k >= 0 else "und")
                    scores.append(float(min(1.0, max(0.0, row[k]))) if k >= 0 else 0.0)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(preds, pa.string()), pa.array(scores, pa.float64())], names=[id_col, "lang_pred", "score"])

    src = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("strata_text"))
    return src.mapInArrow(work, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, lang_pred string, score double")
