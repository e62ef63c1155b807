"""SimHash near-duplicates with bit-sliced comparison.

Fingerprints are compared in blocks that an exact pigeonhole key yields: 64 bits in ``radius + 2`` parts, of which any
two fingerprints within the radius share two, so that each pair meets under one of the part pairs. Fingerprints in the order
of their keys are stored vertically, 64 bit planes with a machine word for 64 neighbours. Planes against themselves,
shifted, give the differing bits of 64 pairs a word; three carry-save counter planes and an overflow plane update all
distances at once, and 64 pairs are given up once all are beyond the radius. Groups of one key with too many fingerprints
are keyed again by parts of the bits that are left, which stays exact.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parts, prepare_workers, remove_path, stage
from .components import components, with_least

WIDTH = 4
SEED = 42


def fingerprint(text: bytes, width: int = WIDTH, seed: int = SEED) -> int:
    """SimHash of the shingles of ``width`` words; A-Z count as a-z, words are what ASCII white space leaves."""
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    digest = xxhash.xxh64_digest
    if len(words) <= width:
        hashes = digest(joined, seed)
    else:
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))
        hashes = b"".join([digest(joined[s:e], seed) for s, e in zip(starts[: len(words) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)])
    bits = np.unpackbits(np.frombuffer(hashes, dtype=np.uint8).reshape(-1, 8), axis=1)
    ones = bits.sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(bits)).tobytes(), "big")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """(id_col, fp long) for every row; null and blank texts have fingerprint 0, other columns are not read."""
    prepare_workers(docs.sparkSession)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([_signed(fingerprint(t or b"", width, seed)) for t in b.column(1).to_pylist()], pa.int64())], names=[id_col, "fp"])

    src = docs.select(F.col(id_col), F.col(text_col).cast("string").cast("binary").alias("strata_text"))
    return src.mapInArrow(work, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, fp long")


class Planes:
    """Fingerprints stored vertically: word w of plane k holds bit k of fingerprints 64 w to 64 w + 63."""

    def __init__(self, fps: np.ndarray, at_once: int = 1 << 16):
        self.words = np.zeros((64, len(fps) // 64 + 2), dtype=np.uint64)  # shifted reads run into a spare word of zeros
        packed = self.words.view(np.uint8)
        for s in range(0, len(fps), at_once):
            bits = np.unpackbits(np.ascontiguousarray(fps[s : s + at_once]).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            some = np.packbits(bits.T, axis=1, bitorder="little")
            packed[:, s // 8 : s // 8 + some.shape[1]] = some

    def near(self, at: np.ndarray, step: int, radius: int) -> np.ndarray:
        """Those of the ascending places ``at`` whose fingerprint is within ``radius`` (up to 7) bits of the one ``step`` further on.

        64 neighbouring places are a block. Two planes at a time enter the counters of all blocks; blocks whose places have
        all gone beyond the radius are given up.
        """
        if not len(at):
            return at
        first = np.flatnonzero(np.diff(at >> 6, prepend=-1))
        block = at[first] >> 6
        live = np.bitwise_or.reduceat(np.uint64(1) << (at & 63).astype(np.uint64), first)
        far, shift = step >> 6, np.uint64(step & 63)
        rest = np.uint64(64) - shift
        one, two, four, over = (np.zeros(len(block), dtype=np.uint64) for _ in range(4))

        def differ(plane: np.ndarray) -> np.ndarray:
            other = plane[block + far]
            if shift:
                # places that reach beyond the last fingerprint are none of ``at``
                other = other >> shift | plane[np.minimum(block + far + 1, len(plane) - 1)] << rest
            return plane[block] ^ other

        for k in range(0, 64, 2):
            x, y = differ(self.words[k]), differ(self.words[k + 1])
            half = x ^ y
            carry = (x & y) | (one & half)  # a full adder takes two planes at a time
            one = one ^ half
            up = two & carry
            two = two ^ carry
            over |= four & up
            four = four ^ up
            if k % 8 == 6:
                live &= ~(over | _beyond(one, two, four, radius))
                left = np.flatnonzero(live)
                if not len(left):
                    return at[:0]
                if 4 * len(left) < 3 * len(live):
                    block, live, one, two, four, over = (c[left] for c in (block, live, one, two, four, over))
        bits = np.unpackbits(live.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        i, lane = np.nonzero(bits)
        return block[i] * 64 + lane


def _beyond(one, two, four, radius: int):
    """Where the three-bit counters exceed ``radius``."""
    more, same = np.zeros_like(one), ~np.zeros_like(one)
    for plane, bit in ((four, 4), (two, 2), (one, 1)):
        if radius & bit:
            same = same & plane
        else:
            more, same = more | (same & plane), same & ~plane
    return more


def _links(fps: np.ndarray, keys: list[np.ndarray], radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal keys, thinned to a spanning star of each local component."""
    order = np.lexsort(keys)
    fps = fps[order]
    same = np.ones(len(fps), dtype=bool)
    same[:1] = False
    for k in keys:
        k = k[order]
        same[1:] &= k[1:] == k[:-1]
    head = np.flatnonzero(~same)
    sizes = np.diff(np.concatenate((head, [len(fps)])))
    left = np.repeat(head + sizes, sizes) - np.arange(len(fps)) - 1  # partners after each one in its run
    planes, label, step = Planes(fps), np.arange(len(fps)), 1
    while True:
        at = np.flatnonzero(left >= step)
        if not len(at):
            break
        at = at[label[at] != label[at + step]]  # what is linked already needs no comparison
        for s in range(0, len(at), 1 << 16):
            a = at[s : s + (1 << 16)]
            a = planes.near(a, step, radius)
            b = a + step
            while (label[a] != label[b]).any():  # roots sink to the smallest place of the component
                x, y = label[a], label[b]
                np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
                while (label != label[label]).any():
                    label = label[label]
        step += 1
    moved = np.flatnonzero(label != np.arange(len(fps)))
    return fps[moved], fps[label[moved]]


def _masks(radius: int) -> list[int]:
    parts_ = [range(p, 64, radius + 2) for p in range(radius + 2)]
    mask = lambda bits: sum(1 << b for b in bits)
    return [mask(parts_[i]) | mask(parts_[j]) for i, j in combinations(range(radius + 2), 2)]


def _finer(mask: int, radius: int) -> list[int]:
    """Pigeonhole once more: one of ``radius + 1`` parts of the bits outside ``mask`` agrees as well."""
    rest = [b for b in range(64) if not mask >> b & 1]
    return [mask | sum(1 << b for b in rest[p :: radius + 1]) for p in range(radius + 1)]


def near_links(nodes: DataFrame, radius: int = 4, cap: int = 2048, levels: int = 3) -> DataFrame:
    """(a, b: long) links whose components are those of all pairs of distinct ``fp`` within ``radius`` bits.

    ``nodes`` has a distinct ``fp``. Only candidate keys, never pairs, are shuffled. A block of more than ``cap``
    fingerprints is keyed again by more bits, at most ``levels`` - 1 times; what is still larger is compared as it is.
    """
    spark = nodes.sparkSession
    masks = _masks(radius)
    rows = nodes.select("fp", F.explode(F.array(*[F.lit(_signed(m)) for m in masks])).alias("mask")).withColumn("key", F.expr("fp & mask"))
    ready = None
    for level in range(1, levels):
        crowded = rows.groupBy("mask", "key").count().filter(F.col("count") > cap).drop("count")
        if crowded.isEmpty():
            break
        crowded = crowded.withColumn("crowded", F.lit(True))
        marked = rows.join(crowded, ["mask", "key"], "left")
        keep = marked.filter("crowded is null").drop("crowded")
        ready = keep if ready is None else ready.unionByName(keep)
        finer = F.create_map(*[x for m in masks for x in (F.lit(_signed(m)), F.array(*[F.lit(_signed(f)) for f in _finer(m, radius)]))])
        rows = marked.filter("crowded").select("fp", F.explode(finer[F.col("mask")]).alias("mask")).withColumn("key", F.expr("fp & mask"))
        masks = [f for m in masks for f in _finer(m, radius)]
    rows = rows if ready is None else ready.unionByName(rows)
    slots = parts(spark) * 4

    def work(table: pa.Table) -> pa.Table:
        fps, mask, key = (table[c].to_numpy().view(np.uint64) for c in ("fp", "mask", "key"))
        a, b = _links(fps, [key, mask], radius)
        return pa.table({"a": pa.array(a.view(np.int64)), "b": pa.array(b.view(np.int64))})

    return rows.withColumn("slot", F.pmod(F.xxhash64("mask", "key"), F.lit(slots)).cast("int")).groupBy("slot").applyInArrow(work, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, radius: int = 4, cap: int = 2048) -> DataFrame:
    """One row per row of ``docs``: (id_col, fp long, component_id): the smallest id reachable over links of ``radius`` bits or fewer.

    Rows without text have fingerprint 0 and are linked like any other. Null ids belong to a component but never name
    one, unless it has no other (then ``component_id`` is null). Equal fingerprints are one node, so thousands of copies
    cost one comparison. An empty table gives an empty result; other columns are not read.
    """
    marked, _ = stage(fingerprints(docs, id_col, text_col, width), "fingerprints")
    nodes, _ = stage(marked.groupBy("fp").agg(F.min(id_col).alias("least")), "nodes")
    links, lpath = stage(near_links(nodes.select("fp"), radius, cap).distinct(), "near")
    comp, _ = stage(components(links), "components")
    remove_path(docs.sparkSession, lpath)
    owner = nodes.join(comp.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    by_fp = with_least(owner, "component", "least", nodes.count()).select("fp", F.col("m").alias("component_id"))
    return marked.join(by_fp, "fp", "left").select(id_col, "fp", "component_id")


def as_hex(col):
    return F.lower(F.lpad(F.hex(col), 16, "0"))
