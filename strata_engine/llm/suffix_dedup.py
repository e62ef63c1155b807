"""Exact repeated-passage removal by distributed prefix doubling over synchronised positions.

A byte goes when a ``length``-byte string that covers it also starts in a document with a smaller id. Prefix doubling
ranks positions by their first 1, 2, 4, ... bytes: the rank at twice the length is that of a pair, the rank at the position
and the rank one length further on. Positions whose rank is unique leave, and the rest goes on until the threshold.

To rank every position would move a dozen bytes for each byte of text in each round. So positions are thinned first: each
``length``-byte window elects the position in it whose 8-byte content hashes lowest, hence equal windows elect equal
offsets, and about one position in eighteen stands for all windows. Ranks of up to 8 bytes are the bytes themselves, which
nothing need sort. From there on a pair's rank is a name made of both names, Spark brings equal names of all chunks
together, they are sorted, and each chunk learns which of its positions go on (for ``length`` 50):

* round 1 ranks 16 bytes at each elected position;
* round 2 ranks 32 bytes, the pair at offset 16, in the position's windows: those that reach far enough behind it take the
  pair that starts at it, the others the pair that ends with its 16 bytes;
* round 3 is past the threshold: it ranks the whole stretch of such windows (50 to 68 bytes) as the overlapping pair of its
  first and last 32 (or 64) bytes. A stretch that a smaller document has is removed at once; where all stretches of a
  32-byte rank agree, nothing is left to find;
* round 4 ranks the single windows, pairs of 32 bytes at offset 18, where stretches differ, which are the ends of passages.

Text moves once: documents are dealt into chunks and written as a bucketed table, and each round joins its answers to the
chunks on the bucket key without a new exchange. A chunk sends every name once however often it occurs in it, so a passage
in a third of all documents costs one row a chunk. Names travel as runs of fixed width, a run for each chunk and range of
names; files, chunks and ranges are sized by the bytes of text, so that tasks stay of one size.
"""

from __future__ import annotations

import math
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_path, parts, prepare_workers, remove_path, stage, text_bytes, trim

U64 = np.uint64
TILE = 1 << 15
LOW20 = U64((1 << 20) - 1)
M1, M2, M3 = U64(0x9E3779B97F4A7C15), U64(0xD6E8FEB86659FD93), U64(0xC2B2AE3D27D4EB4F)
#: What chunks send: a run of sorted names of one kind and range, with a second column of names and documents where they matter.
SENT = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("kind", pa.int32()), ("n", pa.int32()), ("names", pa.binary()), ("other", pa.binary()), ("extra", pa.binary())])
ANSWER = pa.schema([("chunk", pa.int32()), ("kind", pa.int32()), ("bucket", pa.int32()), ("n", pa.int32()), ("flags", pa.binary())])
#: Kinds of names: two that ask whether a name recurs, stretches and windows that ask for a smaller document, and 32-byte ranks that ask whether their stretches differ.
SEED, TWICE, STRETCH, DIFFER, WINDOW = 1, 2, 3, 4, 5


def _ddl(schema: pa.Schema) -> str:
    return ", ".join(f"{f.name} {'int' if f.type == pa.int32() else 'binary'}" for f in schema)


def _pair(x: np.ndarray, y: np.ndarray, m: np.uint64, k: np.uint64) -> np.ndarray:
    """A name for each pair of names."""
    h = x * m
    h ^= h >> U64(32)
    h ^= y
    h *= k
    h ^= h >> U64(29)
    h *= m
    h ^= h >> U64(32)
    return h


def _data(column: pa.ChunkedArray | pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a binary column, without copies of its values."""
    arr = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if isinstance(arr, pa.ChunkedArray):
        arr = pa.concat_arrays(arr.chunks) if arr.num_chunks else pa.array([], pa.binary())
    if not len(arr):
        return np.zeros(1, dtype=np.int64), np.zeros(0, dtype=np.uint8)
    _, offsets, data = arr.buffers()
    ends = np.frombuffer(offsets, dtype=np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    values = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    return ends - ends[0], values[ends[0] : ends[-1]]


def _runs(values: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Successive runs of ``values``'s bytes, which end at ``ends`` bytes, as a binary column."""
    offsets = np.concatenate(([0], ends)).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(values))])


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The ranges that start at ``first`` and have ``count`` members, end to end."""
    return np.arange(int(count.sum()), dtype=np.int64) + np.repeat(first - (np.cumsum(count) - count), count)


class Chunk:
    """The documents of one chunk as one buffer, in the order of their ids, with the stretches of windows of each elected position."""

    def __init__(self, table: pa.Table, length: int, seed: int):
        order = pc.sort_indices(table.select(["doc_id", "row"]), sort_keys=[("doc_id", "ascending"), ("row", "ascending")])
        table = table.select(["doc_id", "row", "text"]).take(order)
        self.ids, self.row = table["doc_id"].to_numpy(), table["row"]
        offsets, data = _data(table["text"])
        self.starts, self.ends, self.size = offsets[:-1], offsets[1:], int(offsets[-1])
        self.buf = np.concatenate((data, np.zeros(128 + length, dtype=np.uint8)))
        self.length, self.seed = length, seed
        self.words = np.ndarray((self.size + 120,), dtype="<u8", buffer=self.buf, strides=(1,))  # the 8 bytes from each on
        self._stretches()

    def _stretches(self) -> None:
        n, length, w = self.size, self.length, self.length - self.seed + 1
        step = np.zeros(n + 1, dtype=np.int8)
        fits = self.ends - self.starts >= length
        np.add.at(step, self.starts[fits], 1)
        np.add.at(step, self.ends[fits] - length + 1, -1)
        valid = np.cumsum(step[:n], dtype=np.int8) > 0
        lows, highs, seats = [], [], []
        for t in range(0, n, TILE):
            m = min(TILE, n - t)
            key = self.words[t : min(t + m + w, n + 120)] * M1
            key ^= key >> U64(32)
            key *= M2
            key = (key & ~LOW20) | np.arange(len(key), dtype=U64)
            span = 1
            while span * 2 <= w:
                key = np.minimum(key[:-span], key[span:])
                span *= 2
            if span < w:
                key = np.minimum(key[: len(key) - (w - span)], key[w - span :])
            at = np.flatnonzero(valid[t : t + m])
            if not len(at):
                continue
            seat = (key[at] & LOW20).astype(np.int64)
            cut = np.flatnonzero((seat[1:] != seat[:-1]) | (at[1:] != at[:-1] + 1))
            lows.append(at[np.concatenate(([0], cut + 1))] + t)
            highs.append(at[np.concatenate((cut, [len(at) - 1]))] + t)
            seats.append(seat[np.concatenate(([0], cut + 1))] + t)
        cat = lambda x: np.concatenate(x) if x else np.zeros(0, dtype=np.int64)
        self.lo, self.hi, self.seat = cat(lows), cat(highs), cat(seats)
        self.doc = self.ids[np.searchsorted(self.ends, self.lo, side="right")] if len(self.lo) else np.zeros(0, dtype=np.int64)

    # Names are recomputed from the text in each round, so that they are the same whenever a lost task runs again.
    def rank(self, at: np.ndarray, size: int, m: np.uint64 = M1, k: np.uint64 = M2) -> np.ndarray:
        """Ranks by ``size`` bytes, a power of two, 8 at least: those of pairs at half the size."""
        if size == 8:
            return self.words[at]
        return _pair(self.rank(at, size // 2, m, k), self.rank(at + size // 2, size // 2, m, k), m, k)

    def string(self, at: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Two independent ranks by ``sizes`` bytes: those of the pair of first and last bytes, overlapping, a power of two each."""
        a, b = np.zeros(len(at), dtype=U64), np.zeros(len(at), dtype=U64)
        half = 1 << (np.frexp(sizes.astype(np.float64))[1] - 1)
        for one in np.unique(half).tolist():
            pick = np.flatnonzero(half == one)
            first, last = at[pick], at[pick] + sizes[pick] - one
            size = sizes[pick].astype(U64)
            a[pick] = _pair(_pair(self.rank(first, one), self.rank(last, one), M1, M2), size, M3, M1)
            b[pick] = _pair(_pair(self.rank(first, one, M3, M1), self.rank(last, one, M3, M1), M3, M1), size, M1, M2)
        return a, b

    def parts(self, pick: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(first window, last window, where twice the seed's bytes start that all of them hold, document) of the stretches picked.

        Windows that end at least twice the seed after the seat take the bytes from the seat on; the others, which start
        at least a seed before it, those that end with the seat's seed.
        """
        lo, hi, seat, doc = self.lo[pick], self.hi[pick], self.seat[pick], self.doc[pick]
        edge = seat + 2 * self.seed - self.length  # the first window of the former sort
        near, far = np.flatnonzero(hi >= edge), np.flatnonzero(lo < edge)
        join = lambda x, y: np.concatenate((x[near], y[far]))
        return join(np.maximum(lo, edge), lo), join(hi, np.minimum(hi, edge - 1)), join(seat, seat - self.seed), join(doc, doc)


class Names:
    """Distinct names in order; of each its smallest document, whether several documents have it, and the rows' places."""

    def __init__(self, names: np.ndarray, docs: np.ndarray):
        order = np.argsort(names)
        s = names[order]
        head = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1]))) if len(s) else np.zeros(0, dtype=np.int64)
        self.order, self.head, self.names = order, head, s[head]
        self.place = np.empty(len(s), dtype=np.int64)
        self.place[order] = np.repeat(np.arange(len(head)), np.diff(np.append(head, len(s))))
        self.first = self.least(docs)
        self.several = self.first != self.most(docs)

    def least(self, values: np.ndarray) -> np.ndarray:
        return np.minimum.reduceat(values[self.order], self.head) if len(self.head) else values[:0]

    def most(self, values: np.ndarray) -> np.ndarray:
        return np.maximum.reduceat(values[self.order], self.head) if len(self.head) else values[:0]


class Mail:
    """One chunk's exchange with the ranges of names: what it sends, and the flags that came back."""

    def __init__(self, chunk: int, buckets: int, width: int, answers: pa.Table | None):
        self.chunk, self.width, self.answers = chunk, width, answers
        self.buckets, self.edges = buckets, (np.arange(1, buckets, dtype=np.float64) * (2.0**64 / buckets)).astype(U64)

    def cuts(self, names: np.ndarray) -> np.ndarray:
        return np.concatenate(([0], np.searchsorted(names, self.edges), [len(names)]))

    def send(self, kind: int, names: np.ndarray, other: np.ndarray | None = None, extra: np.ndarray | None = None) -> pa.Table:
        """A run for each range with names; recurring names alone are cut to ``width`` bytes, the range tells the rest."""
        cuts = self.cuts(names)
        some = np.flatnonzero(np.diff(cuts))
        ends, n = cuts[some + 1], np.diff(cuts)[some]
        same = lambda v: pa.array(np.full(len(some), v, dtype=np.int32))
        size = 8 if other is not None else self.width
        short = np.ascontiguousarray(names).view(np.uint8).reshape(-1, 8)[:, :size]
        rest = [pa.nulls(len(some), pa.binary()) if x is None else _runs(np.ascontiguousarray(x).view(np.uint8), 8 * ends) for x in (other, extra)]
        return pa.Table.from_arrays([pa.array(some.astype(np.int32)), same(self.chunk), same(kind), pa.array(n.astype(np.int32)), _runs(short, size * ends), *rest], schema=SENT)

    def flags(self, kind: int, names: np.ndarray) -> np.ndarray:
        """The flags of what :meth:`send` sent, in the order of the names; none came for runs without a set one."""
        got = np.zeros(len(names), dtype=bool)
        if self.answers is not None:
            mine = self.answers.filter(pc.equal(self.answers["kind"], kind))
            if mine.num_rows:
                at = spread(self.cuts(names)[mine["bucket"].to_numpy()], mine["n"].to_numpy().astype(np.int64))
                got[at] = _data(mine["flags"])[1].astype(bool)
        return got


def _resolve(c: Chunk, upto: int, mail: Mail) -> pa.Table | np.ndarray:
    """Replay the rounds that have answers and return what round ``upto`` sends, or the removed-byte mask at the end."""
    seeds = Names(c.rank(c.seat, c.seed), c.doc)
    if upto == 1:
        return mail.send(SEED, seeds.names)
    lo, hi, at, doc = c.parts(np.flatnonzero((mail.flags(SEED, seeds.names) | seeds.several)[seeds.place]))
    rank = c.rank(at, 2 * c.seed)
    twice = Names(rank, doc)
    if upto == 2:
        return mail.send(TWICE, twice.names)
    live = np.flatnonzero((mail.flags(TWICE, twice.names) | twice.several)[twice.place])
    lo, hi, doc, rank = lo[live], hi[live], doc[live], rank[live]
    a, b = c.string(lo, hi - lo + c.length)
    whole, differ = Names(a, doc), Names(rank, doc)
    if upto == 3:
        return pa.concat_tables([mail.send(STRETCH, whole.names, b[whole.order[whole.head]], whole.first), mail.send(DIFFER, differ.names, differ.least(a), differ.most(a))])
    earlier = mail.flags(STRETCH, whole.names)[whole.place] | (doc > whole.first[whole.place])
    todo = np.flatnonzero(~earlier & mail.flags(DIFFER, differ.names)[differ.place])
    count = hi[todo] - lo[todo] + 1
    starts, docs = spread(lo[todo], count), np.repeat(doc[todo], count)
    a, b = c.string(starts, np.full(len(starts), c.length))
    single = Names(a, docs)
    if upto == 4:
        return mail.send(WINDOW, single.names, b[single.order[single.head]], single.first)
    gone = starts[mail.flags(WINDOW, single.names)[single.place] | (docs > single.first[single.place])]
    step = np.zeros(c.size + 1, dtype=np.int32)  # how many windows cover a byte, by differences
    for first, last in ((lo[earlier], hi[earlier]), (gone, gone)):
        np.add.at(step, first, 1)
        np.add.at(step, last + c.length, -1)
    return np.cumsum(step[: c.size], dtype=np.int32) > 0


def _judge(table: pa.Table) -> pa.Table:
    """All chunks' names of one range and kind, sorted together; a flag for each name goes back to its chunk."""
    if not table.num_rows:
        return ANSWER.empty_table()
    kind, sizes = table["kind"][0].as_py(), table["n"].to_numpy().astype(np.int64)
    whole = lambda c, t: np.ascontiguousarray(_data(table[c])[1]).view(t)
    if kind in (SEED, TWICE):
        short = whole("names", np.uint8)
        raw = np.zeros((int(sizes.sum()), 8), dtype=np.uint8)
        raw[:, : len(short) // len(raw)] = short.reshape(len(raw), -1)
        names = raw.view("<u8").ravel()
        order = np.argsort(names)
        s = names[order]
        same = s[1:] == s[:-1]
        flag = np.concatenate(([False], same)) | np.concatenate((same, [False]))
    elif kind == DIFFER:
        names = Names(whole("names", "<u8"), whole("other", "<u8"))
        order, flag = names.order, (names.first != names.most(whole("extra", "<u8")))[names.place[names.order]]
    else:
        a, b, docs = whole("names", "<u8"), whole("other", "<u8"), whole("extra", "<i8")
        order = np.lexsort((docs, b, a))
        sa, sb, sd = a[order], b[order], docs[order]
        head = np.flatnonzero(np.concatenate(([True], (sa[1:] != sa[:-1]) | (sb[1:] != sb[:-1]))))
        flag = sd > np.repeat(sd[head], np.diff(np.append(head, len(sa))))
    back = np.empty(len(flag), dtype=np.uint8)
    back[order] = flag
    ends = np.cumsum(sizes)
    out = pa.Table.from_arrays([table["chunk"], table["kind"], table["bucket"], table["n"], _runs(back, ends)], schema=ANSWER)
    return out.filter(pa.array(np.add.reduceat(back.astype(np.int64), ends - sizes) > 0))


def _result(c: Chunk, gone: np.ndarray) -> pa.Table:
    n = len(c.ids)
    total = np.zeros(len(gone) + 1, dtype=np.int32 if len(gone) < 1 << 31 else np.int64)
    np.cumsum(gone, out=total[1:])
    removed = total[c.ends] - total[c.starts]
    start = gone.copy()
    start[1:] &= ~gone[:-1]
    stop = gone.copy()
    stop[:-1] &= ~gone[1:]
    inside = c.starts[(c.starts < c.size) & (c.starts < c.ends)]
    start[inside] |= gone[inside]
    last = c.ends[c.ends > c.starts] - 1
    stop[last] |= gone[last]
    s, e = np.flatnonzero(start), np.flatnonzero(stop) + 1
    n_before = np.searchsorted(s, c.starts)
    n_spans = np.searchsorted(s, c.ends) - n_before
    n_spans[c.starts == c.ends] = 0
    kept = np.ascontiguousarray(c.buf[: c.size][~gone])
    offsets = np.concatenate(([0], np.cumsum(c.ends - c.starts - removed)))
    span_offsets = pa.array(np.concatenate(([0], np.cumsum(n_spans))), type=pa.int32())
    owner = np.repeat(c.starts, n_spans)
    kept_col = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(kept)])
    return pa.table({
        "doc_id": pa.array(c.ids), "row": c.row, "n_bytes": pa.array(c.ends - c.starts), "n_removed": pa.array(removed.astype(np.int64)), "n_spans": pa.array(n_spans.astype(np.int64)),
        "span_starts": pa.ListArray.from_arrays(span_offsets, pa.array(s - owner)), "span_ends": pa.ListArray.from_arrays(span_offsets, pa.array(e - owner)), "kept": kept_col,
    })


RESULT = "doc_id long, row long, n_bytes long, n_removed long, n_spans long, span_starts array<long>, span_ends array<long>, kept binary"
LAST = np.iinfo(np.int64).max
#: Tables are bucketed into no more files than Spark allows by default.
MOST_FILES = 100_000


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 50, chunk_mb: float = 5.0, range_mb: float = 40.0, file_mb: float = 128.0) -> DataFrame:
    """One row per row of ``docs``: (doc_id, row, n_bytes, n_removed, n_spans, span_starts, span_ends, kept).

    ``kept`` holds the bytes that stay, ``span_*`` the maximal removed runs as byte offsets. Null texts count as empty
    and give zeros. Rows with equal ids don't remove each other's passages; a null id counts as greater than all others
    and comes back null. Repeated rows each give a row (``row`` tells texts apart). Texts shorter than ``length`` (23 at
    least) are kept whole. An empty table gives an empty result; other columns of ``docs`` are not read. Beyond a gigabyte
    of text, chunks grow with its square root, up to 64 MB, and ranges of names (``range_mb`` of text) likewise to eight
    times their size; files hold ``file_mb`` of text.
    """
    spark = docs.sparkSession
    prepare_workers(spark)
    if length < 23:
        raise ValueError("length must be at least 23")
    seed = 1 << int(math.log2((length + 1) / 3))  # a seed before the seat or two behind it are within every window
    src = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(LAST)).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary").alias("text"))
    total = text_bytes(docs, text_col)
    grow = lambda unit, most: min(most, max(1.0, math.sqrt(total / unit)))
    chunks = max(48, math.ceil(total / (chunk_mb * 1e6 * grow(1e9, 12.8))))
    buckets = max(64, math.ceil(total / (range_mb * 1e6 * grow(3e10, 8.0))))
    width = min(8, max(4, math.ceil((math.log2(total + 2) + 4) / 8)))  # of a name, so that few differ that look equal
    dealt = src.withColumn("row", F.xxhash64("text")).select(F.pmod(F.xxhash64("doc_id", "row"), F.lit(chunks)).cast("int").alias("chunk"), "doc_id", "row", "text")
    name, path = f"strata_chunks_{uuid.uuid4().hex}", new_path(spark, "chunks")
    n = min(MOST_FILES, max(parts(spark), math.ceil(total / (file_mb * 1e6))))
    dealt.repartition(n, "chunk").write.bucketBy(n, "chunk").option("path", path).option("compression", "zstd").format("parquet").saveAsTable(name)
    answers, written = None, []
    try:
        for upto in (1, 2, 3, 4):
            sent = _pass(spark.table(name), answers, upto, length, seed, buckets, width, _ddl(SENT))
            judged = sent.repartition(min(n, buckets), "bucket").groupBy("bucket", "kind").applyInArrow(_judge, _ddl(ANSWER))
            found, where = stage(judged, f"answers{upto}")
            answers = found if answers is None else answers.unionByName(found)
            written.append(where)
        out, _ = stage(_pass(spark.table(name), answers, 5, length, seed, buckets, width, RESULT), "passages")
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        for p in [path, *written]:
            remove_path(spark, p)
    return out.withColumn("doc_id", F.when(F.col("doc_id") != LAST, F.col("doc_id")))


def _pass(table: DataFrame, answers: DataFrame | None, upto: int, length: int, seed: int, buckets: int, width: int, schema: str) -> DataFrame:
    def work(left: pa.Table, right: pa.Table | None) -> pa.Table:
        if not left.num_rows:
            return SENT.empty_table() if upto < 5 else _result(Chunk(left, length, seed), np.zeros(0, dtype=bool))
        c = Chunk(left, length, seed)
        out = _resolve(c, upto, Mail(left["chunk"][0].as_py(), buckets, width, right))
        out = _result(c, out) if upto == 5 else out
        del c
        trim()
        return out

    if answers is None:
        return table.groupBy("chunk").applyInArrow(lambda left: work(left, None), schema)
    return table.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(work, schema)


def brute_force(rows: list[tuple[int, bytes]], length: int = 50) -> dict[int, tuple[int, int, int, bytes]]:
    """The definition, for tests: (n_bytes, n_removed, n_spans, kept) of each id."""
    first: dict[bytes, int] = {}
    for i, t in sorted(rows):
        for p in range(len(t) - length + 1):
            first.setdefault(t[p : p + length], i)
    out = {}
    for i, t in rows:
        gone = bytearray(len(t))
        for p in range(len(t) - length + 1):
            if first[t[p : p + length]] < i:
                gone[p : p + length] = b"\1" * length
        spans = sum(1 for p in range(len(t)) if gone[p] and (p == 0 or not gone[p - 1]))
        out[i] = (len(t), sum(gone), spans, bytes(b for b, g in zip(t, gone, strict=True) if not g))
    return out
