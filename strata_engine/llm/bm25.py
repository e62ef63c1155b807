"""Exact top-k BM25 search: an inverted index for each shard, pruned by block maxima, merged with global statistics.

Document frequencies and lengths are counted over all documents first and once for all queries, so that scores don't
depend on the shards. A shard puts documents of like vocabulary into blocks. For a query, the bound of a block is the sum
of its words' block maxima, or what the block's documents really get from rare words, whose postings are short. Blocks are
taken by falling bound, and those whose bound can't reach the k-th best score so far are never scored. Bounds are never
below scores, so nothing of the true top k is lost. Small shares of the documents go first, each share several times the
one before, so that the rest starts with a good score to beat and yields few candidates however many tasks there are.
Frequent words are scored for many queries of like length at once in single precision; how many words count as frequent is
what is cheapest for those queries. Whatever could be in the top k despite rounding is scored again in double precision.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import new_path, prepare_workers, remove_path, stage, trim
from .grams import WORDS


def terms_of(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted 64-bit term hashes and their frequencies."""
    c = Counter(WORDS((text or "").lower()))
    if not c:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int32)
    t = np.array([xxhash.xxh64_intdigest(w) for w in c], dtype=np.uint64).view(np.int64)
    o = np.argsort(t)
    return t[o], np.fromiter(c.values(), dtype=np.int32, count=len(c))[o]


def places(words: np.ndarray, vocab: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which words are in the sorted ``vocab``, and the places of those."""
    if not len(vocab):
        return np.zeros(len(words), dtype=bool), np.zeros(0, dtype=np.int64)
    if len(words) * 4 > len(vocab):
        at = near(words, vocab)
    else:
        at = np.searchsorted(vocab, words)
        at[at == len(vocab)] = 0
    known = vocab[at] == words
    return known, at[known]


def near(words: np.ndarray, vocab: np.ndarray) -> np.ndarray:
    """For each word its place in the sorted ``vocab``, or any place if it isn't there.

    Hashes are spread evenly, so their leading bits tell a place to within a few, and the rest is a short walk.
    """
    shift = np.uint64(63 - len(vocab).bit_length())
    lead = lambda x: ((x.view(np.uint64) ^ np.uint64(1 << 63)) >> shift).astype(np.int64)
    at = np.searchsorted(lead(vocab), np.arange(1 << (64 - int(shift))))[lead(words)]
    end = np.append(vocab, np.iinfo(np.int64).max)
    walk = np.flatnonzero(end[at] < words)
    for _ in range(16):
        if not len(walk):
            break
        at[walk] += 1
        walk = walk[end[at[walk]] < words[walk]]
    at[walk] = np.searchsorted(vocab, words[walk])  # words that aren't spread
    at[at == len(vocab)] = 0
    return at


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The ranges that start at ``first`` and have ``count`` members, end to end."""
    return np.arange(int(count.sum())) + np.repeat(first - (np.cumsum(count) - count), count)


def by_value(x: np.ndarray) -> np.ndarray:
    """Places of ``x`` by value, equal ones in order; ``x`` isn't negative. Sorting both as one number is faster than an argsort."""
    bits = len(x).bit_length()
    both = (x.astype(np.int64) << bits) | np.arange(len(x))
    both.sort()
    return both & ((1 << bits) - 1)


#: A posting, fetched as one number.
PACKED = np.dtype([("doc", np.int32), ("part", np.float32)])
#: Following a posting takes about as long as so many multiplications in a product of matrices, with blocks left out.
POSTING = 350


class Asked:
    """A block of queries: their words as places in a sorted vocabulary, in the order of their numbers of words."""

    def __init__(self, rows: list[tuple[int, int, bytes, bytes]]):
        sizes = np.array([len(r[2]) // 8 for r in rows], dtype=np.int64)
        words = np.frombuffer(b"".join(r[2] for r in rows), dtype="<i8")
        self.vocab, at = np.unique(words, return_inverse=True)
        weight = np.frombuffer(b"".join(r[3] for r in rows), dtype="<i4").astype(np.float64)
        order = np.argsort(sizes, kind="stable")
        pick = spread((np.cumsum(sizes) - sizes)[order], sizes[order])
        self.row = np.array([r[0] for r in rows], dtype=np.int64)[order]
        self.id = np.array([r[1] for r in rows], dtype=np.int64)[order]
        self.at, self.weight = at[pick].astype(np.int32), weight[pick]
        self.first = np.concatenate(([0], np.cumsum(sizes[order])))


def leading(at: np.ndarray, tf: np.ndarray, sizes: np.ndarray, common: np.ndarray) -> np.ndarray:
    """Each text's most frequent word, the commoner one of equals; -1 without words."""
    out = np.full(len(sizes), -1, dtype=np.int64)
    has = np.flatnonzero(sizes)
    if len(has):
        value = tf + common[at] / (common.max() + 1.0)
        start = (np.cumsum(sizes) - sizes)[has]
        most = np.maximum.reduceat(value, start)
        hit = np.flatnonzero(value == np.repeat(most, sizes[has]))
        owner = np.repeat(has, sizes[has])[hit]
        out[owner[::-1]] = at[hit[::-1]]
    return out


class Shard:
    """Documents of one shard with their BM25 contributions, and block maxima.

    ``rows`` are (id, terms, tfs, size). Equal documents are scored once; of their ids the ``k`` smallest can matter.
    """

    def __init__(self, rows: list[tuple[int, bytes, bytes, int]], vocab: np.ndarray, df: np.ndarray, n: int, mean: float, k: int, k1: float, b: float, block: int, most_dense: int = 2048):
        same: dict[tuple[bytes, bytes], list[int]] = {}
        for i, t, f, _ in rows:
            same.setdefault((t, f), []).append(i)
        lens = np.array([len(t) // 8 for t, _ in same], dtype=np.int64)
        known, at = places(np.frombuffer(b"".join(t for t, _ in same), dtype="<i8"), vocab)
        tf = np.frombuffer(b"".join(f for _, f in same), dtype="<i4")
        size = np.add.reduceat(tf, np.cumsum(lens) - lens).astype(np.float64) if len(lens) else np.zeros(0)
        owner = np.repeat(np.arange(len(lens)), lens)[known]
        tf = tf[known].astype(np.float64)
        lens = np.bincount(owner, minlength=len(lens))
        order = np.lexsort((size, leading(at, tf, lens, df)))
        members = list(same.values())
        self.ids = [sorted(members[i])[:k] for i in order]
        pick = spread((np.cumsum(lens) - lens)[order], lens[order])
        lens, at, tf = lens[order], at[pick].astype(np.int32), tf[pick]
        doc = np.repeat(np.arange(len(lens), dtype=np.int32), lens)
        idf = np.log(1 + (n - df + 0.5) / (df + 0.5))
        self.part = idf[at] * tf * (k1 + 1) / (tf + k1 * (1 - b + b * size[order] / max(mean, 1e-9))[doc])
        self.at, self.first, self.n = at, np.concatenate(([0], np.cumsum(lens))), len(lens)
        self.starts = np.arange(0, self.n, block)
        self.block = block
        local = np.bincount(at, minlength=len(vocab))
        often = np.flatnonzero(local * 128 >= max(1, self.n))
        often = often[np.argsort(-local[often], kind="stable")[:most_dense]]
        self.column = np.full(len(vocab), -1, dtype=np.int32)
        self.column[often] = np.arange(len(often))
        col = self.column[at]
        self.dense = np.zeros((len(often), self.n), dtype=np.float32)
        d = col >= 0
        self.dense[col[d], doc[d]] = self.part[d]
        self.maxima = np.maximum.reduceat(self.dense, self.starts, axis=1) if len(often) and self.n else np.zeros((len(often), len(self.starts)), dtype=np.float32)
        r = by_value(at)
        posts = np.empty(len(r), dtype=PACKED)
        posts["doc"], posts["part"] = doc[r], self.part[r]
        self.posts, self.posts_first = posts.view(np.int64), np.concatenate(([0], np.cumsum(local)))

    def top(self, asked: Asked, lo: int, hi: int, least: np.ndarray, k: int) -> Iterator[tuple[int, list[tuple[float, int]]]]:
        """(query, its documents that can be among the k best) of queries lo to hi; ``least`` has scores to reach."""
        nq, a, z = hi - lo, asked.first[lo], asked.first[hi]
        count = np.diff(asked.first[lo : hi + 1])
        owner, at, w = np.repeat(np.arange(nq), count), asked.at[a:z], asked.weight[a:z]
        col, first = self.column[at], self.posts_first[at]
        size = self.posts_first[at + 1] - first
        left = np.bincount(col + 1, weights=size, minlength=len(self.dense) + 1)
        left = left.sum() - np.concatenate(([0], np.cumsum(left[1:])))  # postings to follow if so many words are dense
        width = int(np.argmin(left * POSTING + np.arange(len(left)) * (nq * self.n)))
        d = (col >= 0) & (col < width)
        q = np.zeros((nq, width), dtype=np.float32)
        q[owner[d], col[d]] = w[d]
        dense, maxima = self.dense[:width], self.maxima[:width]
        r = np.flatnonzero(~d & (size > 0))
        first, size, w, ends = first[r], size[r], w[r], np.searchsorted(owner[r], np.arange(nq + 1)).tolist()
        many = np.concatenate(([0], np.cumsum(size)))
        steps = np.arange(int(np.diff(many[ends]).max(initial=0)))
        rare = np.zeros((nq, self.n), dtype=np.float32)
        for i, (a, z) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
            if a < z:
                post = np.repeat(first[a:z] - (many[a:z] - many[a]), size[a:z])
                post += steps[: len(post)]
                got = self.posts[post].view(PACKED)
                rare[i] = np.bincount(got["doc"], weights=got["part"] * np.repeat(w[a:z], size[a:z]), minlength=self.n)
        slack = 1 + (count + 16) * 2.0**-22  # more than rounding can add up to: all terms are positive
        bound = (np.maximum.reduceat(rare, self.starts, axis=1) + q @ maxima) * slack[:, None]
        theta = least.copy()
        best = np.zeros((nq, k), dtype=np.float32)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        for x in np.argsort(-bound.max(axis=0), kind="stable").tolist():
            live = np.flatnonzero((bound[:, x] >= theta) & (bound[:, x] > 0))
            if not len(live):
                continue
            s = slice(self.starts[x], min(self.starts[x] + self.block, self.n))
            score = q[live] @ dense[:, s]
            score += rare[live, s]
            most = score.max(axis=1)
            hit = np.flatnonzero((most * slack[live] >= theta[live]) & (most > 0))
            if not len(hit):
                continue
            live, score = live[hit], score[hit]
            both = np.concatenate((best[live], score), axis=1)
            best[live] = np.partition(both, both.shape[1] - k, axis=1)[:, -k:]
            theta[live] = np.maximum(theta[live], best[live].min(axis=1) / slack[live])
            i, j = np.nonzero((score * slack[live][:, None] >= theta[live][:, None]) & (score > 0))
            found.append((live[i], j + s.start, score[i, j]))
        if not found:
            return
        who, docs, score = (np.concatenate(c) for c in zip(*found, strict=True))
        keep = score * slack[who] >= theta[who]
        by = np.argsort(who[keep], kind="stable")
        who, docs = who[keep][by], docs[keep][by]
        cuts = np.searchsorted(who, np.arange(nq + 1))
        full = np.zeros(len(self.column))
        for i in np.flatnonzero(np.diff(cuts)).tolist():
            mine = docs[cuts[i] : cuts[i + 1]]
            s = slice(asked.first[lo + i], asked.first[lo + i + 1])
            full[asked.at[s]] = asked.weight[s]
            size = self.first[mine + 1] - self.first[mine]
            post = spread(self.first[mine], size)
            exact = np.bincount(np.repeat(np.arange(len(mine)), size), weights=self.part[post] * full[self.at[post]], minlength=len(mine))
            full[asked.at[s]] = 0.0
            yield lo + i, [(round(v, 9), one) for v, m in zip(exact.tolist(), mine.tolist(), strict=True) for one in self.ids[m]]


def search(docs: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "doc_id", text_col: str = "text", query_col: str = "query_id", query_text: str = "text", k1: float = 1.2, b: float = 0.75, block: int = 128, shard_docs: int = 16_000, shard_terms: int = 2_400_000, query_block: int = 8_000, query_mb: float = 32.0, growth: int = 8, words_at_once: int = 4_000_000) -> DataFrame:
    """The exact top ``k`` documents of every query: (query_col, rank, doc_id, score), score rounded to 6 places.

    Ties go to the smaller id. Documents that share no word with a query don't answer it; null and empty texts and
    queries give nothing, rows with a null id are left out. Queries go to all shards in blocks of about ``query_block``
    and ``query_mb`` MB, which bounds what is broadcast at once; a shard is a run of documents, ``shard_docs`` at most or
    about ``shard_terms`` postings, so nothing is shuffled but document frequencies and candidates. The first share of
    documents fills half a shard and each next one is ``growth`` times as large, so a query has about ``growth * k``
    candidates a share. Repeated rows answer each by itself; extra columns are not read.
    """
    spark = docs.sparkSession
    prepare_workers(spark)

    def split(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [terms_of(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t.tobytes() for t, _ in found], pa.binary()), pa.array([f.tobytes() for _, f in found], pa.binary()), pa.array([int(f.sum()) for _, f in found], pa.int64())], names=["id", "terms", "tfs", "size"])

    shape = "id long, terms binary, tfs binary, size long"
    pick = lambda df, i, t: df.filter(F.col(i).isNotNull()).select(F.col(i).cast("long").alias("id"), F.col(t).cast("string").alias("text"))
    count = docs.count()
    steps = 0
    while count > shard_docs // 2 * growth**steps:
        steps += 1
    # The share of a row: the smallest one, 0, has every growth**steps-th row, the next one the growth**(steps-1)-th, ...
    place = F.pmod(F.xxhash64("id", "size"), F.lit(growth**steps))
    share = F.lit(steps)
    for x in range(steps):
        share = F.when(place % growth ** (steps - x) == 0, F.least(share, F.lit(x))).otherwise(share)
    index = pick(docs, id_col, text_col).mapInArrow(split, shape).withColumn("share", share.cast("int"))
    at = new_path(spark, "postings")
    index.write.option("compression", "zstd").partitionBy("share").parquet(at)
    index = spark.read.schema(index.schema).parquet(at)
    asked, _ = stage(pick(queries, query_col, query_text).mapInArrow(split, shape).filter("size > 0").withColumn("row", F.monotonically_increasing_id()), "queries")
    shares = {x["share"]: x for x in index.groupBy("share").agg(F.count("*").alias("n"), F.sum("size").alias("size")).collect()}
    n = sum(x["n"] for x in shares.values())
    mean = sum(x["size"] for x in shares.values()) / max(1, n)
    n_asked, asked_bytes = asked.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("terms") + F.octet_length("tfs")), F.lit(0))).first()
    blocks = max(1, -(-n_asked // query_block), int(-(-asked_bytes // (query_mb * 1e6))))
    frequencies = _frequencies(index, asked, words_at_once)
    path = new_path(spark, "answers")
    out = f"{query_col} long, rank long, doc_id long, score double"
    for some in range(blocks):
        rows = asked.filter(F.pmod(F.xxhash64("row"), F.lit(blocks)) == some).select("row", "id", "terms", "tfs").collect()
        here = Asked([(r[0], r[1], bytes(r[2]), bytes(r[3])) for r in rows])
        df = _known(frequencies, here.vocab)
        least, ranked = np.zeros(len(here.row)), None
        for x in sorted(shares):
            part = index.filter(F.col("share") == x)
            if x < steps:
                part = part.coalesce(-(-shares[x]["n"] // shard_docs))
            found, sent = _answers(part, here, df, least, n, mean or 1.0, k, k1, b, block, shard_docs, shard_terms)
            found = found if ranked is None else found.unionByName(ranked)
            found = found.withColumn("rank", F.row_number().over(Window.partitionBy("row").orderBy(F.col("score").desc(), "id"))).filter(F.col("rank") <= k)
            ranked, _ = stage(found.select("row", "q", "rank", "id", "score"), "ranked")
            sent.destroy()
            if x < max(shares):
                reached = ranked.filter(F.col("rank") == k).select("row", "score").toArrow()  # a row a query of the block
                at = np.argsort(here.row)
                least[at[np.searchsorted(here.row[at], reached["row"].to_numpy())]] = reached["score"].to_numpy() * (1 - 1e-9)
                ranked = ranked.drop("rank")
        if ranked is not None:
            ranked.select(F.col("q").alias(query_col), F.col("rank").cast("long").alias("rank"), F.col("id").alias("doc_id"), F.round("score", 6).alias("score")).write.mode("append").parquet(path)
    if not shares:
        return spark.createDataFrame([], out)
    return spark.read.schema(out).parquet(path)


def _frequencies(index: DataFrame, asked: DataFrame, words_at_once: int) -> DataFrame:
    """(term, df): in how many documents each word of any query occurs, written once.

    Documents are read once for every ``words_at_once`` words, which bounds what is broadcast.
    """
    spark = index.sparkSession

    def spell(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(np.frombuffer(b"".join(batch.column(0).to_pylist()), dtype="<i8")))], names=["term"])

    words, written = stage(asked.select("terms").mapInArrow(spell, "term long").distinct(), "words")
    path = new_path(spark, "frequencies")
    rounds = max(1, -(-words.count() // words_at_once))
    for some in range(rounds):
        vocab = np.sort(words.filter(F.pmod(F.xxhash64("term"), F.lit(rounds)) == some).toArrow()["term"].to_numpy())
        shared = spark.sparkContext.broadcast(vocab)

        def count(batches: Iterable[pa.RecordBatch], shared: Broadcast = shared) -> Iterator[pa.RecordBatch]:
            known = shared.value
            total = np.zeros(len(known), dtype=np.int64)
            held, size = [], 0
            for batch in batches:
                held += batch.column(0).to_pylist()
                size += batch.nbytes
                if size > 16_000_000:
                    total += np.bincount(places(np.frombuffer(b"".join(held), dtype="<i8"), known)[1], minlength=len(known))
                    held, size = [], 0
            total += np.bincount(places(np.frombuffer(b"".join(held), dtype="<i8"), known)[1], minlength=len(known))
            hit = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(known[hit]), pa.array(total[hit])], names=["term", "df"])

        index.select("terms").mapInArrow(count, "term long, df long").groupBy("term").agg(F.sum("df").alias("df")).write.mode("append").parquet(path)
        shared.destroy()
    remove_path(spark, written)
    return spark.read.schema("term long, df long").parquet(path)


def _known(frequencies: DataFrame, vocab: np.ndarray) -> np.ndarray:
    """In how many documents each word of a block of queries occurs."""
    shared = frequencies.sparkSession.sparkContext.broadcast(vocab)

    def pick(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = shared.value
        for batch in batches:
            known, at = places(batch.column(0).to_numpy(zero_copy_only=False), words)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), batch.column(1).filter(pa.array(known))], names=["at", "df"])

    df = np.zeros(len(vocab), dtype=np.int64)
    counted = frequencies.mapInArrow(pick, "at int, df long").toArrow()
    df[counted["at"].to_numpy()] = counted["df"].to_numpy()
    shared.destroy()
    return df


def _answers(index: DataFrame, asked: Asked, df: np.ndarray, reached: np.ndarray, n: int, mean: float, k: int, k1: float, b: float, block: int, shard_docs: int, shard_terms: int, at_once: int = 512) -> tuple[DataFrame, Broadcast]:
    """(row, q, id, score), at most k for a task and query and none below ``reached``; also what was broadcast."""
    shared = index.sparkSession.sparkContext.broadcast((asked, df, reached))

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, dfs, least = shared.value
        least = least.copy()
        best: list[list[tuple[float, int]]] = [[] for _ in q.row]

        def finish(rows: list) -> None:
            shard = Shard(rows, q.vocab, dfs, n, mean, k, k1, b, block)
            rows.clear()
            trim()
            for lo in range(0, len(q.row), at_once) if shard.n else ():
                hi = min(lo + at_once, len(q.row))
                for i, more in shard.top(q, lo, hi, least[lo:hi], k):
                    best[i] = sorted(best[i] + [x for x in more if x[0] >= least[i]], key=lambda x: (-x[0], x[1]))[:k]
                    if len(best[i]) == k:
                        least[i] = best[i][-1][0] * (1 - 1e-9)

        held, terms = [], 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.append(row)
                terms += len(row[1]) // 8
                if terms >= shard_terms or len(held) >= shard_docs:
                    finish(held)
                    terms = 0
        if held:
            finish(held)
        step = 50_000
        for s in range(0, len(best), step):
            rows = [(int(q.row[i]), int(q.id[i]), x, v) for i in range(s, min(s + step, len(best))) for v, x in best[i]]
            cols = list(zip(*rows, strict=True)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.float64())], names=["row", "q", "id", "score"])

    return index.filter("size > 0").select("id", "terms", "tfs", "size").mapInArrow(work, "row long, q long, id long, score double"), shared
