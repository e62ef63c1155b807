"""Connected components of a link table, by alternating star contractions; nothing is gathered on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import remove_path, stage

#: Keys that ``with_least`` may broadcast at most: no more can have over a share of ``1 / HOT`` of the rows.
HOT = 10_000


def _signature(df: DataFrame):
    return tuple(df.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first())


def with_least(rows: DataFrame, key: str, value: str, total: int) -> DataFrame:
    """``rows`` with ``m``, the least ``value`` of their ``key``; keys are not null, ``total`` is at least the number of rows.

    Minima are pre-aggregated before they are shuffled. Keys of more than ``limit`` rows, of which there are at most
    ``HOT``, are looked up in a broadcast table, so that no task gets all rows of a hot key; the others meet in a shuffle.
    """
    limit = max(64, -(-total // HOT))
    least = rows.groupBy(key).agg(F.min(value).alias("m"), F.count("*").alias("strata_n"))
    hot = F.broadcast(least.filter(F.col("strata_n") > limit).select(key, "m"))
    few = least.filter(F.col("strata_n") <= limit).select(key, "m")
    return rows.join(hot, key).unionByName(rows.join(hot.select(key), key, "left_anti").join(few, key))


def components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of ``links`` (a, b: long): the component is its smallest reachable node.

    Each round hangs every node's larger neighbours on its smallest one, then its smaller neighbours likewise, until the
    table of stars stays as it is. A node with many links is hung by ``with_least``, in as many tasks as its links lie in.
    An empty table gives an empty result; self-links and repeated links do no harm.
    """
    stars, path = stage(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), "links")
    before = _signature(stars)
    while before[0]:
        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hung = with_least(both, "a", "b", 2 * before[0]).filter("b > a")
        large = hung.select(F.col("b").alias("a"), F.least("a", "m").alias("b")).filter("a <> b").distinct()
        large, middle = stage(large, "larger")
        joined = with_least(large, "a", "b", 2 * before[0])
        least = joined.select("a", F.col("m").alias("b"))
        small = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").unionByName(least).distinct()
        stars, newer = stage(small, "stars")
        for old in (path, middle):
            remove_path(links.sparkSession, old)
        path, after = newer, _signature(stars)
        if after == before:
            break
        before = after
    roots = stars.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return stars.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)
