"""The relational operators around the methods: features, joins, windows, sets, pivots, ranges and as-of lookups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """Latest ``right`` value at or before each left time, by one sort of both sides in place of a range join."""
    a = left.select("*", F.col(left_ts).alias("strata_t"), F.lit(None).cast(right.schema[value].dataType).alias("strata_v"), F.lit(1).alias("strata_side"))
    b = right.select(*[F.col(key) if c == key else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(right_ts).alias("strata_t"), F.col(value).alias("strata_v"), F.lit(0).alias("strata_side"))
    w = Window.partitionBy(key).orderBy("strata_t", "strata_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last("strata_v", ignorenulls=True).over(w)).filter("strata_side = 1").drop("strata_t", "strata_v", "strata_side")


def interval_pairs(a: DataFrame, b: DataFrame, key: str, ts: str, hours: int) -> DataFrame:
    """Pairs of a key whose times lie within ``hours`` after each other: rows meet in hour buckets, never all with all."""
    width = hours * 3600
    bucket = F.floor(F.unix_timestamp(ts) / width)
    x = a.select(F.col(key), F.col("event_id").alias("a_id"), F.col(ts).alias("a_ts"), bucket.alias("bucket"))
    y = b.select(F.col(key), F.col("event_id").alias("b_id"), F.col(ts).alias("b_ts"), F.explode(F.array(bucket, bucket - 1)).alias("bucket"))
    near = x.join(y, [key, "bucket"])
    gap = F.unix_micros("b_ts") - F.unix_micros("a_ts")
    return near.filter((gap >= 0) & (gap <= width * 1_000_000)).select(key, "a_id", "b_id")


def quantile_bins(df: DataFrame, key: str, col: str, bins: int) -> DataFrame:
    """(key, bin) by exact quantile edges: the edges are ``bins`` - 1 numbers, joined as a literal range."""
    edges = df.agg(F.percentile(col, F.array(*[F.lit(i / bins) for i in range(1, bins)])).alias("e")).first()["e"]
    at = F.lit(0)
    for e in edges or []:
        at = at + F.when(F.col(col) >= F.lit(float(e)), 1).otherwise(0)
    return df.select(key, at.cast("int").alias("bin"))


def contingency(a: DataFrame, b: DataFrame) -> DataFrame:
    """(x, y, n): rows by their strata in two versions."""
    return a.select("id", F.col("stratum").alias("x")).join(b.select("id", F.col("stratum").alias("y")), "id").groupBy("x", "y").agg(F.count("*").alias("n"))


def adjusted_rand(table: DataFrame) -> DataFrame:
    """(ari, n) from a contingency table."""
    two = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2.0)
    cells = table.agg(two("n").alias("cells"), F.sum("n").alias("n")).withColumn("k", F.lit(1))
    rows = table.groupBy("x").agg(F.sum("n").alias("r")).agg(two("r").alias("rows")).withColumn("k", F.lit(1))
    cols = table.groupBy("y").agg(F.sum("n").alias("c")).agg(two("c").alias("cols")).withColumn("k", F.lit(1))
    j = cells.join(rows, "k").join(cols, "k")
    expected = F.col("rows") * F.col("cols") / (F.col("n") * (F.col("n") - 1) / 2.0)
    return j.select(((F.col("cells") - expected) / ((F.col("rows") + F.col("cols")) / 2 - expected)).alias("ari"), "n")
