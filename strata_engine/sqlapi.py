"""SQL names of the methods: kernels and uniforms as SQL functions, draws and partitions as table functions."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .functions.theory import partitions
from .sources.io import prepare_workers


@udtf(returnType="iter int, stratum int, pos int, weight double")
class DrawStrata:
    """Draws from sizes: a row (stratum, n_h, n) of the table argument gives one place an iteration."""

    def eval(self, row, iters: int, seed: int):
        for it in range(iters):
            u = int(hashlib.md5(f"{seed}|draw|{it}|{row['stratum']}|0".encode()).hexdigest()[:13], 16) / float(1 << 52)
            yield it, row["stratum"], int(u * row["n_h"]), row["n_h"] / row["n"]


@udtf(returnType="pid int, row int, block int")
class EnumeratePartitions:
    def eval(self, n: int, k: int):
        for p, blocks in enumerate(partitions(n, k)):
            for r, b in enumerate(blocks):
                yield p, r, b


FUNCTIONS = [
    "rbf(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, g DOUBLE) RETURNS DOUBLE RETURN exp(-g * aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, v) -> s + v))",
    "rbf_mix(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(transform(array(0.001D, 0.01D, 0.1D, 1.0D, 10.0D), g -> exp(-g * aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, v) -> s + v))), 0.0D, (s, v) -> s + v)",
    "quad_kernel(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, mu ARRAY<DOUBLE>) RETURNS DOUBLE RETURN power(aggregate(zip_with(zip_with(a, mu, (x, m) -> x - m), zip_with(b, mu, (y, m) -> y - m), (x, y) -> x * y), 0.0D, (s, v) -> s + v), 2.0D)",
    "portable_u(seed STRING, purpose STRING, id STRING) RETURNS DOUBLE RETURN cast(conv(substring(md5(concat_ws('|', seed, purpose, id)), 1, 13), 16, 10) as bigint) / 4503599627370496.0D",
]


def register(spark: SparkSession) -> None:
    """Make the names known to this session; calling it again is harmless."""
    prepare_workers(spark)
    for f in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {f}")
    spark.udtf.register("draw_strata", DrawStrata)
    spark.udtf.register("enumerate_partitions", EnumeratePartitions)
