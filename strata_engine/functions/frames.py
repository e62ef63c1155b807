"""Feature frames (id, z, y, domain, env) on the given tables, and the shift constructors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.io import dealt, load
from . import exprs as E

SEED = 42


def checked(ff: DataFrame, d: int, on_bad: str = "raise") -> DataFrame:
    """Rows with whole vectors of length ``d``; others raise with their number, unless ``on_bad='drop'``."""
    if on_bad == "raise" and (bad := ff.filter(~E.finite("z", d)).count()):
        raise ValueError(f"{bad} rows have a null, short, long or non-finite vector")
    return ff.filter(E.finite("z", d))


def with_domain(ff: DataFrame, how: str, component: int = 0, seed: int = SEED, scale: float = 1.5, offset: float = 0.25) -> DataFrame:
    """``hard``, ``soft``, ``null`` or ``affine`` source and target, from portable uniforms keyed by id."""
    u, z0 = E.portable_u(seed, how, F.col("id")), F.col("z")[component]
    if how == "hard":
        return ff.withColumn("domain", F.when(z0 >= 0, "s").otherwise("t"))
    if how == "soft":
        return ff.withColumn("domain", F.when(u < F.when(z0 >= 0, 0.8).otherwise(0.2), "s").otherwise("t"))
    ff = ff.withColumn("domain", F.when(u < 0.5, "s").otherwise("t"))
    if how == "affine":
        return ff.withColumn("z", F.when(F.col("domain") == "t", F.transform("z", lambda x: x * scale + offset)).otherwise(F.col("z")))
    if how != "null":
        raise ValueError(f"unknown constructor {how}")
    return ff


def embeddings(spark: SparkSession, sf_dir: str, how: str = "soft") -> DataFrame:
    src = load(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"])
    return with_domain(src.select(F.col("vec_id").alias("id"), E.vec("embedding").alias("z"), F.col("label").cast("int").alias("y")), how)


LINE = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")


def standardised(df: DataFrame, columns) -> DataFrame:
    """``z`` of the columns, less their mean and divided by their population deviation: one aggregate, then literals."""
    s = df.agg(*[f(c).alias(f"{n}_{c}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    return df.withColumn("z", F.array(*[(F.col(c).cast("double") - F.lit(s[f"m_{c}"])) / F.lit(s[f"s_{c}"] or 1.0) for c in columns]))


def lineitem(spark: SparkSession, sf_dir: str, how: str = "affine") -> DataFrame:
    """Line items: the id is 60 bits of a hash of the five columns that tell rows apart."""
    src = dealt(load(spark, sf_dir, "lineitem", [*LINE, *LINE_KEY, "l_returnflag", "l_linestatus"]))
    key = [F.date_format("l_shipdate", "yyyy-MM-dd") if c == "l_shipdate" else F.col(c) for c in LINE_KEY]
    src = src.withColumn("id", E.hash_bits(*key, digits=15)).withColumn("env", F.concat("l_returnflag", "l_linestatus"))
    return with_domain(standardised(src, LINE).select("id", "z", "env", F.floor(F.col("l_quantity") / 12.75).cast("int").alias("y")), how)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = dealt(load(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"])), load(spark, sf_dir, "labels")
    one = labels.groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    f = E.text_features("text")
    return docs.select("doc_id", F.array(*f.values()).alias("z"), F.col("lang").alias("env"), "source").join(one, "doc_id", "left").select(F.col("doc_id").alias("id"), "z", "env", "source", F.col("quality").alias("y"), "toxic")


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with customer numbers; the region is the environment. The dimension tables are small by their nature."""
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"])
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_acctbal"])
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    month = F.month("o_orderdate") * F.lit(np.pi / 6)
    return j.select(F.col("o_orderkey").alias("id"), F.array(F.col("o_totalprice") / 1e4, F.col("c_acctbal") / 5e3, F.sin(month), F.cos(month)).alias("z"), F.col("r_name").alias("env"))


def planted(ids: np.ndarray, z: np.ndarray, env: np.ndarray, classes: int, target: str, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Learning workload: class = quantile of a fixed linear score of clean features; every environment then distorts its
    features by its own affine map, and one spurious coordinate agrees with the class in 0.9 of source rows and at random in the target."""
    rng = np.random.default_rng(seed)
    z = (z - z.mean(0)) / np.maximum(z.std(0), 1e-9)
    score = z @ rng.normal(size=z.shape[1])
    y = np.searchsorted(np.quantile(score, np.arange(1, classes) / classes), score)
    out = np.empty((len(z), z.shape[1] + 1))
    noise = np.random.default_rng([seed, 1]).random(len(z))
    for e in np.unique(env):
        g = np.random.default_rng([seed, 2, *map(ord, str(e))])
        q, _ = np.linalg.qr(np.eye(z.shape[1]) + 0.35 * g.normal(size=(z.shape[1],) * 2))
        at = env == e
        out[at, :-1] = (z[at] @ q) * (1 + 0.2 * g.random()) + 0.4 * g.normal(size=z.shape[1])
    agree = np.where(env == target, 1.0 / classes, 0.9)
    out[:, -1] = np.where(noise < agree, y, rng.integers(0, classes, len(z))) / max(classes - 1, 1) * 2 - 1
    return out, y
