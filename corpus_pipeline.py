"""The corpus pipeline: each stage takes what its predecessor kept, as written and read again, and returns a table.

run(spark, sf_dir) applies the stages to ``documents``. The stages: language identification drops documents without a
recognised language, near-duplicate groups keep their first document, passages that an earlier document has are cut,
documents with copies of test items go, and the rest is encoded. Every row counts by itself: ids may be null or repeated.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strata_engine.llm import bpe, decontaminate, langid, simhash, suffix_dedup
from strata_engine.llm.common import bucket_of, load, remove_path, stage
from strata_engine.llm.queries import vocabulary

#: A document whose cosine with the nearest language prototype is below this has no recognised language.
MIN_COSINE = 0.1


def _keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with ``strata_row``, a key of each row, in the order of ids, null ones last.

    It is the id where ids are neither null nor repeated. Otherwise rows are numbered in the order of ids, those of one id
    in that of a hash of the row, and written with their numbers, so that every later reading has the same keys.
    """
    if docs.groupBy("doc_id").count().filter("count > 1 or doc_id is null").isEmpty():
        return docs.withColumn("strata_row", F.col("doc_id").cast("long"))
    ordered = docs.orderBy(F.col("doc_id").asc_nulls_last(), F.xxhash64(*docs.columns))
    return stage(ordered.withColumn("strata_row", F.monotonically_increasing_id()), "pipeline-keyed")[0]


def _identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognised language; null texts and texts without letters have none."""
    rows = _keyed(docs)
    held = F.coalesce(bucket_of("doc_id", 4) == 2, F.lit(False))
    model = langid.fit(docs.filter(~held))
    kept = langid.predict(rows, model, id_col="strata_row").filter((F.col("lang_pred") != "und") & (F.col("score") >= MIN_COSINE)).select("strata_row")
    return rows.join(kept, "strata_row", "left_semi").select(*docs.columns)


def _near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first row of each group of near-duplicates, in the order of ids; null ids come last, and one row stays whatever ids repeat."""
    rows = _keyed(docs)
    groups = simhash.near_duplicates(rows, id_col="strata_row")
    return rows.join(groups.filter("strata_row = component_id").select("strata_row"), "strata_row", "left_semi").select(*docs.columns)


def _passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that an earlier row has, in the order of ids; those left without text go.

    Rows of one id, or of none, are documents of their own. A character that a cut leaves in part is dropped, as its bytes
    aren't text.
    """
    rows = _keyed(docs)
    cut = suffix_dedup.repeated_passages(rows, id_col="strata_row")
    cut = cut.withColumnRenamed(cut.columns[0], "strata_row").filter("n_removed > 0").select("strata_row", F.expr("try_validate_utf8(cast(kept as string))").alias("whole"), F.expr("make_valid_utf8(cast(kept as string))").alias("loose"), "n_removed")
    text = F.coalesce("whole", F.replace("loose", F.lit("�"), F.lit("")))
    cut = cut.select("strata_row", text.alias("new_text"), "n_removed")
    out = rows.join(cut, "strata_row", "left").withColumn("text", F.coalesce("new_text", "text"))
    out = out.withColumn("n_chars", F.when(F.col("n_removed").isNotNull(), F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return out.filter(F.col("n_removed").isNull() | (F.trim("text") != "")).select(*docs.columns)


def _decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a copy of a test item; rows of one id, or of none, are judged one by one."""
    rows = _keyed(docs)
    hits = decontaminate.contaminated(rows, load(spark, sf_dir, "benchmark"), id_col="strata_row")
    return rows.join(hits.select("strata_row").distinct(), "strata_row", "left_anti").select(*docs.columns)


def _encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and digests of the ids and of what they decode to."""
    path, pattern = vocabulary()
    ids = bpe.encode(docs, path, pattern).select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), "ids")
    return bpe.decode(ids, path, pattern).select("doc_id", "n_tokens", "ids_sha256", F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [("language_id", _identified), ("simhash_near_dedup", _near_dedup), ("suffix_dedup", _passages), ("decontamination", _decontaminated), ("bpe", _encoded)]

#: Hyperdimensional profiles and byte-level BPE aren't SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = load(spark, sf_dir, "documents"), None
    for name, step in STAGES:
        docs, path = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
        if before:  # its successor is written
            remove_path(spark, before)
        before = path
    return docs
