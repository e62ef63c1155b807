"""The queries of the training-data operators and, where SQL can express one, its DuckDB form."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bm25, bpe, decontaminate, html_blocks, importance, langid, licenses, simhash, suffix_dedup, toxicity
from .common import bucket_of, load


def vocabulary() -> tuple[str, str]:
    """(path of the token ranks, pattern) that the contract of encoding names."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.repeated_passages(load(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op2_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    # All labelled rows count, and their number grows with the corpus: a merge join at every size, never a broadcast.
    good = docs.select("doc_id", "text").join(labels.filter("quality = 1").select("doc_id").distinct().hint("merge"), "doc_id", "left_semi")
    share = labels.agg(F.avg(F.col("quality").cast("double"))).first()[0] or 0.0
    return importance.resample(docs, good, share)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    held = bucket_of("doc_id", 4) == 2
    model = langid.fit(docs.filter(F.coalesce(~held, F.lit(True))))
    return langid.predict(docs, model).select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "lang_pred", "score")


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(load(spark, sf_dir, "documents"), licenses.known(spark))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def op6_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_blocks.extract(load(spark, sf_dir, "pages"))


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path, pattern = vocabulary()
    ids = bpe.encode(load(spark, sf_dir, "documents"), path, pattern)
    marked = ids.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), "ids")
    return bpe.decode(marked, path, pattern).select("doc_id", "n_tokens", "ids_sha256", F.sha2("decoded", 256).alias("decoded_sha256"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(load(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.as_hex("fp").alias("fingerprint"), "component_id")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    known = labels.filter((bucket_of("doc_id", 5) != 0) & F.col("toxic").isNotNull()).select("doc_id", "toxic")
    model = toxicity.fit(docs.select("doc_id", "text").join(known, "doc_id"))
    held = F.coalesce(bucket_of("doc_id", 5) == 0, F.lit(False))
    return toxicity.score(docs, model).select("doc_id", held.alias("held_out"), "score", "predicted")


def op10_bm25(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    asked = docs.filter(F.col("doc_id") % 50 == 0).withColumnRenamed("doc_id", "query_id")
    return bm25.search(docs, asked, k=10)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def _canonical_sql(x: str) -> str:
    out = f"translate(coalesce({x}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    out = rf"regexp_replace({out}, '(^|\n)[ \t#*/]*(\(c\)|©|copyright)[^\n]*', chr(10), 'g')"
    out = rf"' ' || regexp_replace({out}, '[\x00-/:-@\[-`{{-\x7f]+', '  ', 'g') || ' '"
    for a, b in licenses.SPELLINGS:
        out = f"replace({out}, ' {a} ', ' {b} ')"
    return f"trim(regexp_replace({out}, ' +', ' ', 'g'))"


def _license_sql() -> str:
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    rows = ", ".join(f"({quote(n)}, {quote(t)})" for n, ts in licenses.TEXTS.items() for t in ts)
    return f"""with texts(license, body) as (values {rows}),
known as (select sha256({_canonical_sql('body')}) as digest, min(license) as license from texts group by 1),
whole as (select doc_id, text, sha256({_canonical_sql('text')}) as digest from documents),
pieces as (select doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line from documents),
hits as (select doc_id, count(*) as n, string_agg(distinct license, ',' order by license) as names
         from (select doc_id, sha256({_canonical_sql('line')}) as digest from pieces) join known using (digest) group by doc_id)
select w.doc_id, k.license, cast(coalesce(h.n, 0) as bigint) as n_lines, coalesce(h.names, '') as line_licenses
from whole w left join known k using (digest) left join hits h on h.doc_id = w.doc_id"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_suffix_dedup, op2_importance_resampling, op3_language_id, op4_license_scan, op5_decontamination, op6_html_extraction, op7_bpe, op8_simhash, op9_toxicity, op10_bm25, pipeline)}


SUFFIX_SQL = """with d as (select doc_id, hex(encode(coalesce(text, ''))) as h, cast(octet_length(encode(coalesce(text, ''))) as bigint) as n from documents),
starts as (select doc_id, p, substr(h, 2 * p + 1, 100) as s from (select doc_id, h, unnest(range(0, greatest(0, n - 49))) as p from d)),
seen as (select s, min(doc_id) as least from starts group by s),
hit as (select doc_id, p from starts join seen using (s) where least < doc_id),
runs as (select doc_id, p, case when p > 50 + lag(p) over w or lag(p) over w is null then 1 else 0 end as new from hit window w as (partition by doc_id order by p)),
spans as (select doc_id, k, min(p) as a, max(p) + 50 as b from (select doc_id, p, sum(new) over (partition by doc_id order by p) as k from runs) group by doc_id, k),
gaps as (select doc_id, a, b, coalesce(lag(b) over (partition by doc_id order by a), 0) as before from spans),
kept as (select g.doc_id, string_agg(substr(d.h, 2 * before + 1, 2 * (a - before)), '' order by a) as front, max(b) as last, sum(b - a) as n_removed, count(*) as n_spans from gaps g join d using (doc_id) group by g.doc_id)
select d.doc_id, d.n as n_bytes, cast(coalesce(k.n_removed, 0) as bigint) as n_removed, cast(coalesce(k.n_spans, 0) as bigint) as n_spans,
       sha256(unhex(coalesce(k.front, '') || substr(d.h, 2 * coalesce(k.last, 0) + 1))) as kept_sha256
from d left join kept k on k.doc_id = d.doc_id"""


def oracle_sql() -> dict[str, str]:
    return {"op1_suffix_dedup": SUFFIX_SQL, "op4_license_scan": _license_sql()}
