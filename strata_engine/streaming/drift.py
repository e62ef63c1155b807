"""Windows over event streams: moments, drift against a reference, one kept row a stratum. Batch and stream share the plans."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import exprs as E

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def clean(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def late_limit(events: DataFrame, delay: str) -> DataFrame:
    """The watermark, on streams only: batches have all their rows."""
    return events.withWatermark("ts", delay) if events.isStreaming else events


def late_rows(query: StreamingQuery) -> int:
    """Rows that a run dropped as older than its watermark, over the progress reports that it still holds.

    Windowed aggregates pre-aggregate a micro-batch first, so there late rows of one group, window and task count as one.
    """
    return sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])


def tumbling(events: DataFrame, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    g = late_limit(clean(events), delay).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean_value"))
    return g.select(F.col("window.start").alias("window_start"), "event_type", "n", "mean_value")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", delay: str = "1 hour") -> DataFrame:
    g = late_limit(clean(events), delay).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"), F.avg("value").alias("mean_value"))
    return g.select(F.col("window.start").alias("window_start"), "n", "mean_value")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    g = late_limit(clean(events), delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return g.select("user_id", F.col("session_window.start").alias("session_start"), "n", "total")


def reservoir(events: DataFrame, width: str = "1 day", seed: int = 42, delay: str = "1 hour") -> DataFrame:
    """One uniform event for each window and type: the one with the least keyed hash; state is one row a key."""
    u = E.portable_u(seed, "reservoir", F.col("event_id"))
    g = late_limit(clean(events), delay).withColumn("u", u).groupBy(F.window("ts", width), "event_type").agg(F.min_by("event_id", F.struct("u", "event_id")).alias("event_id"), F.count("*").alias("n"))
    return g.select(F.col("window.start").alias("window_start"), "event_type", "event_id", "n")


def features(events: DataFrame) -> DataFrame:
    """(event_id, ts, f0, f1, f2): log value and the hour on a circle."""
    hour = F.hour("ts") * F.lit(3.141592653589793 / 12)
    return clean(events).select("event_id", "ts", F.log1p("value").alias("f0"), F.sin(hour).alias("f1"), F.cos(hour).alias("f2"))


def _moments():
    f = ("f0", "f1", "f2")
    second = [F.avg(F.col(x) * F.col(y)).alias(f"q_{x}_{y}") for i, x in enumerate(f) for y in f[i:]]
    return [F.count("*").alias("n"), *second, *[F.avg(x).alias(f"m_{x}") for x in f], *[F.covar_samp(x, y).alias(f"c_{x}_{y}") for i, x in enumerate(f) for y in f[i:]]]


def reference(events: DataFrame, until: str) -> dict:
    return features(events).filter(F.col("ts") < F.lit(until).cast("timestamp")).agg(*_moments()).first().asDict()


def drift(events: DataFrame, ref: dict, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    """(window_start, n, cad, mean_shift, med) of each window against the reference moments, which are sixteen numbers.

    ``mean_shift`` is the squared distance of means, the discrepancy under the linear kernel, ``med`` that under the
    quadratic kernel about zero, by its exact map; in streams as in batches. A window of one row has a null ``cad``.
    """
    g = late_limit(features(events), delay).groupBy(F.window("ts", width)).agg(*_moments())
    f = ("f0", "f1", "f2")
    cad, shift, med = F.lit(0.0), F.lit(0.0), F.lit(0.0)
    for i, x in enumerate(f):
        shift = shift + F.pow(F.col(f"m_{x}") - F.lit(ref[f"m_{x}"]), F.lit(2.0))
        for y in f[i:]:
            cad = cad + (1.0 if x == y else 2.0) * F.pow(F.col(f"c_{x}_{y}") - F.lit(ref[f"c_{x}_{y}"]), F.lit(2.0))
            med = med + (1.0 if x == y else 2.0) * F.pow(F.col(f"q_{x}_{y}") - F.lit(ref[f"q_{x}_{y}"]), F.lit(2.0))
    return g.select(F.col("window.start").alias("window_start"), "n", cad.alias("cad"), shift.alias("mean_shift"), med.alias("med"))


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """The first row of every event id; in streams, ids are remembered no longer than the watermark's delay."""
    e = clean(events)
    return late_limit(e, delay).dropDuplicatesWithinWatermark(["event_id"]) if e.isStreaming else e.dropDuplicates(["event_id"])


def running_moments(events: DataFrame) -> DataFrame:
    """(event_type, n, mean_value, var_value) of all rows so far, once a micro-batch for every type in it.

    State is three numbers a type, whatever the rows: counts, means and squared deviations of micro-batches are merged.
    Null values are left out, a type without any gives no row.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean, dev = state.get if state.exists else (0, 0.0, 0.0)
        for b in batches:
            v = b["value"].dropna()
            if len(v):
                m, gap = float(v.mean()), float(v.mean()) - mean
                dev += float(((v - m) ** 2).sum()) + gap * gap * n * len(v) / (n + len(v))
                mean += gap * len(v) / (n + len(v))
                n += len(v)
        if n:
            state.update((n, mean, dev))
            yield pd.DataFrame({"event_type": [key[0]], "n": [n], "mean_value": [mean], "var_value": [dev / n]})

    out, kept = "event_type string, n long, mean_value double, var_value double", "n long, mean double, dev double"
    return events.select("event_type", "value").groupBy("event_type").applyInPandasWithState(update, out, kept, "update", GroupStateTimeout.NoTimeout)
