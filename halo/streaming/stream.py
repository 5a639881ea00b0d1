"""Streams: grids and windows with watermarks, running covariances, forecasts, joins, sinks."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType


def grid(df: DataFrame, ts: str, step: str, delay: str, *keys: str) -> DataFrame:
    """Counts of tumbling windows."""
    return df.withWatermark(ts, delay).groupBy(F.window(ts, step), *keys).agg(F.count(F.lit(1)).alias("v"))


def sliding(df: DataFrame, ts: str, width: str, every: str, *keys: str) -> DataFrame:
    return df.groupBy(F.window(ts, width, every), *keys).agg(F.count(F.lit(1)).alias("v"))


def sessions(df: DataFrame, ts: str, gap: str, *keys: str) -> DataFrame:
    return df.groupBy(F.session_window(ts, gap), *keys).agg(F.count(F.lit(1)).alias("v"))


def late_report(live: DataFrame, ts: str, step: str, delay: str, fed: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Rows fed to a windowed count, rows it kept, and rows that came after the watermark and were left out: fed, kept, late."""
    got = run(grid(live, ts, step, delay), path, checkpoint, "update")
    last = got.groupBy("window").agg(F.max("v").alias("v")).agg(F.sum("v").alias("kept"))
    return fed.agg(F.count(F.lit(1)).alias("fed")).crossJoin(last).select("fed", "kept", (F.col("fed") - F.col("kept")).alias("late"))


def dedup(df: DataFrame, key: str, ts: str, delay: str) -> DataFrame:
    return df.withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def score(df: DataFrame, model: DataFrame, on: str) -> DataFrame:
    """A stream joined with a static table of parameters (Spark broadcasts it where its size allows)."""
    return df.join(model, on)


def interval_join(left: DataFrame, right: DataFrame, key: str, within: str) -> DataFrame:
    """Pairs of two streams (columns lts, rts, both watermarked) with rts in [lts, lts + within]."""
    return left.join(right, F.expr(f"{key}_l = {key}_r AND rts >= lts AND rts <= lts + INTERVAL {within}"))


def autocov(df: DataFrame, key: str, max_lag: int) -> DataFrame:
    """Running lag sums by key (columns idx, v), updated in each micro-batch: key, lag, n, s.

    State: the last max_lag rows and the sums so far, as JSON; rows of a batch are sorted by idx.
    """

    def update(k, batches: Iterator[pd.DataFrame], state):
        held = json.loads(state.get[0]) if state.exists else {"tail": [], "n": [0] * (max_lag + 1), "s": [0] * (max_lag + 1)}
        rows = sorted((int(i), int(v)) for b in batches for i, v in zip(b["idx"], b["v"]))
        known = dict(map(tuple, held["tail"]))
        for i, v in rows:
            known[i] = v
            for h in range(max_lag + 1):
                if i - h in known:
                    held["n"][h] += 1
                    held["s"][h] += known[i - h] * v
            known.pop(i - max_lag - 1, None)
        held["tail"] = sorted(known.items())[-max_lag:] if max_lag else []
        state.update((json.dumps(held),))
        yield pd.DataFrame({key: [k[0]] * (max_lag + 1), "lag": range(max_lag + 1), "n": held["n"], "s": held["s"]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    kind = dict(df.dtypes)[key]
    return df.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, lag int, n bigint, s bigint", "held string", "update", GroupStateTimeout.NoTimeout)


def arma_forecast(df: DataFrame, key: str, a: list[float], b: list[float]) -> DataFrame:
    """One-step forecasts by key with state of the last max(p, q) values and innovations: key, idx, yhat (for idx + 1)."""

    def update(k, batches, state):
        held = json.loads(state.get[0]) if state.exists else {"x": [], "e": [], "f": 0.0}
        out = []
        for i, v in sorted((int(i), float(v)) for d in batches for i, v in zip(d["idx"], d["v"])):
            held["e"] = ([v - held["f"]] + held["e"])[: max(1, len(b))]
            held["x"] = ([v] + held["x"])[: max(1, len(a))]
            held["f"] = sum(w * x for w, x in zip(a, held["x"])) + sum(w * e for w, e in zip(b, held["e"]))
            out.append((i, held["f"]))
        state.update((json.dumps(held),))
        yield pd.DataFrame({key: [k[0]] * len(out), "idx": [i for i, _ in out], "yhat": [f for _, f in out]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    kind = dict(df.dtypes)[key]
    return df.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, idx bigint, yhat double", "held string", "append", GroupStateTimeout.NoTimeout)


def run(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run to the end of what is there, batch tables below `path`; the rows of all batches with column batch."""
    spark = df.sparkSession

    def sink(batch, number):
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
    return spark.read.schema(StructType([*df.schema.fields, StructField("batch", LongType())])).parquet(path)
