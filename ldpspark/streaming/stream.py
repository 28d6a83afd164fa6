"""Streams of private records.

Every function takes a batch or a streaming frame alike; the batch form is the twin that tests hold the stream against.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.erm.descent import Model, gradient_sums, prepared, update
from ldpspark.operators.relops import numbered
from ldpspark.sources.ship import ship


def event_stream(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def timed(events: DataFrame, delay: str | None = None) -> DataFrame:
    """Event time as a timestamp with a zone (watermarks need one), and a watermark if ``delay`` is given."""
    out = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return out.withWatermark("ts", delay) if delay else out


def one_per_period(events: DataFrame, user: str, period: str) -> DataFrame:
    """One record per user and window: in a stream the first that arrives, within the watermark. Needs ``timed``."""
    marked = events.withColumn("period", F.window("ts", period)["start"])
    if events.isStreaming:
        return marked.dropDuplicatesWithinWatermark([user, "period"])
    return marked.dropDuplicates([user, "period"])


def tumbling(reports: DataFrame, period: str) -> DataFrame:
    """(start, j, total, reports) per window of signs."""
    out = reports.groupBy(F.window("ts", period).alias("w"), "j").agg(F.sum("sign").cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))
    return out.select(F.col("w.start").alias("start"), "j", "total", "reports")


def sliding(reports: DataFrame, period: str, step: str) -> DataFrame:
    out = reports.groupBy(F.window("ts", period, step).alias("w"), "j").agg(F.sum("sign").cast("long").alias("total"), F.count(F.lit(1)).alias("reports"))
    return out.select(F.col("w.start").alias("start"), "j", "total", "reports")


def sessions(events: DataFrame, user: str, gap: str) -> DataFrame:
    """(user, start, end, n) of each user's sessions."""
    out = events.groupBy(user, F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return out.select(user, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


LEDGER = "user_id long, reports long, spent double, refused long"


def budget_gate(reports: DataFrame, limit: float, eps: float, horizon_seconds: int | None = None) -> DataFrame:
    """Running ledger of each user in a stream: (user_id, reports, spent, refused); what would pass ``limit`` is refused.

    State is three numbers per user. Without a horizon it is kept for ever, as a forgotten user would get a new budget. With one, ``limit`` holds for users who are
    heard of again within ``horizon_seconds`` of event time ``ts``, which needs a watermark; the ledger of a user silent for longer is dropped.
    """
    ship(reports.sparkSession)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, spent, refused = state.get if state.exists else (0, 0.0, 0)
        last = 0
        for pdf in frames:
            for _ in range(len(pdf)):
                if spent + eps <= limit + 1e-12:
                    n, spent = n + 1, spent + eps
                else:
                    refused += 1
            if horizon_seconds is not None and len(pdf):
                last = max(last, int(pdf["ts"].max().timestamp() * 1000))
        state.update((n, spent, refused))
        if horizon_seconds is not None:
            state.setTimeoutTimestamp(max(last + horizon_seconds * 1000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame([(key[0], n, spent, refused)], columns=["user_id", "reports", "spent", "refused"])

    timeout = "NoTimeout" if horizon_seconds is None else "EventTimeTimeout"
    return reports.groupBy("user_id").applyInPandasWithState(step, LEDGER, "reports long, spent double, refused long", "update", timeout)


class StreamTrainer:
    """Mini-batch descent fed by micro-batches, for ``foreachBatch``.

    Weights, step and the sums of the open group are one small JSON document per stream batch in the shared store; a batch that comes again after a failure
    starts from the document of the batch before, so a replay gives the same weights.
    """

    def __init__(self, spark: SparkSession, path: str, dim: int, eps: float, group: int, kind: str, lam: float = 1e-4, gamma0: float = 1.0):
        self.spark, self.path = spark, path.rstrip("/")
        self.dim, self.eps, self.group, self.kind, self.lam, self.gamma0 = dim, eps, group, kind, lam, gamma0

    def _state(self, batch: int) -> dict:
        fresh = {"weights": [0.0] * self.dim, "step": 0, "open": 0, "sums": {}}
        if batch < 0:
            return fresh
        text = self.spark.read.text(f"{self.path}/batch={batch}", wholetext=True).collect()
        return json.loads(text[0][0])

    def __call__(self, frame: DataFrame, batch: int) -> None:
        """Users of the batch in the order of ``ts``, if there is one, and ``ukey``; each group of ``group`` users sees the weights of the groups before it."""
        state = self._state(batch - 1)
        order = [F.col(c) for c in ("ts", "ukey") if c in frame.columns]
        users = numbered(prepared(frame, mode="xx"), order, "seq").persist()
        try:
            n = users.count()
            spans, done = [], 0
            while done < n:
                take = min(self.group - state["open"], n - done)
                spans.append((done, take))
                model = Model("stream", self.dim, self.eps, 1, weights=state["weights"])
                part = users.where((F.col("seq") >= done) & (F.col("seq") < done + take)).withColumn("ub", F.lit(0.0))
                for r in gradient_sums(part, [model], 0, self.kind, self.lam).collect():
                    total, count = state["sums"].get(str(r["j"]), (0, 0))
                    state["sums"][str(r["j"])] = (total + r["total"], count + r["reports"])
                state["open"] += take
                done += take
                if state["open"] == self.group:
                    update(model, {int(j): tuple(v) for j, v in state["sums"].items()}, state["step"], self.gamma0, 0.0)
                    state = {"weights": model.weights, "step": state["step"] + 1, "open": 0, "sums": {}}
        finally:
            users.unpersist()
        self.spark.createDataFrame([(json.dumps(state),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/batch={batch}")

    def weights(self, batch: int) -> list[float]:
        return self._state(batch)["weights"]
