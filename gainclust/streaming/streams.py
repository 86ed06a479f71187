"""Streams of vectors: scoring with a saved state, absorbing new rows, windows and duplicates."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from gainclust.functions.vectors import dot, norm2
from gainclust.operators import kway


def score_stream(stream: DataFrame, state: DataFrame) -> DataFrame:
    """Append (id, cluster): nearest centroid of a static state, row by row and without shuffle or Python."""
    c = state.where("cnt > 0").agg(F.array_sort(F.collect_list(F.struct("cluster", "cnt", "sum_vec", F.col("dd").cast("double").alias("dd")))).alias("every"))
    d2 = F.transform("every", lambda s: F.struct((s["dd"].cast("double") / (s["cnt"].cast("double") * s["cnt"]) - 2 * dot(F.col("vec"), s["sum_vec"]) / s["cnt"]).alias("d"), s["cluster"].alias("c")))
    return stream.crossJoin(F.broadcast(c)).select("id", F.array_min(d2)["c"].alias("cluster"))


def absorb(batch: DataFrame, state: DataFrame) -> DataFrame:
    """New state after each row joins the cluster whose score it raises most: one pass, sums combine before the shuffle."""
    every = state.agg(F.array_sort(F.collect_list(F.struct("cluster", "cnt", "sum_vec", F.col("dd").cast("double").alias("dd")))).alias("every"))
    q = norm2(F.col("vec"))
    won = lambda s: F.when(s["cnt"] == 0, q).otherwise((2 * dot(F.col("vec"), s["sum_vec"]) + q - s["dd"] / F.nullif(s["cnt"], F.lit(0))) / (s["cnt"] + 1))
    best = F.array_max(F.transform("every", lambda s: F.struct(won(s).alias("g"), (-s["cluster"]).alias("neg"))))
    placed = batch.crossJoin(F.broadcast(every)).select("vec", (-best["neg"]).cast("int").alias("cluster"))
    old = state.select("cluster", "cnt", "xx", F.posexplode("sum_vec").alias("pos", "s"))
    new = placed.select("cluster", norm2(F.col("vec")).alias("q"), F.posexplode("vec").alias("pos", "x")).groupBy("cluster", "pos").agg(F.count(F.lit(1)).alias("n"), F.sum("q").alias("q"), F.sum("x").alias("x"))
    both = old.join(new, ["cluster", "pos"], "left").select("cluster", "pos", (F.col("cnt") + F.coalesce("n", F.lit(0))).alias("cnt"), (F.col("xx") + F.coalesce("q", F.lit(0.0))).alias("xx"), (F.col("s") + F.coalesce("x", F.lit(0.0))).alias("s"))
    g = both.groupBy("cluster").agg(F.max("cnt").alias("cnt"), F.transform(F.array_sort(F.collect_list(F.struct("pos", "s"))), lambda p: p["s"]).alias("sum_vec"), F.max("xx").alias("xx"))
    return g.select("cluster", "cnt", "sum_vec", norm2(F.col("sum_vec")).alias("dd"), "xx")


class Absorber:
    """foreachBatch sink: each batch id writes its own state folder once, so replays change nothing."""

    def __init__(self, path: str):
        self.path = path

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        state = spark.read.parquet(f"{self.path}/batch={batch_id - 1}")
        absorb(batch, state).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")


class Refresher:
    """foreachBatch sink: keeps the rows, and every `every` batches refines the labels of all of them by gain moves.

    Folder rows/batch=i holds the rows of a batch, labels/batch=i the labels after it; a replayed batch writes the same
    folders again. Start: labels of the first batch by `k` random labels.
    """

    def __init__(self, path: str, k: int, every: int = 10, max_epochs: int = 5, seed: int = 42):
        self.path, self.k, self.every, self.max_epochs, self.seed = path, k, every, max_epochs, seed

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        batch.select("id", "vec").write.mode("overwrite").parquet(f"{self.path}/rows/batch={batch_id}")
        if (batch_id + 1) % self.every:
            return
        rows = spark.read.parquet(*[f"{self.path}/rows/batch={i}" for i in range(batch_id + 1)])
        start = kway.random_labels(rows.select("id"), self.k, self.seed)
        if batch_id >= self.every:
            known = spark.read.parquet(f"{self.path}/labels/batch={batch_id - self.every}").withColumnRenamed("cluster", "old")
            start = start.join(known, "id", "left").select("id", F.coalesce("old", "cluster").alias("cluster"))
        got = kway.gain_kway(rows, self.k, start, max_epochs=self.max_epochs, seed=self.seed)
        got.assignments.write.mode("overwrite").parquet(f"{self.path}/labels/batch={batch_id}")


PROFILE = "user_id long, n long, sum_vec array<double>"


def profiles(stream: DataFrame, d: int, idle_ms: int | None = 86_400_000) -> DataFrame:
    """Running (user_id, n, sum_vec) of a stream (user_id, vec): one state row per user, forgotten after idle_ms without rows.

    A query with such a timeout keeps looking for idle users, so it runs until it is stopped, even if it should only
    take what is there; idle_ms=None keeps every user.
    """

    def update(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, total = state.get if state.exists else (0, [0.0] * d)
        total = np.asarray(total, float)
        for f in frames:
            n += len(f)
            total = total + np.stack(f["vec"].to_numpy()).astype(float).sum(0)
        state.update((n, total.tolist()))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "sum_vec": [total.tolist()]})

    return stream.groupBy("user_id").applyInPandasWithState(update, PROFILE, "n long, sum_vec array<double>", "update", GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout)


MAX_VERSIONS = 100_000


def as_of(rows: DataFrame, versions: DataFrame) -> DataFrame:
    """Rows with the version (version, since) in force at their ts; rows before the first have none.

    Versions are turned into intervals that do not overlap, checked to be few, and broadcast: one match a row.
    """
    n = versions.count()
    if n > MAX_VERSIONS:
        raise ValueError(f"{n} versions are too many to broadcast")
    spans = versions.select("version", "since", F.lead("since").over(Window.orderBy("since", "version")).alias("until"))
    return rows.join(F.broadcast(spans), (F.col("ts") >= F.col("since")) & (F.col("until").isNull() | (F.col("ts") < F.col("until"))), "left").drop("since", "until")


def followed_by(events: DataFrame, first: str, then: str, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """(user_id, first_id, then_id): events of one kind and those of another by the same user up to `within` later.

    On a stream both sides carry the watermark, so state older than both bounds is dropped.
    """
    side = lambda kind, p: events.where(F.col("event_type") == kind).select("user_id", F.col("event_id").alias(f"{p}_id"), F.col("ts").alias(f"{p}_ts")).withWatermark(f"{p}_ts", late)
    a, b = side(first, "first").alias("a"), side(then, "then").alias("b")
    near = (F.col("then_ts") >= F.col("first_ts")) & (F.col("then_ts") <= F.col("first_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & near).select("a.user_id", "first_id", "then_id")


def user_windows(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """Event counts per user and window (tumbling, or sliding if slide is given); later rows are dropped by the watermark."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    marked = events.withWatermark("ts", late)
    kinds = [F.sum(F.when(F.col("event_type") == x, 1).otherwise(0)).alias(x) for x in ("click", "purchase", "error", "signup", "view")]
    return marked.groupBy(w.alias("w"), "user_id").agg(*kinds, F.max("value").alias("top")).select("user_id", F.col("w.start").alias("start"), "click", "purchase", "error", "signup", "view", "top")


def user_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    g = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def first_events(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Replayed events once each, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drift(scored: DataFrame, width: str = "1 day") -> DataFrame:
    """Mean squared distance per event-time window."""
    return scored.groupBy(F.window("ts", width).alias("w")).agg(F.avg("dist2").alias("distortion"), F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "distortion", "n")
