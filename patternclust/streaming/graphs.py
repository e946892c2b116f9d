"""Streams of graphs against a frozen model, session graphs, windows of counts, running decisions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.binomial import decide
from ..plans.clustering import Model
from ..sqlapi import graph_code


def assign_stream(graphs: DataFrame, model: Model) -> DataFrame:
    """Stateless assignment of arriving graphs."""
    return model.predict(graphs)


def session_graphs(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    """Closed sessions of each user as compact path graphs: events in order, consecutive ones linked. Rows behind the watermark are dropped."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    grouped = timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("es"))
    n = F.size("es")
    places = F.when(n > 1, F.sequence(F.lit(0), n - 2)).otherwise(F.array().cast("array<int>"))
    return grouped.select(
        F.xxhash64("user_id", "w.start").alias("graph_id"), "user_id", F.col("w.start").alias("start"), F.transform("es", lambda e: e["event_type"]).alias("vl"),
        places.alias("eu"), F.transform(places, lambda i: i + 1).alias("ew"), F.transform(places, lambda i: F.lit("next")).alias("el"),
    )


def drift(assigned: DataFrame, model: Model, every: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """``(start, cluster_id, n, hcov, drifting)`` per window of ``(ts, cluster_id, gsize)``: coverage under the split threshold flags drift."""
    sizes = {c: sum(g.size for g in r) / len(r) for c, r in model.representatives.items()}
    mean_size = F.create_map(*[F.lit(x) for c, s in sizes.items() for x in (c, float(s))]) if sizes else F.create_map(F.lit(-2), F.lit(0.0))
    w = F.window("ts", every, slide) if slide else F.window("ts", every)
    out = assigned.withWatermark("ts", late).groupBy(w.alias("w"), "cluster_id").agg(F.count(F.lit(1)).alias("n"), F.avg("gsize").alias("g"))
    hcov = mean_size[F.col("cluster_id")] / F.col("g")
    return out.select(F.col("w.start").alias("start"), "cluster_id", "n", hcov.alias("hcov"), (hcov <= model.cfg.split_threshold).alias("drifting"))


def distinct_graphs(graphs: DataFrame, late: str = "1 hour") -> DataFrame:
    """Graphs of ``(ts, vl, eu, ew, el)`` without isomorphic ones that came within the watermark."""
    coded = graphs.withColumn("code", graph_code(F.struct("vl", "eu", "ew", "el")))
    return coded.withWatermark("ts", late).dropDuplicatesWithinWatermark(["code"])


class RunningSupport(StatefulProcessor):
    """Hits and draws of each pattern, and what they decide so far."""

    def __init__(self, minsup: float, alpha: float, h_min: int = 30):
        self.minsup, self.alpha, self.h_min = minsup, alpha, h_min

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("counts", "k bigint, n bigint, tested bigint, decision string")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        k, n, tested, decision = self.state.get() if self.state.exists() else (0, 0, 0, "UNDECIDED")
        for pdf in rows:
            for hit in pdf["hit"].tolist():
                k, n = k + int(hit), n + 1
                # tests at doubling counts only, as many as the correction allows for
                if decision == "UNDECIDED" and n >= self.h_min and n == self.h_min << max(0, (n // self.h_min).bit_length() - 1):
                    tested, decision = tested + 1, decide(k, n, self.minsup, self.alpha)
        self.state.update((k, n, tested, decision))
        yield pd.DataFrame([(key[0], k, n, tested, decision)], columns=["pattern", "k", "n", "tested", "decision"])

    def close(self) -> None:
        pass


def running_support(hits: DataFrame, minsup: float, alpha: float) -> DataFrame:
    """``(pattern, k, n, tested, decision)`` from a stream of ``(pattern, hit)``; needs the RocksDB state store."""
    return hits.groupBy("pattern").transformWithStateInPandas(RunningSupport(minsup, alpha), "pattern string, k bigint, n bigint, tested bigint, decision string", "Update", "None")


def refit_noise(model: Model, share: float, refit):
    """A function for foreachBatch: calls ``refit(noise rows, batch id)`` when more than ``share`` of a batch is noise."""

    def on_batch(batch: DataFrame, number: int) -> None:
        row = batch.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("cluster_id") == -1, 1)).alias("noise")).first()
        if row["n"] and row["noise"] / row["n"] > share:
            refit(batch.where("cluster_id = -1"), number)

    return on_batch
