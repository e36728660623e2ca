"""Arrays that grow in time, as streams.

Time is a mode, and for every other mode the Gram matrix is a sum over time slices: a
slice enters once, when its window has closed, and state is one small matrix for each
mode. Late rows beyond the watermark are dropped by the engine and counted by it.
"""

from __future__ import annotations

import json
from collections.abc import Callable
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery


def tumbling_slices(events: DataFrame, width: str = "1 hour", late: str = "2 hours", step: str | None = None) -> DataFrame:
    """start, event_type, n, total: one row for each window and type once it has closed."""
    ts = F.col("ts").cast("timestamp")
    window = F.window("ts", width, step) if step else F.window("ts", width)
    grouped = events.withColumn("ts", ts).withWatermark("ts", late).groupBy(window.alias("w"), "event_type")
    return grouped.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def session_slices(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    grouped = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    return grouped.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def pairs_within(events: DataFrame, first: str, then: str, seconds: int, late: str = "2 hours") -> DataFrame:
    """Interval join of two kinds of events of one user."""
    side = lambda kind, p: events.filter(F.col("event_type") == kind).select(F.col("ts").cast("timestamp").alias(f"{p}_ts"), F.col("user_id").alias(f"{p}_user"), F.col("event_id").alias(f"{p}_id")).withWatermark(f"{p}_ts", late)
    a, b = side(first, "a"), side(then, "b")
    return a.join(b, (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {seconds} SECONDS")))


class GramState:
    """S += slab slab' over closed slices, and moments by merging; kept with the last batch id, so a replayed batch counts once."""

    def __init__(self, folder: str, labels: list[str]):
        self.path, self.labels = Path(folder) / "gram.json", labels
        if self.path.exists():
            kept = json.loads(self.path.read_text())
            self.batch, self.gram = kept["batch"], np.array(kept["gram"])
            self.count, self.mean, self.m2 = kept["count"], kept["mean"], kept["m2"]
        else:
            self.batch, self.gram = -1, np.zeros((len(labels),) * 2)
            self.count, self.mean, self.m2 = 0, 0.0, 0.0

    def update(self, slices: DataFrame, batch: int) -> None:
        """foreachBatch: only pair sums (labels squared) and moments come to the driver."""
        if batch <= self.batch:
            return
        own = slices.select("start", "event_type", F.col("n").cast("double").alias("v"))
        other = own.withColumnRenamed("event_type", "b").withColumnRenamed("v", "y")
        at = {x: i for i, x in enumerate(self.labels)}
        for r in own.join(other, "start").groupBy("event_type", "b").agg(F.sum(F.col("v") * F.col("y")).alias("s")).collect():
            self.gram[at[r.event_type], at[r.b]] += r.s
        n, mean, var = own.agg(F.count("*"), F.avg("v"), F.var_pop("v")).first()
        if n:
            shift, total = mean - self.mean, self.count + n
            self.m2 += var * n + shift**2 * self.count * n / total
            self.mean += shift * n / total
            self.count = total
        self.batch = batch
        new = self.path.with_suffix(".new")
        new.write_text(json.dumps({"batch": batch, "gram": self.gram.tolist(), "count": self.count, "mean": self.mean, "m2": self.m2}))
        new.replace(self.path)


def run_available(stream: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Everything that is there, in batches, then stop."""
    query = stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query
