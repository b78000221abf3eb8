"""Counts, Grams and ranks kept up to date over a stream of events.

Every function takes a streaming (or batch) DataFrame; rows later than the watermark are dropped by Spark.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilealg.workers import shipped

shipped(__name__)

def tumbling_counts(events: DataFrame, size: str = "1 hour", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding_counts(events: DataFrame, size: str = "2 hours", slide: str = "1 hour", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, slide).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def once(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each event_id once, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def link_gaps(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """(src, dst, gap_us): consecutive events of a user as links between kinds, with a state of one event for each user.

    Events wait until the watermark has passed them, so they are linked in order of time and id; the last event stays.
    """
    waiting = events.withWatermark("ts", late).select("user_id", "event_id", "event_type", "ts")
    return waiting.groupBy("user_id").applyInPandasWithState(_linked, "src string, dst string, gap_us long", "waiting array<struct<ts:long,id:long,kind:string>>", "append", "EventTimeTimeout")


def _linked(key, frames, state):
    import pandas as pd

    kept = [tuple(r) for r in state.get[0]] if state.exists else []
    for f in frames:
        kept += list(zip(f["ts"].astype("datetime64[us]").astype("int64").tolist(), f["event_id"].tolist(), f["event_type"].tolist(), strict=True))
    kept.sort()
    mark = state.getCurrentWatermarkMs() * 1000
    ready = [x for x in kept if x[0] <= mark]
    yield pd.DataFrame([(a[2], b[2], b[0] - a[0]) for a, b in zip(ready, ready[1:], strict=False)], columns=["src", "dst", "gap_us"])
    left = kept[max(len(ready) - 1, 0) :]
    state.update((left,))
    if len(left) > 1:
        state.setTimeoutTimestamp(left[-1][0] // 1000 + 1)


class RunningGram:
    """Gram of user rows over event kinds, brought up to date by micro-batches with ``foreachBatch``.

    Keeps counts (user, kind) in a table of its own version each batch; replays of a batch change nothing.  A new
    object over the same folder goes on from the last version that was wholly written.
    """

    def __init__(self, folder: str):
        self.folder, self.done = folder, None

    def _last(self, spark) -> int:
        """The newest version whose write was committed; -1 if there is none."""
        jvm = spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/v*/_SUCCESS")
        found = path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).globStatus(path) or []
        return max((int(f.getPath().getParent().getName()[1:]) for f in found), default=-1)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if self.done is None:
            self.done = self._last(batch.sparkSession)
        if batch_id <= self.done:
            return
        fresh = batch.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
        if self.done >= 0:
            fresh = fresh.unionByName(self.counts(batch.sparkSession)).groupBy("user_id", "event_type").agg(F.sum("n").alias("n"))
        fresh.write.mode("overwrite").parquet(f"{self.folder}/v{batch_id}")
        self.done = batch_id

    def counts(self, spark) -> DataFrame:
        if self.done is None:
            self.done = self._last(spark)
        return spark.read.parquet(f"{self.folder}/v{self.done}")

    def gram(self, spark) -> DataFrame:
        """(a, b, v): products of kinds over users."""
        c = self.counts(spark)
        return c.select("user_id", F.col("event_type").alias("a"), F.col("n").alias("x")).join(c.select("user_id", F.col("event_type").alias("b"), F.col("n").alias("y")), "user_id").groupBy("a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def refresh_ranks(counts: Callable[[], DataFrame], iters: int = 20) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that ranks the links gathered so far; the last ranks are its ``latest``."""
    from tilealg.operators.pagerank import pagerank

    def update(batch: DataFrame, batch_id: int) -> None:
        update.latest = pagerank(counts(), iters=iters, weighted=True)

    update.latest = None
    return update
