"""Structured Streaming over events: source, assignment to fixed centres, windowed loads, dedup, alerts, warm restarts.

Every stateful operator has a watermark, so its state is bounded; block-keyed state has k rows.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.operators import kmeans
from meshcut.operators.kmeans import Centre, Centres
from meshcut.operators.relational import migration

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of events as they arrive, with the declared schema."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def as_points(events: DataFrame) -> DataFrame:
    """pid, x (days since 2024-01-01), y, w; the time and user stay."""
    origin = F.unix_micros(F.lit("2024-01-01 00:00:00+00:00").cast("timestamp"))
    x = (F.unix_micros(F.col("ts").cast("timestamp")) - origin) / F.lit(86_400_000_000.0)
    return events.select(F.col("event_id").alias("pid"), x.alias("x"), (F.col("value") / 10).alias("y"), F.lit(1).cast("long").alias("w"), "ts", "user_id")


def assign_stream(events: DataFrame, centres: Centres) -> DataFrame:
    """Stateless: the batch expression on arriving rows."""
    return kmeans.assign(as_points(events), centres, ["x", "y"])


def window_load(assigned: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, block, load) of tumbling or sliding windows; rows older than the watermark are dropped."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    rows = assigned.withWatermark("ts", late) if assigned.isStreaming else assigned
    return rows.groupBy(w.alias("win"), "block").agg(F.sum("w").alias("load")).select(F.col("win.start").alias("start"), "block", "load")


def session_load(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, n) of each user's sessions; an event exactly a gap later still belongs."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), "n")


def dedup(events: DataFrame, late: str = "1 hour") -> DataFrame:
    if events.isStreaming:
        return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def interval_events(events: DataFrame, first: str = "view", then: str = "purchase", within: str = "10 minutes") -> DataFrame:
    """Pairs of a user's events at most `within` apart; streams keep rows until the watermark passes the bound."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u1"), F.col("event_id").alias("e1"), F.col("ts").alias("t1"))
    b = events.where(F.col("event_type") == then).select(F.col("user_id").alias("u2"), F.col("event_id").alias("e2"), F.col("ts").alias("t2"))
    if events.isStreaming:
        a, b = a.withWatermark("t1", "1 hour"), b.withWatermark("t2", "1 hour")
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select(F.col("u1").alias("user_id"), "e1", "e2")


class Rebalancer:
    """foreachBatch sink: running block weights, alerts while imbalance is over eps for `windows` batches in a row, and then
    other influences, or with repartition=True a new partition of the batch's points from the present centres on, whose
    migration (was, now, n, w) is kept in `moves`.

    The state (k rows) is written to `folder` after each batch under the batch's id, and read from there, so a restarted
    stream goes on where it was and a repeated batch changes nothing. The states of the last two batches are kept.
    """

    def __init__(self, centres: Centres, eps: float = 0.03, windows: int = 2, folder: str | None = None, repartition: bool = False):
        self.centres, self.eps, self.windows, self.folder, self.repartition = centres, eps, windows, folder, repartition
        self.loads = [0] * len(centres.rows)
        self.over, self.alerts, self.moves, self.last = 0, [], [], -1

    def _files(self, spark: SparkSession) -> dict[int, str]:
        path = spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        fs = path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
        names = [f.getPath().getName() for f in fs.listStatus(path)] if fs.exists(path) else []
        # a folder without the mark of success is a batch that was cut short
        return {int(n.split("-")[1]): f"{self.folder}/{n}" for n in names if n.startswith("batch-") and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{n}/_SUCCESS"))}

    def _load(self, spark: SparkSession) -> None:
        files = self._files(spark) if self.folder else {}
        if files and max(files) > self.last:
            self.last = max(files)
            state = json.loads(spark.read.text(files[self.last]).first()[0])
            self.loads, self.over = state["loads"], state["over"]
            self.alerts, self.moves = [tuple(a) for a in state["alerts"]], [tuple(m) for m in state["moves"]]
            self.centres = Centres([Centre(b, tuple(at), i) for b, at, i in state["centres"]])

    def _save(self, spark: SparkSession, batch_id: int) -> None:
        self.last = batch_id
        if not self.folder:
            return
        state = {"loads": self.loads, "over": self.over, "alerts": self.alerts, "moves": self.moves, "centres": [[c.block, list(c.at), c.influence] for c in self.centres.rows]}
        spark.createDataFrame([(json.dumps(state),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.folder}/batch-{batch_id}")
        for n, path in self._files(spark).items():
            if n < batch_id - 1:
                p = spark._jvm.org.apache.hadoop.fs.Path(path)
                p.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(p, True)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        self._load(spark)
        if batch_id <= self.last:
            return
        p = as_points(batch)
        for r in kmeans.assign(p, self.centres, ["x", "y"]).groupBy("block").agg(F.sum("w").alias("w")).collect():
            self.loads[r["block"]] += r["w"]
        mean = sum(self.loads) / len(self.loads)
        now = max(self.loads) / mean - 1 if mean else 0.0
        self.over = self.over + 1 if now > self.eps else 0
        if self.over >= self.windows:
            self.alerts.append((batch_id, now))
            if self.repartition:
                self._repartition(p, batch_id)
            else:
                self.centres = self.centres.moved(influence=[c.influence * kmeans.influence_factor(mean, s, 2) for c, s in zip(self.centres.rows, self.loads)])
        self._save(spark, batch_id)

    def _repartition(self, p: DataFrame, batch_id: int) -> None:
        r = kmeans.balanced_kmeans(p, len(self.centres.rows), eps=self.eps, max_iter=10, start=self.centres)
        old = kmeans.assign(p, self.centres, ["x", "y"])
        moved = migration(old, r.assignment, p).where("was <> now").orderBy("was", "now").collect()
        self.moves += [(batch_id, m["was"], m["now"], m["n"], m["w"]) for m in moved]
        self.centres, self.over = r.centres, 0
        self.loads = [0] * len(self.loads)


def run_once(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there, into a memory table."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
