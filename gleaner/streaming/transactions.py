"""Transactions and samples from streams of events."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform
from gleaner.sources.shared import shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, folder: str, late: str = "2 days", files: int | None = None) -> DataFrame:
    """A stream of event files, so many a batch (all there are if None), oldest first. Watermarks need a time with a zone; an event seen again within the watermark is left out."""
    reader = spark.readStream.schema(EVENTS)
    rows = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(folder).where("value > 0").withColumn("at", F.to_timestamp(F.date_format("ts", "yyyy-MM-dd HH:mm:ss.SSS")))
    return rows.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"])


def windowed(stream: DataFrame, kind: str = "tumbling", length: str = "1 day", slide: str = "6 hours") -> DataFrame:
    """(user_id, start, item, w) of closed windows: tumbling, sliding, or sessions that a pause ends.

    Distinct items of a transaction are the rows of a window. A session gives (user_id, start, n, s) at once, n of distinct items.
    """
    window = {"tumbling": lambda: F.window("at", length), "sliding": lambda: F.window("at", length, slide), "session": lambda: F.session_window("at", length)}[kind]()
    keys = ["user_id"] if kind == "session" else ["user_id", "event_type"]
    rows = stream.groupBy(*keys, window.alias("win"))
    if kind == "session":
        return rows.agg(F.size(F.collect_set("event_type")).alias("n"), F.sum("value").alias("s")).select("user_id", F.col("win.start").alias("start"), "n", "s")
    return rows.agg(F.sum("value").alias("w")).select("user_id", F.col("win.start").alias("start"), F.col("event_type").alias("item"), "w")


def replay(stream: DataFrame, mode: str = "append", each: Callable | None = None) -> DataFrame:
    """All that a stream gives when everything there is has been read, as a table in the shared folder.

    In complete mode that is the whole answer so far, open windows included: what a batch query over the same rows gives.
    """
    return replay_counted(stream, mode, each)[0]


def replay_counted(stream: DataFrame, mode: str = "append", each: Callable | None = None) -> tuple[DataFrame, int]:
    """The same, and how many rows came after the watermark had passed them."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    last = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out-{number}")
        last.append(f"{base}/out-{number}")

    if each is not None or mode == "complete":
        query = writer.foreachBatch(each or keep).start()
    else:
        query = writer.format("parquet").option("path", f"{base}/out").start()
    query.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
    if each is not None:
        return spark.range(0), late
    path = (last or [None])[-1] if mode == "complete" else f"{base}/out"
    return (spark.read.schema(stream.schema).parquet(path) if path else spark.createDataFrame([], stream.schema)), late


def pairs_within(left: DataFrame, right: DataFrame, reach: str = "1 hour") -> DataFrame:
    """(user_id, event_id, other_id): stream-stream join of events with those of the same user at most ``reach`` later.

    Both sides have watermarks and the join a bound on time, so that state is dropped as time goes on.
    """
    other = right.select(F.col("user_id").alias("user_2"), F.col("event_id").alias("other_id"), F.col("at").alias("at_2"))
    near = F.expr(f"user_id = user_2 AND at_2 > at AND at_2 <= at + INTERVAL {reach}")
    return left.join(other, near).select("user_id", "event_id", "other_id")


SLOTS = "block int, slot int, tid long, n int, log_total double"


def stored_reservoir(weights: DataFrame, k: int, seed: int = 0, blocks: int = 8) -> DataFrame:
    """SLOTS rows of a stream of (tid, n, logw): k slots for each block of transactions, kept in the state store.

    State (k winners and the log of the total weight) is part of the checkpoint, so a query that starts again goes on from it.
    Rows of a block are taken in the order of tid, and dice come of the seed and the count of rows seen: a retried batch repeats itself.
    """
    import numpy as np
    import pandas as pd

    def step(key, batches, state):  # noqa: ANN001, ANN202
        total, seen, tids, sizes = state.get if state.exists else (-math.inf, 0, [0] * k, [0] * k)
        rows = pd.concat(list(batches)).sort_values("tid")
        if len(rows):
            dice = np.random.default_rng([seed, key[0], seen])
            logw, top = rows["logw"].to_numpy(), float(rows["logw"].max())
            run = np.cumsum(np.exp(logw - top))
            at = np.minimum(np.searchsorted(run, dice.random(k) * run[-1]), len(run) - 1)
            own = top + math.log(run[-1])
            both = float(np.logaddexp(total, own))
            new = dice.random(k) < math.exp(own - both)
            tids = np.where(new, rows["tid"].to_numpy()[at], tids).tolist()
            sizes = np.where(new, rows["n"].to_numpy()[at], sizes).tolist()
            total, seen = both, seen + len(rows)
            state.update((total, seen, tids, sizes))
        yield pd.DataFrame({"block": key[0], "slot": range(k), "tid": tids, "n": sizes, "log_total": total})

    dealt = weights.select(F.pmod(F.xxhash64("tid"), F.lit(blocks)).cast("int").alias("block"), F.col("tid").cast("long").alias("tid"), F.col("n").cast("int").alias("n"), "logw")
    return dealt.groupBy("block").applyInPandasWithState(step, SLOTS, "total double, seen long, tids array<long>, sizes array<int>", "update", "NoTimeout")


def merged_slots(slots: DataFrame, seed: int = 0) -> DataFrame:
    """(slot, tid, n): blocks meet; each slot takes a block's winner with the share of its total."""
    key = F.col("log_total") - F.ln(-F.ln(uniform(seed, F.col("slot"), F.col("block"), "merge")))
    return slots.groupBy("slot").agg(F.max_by(F.struct("tid", "n"), key).alias("t")).select("slot", "t.tid", "t.n")


class Reservoir:
    """k slots of (tid, n): each slot holds one transaction drawn in proportion to weight among all seen so far.

    A batch brings its own winners and total; a slot keeps its winner with the share of the totals. State is k rows.
    """

    def __init__(self, k: int, seed: int = 0) -> None:
        self.k, self.seed, self.log_total, self.slots, self.batch = k, seed, -math.inf, {}, -1

    def add(self, weights: DataFrame, batch: int = 0) -> None:
        """``weights``: (tid, n, logw) of transactions closed in this batch. A batch seen before is left out."""
        from gleaner.functions.chance import uniform_value
        from gleaner.operators.jump import pick_by_prefix

        if batch <= self.batch:
            return
        row = weights.agg(F.max("logw").alias("top")).first()
        self.batch = batch
        if row.top is None:
            return
        own = row.top + math.log(weights.agg(F.sum(F.exp(F.col("logw") - row.top))).first()[0])
        picks = pick_by_prefix(weights.withColumn("w", F.exp("logw")), self.k, self.seed * 100_003 + batch).collect()  # k rows
        both = own if self.log_total == -math.inf else max(own, self.log_total) + math.log1p(math.exp(-abs(own - self.log_total)))
        for p in picks:
            if p.draw_id not in self.slots or uniform_value(self.seed, batch, p.draw_id, "slot") < math.exp(own - both):
                self.slots[p.draw_id] = (p.tid, p.n)
        self.log_total = both


def thinned(stream: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """A hash sample of a stream: the same events whatever the batches."""
    return stream.where(uniform(seed, F.col("event_id")) < share)
