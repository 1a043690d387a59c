"""Check-in streams: slots, sessions, de-duplication, the enforcement gate and budgets."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

#: What event files hold; stamps without a zone are read as they are and cast.
EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, late: str = "1 hour", files: int | None = None) -> DataFrame:
    """Events of a folder as a stream with a watermark, which needs a zoned time stamp."""
    r = spark.readStream.schema(EVENTS)
    if files:
        r = r.option("maxFilesPerTrigger", files)
    return r.parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def slot_counts(events: DataFrame, hours: int) -> DataFrame:
    return events.groupBy(F.window("ts", f"{hours} hours").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("slot_start"), "event_type", "n")


def sliding(events: DataFrame, hours: int, every: int) -> DataFrame:
    return events.groupBy(F.window("ts", f"{hours} hours", f"{every} hours").alias("w")).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "n", "users")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def dedup(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def gate(events: DataFrame, decisions: DataFrame) -> DataFrame:
    """``released`` by the decision for (user_id, item); a cell without one is hidden."""
    return events.join(decisions, ["user_id", "item"], "left").withColumn("released", F.coalesce("decision", F.lit(0)) == 1).drop("decision")


def match(answers: DataFrame, visits: DataFrame, within: str = "6 hours") -> DataFrame:
    """Stated answers with check-ins of the same user in the time before; both sides carry watermarks."""
    a, v = answers.alias("a"), visits.alias("v")
    return a.join(v, F.expr(f"a.user_id = v.user_id AND v.ts <= a.ts AND v.ts >= a.ts - INTERVAL {within}")).select(F.col("a.user_id").alias("user_id"), F.col("a.event_id").alias("answer_id"), F.col("v.event_id").alias("visit_id"))


def budgeted_reports(events: DataFrame, eps_each: float, eps_total: float) -> DataFrame:
    """Each report spends ``eps_each`` of its user's ``eps_total``; what comes after is refused.

    The spent budget is state, so a restart from a checkpoint doesn't hand it out again.
    Inside a batch, reports spend in order of their ids.
    """

    def spend(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        spent = state.get[0] if state.exists else 0.0
        for rows in [pd.concat(list(batches)).sort_values("event_id")]:
            ok = []
            for _ in range(len(rows)):
                ok.append(spent + eps_each <= eps_total + 1e-12)
                spent += eps_each if ok[-1] else 0.0
            yield pd.DataFrame({"user_id": rows["user_id"], "event_id": rows["event_id"], "accepted": ok})
        state.update((spent,))

    return events.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(spend, "user_id long, event_id long, accepted boolean", "spent double", "append", "NoTimeout")


def permanent_bits(visits: DataFrame, p: float) -> DataFrame:
    """``user_id, item, ybit``: a noisy bit for every visit of a stream (user_id, item).

    The first visit to an item draws its bit from the system's entropy; every later one
    repeats it, also after a restart, as the user's bits are state. With probability p a
    fair coin replaces the true bit.
    """

    def recall(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        import json
        import secrets

        known = json.loads(state.get[0]) if state.exists else {}
        for rows in batches:
            for item in rows["item"]:
                if item not in known:
                    known[item] = secrets.randbits(1) if secrets.randbits(53) / 2**53 < p else 1
            yield pd.DataFrame({"user_id": rows["user_id"], "item": rows["item"], "ybit": [known[i] for i in rows["item"]]})
        state.update((json.dumps(known),))

    return visits.select("user_id", "item").groupBy("user_id").applyInPandasWithState(recall, "user_id long, item string, ybit int", "bits string", "append", "NoTimeout")


def late_metric(query: StreamingQuery) -> int:
    """Rows that state operators dropped as too late."""
    return sum(int(s.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for s in p["stateOperators"])


def refit(events: DataFrame, path: str, checkpoint: str, on_batch=None) -> StreamingQuery:
    """Keeps the last label of every (user_id, event_type) as a table, rewritten by each batch."""

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = batch.select("user_id", "event_type", "ts", "event_id", (F.col("value") >= 35).cast("int").alias("label"))
        if number:
            new = new.unionByName(spark.read.parquet(f"{path}/{number - 1}"))
        new.groupBy("user_id", "event_type").agg(F.max(F.struct("ts", "event_id", "label")).alias("m")).select("user_id", "event_type", "m.*").write.mode("overwrite").parquet(f"{path}/{number}")
        if on_batch:
            on_batch(spark.read.parquet(f"{path}/{number}"), number)

    return events.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> StreamingQuery:
    """Everything there is now into a memory table, for tests and small looks."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q
