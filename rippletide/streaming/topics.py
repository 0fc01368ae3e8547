"""Streaming forms of the topic pipeline: counts, sessions, late posts, agreement, topic growth.

Each query reads the events as a file stream with the available-now trigger, so it also runs as an
incremental batch; results are read back from a Parquet sink or from the last complete state."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import IntegerType, StructField, StructType

from rippletide.operators.topics import post_opinion
from rippletide.oracles import SEED_EPOCHS, SUCCESSION
from rippletide.plans.storage import shared_dir, stored


def post_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    e = spark.readStream.schema(schema).option("pathGlobFilter", name).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return e.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("int").alias("topic"), post_opinion(F.col("event_type"), F.col("value")).alias("opinion"))


def run(df: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Run to the end of what is there. Append: the sink's rows. Update: the last row of each key.
    Complete: the rows of the last batch."""
    spark = df.sparkSession
    base = f"{shared_dir(spark)}/rippletide/stream-{uuid.uuid4().hex}"
    out = f"{base}/out"
    schema = df.schema

    def land(batch: DataFrame, n: int) -> None:
        batch.withColumn("batch", F.lit(n)).write.mode("append").parquet(out)

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(land).start()
    q.awaitTermination()
    rows = spark.read.schema(StructType([*schema.fields, StructField("batch", IntegerType())])).parquet(out)
    if mode == "complete":
        return rows.join(F.broadcast(rows.agg(F.max("batch").alias("batch"))), "batch", "left_semi").drop("batch")
    if keys:
        best = rows.groupBy(*keys).agg(F.max_by(F.struct(*[c for c in rows.columns if c not in [*keys, "batch"]]), "batch").alias("r"))
        return best.select(*keys, "r.*")
    return rows.drop("batch")


def topic_counts(posts: DataFrame, width: str = "1 day") -> DataFrame:
    """Posts and summed opinion per topic and tumbling window."""
    return posts.withWatermark("ts", "1 hour").groupBy(F.window("ts", width).alias("w"), "topic").agg(F.count(F.lit(1)).alias("posts"), F.sum("opinion").alias("opinion")).select(F.col("w.start").alias("start"), "topic", "posts", "opinion")


def topic_sessions(posts: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Session epochs: a topic's posts with gaps of less than ``gap``. Without a watermark, for the complete
    mode: in append mode the sessions that are still open at the end would be missing."""
    return posts.groupBy(F.session_window("ts", gap).alias("w"), "topic").agg(F.count(F.lit(1)).alias("posts")).select("topic", F.col("w.start").alias("start"), "posts")


def unique_posts(posts: DataFrame) -> DataFrame:
    return posts.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def running_opinion(posts: DataFrame) -> DataFrame:
    return posts.groupBy("user_id").agg(F.avg("opinion").alias("opinion"), F.count(F.lit(1)).alias("posts"))


def topic_activity(posts: DataFrame, background: DataFrame) -> DataFrame:
    """Stream-static join: posts by users with background arcs, counted per user's out-degree."""
    out = background.groupBy(F.col("u").alias("user_id")).agg(F.count(F.lit(1)).alias("arcs"))
    return posts.join(out, "user_id").groupBy("topic").agg(F.sum("arcs").alias("reachable"))


class TopicGrowth(StatefulProcessor):
    """Per topic, in time order: who is in the subgraph and when the last new seed came, that is a new
    member none of whose background predecessors is one; an epoch ends when no seed came for longer than
    the topic's threshold. The rule is the batch form's; state holds one epoch's members only."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.members = handle.getMapState("members", "user_id long", "first double")
        self.place = handle.getValueState("place", "epoch long, last double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        epoch, last = self.place.get() if self.place.exists() else (0, None)
        out = []
        frame = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for event, user, ts, sources, limit in zip(frame["event_id"], frame["user_id"], frame["ts"], frame["sources"], frame["threshold"], strict=True):
            now = ts.timestamp()
            if last is not None and now - last > limit:
                epoch, last = epoch + 1, None
                self.members.clear()
            if not self.members.containsKey((int(user),)):
                reached = any(self.members.containsKey((int(x),)) for x in (sources if sources is not None else ()))
                self.members.updateValue((int(user),), (now,))
                if not reached or last is None:
                    last = now
            out.append((int(key[0]), int(event), epoch))
        self.place.update((epoch, last))
        yield pd.DataFrame(out, columns=["topic", "event_id", "epoch"])

    def close(self) -> None:
        pass


def topic_growth(posts: DataFrame, background: DataFrame, thresholds: DataFrame) -> DataFrame:
    """(topic, event_id, epoch) as posts come; ``background`` (u, v) and ``thresholds`` (topic, threshold) are
    static. Needs the RocksDB state store, which is set here for the streams started afterwards (a
    runtime setting)."""
    posts.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    sources = background.groupBy(F.col("v").alias("user_id")).agg(F.collect_list("u").alias("sources"))
    rows = posts.join(sources, "user_id", "left").join(thresholds, "topic").select("topic", "event_id", "user_id", "ts", "sources", "threshold")
    return rows.groupBy("topic").transformWithStateInPandas(TopicGrowth(), "topic int, event_id long, epoch long", outputMode="Append", timeMode="None")


def on_time_counts(spark: SparkSession, path: str) -> DataFrame:
    """(day, posts, late): posts counted per day, and those that came after the watermark had passed their
    day. Every tenth post comes in a third batch, one batch a file: rows are late by the watermark that held
    before the batch ahead of theirs."""
    base = f"{shared_dir(spark)}/rippletide/late-{uuid.uuid4().hex}"
    events = spark.read.parquet(path)
    last = F.col("event_id") % 10
    for part in ((last >= 1) & (last <= 5), last > 5, last == 0):
        events.where(part).coalesce(1).write.mode("append").parquet(base)
        time.sleep(1.1)  # files are taken in order of their times
    e = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(base)
    posts = e.select(F.col("ts").cast("timestamp").alias("ts"))
    counts = posts.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("posts")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "posts")
    counted = run(counts, "update", ["day"])
    all_ = events.groupBy(F.date_format(F.col("ts").cast("timestamp"), "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("came"))
    return all_.join(counted, "day", "left").select("day", F.coalesce("posts", F.lit(0)).alias("posts"), (F.col("came") - F.coalesce("posts", F.lit(0))).alias("late"))


def _posts(s: SparkSession, d: str) -> DataFrame:
    return post_stream(s, f"{d}/events.parquet")


P_ = "(SELECT event_id, user_id, ts, CAST(json_extract_string(props,'$.k') AS INTEGER) topic, CASE WHEN event_type='view' THEN 0.0::DOUBLE WHEN event_type='error' THEN -(value/(value+50)) ELSE value/(value+50) END opinion FROM events)"
STREAMS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "stream_topic_counts": (
        lambda s, d: run(topic_counts(_posts(s, d)), "update", ["start", "topic"]).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "topic", "posts", (F.round("opinion", 6) + 0.0).alias("opinion")),
        f"SELECT strftime(ts, '%Y-%m-%d') AS day, topic, CAST(count(*) AS BIGINT) posts, round(sum(opinion),6)+0.0 opinion FROM {P_} GROUP BY 1, 2",
    ),
    "stream_sessions": (
        lambda s, d: run(topic_sessions(_posts(s, d)), "complete").groupBy("topic").agg(F.count(F.lit(1)).alias("sessions"), F.sum("posts").alias("posts")),
        f"SELECT topic, CAST(sum(cut) AS BIGINT) sessions, CAST(count(*) AS BIGINT) posts FROM (SELECT topic, CASE WHEN epoch_us(ts)-lag(epoch_us(ts)) OVER (PARTITION BY topic ORDER BY ts)<21600000000 THEN 0 ELSE 1 END cut FROM {P_}) GROUP BY 1",
    ),
    "stream_late_drop": (
        lambda s, d: on_time_counts(s, f"{d}/events.parquet"),
        "WITH e AS (SELECT ts, event_id%10=0 tardy, event_id%10 BETWEEN 1 AND 5 early, date_trunc('day', ts) d FROM events), w AS (SELECT max(ts)-INTERVAL 1 HOUR mark FROM e WHERE early), c AS (SELECT d, count(*) came, count(*) FILTER (WHERE tardy AND d+INTERVAL 1 DAY<=mark) late FROM e, w GROUP BY 1) SELECT strftime(d, '%Y-%m-%d') AS day, CAST(came-late AS BIGINT) posts, CAST(late AS BIGINT) late FROM c",
    ),
    "stream_unique": (lambda s, d: run(unique_posts(_posts(s, d)).select("event_id", "topic"), "append"), f"SELECT event_id, topic FROM {P_}"),
    "stream_running_opinion": (lambda s, d: run(running_opinion(_posts(s, d)), "update", ["user_id"]).select("user_id", (F.round("opinion", 7) + 0.0).alias("opinion"), "posts"), f"SELECT user_id, round(avg(opinion),7)+0.0 opinion, CAST(count(*) AS BIGINT) posts FROM {P_} GROUP BY 1"),
}


def _static(s: SparkSession, d: str) -> DataFrame:
    from rippletide.operators.graphs import succession_edges

    return run(topic_activity(_posts(s, d), succession_edges(s, d)), "update", ["topic"])


def _growth(s: SparkSession, d: str) -> DataFrame:
    from rippletide.operators.graphs import succession_edges
    from rippletide.operators.topics import gap_threshold, topic_posts

    grown = topic_growth(_posts(s, d), stored(succession_edges(s, d).select("u", "v"), "background"), stored(gap_threshold(topic_posts(s, d)), "thresholds"))
    return run(grown, "append").groupBy("topic", "epoch").agg(F.count(F.lit(1)).alias("posts"))


STREAMS["stream_static_join"] = (_static, f"WITH {SUCCESSION} SELECT topic, CAST(sum(arcs) AS BIGINT) reachable FROM {P_} JOIN (SELECT u, count(*) arcs FROM suc GROUP BY u) ON u=user_id GROUP BY 1")
STREAMS["stream_topic_state"] = (_growth, SEED_EPOCHS)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, (f, _) in STREAMS.items()}


def oracles() -> dict[str, str]:
    return {k: q for k, (_, q) in STREAMS.items() if q}
