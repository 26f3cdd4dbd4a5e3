"""The events table as a stream: windows, late and repeated events, state a vertex, inserts into bit vectors.

Streams read the table's folder by file name, run to its end (availableNow) and write tables of the shared
folder, with checkpoints there too; ``ts`` is cast to a time zone's timestamp, which watermarks need.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.store import shared_folder
from ..graphs import derive

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over what there is and returns the rows it wrote."""
    spark, at = df.sparkSession, f"{shared_folder(df.sparkSession)}/packgraph-stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/check").outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")
    # complete results replace one another batch by batch
    q = df.writeStream.foreachBatch(lambda b, k: b.write.mode("overwrite").parquet(f"{at}/out")).option("checkpointLocation", f"{at}/check").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def _text(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = stream(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("day"), "event_type", "n"), "complete").select(_text("day"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = stream(spark, sf_dir).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("start"), "n"), "complete").select(_text("start"), "n")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = stream(spark, sf_dir).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select("user_id", F.col("w.start").alias("start"), "n"), "complete").select("user_id", _text("start"), "n")


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events twice over, one of each kept."""
    s = stream(spark, sf_dir).select("event_id", "ts", "user_id")
    twice = s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return drained(twice.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "user_id")


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream against a table: customers' nations by user id."""
    c = derive.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return drained(stream(spark, sf_dir).select("event_id", "user_id").join(c, "user_id"))


def stream_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user-type edges counted as they come: each batch's counts are added to a table, which is compacted when read."""
    at = f"{shared_folder(spark)}/packgraph-stream-{uuid.uuid4().hex}"
    s = stream(spark, sf_dir).select("user_id", "event_type")
    q = s.writeStream.foreachBatch(lambda b, k: b.groupBy("user_id", "event_type").agg(F.count("*").alias("w")).withColumn("batch", F.lit(k)).write.mode("overwrite").parquet(f"{at}/out/batch={k}")).option("checkpointLocation", f"{at}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema("user_id long, event_type string, w long").parquet(f"{at}/out").groupBy("user_id", "event_type").agg(F.sum("w").alias("w"))


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, later_id): views and the clicks of the same user within six hours after; both sides are streams, watermarks bound what they keep."""
    s = stream(spark, sf_dir).select("event_id", "ts", "user_id", "event_type")
    a = s.where("event_type = 'view'").withWatermark("ts", "1 hour").select("event_id", F.col("ts").alias("at"), "user_id")
    b = s.where("event_type = 'click'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("later_id"), F.col("ts").alias("then"), F.col("user_id").alias("who"))
    return drained(a.join(b, F.expr("user_id = who AND then >= at AND then <= at + INTERVAL 6 HOURS")).select("event_id", "later_id"))


def late_counted(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    """(batch, kept, late): events in two batches, the younger half first; a batch's late ones are older than the watermark that batches before it
    set (their greatest time less the delay). Late rows are counted, not lost in silence."""
    events = derive.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    middle = events.agg(F.expr("percentile_approx(unix_micros(ts), 0.5, 100000)")).first()[0]
    at = f"{shared_folder(spark)}/packgraph-stream-{uuid.uuid4().hex}"
    for k, part in enumerate((F.expr("unix_micros(ts)") >= middle, F.expr("unix_micros(ts)") < middle)):
        events.where(part).withColumn("k", F.lit(k)).coalesce(1).write.mode("append").parquet(f"{at}/in")
    mark: dict[str, object] = {"greatest": None}

    def note(b: DataFrame, k: int) -> None:
        line = F.lit(mark["greatest"]).cast("timestamp") - F.expr(f"INTERVAL {delay}")
        late = F.coalesce(F.col("ts") < line, F.lit(False)) if mark["greatest"] is not None else F.lit(False)
        got = b.agg(F.sum(F.when(late, 0).otherwise(1)).cast("long").alias("kept"), F.sum(F.when(late, 1).otherwise(0)).cast("long").alias("late"), F.max("ts").alias("m")).first()
        spark.createDataFrame([(k, got["kept"], got["late"])], "batch long, kept long, late long").write.mode("overwrite").parquet(f"{at}/out/run={k}")
        mark["greatest"] = max(x for x in (mark["greatest"], got["m"]) if x is not None)

    s = spark.readStream.schema("event_id long, ts timestamp, k int").option("maxFilesPerTrigger", 1).parquet(f"{at}/in")
    q = s.writeStream.foreachBatch(note).option("checkpointLocation", f"{at}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema("batch long, kept long, late long").parquet(f"{at}/out")


def adjacency_state(spark: SparkSession, sf_dir: str, days: int = 7) -> DataFrame:
    """(user_id, event_type): a user's neighbours in the graph of users and kinds of event. State is a row a user, each neighbour with the time it
    was last met; neighbours not met for ``days`` before the user's last event are forgotten."""
    ttl = days * 86_400 * 1_000_000

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = dict(zip(*state.get)) if state.exists else {}
        for b in batches:
            for kind, at in b.groupby("event_type")["at"].max().items():
                last[kind] = max(int(at), last.get(kind, int(at)))
        newest = max(last.values())
        last = {k: x for k, x in last.items() if x >= newest - ttl}
        state.update((list(last), list(last.values())))
        yield pd.DataFrame({"user_id": [key[0]], "near": [sorted(last)], "newest": [newest]})

    s = stream(spark, sf_dir).select("user_id", "event_type", F.expr("unix_micros(ts)").alias("at"))
    out = s.groupBy("user_id").applyInPandasWithState(step, "user_id long, near array<string>, newest long", "kinds array<string>, times array<long>", "append", "NoTimeout")
    every = drained(out)
    return every.groupBy("user_id").agg(F.max_by("near", "newest").alias("near")).select("user_id", F.explode("near").alias("event_type"))


def width_changes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, d, width): each time the bits that a user's count of distinct kinds of event needs change. State is one small set a user."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        have = set(state.get[0]) if state.exists else set()
        old = len(have)
        for b in batches:
            have |= set(b["event_type"])
        state.update((sorted(have),))
        if len(have).bit_length() != old.bit_length():
            yield pd.DataFrame({"user_id": [key[0]], "d": [len(have)], "width": [len(have).bit_length()]})

    s = stream(spark, sf_dir).select("user_id", "event_type")
    out = s.groupBy("user_id").applyInPandasWithState(step, "user_id long, d long, width long", "kinds array<string>", "append", "NoTimeout")
    return drained(out)


def late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts of a stream whose watermark closes days: emitted when no later event can change them."""
    w = stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("day"), "n"))


LEAF = 4096


def insert_ones(ones: DataFrame, new: DataFrame) -> DataFrame:
    """(place): ones of a bit vector after inserting a one before each of the places ``new`` (place, seq) of the vector as it was.

    A one moves up by the inserts at or before it; inserts of one place keep the order of ``seq``. Leaves of ``LEAF`` places are worked on
    apart: what the leaves before hold is a sum over leaves (two passes), the rest is counted within the leaf.
    """
    from ..core.ids import prefix_sums

    leaf = F.floor(F.col("place") / LEAF)
    both = ones.select("place", F.lit(None).cast("long").alias("seq"), F.lit(0).alias("new")).unionByName(new.select("place", "seq", F.lit(1).alias("new"))).withColumn("leaf", leaf)
    before = prefix_sums(both.groupBy("leaf").agg(F.sum("new").cast("long").alias("k")), [F.col("leaf")], "k", "shift").select("leaf", "shift")
    # inserts come before the one that stood there
    within = F.sum("new").over(Window.partitionBy("leaf").orderBy("place", F.desc("new"), "seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("new")
    return both.withColumn("w", within).join(before, "leaf").select((F.col("place") + F.col("shift") + F.col("w")).alias("place"))


def leaf_insert(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(place): ones of a bit vector of a week's minutes after inserting each event before its minute; a batch's inserts are one join on leaves and the
    vector is a table that each batch writes anew, so nothing is kept on the driver."""
    at = f"{shared_folder(spark)}/packgraph-stream-{uuid.uuid4().hex}"
    current = {"path": None}

    def add(b: DataFrame, k: int) -> None:
        ones = spark.read.schema("place long").parquet(current["path"]) if current["path"] else spark.createDataFrame([], "place long")
        insert_ones(ones, b.select("place", F.col("event_id").alias("seq"))).write.mode("overwrite").parquet(f"{at}/vector-{k}")
        current["path"] = f"{at}/vector-{k}"

    s = stream(spark, sf_dir).select("event_id", F.expr("(unix_seconds(ts) div 60) % 10080").alias("place"))
    q = s.writeStream.foreachBatch(add).option("checkpointLocation", f"{at}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema("place long").parquet(current["path"])


def btree_insert(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places of ones after inserting each event's hour into a bit vector of leaves, batch by batch. The driver inserts; a batch comes to it a partition at a time."""
    import numpy as np

    from ..offsets.kinds import BTree

    tree = BTree(np.zeros(0, np.int64), 1, 256)
    at = f"{shared_folder(spark)}/packgraph-stream-{uuid.uuid4().hex}"

    def add(b: DataFrame, k: int) -> None:
        for r in b.orderBy("event_id").toLocalIterator():
            tree.insert(min(int(r["h"]), int(tree.ends[-1])))

    s = stream(spark, sf_dir).select("event_id", F.hour("ts").alias("h"))
    q = s.writeStream.foreachBatch(add).option("checkpointLocation", f"{at}/check").trigger(availableNow=True).start()
    q.awaitTermination()
    ones = tree.select(np.arange(int(tree.ones[-1])))
    return spark.createDataFrame([(int(x),) for x in ones], "place long")


QUERIES = {"stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": session, "stream_dedup": dedup, "stream_join": stream_join, "stream_edges": stream_edges, "stream_width_changes": width_changes, "stream_late": late, "stream_late_counted": late_counted, "stream_interval_join": interval_join, "stream_adjacency": adjacency_state, "stream_btree_insert": btree_insert, "stream_leaf_insert": leaf_insert}
ORACLES = {
    "stream_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT date_trunc('day', ts) AS s FROM events UNION ALL SELECT date_trunc('day', ts) - INTERVAL 1 DAY FROM events) q GROUP BY 1",
    "stream_session": "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT user_id, ts, event_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events) a) b GROUP BY user_id, g",
    "stream_dedup": "SELECT event_id, user_id FROM events",
    "stream_join": "SELECT event_id, user_id, c_nationkey FROM events JOIN customer ON c_custkey = user_id",
    "stream_interval_join": "SELECT a.event_id, b.event_id AS later_id FROM events a JOIN events b ON b.user_id = a.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'view' AND b.event_type = 'click'",
    "stream_adjacency": "SELECT user_id, event_type FROM (SELECT user_id, event_type, max(ts) AS last, max(max(ts)) OVER (PARTITION BY user_id) AS newest FROM events GROUP BY 1, 2) q WHERE last >= newest - INTERVAL 7 DAY",
    "stream_leaf_insert": "SELECT CAST(place + row_number() OVER (ORDER BY place, event_id) - 1 AS BIGINT) AS place FROM (SELECT event_id, (CAST(floor(epoch(ts)) AS BIGINT) // 60) % 10080 AS place FROM events) q",
    "stream_edges": "SELECT user_id, event_type, count(*) AS w FROM events GROUP BY 1, 2",
}
