"""Structured Streaming over the events table: windows, joins, dedupe and triangles.

Each query replays a file source with availableNow, writes to a sink in the shared folder
and reads it back, so that a batch answer can check it.
"""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import shared
from ..session import checkpoint_folder, cut
from ..sources import graphs

LATE = "10 minutes"


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream with an event time that watermarks accept.  The file source
    wants a folder: a table that is one file is picked from its folder by name."""
    table = graphs.table(spark, sf_dir, "events")
    single = all(f.rstrip("/").endswith("/events.parquet") for f in table.inputFiles())
    df = spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 4).option("pathGlobFilter", "events.parquet" if single else "*.parquet")
    return df.parquet(sf_dir if single else f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def replay(stream: DataFrame, mode: str = "append", each=None) -> DataFrame:
    """Run a stream to its end and read what it wrote."""
    spark = stream.sparkSession
    base = f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode(mode)
    if each is None and mode == "append":
        writer.format("parquet").start(f"{base}/out").awaitTermination()
        return spark.read.parquet(f"{base}/out")
    if each is None:
        # the newest value of each key replaces older ones: the last batch of complete mode is the answer
        def each(batch, number):
            batch.write.mode("overwrite").parquet(f"{base}/out")

    writer.foreachBatch(each).start().awaitTermination()
    return spark.read.parquet(f"{base}/out")


def windowed_counts(stream: DataFrame, kind: str, size: str = "1 hour", slide: str = "30 minutes", gap: str = "5 minutes", watermark: str = LATE) -> DataFrame:
    df = stream.withWatermark("ts", watermark)
    if kind == "session":
        by = F.session_window("ts", gap)
        return df.groupBy(by.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")
    by = F.window("ts", size) if kind == "tumbling" else F.window("ts", size, slide)
    return df.groupBy(by.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def _plain(df: DataFrame) -> DataFrame:
    """Times as microseconds, so that engines agree on their type."""
    return df.select(*[F.unix_micros(c).alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes])


def st_windows(kind: str):
    return lambda spark, sf_dir: _plain(replay(windowed_counts(source(spark, sf_dir), kind), "complete"))


def st_dedupe(spark, sf_dir):
    s = source(spark, sf_dir).withWatermark("ts", "3650 days").select("ts", "user_id", "event_type")
    return replay(s.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


def st_static_join(spark, sf_dir):
    kinds = spark.createDataFrame([("click", 1), ("purchase", 2)], "event_type string, weight int")
    s = source(spark, sf_dir).join(F.broadcast(kinds), "event_type")
    return replay(s.select("event_id", "weight"))


def st_stream_join(spark, sf_dir):
    """Clicks followed by a purchase of the same user within 10 minutes.  Files may come in
    any order of time, so no watermark drops rows: the state holds every click and purchase."""
    s = source(spark, sf_dir)
    c = s.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    p = source(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    return replay(c.join(p, F.expr("cu = pu AND pt >= ct AND pt <= ct + INTERVAL 10 MINUTES")).select("click", "purchase"))


def st_late(spark, sf_dir):
    """Rows of the batch answer and rows a zero watermark lets through: nothing is late in a sorted replay of one batch."""
    s = source(spark, sf_dir).withWatermark("ts", "0 seconds")
    got = replay(s.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select("n"), "complete")
    return got.agg(F.sum("n").alias("kept"))


def added_triangles(stream: DataFrame, window: str | None) -> DataFrame:
    """w, triangles: what each batch adds to the co-minute graph of each window (a unit of
    date_trunc; None: one window, w = 0).

    Rows (minute, user) and edges are stored, a folder a batch.  A new row is paired with
    the new and stored rows of its minute; a new edge adds the common neighbours of its ends,
    and of a triangle's new edges only the largest counts it.  Files may come in any order
    of time: no row is late, so no window is closed and its state stays.
    """
    base = f"{checkpoint_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    w = F.lit(0).cast("long") if window is None else F.unix_micros(F.date_trunc(window, "k"))

    def each(batch, number):
        spark = batch.sparkSession

        def stored(name, schema):
            kept = [f"{base}/{name}/{i}" for i in range(number)]
            return spark.read.schema(schema).parquet(*kept) if kept else spark.createDataFrame([], schema)

        def store(name, df, schema):
            df.write.mode("overwrite").parquet(f"{base}/{name}/{number}")
            return spark.read.schema(schema).parquet(f"{base}/{name}/{number}")

        rows, edges = "k timestamp, n long", "w long, src long, dst long"
        old = stored("rows", rows)
        seen = batch.select(F.date_trunc("minute", "ts").alias("k"), F.col("user_id").cast("long").alias("n")).dropna().distinct()
        new = store("rows", seen.join(old, ["k", "n"], "left_anti"), rows)
        both = new.join(old.unionByName(new).withColumnRenamed("n", "m"), "k").where("n <> m")
        pairs = both.select(w.alias("w"), F.least("n", "m").alias("src"), F.greatest("n", "m").alias("dst")).distinct()
        before = stored("edges", edges)
        fresh = store("edges", pairs.join(before, ["w", "src", "dst"], "left_anti"), edges)
        known = before.withColumn("new", F.lit(False)).unionByName(fresh.withColumn("new", F.lit(True)))
        arcs = known.select("w", "src", "dst", "new", F.col("src").alias("x"), F.col("dst").alias("c")).unionByName(known.select("w", "src", "dst", "new", F.col("dst").alias("x"), F.col("src").alias("c")))
        side = lambda end: arcs.select("w", F.col("x").alias(end), "c", F.when(F.col("new"), F.struct("src", "dst")).alias(f"by_{end}"))
        at = fresh.select("w", F.col("src").alias("a"), F.col("dst").alias("b"))
        own = F.struct(F.col("a").alias("src"), F.col("b").alias("dst"))
        closed = at.join(side("a"), ["w", "a"]).where(F.col("by_a").isNull() | (F.col("by_a") < own)).join(side("b"), ["w", "b", "c"]).where(F.col("by_b").isNull() | (F.col("by_b") < own))
        closed.groupBy("w").agg(F.count("*").alias("triangles")).write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return stream.sparkSession.read.schema("w long, triangles long").option("recursiveFileLookup", "true").parquet(f"{base}/out")


def window_triangles(stream: DataFrame, window: str, **bounds) -> DataFrame:
    """w, triangles: triangles of the co-minute graph of each window (a unit of date_trunc) that has any.

    State is the rows (minute, user), a folder a batch, and no edges.  Windows that a batch
    touches are counted anew from all their rows; the newest count of a window is its answer.
    Files may come in any order of time: no row is late, so no window is closed."""
    base = f"{checkpoint_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"

    def by_edges(rows):
        e = cut(rows.join(rows.withColumnRenamed("n", "m"), ["w", "k"]).where("n < m").select("w", F.col("n").alias("src"), F.col("m").alias("dst")).distinct())
        wedges = e.join(e.select("w", F.col("src").alias("dst"), F.col("dst").alias("to")), ["w", "dst"])
        closed = wedges.join(e.withColumnRenamed("dst", "to"), ["w", "src", "to"], "left_semi")
        return closed.groupBy("w").agg(F.count("*").alias("triangles"))

    def each(batch, number):
        spark = batch.sparkSession
        minute = F.date_trunc("minute", "ts")
        rows = batch.select(F.unix_micros(F.date_trunc(window, minute)).alias("w"), minute.alias("k"), F.col("user_id").cast("long").alias("n"))
        rows.dropna().distinct().write.mode("overwrite").parquet(f"{base}/rows/{number}")
        kept = [spark.read.schema("w long, k timestamp, n long").parquet(f"{base}/rows/{i}") for i in range(number + 1)]
        state = kept[0] if number == 0 else reduce(DataFrame.unionByName, kept).join(F.broadcast(kept[-1].select("w").distinct()), "w", "left_semi").distinct()
        found = shared.window_triangles(state, by_edges, **bounds)
        found.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/out/{number}")

    stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    out = stream.sparkSession.read.schema("w long, triangles long, batch int").option("recursiveFileLookup", "true").parquet(f"{base}/out")
    return out.groupBy("w").agg(F.max_by("triangles", "batch").alias("triangles"))


def st_window_tc(spark, sf_dir):
    """Triangles of the co-minute graph of each day."""
    return window_triangles(source(spark, sf_dir), "day").withColumnRenamed("w", "day")


def st_incremental_tc(spark, sf_dir):
    """A running triangle count of the co-minute graph: new edges add their common neighbours."""
    return added_triangles(source(spark, sf_dir), None).agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))


def queries() -> dict:
    comin = graphs.SQL["comin"]
    day = "SELECT DISTINCT date_trunc('day', x.ts) AS day, x.user_id AS src, y.user_id AS dst FROM events x JOIN events y ON date_trunc('minute', x.ts) = date_trunc('minute', y.ts) AND x.user_id < y.user_id"
    tri = "e x JOIN e y ON y.src = x.src AND y.dst > x.dst JOIN e z ON z.src = x.dst AND z.dst = y.dst"
    return {
        "st_tumbling": (st_windows("tumbling"), "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
        "st_sliding": (st_windows("sliding"), "SELECT epoch_us(time_bucket(INTERVAL 30 MINUTE, ts) - to_minutes(30 * o)) AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) t(o) GROUP BY 1, 2"),
        "st_session": (st_windows("session"), "SELECT epoch_us(min(ts)) AS start, epoch_us(max(ts) + INTERVAL 5 MINUTE) AS stop, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM "
            "(SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 5 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s"),
        "st_dedupe": (st_dedupe, "SELECT DISTINCT user_id, event_type FROM events"),
        "st_stream_static_join": (st_static_join, "SELECT event_id, CASE event_type WHEN 'click' THEN 1 ELSE 2 END::INT AS weight FROM events WHERE event_type IN ('click', 'purchase')"),
        "st_stream_stream_join": (st_stream_join, "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 10 MINUTE"),
        "st_late": (st_late, "SELECT count(*) AS kept FROM events"),
        "st_window_tc": (st_window_tc, f"WITH e AS ({day}) SELECT epoch_us(x.day) AS day, count(*) AS triangles FROM e x JOIN e y ON y.day = x.day AND y.src = x.src AND y.dst > x.dst JOIN e z ON z.day = x.day AND z.src = x.dst AND z.dst = y.dst GROUP BY 1"),
        "st_incremental_tc": (st_incremental_tc, f"WITH e AS ({comin}) SELECT count(*) AS triangles FROM {tri}"),
    }
