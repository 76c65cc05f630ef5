"""Structured Streaming over events: windows, late rows, repeats, interval joins, quotas."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.linalg import to_matrix
from ..operators import kmeans, metrics
from ..sources.tables import shared_folder, staged, table

Q: dict = {}
SQL: dict[str, str] = {}


def event_stream(spark: SparkSession, sf: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    raw = spark.readStream.schema(schema).parquet(f"{sf}/events.parque[t]")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def run_stream(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run over what is there now. Append goes to files in the shared folder, complete to a table of results
    that is small by nature (windows)."""
    spark = df.sparkSession
    name = f"s{uuid.uuid4().hex}"
    base = shared_folder(spark)
    point = f"{base}/{name}-progress"
    out = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", point)
    if mode == "append":
        out.format("parquet").option("path", f"{base}/{name}").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/{name}")
    out.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def run_complete(df: DataFrame) -> DataFrame:
    """Run over what is there now in complete mode, for results that grow with the input: every micro-batch writes its
    whole result to a folder of its own in the shared folder, and the last one counts. No row passes the driver."""
    spark = df.sparkSession
    out = f"{shared_folder(spark)}/s{uuid.uuid4().hex}"
    last: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        path = f"{out}/{number}"
        batch.write.mode("overwrite").parquet(path)
        last[:] = [path]

    q = df.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{out}-progress")
    q.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(*last) if last else spark.createDataFrame([], df.schema)


def _stamp(c):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


def tumbling(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return run_stream(s.select(_stamp("window.start").alias("start"), "event_type", "n"), "complete")


def sliding(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return run_stream(s.select(_stamp("window.start").alias("start"), "n"), "complete")


def session(spark, sf):
    s = event_stream(spark, sf).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    return run_complete(s.select(_stamp("session_window.start").alias("start"), "user_id", "n"))


def dedup(spark, sf):
    s = event_stream(spark, sf).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return run_stream(s.select("event_id", "user_id"))


def interval_join(spark, sf):
    e = event_stream(spark, sf)
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("vt"), F.col("event_id").alias("v"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"), F.col("event_id").alias("p"))
    v, p = v.withWatermark("vt", "1 hour"), p.withWatermark("pt", "1 hour")
    return run_stream(v.join(p, F.expr("u = user_id and pt > vt and pt <= vt + interval 1 hour")).select("v", "p"))


def quota(spark, sf, cap: int = 100):
    """Admits at most `cap` events of each type, in file order of arrival; state is one counter per type."""

    def admit(key, frames: Iterator[pd.DataFrame], state):
        used = state.get[0] if state.exists else 0
        n = sum(len(f) for f in frames)
        take = min(n, cap - used)
        state.update((used + take,))
        yield pd.DataFrame({"event_type": [key[0]], "admitted": [take]})

    s = event_stream(spark, sf).groupBy("event_type").applyInPandasWithState(
        admit, "event_type string, admitted long", "used long", "append", "NoTimeout"
    )
    return run_stream(s).groupBy("event_type").agg(F.sum("admitted").alias("admitted"))


Q.update(
    stream_tumbling=tumbling, stream_sliding=sliding, stream_session=session, stream_dedup=dedup,
    stream_interval_join=interval_join, stream_quota=quota,
)
SQL.update(
    stream_tumbling="SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
    stream_sliding="SELECT strftime(d - i * INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS start, CAST(sum(n) AS BIGINT) AS n FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS d, count(*) AS n FROM events GROUP BY 1) x, unnest([0, 1]) AS u(i) GROUP BY 1",
    stream_session="WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), h AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM h GROUP BY user_id, s",
    stream_dedup="SELECT DISTINCT event_id, user_id FROM events",
    stream_interval_join="SELECT a.event_id AS v, b.event_id AS p FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    stream_quota="SELECT event_type, least(count(*), 100) AS admitted FROM events GROUP BY 1",
)


# Streams of points and restarts -------------------------------------------------------------------------------


def late(spark, sf):
    """Closed day windows over two runs from one checkpoint; the second run brings rows older than the
    watermark of the first, and they are dropped."""
    base = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    events = table(spark, sf, "events", cast_ntz=True).select("event_id", "ts")
    inbox, out = f"{base}/in", f"{base}/out"
    top = events.agg(F.max("ts")).first()[0]
    for part in (events, events.where(F.col("ts") < F.lit(top) - F.expr("interval 5 days"))):
        part.write.mode("append").parquet(inbox)
        days = spark.readStream.schema(events.schema).parquet(inbox).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"))
        counted = days.agg(F.count("*").alias("n")).select(_stamp("window.start").alias("start"), "n")
        q = counted.writeStream.outputMode("append").format("parquet").trigger(availableNow=True)
        q.option("checkpointLocation", f"{base}/progress").option("path", out).start().awaitTermination()
    return spark.read.schema("start string, n long").parquet(out)


def point_stream(spark, sf):
    schema = spark.read.parquet(f"{sf}/embeddings.parquet").schema
    raw = spark.readStream.schema(schema).parquet(f"{sf}/embeddings.parque[t]")
    return raw.select(F.col("vec_id").alias("point_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))


def _first_ten(spark, sf):
    rows = table(spark, sf, "embeddings").where("vec_id < 10").orderBy("vec_id").select("embedding").collect()
    return to_matrix([x[0] for x in rows])


def route(spark, sf):
    """Arriving points to the nearest node of a fixed level."""
    return run_stream(kmeans.assign(point_stream(spark, sf), _first_ten(spark, sf)).select("point_id", "node"))


def minibatch(spark, sf, decay: float = 0.9):
    """Centroids as decayed means, a new version per micro-batch; returns the mass of the last version."""
    c = _first_ten(spark, sf)
    held = {"c": c, "mass": c[:, 0] * 0, "version": 0}

    def update(batch: DataFrame, _: int) -> None:
        sums, mass, _sse = kmeans._partials(batch, held["c"])
        old = held["mass"] * decay
        both = old + mass
        moved = (held["c"] * old[:, None] + sums) / both.clip(1e-300)[:, None]
        held["c"] = held["c"].copy()
        held["c"][both > 0] = moved[both > 0]
        held["mass"], held["version"] = both, held["version"] + 1

    progress = f"{shared_folder(spark)}/mini-{uuid.uuid4().hex}"
    q = point_stream(spark, sf).writeStream.foreachBatch(update).option("checkpointLocation", progress)
    q.trigger(availableNow=True).start().awaitTermination()
    rows = [(i, float(m), held["version"]) for i, m in enumerate(held["mass"])]
    return spark.createDataFrame(rows, "node long, mass double, version int")


def least_seen(spark, sf, size: int = 10):
    """Requests (events) are served the least-seen of `size` places of their cluster (event type). As service
    goes round in turn, one counter per cluster is the whole state."""

    def serve(key, frames: Iterator[pd.DataFrame], state):
        used = state.get[0] if state.exists else 0
        for f in frames:
            at = range(used, used + len(f))
            used += len(f)
            yield pd.DataFrame({"event_type": key[0], "place": [j % size for j in at], "seen_before": [j // size for j in at]})
        state.update((used,))

    s = event_stream(spark, sf).groupBy("event_type").applyInPandasWithState(
        serve, "event_type string, place long, seen_before long", "used long", "append", "NoTimeout"
    )
    return run_stream(s)


def window_tv(spark, sf):
    """Distance from uniform of the event types in each day window that has closed; one row per window is written
    by foreachBatch."""
    out = f"{shared_folder(spark)}/tv-{uuid.uuid4().hex}"
    types = table(spark, sf, "events").select("event_type").distinct()
    days = event_stream(spark, sf).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))

    def measure(batch: DataFrame, _: int) -> None:
        counts = batch.select(_stamp("window.start").alias("start"), "event_type", "n")
        metrics.tv_uniform(staged(counts), types, ["event_type"], by=["start"]).write.mode("append").parquet(out)

    q = days.writeStream.foreachBatch(measure).outputMode("append").option("checkpointLocation", f"{out}-progress")
    q.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("start string, tv double").parquet(out).select("start", F.round("tv", 8).alias("tv"))


def updates(spark, sf):
    """Running counts by type in update mode, on a processing-time trigger, until all files are read; the last version
    of each count is returned."""
    out = f"{shared_folder(spark)}/up-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("version", F.lit(number)).write.mode("append").parquet(out)

    counts = event_stream(spark, sf).groupBy("event_type").agg(F.count("*").alias("n"))
    q = counts.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", f"{out}-progress")
    q = q.trigger(processingTime="1 second").start()
    q.processAllAvailable()
    q.stop()
    rows = spark.read.schema("event_type string, n long, version int").parquet(out)
    return rows.groupBy("event_type").agg(F.max_by("n", "version").alias("n"))


_NODES = (
    "SELECT vec_id AS point_id, arg_min(node, (d, node)) AS node FROM (SELECT p.vec_id, c.vec_id AS node, list_sum([(z[1]::DOUBLE - z[2]::DOUBLE) * (z[1]::DOUBLE - z[2]::DOUBLE) FOR z IN list_zip(p.embedding, c.embedding)]) AS d "
    "FROM embeddings p, embeddings c WHERE c.vec_id < 10) x GROUP BY vec_id"
)
Q.update(stream_window_tv=window_tv, stream_update_mode=updates)
SQL.update(
    stream_window_tv="WITH c AS (SELECT date_trunc('day', ts)::TIMESTAMP AS d, event_type, count(*) AS n FROM events GROUP BY ALL), t AS (SELECT d, sum(n) AS m FROM c WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY d), k AS (SELECT count(DISTINCT event_type) AS k FROM events) SELECT strftime(t.d, '%Y-%m-%d %H:%M:%S') AS start, round(sum(abs(coalesce(c.n, 0)::DOUBLE / m - 1.0::DOUBLE / k)) / 2, 8) AS tv FROM t CROSS JOIN (SELECT DISTINCT event_type FROM events) e CROSS JOIN k LEFT JOIN c ON c.d = t.d AND c.event_type = e.event_type GROUP BY t.d",
    stream_update_mode="SELECT event_type, count(*) AS n FROM events GROUP BY 1",
)
Q.update(stream_late=late, stream_route=route, stream_minibatch_kmeans=minibatch, stream_least_seen=least_seen)
SQL.update(
    stream_late="SELECT strftime(d, '%Y-%m-%d %H:%M:%S') AS start, n FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS d, count(*) AS n FROM events GROUP BY 1) x WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY",
    stream_route=_NODES,
    stream_minibatch_kmeans=f"SELECT node, count(*)::DOUBLE AS mass, 1 AS version FROM ({_NODES}) y GROUP BY node",
    stream_least_seen="SELECT event_type, j % 10 AS place, j // 10 AS seen_before FROM (SELECT event_type, row_number() OVER (PARTITION BY event_type) - 1 AS j FROM events) x",
)
