"""Streams over the event table, run until the input is used up, beside the SQL of the same answer over the whole table."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from incwalk.operators.registry_of import Registry
from incwalk.plans.update import WalkStore, update_sql
from incwalk.plans.walks import Spec
from incwalk.sources.graphs import edges, edges_sql
from incwalk.store import save, scratch_root, table
from incwalk.streaming.maintain import Maintainer, maintain_stream, sessions, windowed_arrivals

R = Registry()


def _folder(spark, name):
    return f"{scratch_root(spark)}/incwalk-graph/stream-{name}-{uuid.uuid4().hex}"


def arrivals(spark, sf_dir, batches: int = 1):
    """The event table as a stream of files: all in one batch, or in about ``batches`` ones split by the digest of the id, so that rows come out of order."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    folder = _folder(spark, "events")
    if batches == 1:
        events.write.parquet(folder)
        return spark.readStream.schema(events.schema).parquet(folder)
    parts = max(batches, int(spark.conf.get("spark.sql.shuffle.partitions")))
    events.repartition(parts, F.md5(F.col("event_id").cast("string"))).write.parquet(folder)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", -(-parts // batches)).parquet(folder)


def appended(stream, name):
    """All rows that the stream appends, through a Parquet sink that records its batches."""
    spark, out = stream.sparkSession, _folder(stream.sparkSession, name)
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-checkpoint").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def completed(stream, name):
    """The last state of an aggregate: each batch writes a whole version, the newest one is read."""
    spark, out, last = stream.sparkSession, _folder(stream.sparkSession, name), []

    def write(batch, number):
        batch.write.mode("overwrite").parquet(f"{out}/version={number}")
        last.append(number)

    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{out}-checkpoint").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/version={last[-1]}") if last else spark.createDataFrame([], stream.schema)


R.add("stream_windows_tumbling", lambda s, d: completed(windowed_arrivals(arrivals(s, d, 3), "6 hours"), "tumbling").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n"), "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
R.add("stream_arrivals_sliding", lambda s, d: completed(windowed_arrivals(arrivals(s, d, 3), "6 hours", "3 hours"), "sliding").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n"), "SELECT strftime(time_bucket(INTERVAL 3 HOUR, ts) - k * INTERVAL 3 HOUR, '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events, range(2) r(k) GROUP BY 1, 2")
R.add("stream_arrivals_session", lambda s, d: completed(sessions(arrivals(s, d, 2), "2 hours"), "session").select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("start"), "n"), "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, (coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 2 HOUR, true))::INT AS fresh FROM events)) GROUP BY user_id, s")
R.add("dedup_edges", lambda s, d: appended(arrivals(s, d).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"), "dedup"), "SELECT DISTINCT user_id, event_type FROM events")


def enrich_stream(spark, sf_dir):
    """Events joined with the customers' nations, a table small beside the stream; Spark picks the join by its size."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return appended(arrivals(spark, sf_dir).join(c, "user_id", "left").select("event_id", "c_nationkey"), "enriched")


R.add("enrich_stream", enrich_stream, "SELECT event_id, c_nationkey FROM events LEFT JOIN customer ON c_custkey = user_id")


def click_then_purchase(spark, sf_dir):
    """Purchases within six hours of a click of the same user: both streams hold state only as long as the watermarks and the range ask for."""
    click = arrivals(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")).withWatermark("ct", "40 days")
    buy = arrivals(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt")).withWatermark("pt", "40 days")
    return appended(click.join(buy, F.expr("cu = pu AND pt > ct AND pt <= ct + interval 6 hours")).select("click", "purchase", F.col("cu").alias("user_id")), "pairs")


R.add("click_then_purchase", click_then_purchase, "SELECT a.event_id AS click, b.event_id AS purchase, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")


def late_edges_dropped(spark, sf_dir):
    """Days that a watermark of one day has closed when the input ends; rows after that would be late and drop. The last days stay open."""
    s = arrivals(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return appended(s.select(F.col("window.start").alias("start"), "n"), "closed").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


R.add("late_edges_dropped", late_edges_dropped, "SELECT strftime(ts::DATE, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1, ts::DATE HAVING ts::DATE + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")


def running_degree(spark, sf_dir):
    """Arrivals per user, counted in state that lasts over batches; the largest count a user reported."""

    def count(key, frames, state):
        so_far = state.get[0] if state.exists else 0
        so_far += sum(len(f) for f in frames)
        state.update((so_far,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [so_far]})

    s = arrivals(spark, sf_dir, 3).groupBy("user_id").applyInPandasWithState(count, "user_id long, degree long", "n long", "append", GroupStateTimeout.NoTimeout)
    return appended(s, "degree").groupBy("user_id").agg(F.max("degree").alias("degree"))


R.add("running_degree", running_degree, "SELECT user_id, count(*) AS degree FROM events GROUP BY 1")


STREAMED = Spec(reps=2, seed=14)


def stream_replay(spark, sf_dir):
    """Later purchases stream into a maintained store; the visits of its walks at the end.

    All arrive in one batch, whose coins SQL can replay; tests stream several.
    """
    e = save(edges(spark, sf_dir, "cobuy").select("src", "dst", "ord"), "edges")
    fresh = F.substring(F.md5(F.concat_ws("|", "src", "dst")), 1, 2) == "3c"
    folder = _folder(spark, "changes")
    changes = e.where(fresh).select(F.lit("+").alias("op"), "src", "dst", "ord")
    changes.write.parquet(folder)
    keeper = Maintainer(WalkStore.create(e.where(~fresh), STREAMED))
    maintain_stream(spark.readStream.schema(changes.schema).parquet(folder), keeper, f"{folder}-checkpoint").awaitTermination()
    return WalkStore.open(spark, keeper.store.folder).visits().select("src", "rep", "pos", "node", "ended")


_CB = f"SELECT src, dst, ord FROM ({edges_sql('cobuy')})"
_LATE = "substr(md5(src || '|' || dst), 1, 2)"
R.add("stream_replay", stream_replay, "WITH RECURSIVE " + update_sql(f"{_CB} WHERE {_LATE} <> '3c'", f"SELECT '+' AS op, src, dst, ord FROM ({_CB}) WHERE {_LATE} = '3c'", STREAMED) + " SELECT src, rep, pos, node, ended FROM w1")


def stream_rate(spark, sf_dir, rows: int = 1000):
    """A rate source's ticks joined with the customers of those keys: one micro-batch, counted by nation into a memory sink, which holds a row a nation."""
    name = "rate_" + uuid.uuid4().hex
    ticks = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", 4).load()
    hit = ticks.select((F.col("value") + 1).alias("c_custkey")).join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), "c_custkey")
    counted = hit.groupBy("c_nationkey").agg(F.count("*").alias("n"), F.max("c_custkey").alias("last"))
    counted.writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", _folder(spark, "rate")).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


R.add("stream_rate", stream_rate, "SELECT c_nationkey, count(*) AS n, max(c_custkey) AS last FROM customer WHERE c_custkey BETWEEN 1 AND 1000 GROUP BY 1")
