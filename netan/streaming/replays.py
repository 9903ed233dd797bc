"""Streams of events and edges, each run to the end of what is there (availableNow) into a table in the shared folder."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from netan.contraction import contract
from netan.storage import drop, shared_dir, written


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream; ts as a timestamp (of UTC), since watermarks don't take timestamps without a zone."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def replay(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = (), at: str | None = None) -> DataFrame:
    """The stream's whole output as a table. Append goes to files; of complete mode the last batch counts, of update mode the last row
    of each of the keys. at: the folder of an earlier run of the same stream, which this one carries on."""
    spark = stream.sparkSession
    at = at or f"{shared_dir(spark)}/netan/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{at}/state").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{at}/out").start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")
    if mode == "update" and not keys:
        raise ValueError("rows of update mode need keys")
    held = _HELD.setdefault(at, {"table": spark.createDataFrame([], stream.schema)})

    def keep(batch: DataFrame, number: int) -> None:
        before = held["table"]
        rows = batch if mode == "complete" else batch.unionByName(before.join(batch, list(keys), "left_anti"))
        held["table"] = written(rows, f"batch-{number}")
        drop(before)

    query = writer.foreachBatch(keep).start()
    query.awaitTermination()
    return held["table"]


#: What runs that write batch by batch have so far, by their folder.
_HELD: dict[str, dict[str, DataFrame]] = {}


def in_parts(spark: SparkSession, parts: list[DataFrame], build: Callable[[DataFrame], DataFrame], mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Events that come in parts: after each, the stream is started again and carries on from its checkpoint."""
    at, out = f"{shared_dir(spark)}/netan/stream-{uuid.uuid4().hex}", None
    for part in parts:
        part.write.mode("append").parquet(f"{at}/in")
        rows = spark.readStream.schema(part.schema).parquet(f"{at}/in").withColumn("ts", F.col("ts").cast("timestamp"))
        out = replay(build(rows), mode, keys, at)
    return out


def window_counts(stream: DataFrame, size: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(start, event_type, n) by tumbling or sliding windows."""
    rows = stream.withWatermark("ts", late).groupBy(F.window("ts", size, slide), "event_type").agg(F.count("*").alias("n"))
    return rows.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n) of runs of events with no gap as long as that."""
    rows = stream.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return rows.select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    """One event per user, type and second, the others within the watermark dropped."""
    return stream.withColumn("ts", F.date_trunc("second", "ts")).withWatermark("ts", "10 minutes").dropDuplicates(["user_id", "event_type", "ts"]).select("user_id", "event_type", "ts")


def _ntz(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in columns})


def tumbling(spark, sf_dir):
    return _ntz(replay(window_counts(read_events(spark, sf_dir), "1 hour"), "complete"), "start")


def sliding(spark, sf_dir):
    return _ntz(replay(window_counts(read_events(spark, sf_dir), "1 hour", "30 minutes"), "complete"), "start")


def session(spark, sf_dir):
    return _ntz(replay(sessions(read_events(spark, sf_dir)), "complete"), "start")


def dedupe(spark, sf_dir):
    return _ntz(replay(deduplicated(read_events(spark, sf_dir))), "ts")


def stream_static(spark, sf_dir):
    """Error events with what a static table says of their user: the number of all its events."""
    users = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("user_id").agg(F.count("*").alias("events"))
    return replay(read_events(spark, sf_dir).where("event_type = 'error'").join(users, "user_id").select("event_id", "user_id", "events"))


def stream_stream(spark, sf_dir):
    """(view, click): clicks of the same user within an hour after a view."""
    a = read_events(spark, sf_dir).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_id").alias("view")).withWatermark("t", "10 minutes")
    b = read_events(spark, sf_dir).where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click")).withWatermark("ts", "10 minutes")
    pairs = a.join(b, (F.col("u") == F.col("user_id")) & (F.col("ts") > F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 1 HOUR")))
    return replay(pairs.select("view", "click"))


def incremental_components(spark, sf_dir):
    """(id, component) of users who share an event type and value: each batch's edges join the components known so far."""
    edges = read_events(spark, sf_dir).select("event_type", "value", F.col("user_id").alias("id")).writeStream.trigger(availableNow=True)
    at = f"{shared_dir(spark)}/netan/stream-{uuid.uuid4().hex}"
    held: dict[str, DataFrame] = {}

    def merge(batch: DataFrame, number: int) -> None:
        # a value's least user stands for it: a star holds together what all pairs would
        now = batch.groupBy("event_type", "value").agg(F.min("id").alias("hub"))
        if "hubs" in held:
            now = now.unionByName(held["hubs"]).groupBy("event_type", "value").agg(F.min("hub").alias("hub"))
        now = written(now, f"hubs-{number}")
        star = batch.join(now, ["event_type", "value"]).select(F.col("id").alias("src"), F.col("hub").alias("dst"))
        if "hubs" in held:
            moved = held["hubs"].withColumnRenamed("hub", "src").join(now.withColumnRenamed("hub", "dst"), ["event_type", "value"]).select("src", "dst")
            known = held["labels"].select(F.col("id").alias("src"), F.col("component").alias("dst"))
            star = star.union(moved).union(known)
        held["labels"], held["hubs"] = written(contract(star), f"labels-{number}"), now

    edges.option("checkpointLocation", f"{at}/state").foreachBatch(merge).start().awaitTermination()
    return held["labels"]


def _events(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/events.parquet")


def _by_time(events: DataFrame, parts: int = 3) -> list[DataFrame]:
    """The events in so many stretches of time of one length."""
    span = events.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).first()
    cuts = [span["a"] + (span["b"] - span["a"]) * k / parts for k in range(1, parts)]
    place = sum((F.col("ts") >= F.lit(c)).cast("int") for c in cuts) if cuts else F.lit(0)
    return [events.where(place == k) for k in range(parts)]


def late(spark, sf_dir):
    """(start, n) by hours; events older than ten days come after the newest ones and are dropped as late."""
    events = _events(spark, sf_dir)
    newest = events.agg(F.max("ts").alias("m")).first()["m"]
    recent = F.col("ts") >= F.lit(newest) - F.expr("INTERVAL 10 DAYS")
    parts = [events.where(recent), events.where(~recent)]
    hours = lambda rows: rows.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")
    return _ntz(in_parts(spark, parts, hours, "update", ("start",)), "start")


def handed_on(stream: DataFrame) -> DataFrame:
    """(event_type, src, dst): users of two events of a type, one after the other; the last user of a type is its state."""

    def follow(key, batches, state):
        import pandas as pd

        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        users = ([state.get[0]] if state.exists else []) + rows["user_id"].tolist()
        state.update((users[-1],))
        pairs = [(key[0], a, b) for a, b in zip(users, users[1:]) if a != b]
        yield pd.DataFrame(pairs, columns=["event_type", "src", "dst"]).astype({"src": "int64", "dst": "int64"})

    rows = stream.select("event_type", "ts", "event_id", "user_id").groupBy("event_type")
    return rows.applyInPandasWithState(follow, "event_type string, src long, dst long", "user long", "append", GroupStateTimeout.NoTimeout)


def stateful_handoff(spark, sf_dir):
    return in_parts(spark, _by_time(_events(spark, sf_dir)), handed_on)


def incremental_degree(spark, sf_dir):
    """(user_id, events, types): running numbers of each user's events, and of their types."""
    totals = lambda rows: rows.groupBy("user_id").agg(F.count("*").alias("events"), F.size(F.collect_set("event_type")).cast("long").alias("types"))
    return in_parts(spark, _by_time(_events(spark, sf_dir)), totals, "update", ("user_id",))


def restarted(spark, sf_dir):
    """(event_type, n, last): a stream that is stopped and started again counts no event twice and none too few."""
    totals = lambda rows: rows.groupBy("event_type").agg(F.count("*").alias("n"), F.max("event_id").alias("last"))
    return in_parts(spark, _by_time(_events(spark, sf_dir), 2), totals, "complete")


QUERIES = {
    "str_tumbling": (tumbling, "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "str_sliding": (sliding, "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start FROM events) GROUP BY 1, 2"),
    "str_session": (session, "WITH a AS (SELECT user_id, ts, event_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT user_id, min(ts) AS start, count(*) AS n FROM b GROUP BY user_id, s"),
    "str_dedupe": (dedupe, "SELECT DISTINCT user_id, event_type, date_trunc('second', ts) AS ts FROM events"),
    "str_stream_static": (stream_static, "SELECT event_id, user_id, (SELECT count(*) FROM events i WHERE i.user_id = e.user_id) AS events FROM events e WHERE event_type = 'error'"),
    "str_stream_stream": (stream_stream, "SELECT a.event_id AS view, b.event_id AS click FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"),
    "str_late": (late, "SELECT date_trunc('hour', ts) AS start, count(*) AS n FROM events WHERE ts >= (SELECT max(ts) FROM events) - INTERVAL 10 DAY GROUP BY 1"),
    "str_handoff": (stateful_handoff, "SELECT event_type, src, dst FROM (SELECT event_type, user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst"),
    "str_degree": (incremental_degree, "SELECT user_id, count(*) AS events, count(DISTINCT event_type) AS types FROM events GROUP BY 1"),
    "str_restart": (restarted, "SELECT event_type, count(*) AS n, max(event_id) AS last FROM events GROUP BY 1"),
    "str_incremental_cc": (incremental_components, None),
}


def queries() -> dict:
    return {n: f for n, (f, _) in QUERIES.items()}


def oracle_sql() -> dict:
    from netan import oracle

    # users alone in all their values are components too
    alone = "SELECT id, component FROM cc UNION ALL SELECT user_id, user_id FROM events WHERE user_id NOT IN (SELECT id FROM v) GROUP BY 1"
    return {n: s for n, (_, s) in QUERIES.items() if s} | {"str_incremental_cc": oracle.components("covalue", alone)}
