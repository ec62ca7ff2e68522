"""Queries that run as streams until their source is drained; many have the SQL of their batch twin."""

from __future__ import annotations

import time
import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.config import ClusterConfig
from eventpulse.operators import blocks
from eventpulse.plans import sql
from eventpulse.plans.burst_queries import CONV, EVT, RAW, W4, bursts_sql, conv_tokens, events_out, r9
from eventpulse.plans.cluster_queries import PLANT_EVENTS
from eventpulse.plans.scratch import materialize, new_dir
from eventpulse.sources import posts as P
from eventpulse.sources.blocks_source import BlockSource
from eventpulse.sources.tables import table
from eventpulse.streaming import replay
from eventpulse.streaming.bursts import burst_stream
from eventpulse.streaming.clusters import cluster_stream

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
T0 = sql.T0


def query(name: str, oracle: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return put


def events(spark, d, files: int = 6, sentinel: bool = True) -> DataFrame:
    """The events table as a stream of files in time order."""
    e = table(spark, d, "events").select("event_id", "ts", "user_id", "event_type", "value")
    path = new_dir(spark, "events")
    replay.write_replay(e, path, files, sentinel=sentinel)
    return replay.read_replay(spark, path, e.schema)


def tokened_stream(spark, posts: DataFrame, length: str) -> tuple[DataFrame, int]:
    t = blocks.tokened(posts, length, RAW, T0).select("post_id", "ts", "region", "tokens")
    path = new_dir(spark, "tokens")
    replay.write_replay(t, path)
    return replay.read_replay(spark, path, t.schema), T0


def blockwise_stream(spark, tokens: DataFrame, pace: replay.Pause) -> tuple[DataFrame, int]:
    """(stream, files): tokened posts as a stream with a file for each block and one to end it, as many a trigger as the pace takes."""
    t = tokens.select("post_id", "ts", "region", "tokens", "block_no")
    path = new_dir(spark, "blockwise")
    files = replay.write_replay(t, path, "block_no")
    return replay.read_replay(spark, path, t.schema, pace.blocks).drop("block_no"), files


@query("M_K19_burst_stream", bursts_sql(EVT, W4))
def _(spark, d):
    stream, origin = tokened_stream(spark, P.posts_from_events(table(spark, d, "events")), "1 hour")
    return events_out(burst_stream(spark, stream, "1 hour", origin, W4))


@query("M_C19_cluster_stream", PLANT_EVENTS)
def _(spark, d):
    stream, origin = tokened_stream(spark, P.planted_burst_posts(table(spark, d, "benchmark")), "6 minutes")
    fold = replay.to_table(cluster_stream(stream, "6 minutes", origin, ClusterConfig()), "clusters")
    ev = fold.where("kind = 'cluster' and is_event")
    return ev.select("region", "block_no", "n_added", "n_posts", r9("growth").alias("growth"))


@query("M_K17_pausing_source", f"{CONV} select p::double as pause, count(distinct block_no) + 1 as files, true as waited from tok, (select unnest([0.0, 0.05]) as p) group by 1")
def _(spark, d):
    """A replay of the turns, a file a block and one to end it: whether it takes at least a pause for each."""
    t = conv_tokens(spark, d)
    rows = []
    for seconds in (0.0, 0.05):
        pace = replay.Pause(seconds)
        stream, files = blockwise_stream(spark, t, pace)
        took = replay.paced(stream, lambda b, _: b.count(), pace, "paced", files)
        rows.append((seconds, files, took >= seconds * files))
    return spark.createDataFrame(rows, "pause double, files long, waited boolean")


@query("S_2_ordered_replay", "select count(*) as n, sum(event_id)::bigint as ids from events")
def _(spark, d):
    return replay.to_table(events(spark, d, sentinel=False), "replay").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


#: Ticks of the rate source that release a table.
TICKS = 50


@query("S_4_rate_source", f"select count(*) as n, min(event_id) as first_id, {TICKS}::bigint as ticks from events")
def _(spark, d):
    """The rate source as a clock: each of its first ticks releases the events whose number has its remainder. Counts of each
    tick go through the memory sink."""
    part = F.pmod("event_id", F.lit(TICKS))
    held = table(spark, d, "events").groupBy(part.alias("value")).agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"))
    held = materialize(held, "released").hint("broadcast")  # a row a tick
    ticks = spark.readStream.format("rate").option("rowsPerSecond", TICKS).load().where(f"value < {TICKS}")
    name = f"ep_rate_{uuid.uuid4().hex}"
    q = ticks.join(held, "value", "left").select("value", "n", "first_id").writeStream.format("memory").queryName(name).start()
    try:
        while spark.table(name).count() < TICKS and q.isActive:
            time.sleep(0.1)
        if q.exception():
            raise q.exception()
    finally:
        q.stop()
    return spark.table(name).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.min("first_id").alias("first_id"), F.count("*").alias("ticks"))


def _custom(name: str, streaming: bool) -> None:
    @query(name, "select min(event_id) as first_id, max(event_id) as last_id, count(*) as n from events")
    def _(spark, d):
        """The events, dealt to stretches of time by Spark, through a data source in Python."""
        from eventpulse.plans.scratch import ship

        ship(spark)
        spark.dataSource.register(BlockSource)
        e = table(spark, d, "events").select(F.col("event_id").alias("post_id"), "ts", F.lit("ALL").alias("region"), F.col("event_type").alias("text"))
        path = new_dir(spark, "block-source")
        opts = {"path": path, "blocks": str(replay.write_replay(e, path, 4, sentinel=False))}
        if not streaming:
            df = spark.read.format("post_blocks").options(**opts).load()
            return df.agg(F.min("post_id").alias("first_id"), F.max("post_id").alias("last_id"), F.count("*").alias("n"))
        out = new_dir(spark, "block-source-out")
        q = spark.readStream.format("post_blocks").options(**opts).load().select("post_id").writeStream.format("parquet").option("path", out).option("checkpointLocation", new_dir(spark, "block-source-check")).start()
        try:
            q.processAllAvailable()
        finally:
            q.stop()
        return spark.read.schema("post_id long").parquet(out).agg(F.min("post_id").alias("first_id"), F.max("post_id").alias("last_id"), F.count("*").alias("n"))


_custom("S_5_block_source", False)
_custom("S_5_block_source_stream", True)

BY_TYPE = "select event_type, count(*) as n from events group by 1"


def _mode(mode: str) -> None:
    @query(f"K_2_{mode}_mode", BY_TYPE)
    def _(spark, d):
        counts = events(spark, d, sentinel=False).groupBy("event_type").agg(F.count("*").alias("n"))
        if mode == "complete":
            return replay.to_table(counts, "complete", "complete")
        out = new_dir(spark, "update")

        def put(batch: DataFrame, k: int) -> None:
            batch.withColumn("_k", F.lit(k)).write.mode("overwrite").parquet(f"{out}/batch={k}")

        replay.drain(counts.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", new_dir(spark, "update-check")))
        return spark.read.parquet(out).groupBy("event_type").agg(F.max_by("n", "_k").alias("n"))


_mode("complete")
_mode("update")


@query("K_3_upsert", "select user_id, count(*) as n, max(event_id) as last_id from events group by 1")
def _(spark, d):
    """A snapshot that every batch replaces by one with its rows merged in; a repeated batch changes nothing."""
    base = new_dir(spark, "upsert")
    spark.createDataFrame([], "user_id long, n long, last_id long").write.parquet(f"{base}/0")

    last = [0]

    def put(batch: DataFrame, k: int) -> None:
        new = batch.groupBy("user_id").agg(F.count("*").alias("n"), F.max("event_id").alias("last_id"))
        old = batch.sparkSession.read.schema("user_id long, n long, last_id long").parquet(f"{base}/{k}")
        both = old.unionByName(new).groupBy("user_id").agg(F.sum("n").alias("n"), F.max("last_id").alias("last_id"))
        both.write.mode("overwrite").parquet(f"{base}/{k + 1}")
        last[0] = k + 1

    replay.drain(events(spark, d, 3, sentinel=False).writeStream.foreachBatch(put).option("checkpointLocation", new_dir(spark, "upsert-check")))
    return spark.read.schema("user_id long, n long, last_id long").parquet(f"{base}/{last[0]}")


@query("K_4_memory_sink", BY_TYPE)
def _(spark, d):
    counts = events(spark, d, 2, sentinel=False).groupBy("event_type").agg(F.count("*").alias("n"))
    replay.drain(counts.writeStream.outputMode("complete").format("memory").queryName("ep_memory"))
    return spark.table("ep_memory")


@query("J_16_stream_static_join", "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
def _(spark, d):
    c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    s = events(spark, d, 3, sentinel=False).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
    return replay.to_table(s, "static", "complete")


@query("J_17_stream_stream_join", "select a.event_id as a, b.event_id as b from (select * from events where event_type = 'purchase') a join (select * from events where event_type = 'signup') b on a.user_id = b.user_id and epoch_us(b.ts) between epoch_us(a.ts) and epoch_us(a.ts) + 3600000000")
def _(spark, d):
    kind = lambda k, i, t: events(spark, d, 3).where(f"event_type = '{k}'").select(F.col("event_id").alias(i), F.col("user_id").alias(f"u_{i}"), F.col("ts").alias(t)).withWatermark(t, "1 hour")
    a, b = kind("purchase", "a", "ta"), kind("signup", "b", "tb")
    met = a.join(b, F.expr("u_a = u_b and tb between ta and ta + interval 1 hour"))
    return replay.to_table(met.select("a", "b"), "both")


def _hour(c: str = "ts") -> str:
    return f"epoch_us({c}) // 3600000000 * 3600000000"


@query("G_1_tumbling", f"select {_hour()} as start_us, event_type, count(*) as n from events group by 1, 2")
def _(spark, d):
    s = events(spark, d).withWatermark("ts", "0 seconds").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    out = replay.to_table(s, "tumbling").where("event_type is not null")
    return out.select(F.unix_micros("window.start").alias("start_us"), "event_type", "n")


@query("G_2_sliding", f"select {_hour()} - k * 3600000000 as start_us, count(*) as n from events, (select unnest([0, 1]) as k) group by 1")
def _(spark, d):
    s = events(spark, d).withWatermark("ts", "0 seconds").where("event_id is not null or true").groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("event_id").alias("n"))
    return replay.to_table(s, "sliding").where("n > 0").select(F.unix_micros("window.start").alias("start_us"), "n")


SESSION = f"""with t as (select conv_id, {T0} + (conv_id * 360 + turn * 20) * 1000000 as us from conversations),
g as (select *, case when us - lag(us) over (partition by conv_id order by us) < 60000000 then 0 else 1 end as new from t),
s as (select *, sum(new) over (partition by conv_id order by us) as k from g)
select conv_id, min(us) as start_us, count(*) as n from s group by conv_id, k"""


def conversation_times(spark, d) -> DataFrame:
    ts = P.posts_from_conversations(table(spark, d, "conversations")).select("post_id", "ts")
    return ts.select(F.floor(F.col("post_id") / 1000).alias("conv_id"), "ts")


@query("G_3_sessions_batch", SESSION)
def _(spark, d):
    s = conversation_times(spark, d).groupBy("conv_id", F.session_window("ts", "1 minute")).agg(F.count("*").alias("n"))
    return s.select("conv_id", F.unix_micros("session_window.start").alias("start_us"), "n")


@query("G_3_sessions", SESSION)
def _(spark, d):
    c = conversation_times(spark, d)
    path = new_dir(spark, "sessions")
    replay.write_replay(c, path, 3)
    s = replay.read_replay(spark, path, c.schema).withWatermark("ts", "1 minute").groupBy("conv_id", F.session_window("ts", "1 minute")).agg(F.count("*").alias("n"))
    return replay.to_table(s, "sessions").where("conv_id is not null").select("conv_id", F.unix_micros("session_window.start").alias("start_us"), "n")


@query("G_4_late_rows", "select 1::bigint as dropped")
def _(spark, d):
    """A row that comes after the watermark has passed its block is dropped and counted."""
    e = table(spark, d, "events").select("event_id", "ts", "event_type")
    path = new_dir(spark, "late")
    files = replay.write_replay(e, path, 3)
    e.where("event_id = 0").coalesce(1).write.parquet(f"{path}/{files:06d}")
    s = replay.read_replay(spark, path, e.schema).withWatermark("ts", "0 seconds").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    q = replay.drain(s.writeStream.format("noop").option("checkpointLocation", new_dir(spark, "late-check")))
    late = sum(int(o["numRowsDroppedByWatermark"]) for p in q.recentProgress for o in p["stateOperators"])
    return spark.createDataFrame([(late,)], "dropped long")


@query("G_5_dedup_within_watermark", "select count(distinct event_id) as n from events")
def _(spark, d):
    s = events(spark, d, 3).where("event_id is not null")
    twice = s.withColumn("_copy", F.explode(F.array(F.lit(0), F.lit(1)))).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return replay.to_table(twice.select("event_id"), "dedup").agg(F.count("*").alias("n"))


@query("G_7_apply_with_state", BY_TYPE)
def _(spark, d):
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(key, frames, state):
        total = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((total,))
        yield pd.DataFrame({"event_type": [key[0]], "n": [total]})

    s = events(spark, d, 3, sentinel=False).groupBy("event_type").applyInPandasWithState(run, "event_type string, n long", "n long", "update", GroupStateTimeout.NoTimeout)
    out = new_dir(spark, "state")

    def put(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={k}")

    replay.drain(s.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", new_dir(spark, "state-check")))
    return spark.read.parquet(out).groupBy("event_type").agg(F.max("n").alias("n"))


@query("G_8_chained_windows", f"select {_hour()} as start_us, count(distinct event_type) as kinds, count(*) as n from events group by 1")
def _(spark, d):
    s = events(spark, d).withWatermark("ts", "0 seconds").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("k"))
    both = s.groupBy(F.window(F.window_time("window"), "1 hour")).agg(F.count("event_type").alias("kinds"), F.sum("k").alias("n"))
    out = replay.to_table(both, "chained").where("kinds > 0")
    return out.select(F.unix_micros("window.start").alias("start_us"), "kinds", "n")


@query("G_8_shard_to_region", f"select {_hour()} as start_us, count(distinct user_id % 4) as shards, count(*) as n from events group by 1")
def _(spark, d):
    """A count in each shard of an hour, then over the shards: the second state takes the first one's closed windows."""
    s = events(spark, d).withWatermark("ts", "0 seconds").withColumn("shard", F.pmod("user_id", F.lit(4)))
    local = s.groupBy(F.window("ts", "1 hour"), "shard").agg(F.count("*").alias("k"))
    region = local.groupBy(F.window(F.window_time("window"), "1 hour")).agg(F.count("shard").alias("shards"), F.sum("k").alias("n"))
    return replay.to_table(region, "shards").where("shards > 0").select(F.unix_micros("window.start").alias("start_us"), "shards", "n")


@query("G_6_state_with_timers", f"select event_type, {_hour()} + 3600000000 as closed_us, count(*) as n, sum(value)::decimal(18, 2)::double as total from events group by 1, 2")
def _(spark, d):
    """Counts and sums of each type in a value state, sent on by an event-time timer at the end of the hour."""
    from eventpulse.streaming.hours import hourly

    out = replay.to_table(hourly(events(spark, d)), "hourly")
    return out.select("event_type", "closed_us", "n", F.col("total").cast("decimal(18,2)").cast("double").alias("total"))


@query("K_4_console_sink", "select count(*) as n from events")
def _(spark, d):
    """The console sink: rows that the query's progress reports as read."""
    q = replay.drain(events(spark, d, 2, sentinel=False).groupBy("event_type").agg(F.count("*").alias("n")).writeStream.outputMode("complete").format("console").option("numRows", 1))
    return spark.createDataFrame([(sum(p.numInputRows for p in q.recentProgress),)], "n long")


@query("G_9_triggers", "select count(*) as n from events")
def _(spark, d):
    """A fixed interval between batches, stopped when all is read."""
    out = new_dir(spark, "trigger")
    q = events(spark, d, 3, sentinel=False).writeStream.format("parquet").option("path", out).option("checkpointLocation", new_dir(spark, "trigger-check")).trigger(processingTime="50 milliseconds").start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.read.parquet(out).agg(F.count("*").alias("n"))


@query("G_10_restart", "select count(*) as n, count(distinct event_id) as ids from events")
def _(spark, d):
    """A stream that is stopped after its first files and goes on from its checkpoint: each row once."""
    e = table(spark, d, "events").select("event_id", "ts")
    path, out, check = (new_dir(spark, t) for t in ("restart", "restart-out", "restart-check"))
    e.where("event_id % 2 = 0").coalesce(1).write.parquet(f"{path}/000000")
    run = lambda: replay.drain(replay.read_replay(spark, path, e.schema).writeStream.format("parquet").option("path", out).option("checkpointLocation", check))
    run()
    e.where("event_id % 2 = 1").coalesce(1).write.parquet(f"{path}/000001")
    run()
    return spark.read.parquet(out).agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("ids"))


@query("G_11_progress_metrics", "select 'rows' as metric, count(*)::double + 1 as value from events union all select 'batches with durations', 4.0::double")
def _(spark, d):
    """COST rows from the progress reports of a stream (three files and the sentinel), summed: rows read, and batches that tell their durations."""
    q = replay.drain(events(spark, d, 3).writeStream.format("noop").option("checkpointLocation", new_dir(spark, "progress")))
    rows = [("rows", float(p.numInputRows)) for p in q.recentProgress] + [("batches with durations", 1.0) for p in q.recentProgress if p.numInputRows and p.durationMs.get("triggerExecution", 0) > 0]
    return spark.createDataFrame(rows, "metric string, value double").groupBy("metric").agg(F.sum("value").alias("value"))


@query("G_12_last_block", f"select count(distinct {_hour()}) as blocks from events")
def _(spark, d):
    """The sentinel closes the last block."""
    s = events(spark, d).withWatermark("ts", "0 seconds").groupBy(F.window("ts", "1 hour")).agg(F.count("event_id").alias("n"))
    return replay.to_table(s, "last").where("n > 0").agg(F.count("*").alias("blocks"))


