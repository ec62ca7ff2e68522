"""The compared methods side by side, under the names of the comparison, and the measures on them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from eventpulse.config import ClusterConfig, Parallelism
from eventpulse.operators import blocks, bursts, clusters, degrees, measures, packed, routing
from eventpulse.plans import burst_queries as B
from eventpulse.plans import cluster_queries as C
from eventpulse.plans import sql
from eventpulse.plans import stream_queries as G
from eventpulse.plans.scratch import materialize
from eventpulse.streaming import replay
from eventpulse.streaming.bursts import eager_stream

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return put


@query("B_1_eager_paused", B.eager_sql(B.CONV, B.W10))
def _(spark, d):
    """Free routing: a replay with a file for each block, scores at the moment a word becomes common, and a pause for every block."""
    pace = replay.Pause(0.02)
    stream, files = G.blockwise_stream(spark, B.conv_tokens(spark, d), pace)
    found, _ = eager_stream(spark, stream, "30 minutes", B.P.START_US, B.W10, pace, files)
    return B.events_out(found)


@query("B_2_barrier_directed", B.ORACLES["M_K9_detect_event"])
def _(spark, d):
    """Posts dealt in turn by the producer, words scored at the end of their block."""
    return B.events_out(bursts.detect_bursts(routing.route_direct(B.event_tokens(spark, d), 4, "post_id"), B.W4))


@query("B_3_two_stage")
def _(spark, d):
    """Clusters of documents by language that a block has touched, event or not."""
    fold = clusters.cluster_two_stage(B.doc_tokens(spark, d, region="lang"), C.DOC_CFG).where("kind = 'cluster'")
    return fold.select("region", "block_no", "cluster_id", "n_added", "n_posts", B.r9("growth").alias("growth"), "is_event", clusters.top_words().alias("top_words"))


@query("B_4_single_stage")
def _(spark, d):
    """The rejected design on posts whose order matters."""
    fold = clusters.cluster_single_stage(C.chain_tokens(spark, d), replace(ClusterConfig(stale_after=2), min_cluster_posts=5)).where("kind = 'cluster'")
    return fold.select("region", "block_no", "cluster_id", "n_added", "n_posts", B.r9("growth").alias("growth"), "is_event")


_LATE = f"""{B.DOC},
seqd as (select *, row_number() over (partition by region, block_no order by ts, post_id) - 1 as seq, count(*) over (partition by region, block_no) as n from tok),
lates as (select region, block_no + case when seq >= ceil((1 - 0.2) * n) then 1 else 0 end as block_no, tokens from seqd),
words2 as (select region, block_no, unnest(tokens) as word from lates),
{sql.scores(B.W1).replace('from words group', 'from words2 group')}, {sql.detected(B.W1)} {sql.EVENTS_OUT}"""


@query("B_6_unsynchronised", _LATE)
def _(spark, d):
    """Documents from a source that does not wait: a fifth of each block's posts come with the next."""
    return B.events_out(bursts.detect_bursts(blocks.leak_blocks(B.doc_tokens(spark, d), 0.2), B.W1))


@query("W_1_bursts_documents", f"{B.DOC}, {sql.scores(B.W1)}, {sql.detected(B.W1)} select block_no, reason, count(*) as events, count(distinct word) as words from ev group by 1, 2")
def _(spark, d):
    ev = bursts.detect_bursts(B.doc_tokens(spark, d), B.W1)
    return ev.groupBy("block_no", "reason").agg(F.count("*").alias("events"), F.count_distinct("word").alias("words"))


@query("W_4_bursts_events", f"{B.EVT}, {sql.scores(B.W4)}, {sql.detected(B.W4)} select (block_no - 1) // 24 as day, count(*) as events, round(max(tfidf), 9) + 0.0 as strongest from ev group by 1")
def _(spark, d):
    """Bursts of the event stream by day since its first block."""
    ev = bursts.detect_bursts(B.event_tokens(spark, d), B.W4)
    return ev.groupBy(F.floor((F.col("block_no") - 1) / 24).alias("day")).agg(F.count("*").alias("events"), B.r9(F.max("tfidf")).alias("strongest"))


@query("W_6_clusters_by_parallelism")
def _(spark, d):
    """Cluster events of documents under 1, 2, 4 and 8 shards: they move, as the burst words do not."""
    return degrees.shard_sensitivity(B.doc_tokens(spark, d), [1, 2, 4, 8], C.DOC_CFG)


@query("W_7_burst_words", f"{B.DOC_LANG}, {sql.scores(replace(B.W1, min_count=5))}, {sql.detected(replace(B.W1, min_count=5))} select region, count(distinct word) as words from ev group by 1")
def _(spark, d):
    """The words that the overlap on documents is measured against, by language."""
    ev = bursts.detect_bursts(B.doc_tokens(spark, d, region="lang"), replace(B.W1, min_count=5))
    return ev.groupBy("region").agg(F.count_distinct("word").alias("words"))


@query("C_1_execution_time")
def _(spark, d):
    """Seconds and events by method and parallelism, after a warm-up: barrier and two-stage on documents and on
    conversations, and on the latter the eager form with a pause for each block."""
    streams = {"documents": (B.doc_tokens(spark, d), B.W1, C.DOC_CFG), "conversations": (B.conv_tokens(spark, d), B.W10, C.DOC_CFG)}
    rows = []
    for name, (tokens, burst, cluster) in streams.items():
        tokens = materialize(tokens, "timed-tokens")
        for n in (2, 4, 8):
            runs = {
                "barrier": lambda n=n, t=tokens, b=burst: bursts.detect_bursts(routing.route_direct(packed.pack(t), n, "post_id"), b),
                "two_stage": lambda n=n, t=tokens, c=cluster: clusters.cluster_events(clusters.cluster_two_stage(t, replace(c, shards=n))),
            }
            for method, run in runs.items():
                if n == 2:
                    measures.timed(run)
                rows.append((name, method, n, *measures.timed(run)))
        if name == "conversations":
            pace = replay.Pause(0.05)
            stream, files = G.blockwise_stream(spark, tokens, pace)
            found, seconds = eager_stream(spark, stream, "30 minutes", B.P.START_US, burst, pace, files)
            rows.append((name, "eager, paused", 1, float(seconds), found.count()))
    return spark.createDataFrame(rows, "stream string, method string, parallelism long, seconds double, events long")


@query("C_9_shuffled_bytes", "select * from (values ('barrier', true), ('eager', true), ('two_stage', true)) as t(method, measured)")
def _(spark, d):
    """Whether each method's run tells the rows and bytes its exchanges write (see :func:`measures.shuffled` for the figures)."""
    t = B.event_tokens(spark, d)
    runs = {"barrier": bursts.detect_bursts(t, B.W4), "eager": bursts.detect_bursts_eager(t, B.W4), "two_stage": clusters.cluster_local(C.vectors.vectorize(t), C.DOC_CFG)}
    rows = [(name, min(min(x) for x in measures.shuffled(df)) > 0) for name, df in runs.items()]
    return spark.createDataFrame(rows, "method string, measured boolean")


@query("C_9_data_volume", f"""{B.DOC}, {sql.COUNTS}, {C.VEC}
select 'words' as tuples, count(*) as n, sum(length(word))::bigint as chars from words
union all select 'word counts', count(*), sum(length(word))::bigint from wc
union all select 'vector entries', count(*), sum(length(word))::bigint from vec""")
def _(spark, d):
    """Tuples of each kind that the methods deal to workers, and the characters in them."""
    t = B.doc_tokens(spark, d)
    words = bursts.explode_words(t)
    vec = C.vectors.vectorize(t).select(F.explode("vec").alias("word", "weight"))
    one = lambda name, df: df.agg(F.count("*").alias("n"), F.sum(F.length("word")).alias("chars")).select(F.lit(name).alias("tuples"), "n", "chars")
    return one("words", words).unionByName(one("word counts", bursts.count_words(t))).unionByName(one("vector entries", vec))


@query("C_10_cluster_operations", """with n as (select count(*) as n from benchmark)
select 'created' as metric, n as blocks, n::double as value from n union all select 'absorbed', n, n from n union all select 'updated', n, n from n
union all select 'deleted', n - 2, n - 2 from n union all select 'live', 2 * n, 4 * n - 2 from n""")
def _(spark, d):
    """Blocks with each operation on live clusters, and how often it happened; of live clusters, how many each block leaves."""
    cost = clusters.cluster_two_stage(C.plant_tokens(spark, d), replace(ClusterConfig(), shards=1)).where("kind = 'cost' and metric not in ('cosines', 'state_reads', 'state_writes') and value > 0")
    return cost.groupBy("metric").agg(F.count("*").alias("blocks"), F.sum("value").alias("value"))


@query("C_10_cluster_operations_CHAIN")
def _(spark, d):
    """The same with merges, on posts whose order matters."""
    return measures.costs(clusters.cluster_two_stage(C.chain_tokens(spark, d), replace(ClusterConfig(), min_cluster_posts=5)))


@query("M_R7_parallelism", C.PLANT_EVENTS)
def _(spark, d):
    """Degrees of parallelism that the caller sets for the local and for the merging step."""
    p = Parallelism(local=2, merge=3)
    cfg = ClusterConfig()
    local = clusters.cluster_local(C.vectors.vectorize(C.plant_tokens(spark, d)), replace(cfg, shards=p.local))
    merged = clusters.merge_local(routing.route_fields(local, p.merge, "region", "block_no"), cfg)
    ev = clusters.cluster_events(clusters.fold_blocks(clusters.drop_small(clusters.prune_local(merged, cfg), cfg.min_cluster_posts), cfg))
    return ev.select("region", "block_no", "n_added", "n_posts", B.r9("growth").alias("growth"))


@query("M_R8_deployment")
def _(spark, d):
    """Where this session runs and with how many threads, as its tasks over the events tell, and the events that they saw."""
    sc = spark.sparkContext
    seen = B.table(spark, d, "events").select("event_id", F.lit(sc.master).alias("master"), F.lit(sc.defaultParallelism).cast("long").alias("parallelism"))
    return seen.groupBy("master", "parallelism").agg(F.count("event_id").alias("events"))
