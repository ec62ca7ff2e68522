"""The relational operators a user of the detectors needs around them, on the given tables, with SQL."""

from __future__ import annotations


import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from eventpulse.plans.burst_queries import EVT, W4, event_tokens, md5, r9
from eventpulse.plans import sql
from eventpulse.operators import bursts
from eventpulse.plans.scratch import materialize, new_dir
from eventpulse.sources.tables import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return put


def simple(name: str, tables: str, build, oracle: str | None) -> None:
    """A query over a few tables, which ``build`` gets in order."""

    @query(name, oracle)
    def _(spark, d):
        return build(*[table(spark, d, t) for t in tables.split()])


C, S, L = F.col, F.sum, F.lit


def n():
    """The row count of a group."""
    return F.count("*").alias("n")



# --- sources and sinks -------------------------------------------------------------------------
simple("S_1_parquet_scan", "lineitem", lambda l: l.where("l_shipdate >= date'1998-01-01'").select("l_orderkey", "l_quantity"), "select l_orderkey, l_quantity from lineitem where l_shipdate >= date '1998-01-01'")


def _round_trip(fmt: str, **opts: str) -> None:
    @query(f"S_3_round_trip_{fmt}", "select event_type, count(*) as n, sum(event_id)::bigint as ids from events group by 1")
    def _(spark, d):
        path = new_dir(spark, f"round-trip-{fmt}")
        e = table(spark, d, "events").select("event_id", "event_type", "value", "props")
        e.write.mode("overwrite").format(fmt).options(**opts).save(path)
        return spark.read.format(fmt).schema(e.schema).options(**opts).load(path).groupBy("event_type").agg(n(), S("event_id").alias("ids"))


for _fmt in ("json", "csv", "orc", "parquet"):
    _round_trip(_fmt)


@query("S_3_round_trip_text", "select count(*) as n, count(distinct event_type) as types from events")
def _(spark, d):
    path = new_dir(spark, "round-trip-text")
    table(spark, d, "events").select("event_type").write.mode("overwrite").text(path)
    return spark.read.text(path).agg(n(), F.count_distinct("value").alias("types"))


@query("S_6_inline_rows", "select rate, min_count, count(n) as users from (values (1.5::double, 2::bigint), (2.0, 3)) as t(rate, min_count) left join (select user_id, count(*) as n from events group by 1) on n >= min_count group by 1, 2")
def _(spark, d):
    """Inline settings against a table: the users with at least so many events."""
    t = spark.sql("select cast(rate as double) as rate, cast(k as bigint) as min_count from values (1.5, 2), (2.0, 3) as t(rate, k)")
    users = table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("k"))
    return t.join(users, C("n") >= C("min_count"), "left").groupBy("rate", "min_count").agg(F.coalesce(S("k"), L(0)).alias("users"))


@query("K_1_partitioned_sink", "select user_id % 10 as part, count(*) as n from events where user_id % 10 = 3 group by 1")
def _(spark, d):
    path = new_dir(spark, "by-part")
    e = table(spark, d, "events").select("event_id", F.pmod("user_id", L(10)).alias("part"))
    e.write.mode("overwrite").partitionBy("part").parquet(path)
    return spark.read.parquet(path).where("part = 3").groupBy(C("part").cast("long").alias("part")).agg(n())


# --- projection and filter ---------------------------------------------------------------------
simple("F_1_projection", "lineitem", lambda l: l.select("l_orderkey", "l_linenumber", r9(C("l_extendedprice") * (1 - C("l_discount"))).alias("net")), "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 9) + 0.0 as net from lineitem")
simple("F_2_between", "events", lambda e: e.where((C("value").between(20, 40) & (C("event_type") != "click")) | (C("user_id") < 5)).select("event_id"), "select event_id from events where (value between 20 and 40 and event_type <> 'click') or user_id < 5")
simple("F_3_isin", "events", lambda e: e.where(C("event_type").isin("click", "view") & ~F.pmod("user_id", L(10)).isin(1, 2)).select("event_id"), "select event_id from events where event_type in ('click', 'view') and user_id % 10 not in (1, 2)")
simple("F_4_string_predicates", "documents", lambda t: t.select("doc_id", C("text").like("%the%").alias("l"), C("text").rlike("[0-9]{4}").alias("r"), C("text").startswith("Th").alias("s"), C("text").contains("and").alias("c")), "select doc_id, text like '%the%' as l, regexp_matches(text, '[0-9]{4}') as r, starts_with(text, 'Th') as s, contains(text, 'and') as c from documents")
simple("F_5_nulls", "documents labels", lambda t, l: t.join(l, "doc_id", "left").select("doc_id", C("quality").isNull().alias("unknown"), F.coalesce("quality", L(-1)).alias("q"), F.nullif("quality", L(0)).alias("z"), C("quality").eqNullSafe(C("toxic")).alias("same")), "select doc_id, quality is null as unknown, coalesce(quality, -1) as q, nullif(quality, 0) as z, quality is not distinct from toxic as same from documents left join labels using (doc_id)")
simple("F_6_case_when", "events", lambda e: e.groupBy(F.when(C("value") < 25, "low").when(C("value") < 75, "mid").otherwise("high").alias("band")).agg(n()), "select case when value < 25 then 'low' when value < 75 then 'mid' else 'high' end as band, count(*) as n from events group by 1")
simple("F_7_sample", "events", lambda e: e.where("event_id % 10 = 0").agg(n()), "select count(*) as n from events where event_id % 10 = 0")

# --- joins -------------------------------------------------------------------------------------
simple("J_1_hash_join", "events customer", lambda e, c: e.join(c, e.user_id == c.c_custkey).groupBy("c_mktsegment").agg(n()), "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
simple("J_2_broadcast_join", "customer nation region", lambda c, na, r: c.join(F.broadcast(na), c.c_nationkey == na.n_nationkey).join(F.broadcast(r), C("n_regionkey") == r.r_regionkey).groupBy("r_name").agg(n()), "select r_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")
simple("J_3_sort_merge_join", "orders lineitem", lambda o, l: o.select("o_orderkey", "o_orderpriority").join(l.select("l_orderkey", "l_quantity").hint("merge"), C("o_orderkey") == C("l_orderkey")).groupBy("o_orderpriority").agg(r9(S("l_quantity")).alias("q")), "select o_orderpriority, round(sum(l_quantity), 9) + 0.0 as q from orders join lineitem on o_orderkey = l_orderkey group by 1")
simple("J_4_shuffle_hash_join", "lineitem part", lambda l, p: l.select("l_partkey").join(p.select("p_partkey", "p_brand").hint("shuffle_hash"), C("l_partkey") == C("p_partkey")).groupBy("p_brand").agg(n()), "select p_brand, count(*) as n from lineitem join part on l_partkey = p_partkey group by 1")
simple("J_5_left_semi", "customer events", lambda c, e: c.join(e.where("event_type = 'purchase'"), c.c_custkey == e.user_id, "left_semi").select("c_custkey"), "select c_custkey from customer where c_custkey in (select user_id from events where event_type = 'purchase')")
simple("J_6_left_anti", "customer events", lambda c, e: c.join(e.where("event_type = 'purchase'"), c.c_custkey == e.user_id, "left_anti").select("c_custkey"), "select c_custkey from customer where c_custkey not in (select user_id from events where event_type = 'purchase')")
simple("J_7_outer_joins", "nation supplier", lambda na, s: na.join(s, C("n_nationkey") == C("s_nationkey"), "left").groupBy("n_name").agg(F.count("s_suppkey").alias("n")), "select n_name, count(s_suppkey) as n from nation left join supplier on n_nationkey = s_nationkey group by 1")
simple("J_7_right_outer", "supplier nation", lambda s, na: s.join(na, C("n_nationkey") == C("s_nationkey"), "right").groupBy("n_name").agg(F.count("s_suppkey").alias("n")), "select n_name, count(s_suppkey) as n from supplier right join nation on n_nationkey = s_nationkey group by 1")
simple("J_8_full_outer", "events", lambda e: e.where("value < 30").select("event_id", L(1).alias("a")).join(e.where("value > 20").select("event_id", L(1).alias("b")), "event_id", "full").groupBy(C("a").isNull().alias("no_a"), C("b").isNull().alias("no_b")).agg(n()), "select a is null as no_a, b is null as no_b, count(*) as n from (select event_id, 1 as a from events where value < 30) full join (select event_id, 1 as b from events where value > 20) using (event_id) group by 1, 2")


@query("J_9_parameter_grid", f"{EVT}, {sql.scores(W4)} select r::double as rate, count(*) as n from sc join (select unnest([1.0, 1.5, 2.0]) as r) on prev_tfidf > 1e-12 and tfidf / prev_tfidf > r + 1e-9 where cnt >= 2 group by 1")
def _(spark, d):
    """Scores against a grid of three rows: a nested-loop join with a broadcast side of fixed size."""
    ws = bursts.score(event_tokens(spark, d), W4).where("cnt >= 2 and prev_tfidf > 1e-12").select((C("tfidf") / C("prev_tfidf")).alias("growth"))
    grid = spark.sql("select cast(r as double) as rate from values (1.0), (1.5), (2.0) as t(r)")
    return ws.join(F.broadcast(grid), C("growth") > C("rate") + 1e-9).groupBy("rate").agg(n())


@query("J_10_theta_join", f"{EVT}, {sql.COUNTS} select a.block_no, count(*) as n from wc a join wc b on a.block_no = b.block_no and a.cnt > 3 * b.cnt group by 1")
def _(spark, d):
    """Pairs of a block's words whose counts differ threefold, by its distinct counts: words of one count are joined as one row."""
    a = bursts.count_words(event_tokens(spark, d)).groupBy("block_no", C("cnt").alias("ca")).agg(F.count("*").alias("na"))
    b = a.select("block_no", C("ca").alias("cb"), C("na").alias("nb"))
    return a.join(b, "block_no").where("ca > 3 * cb").groupBy("block_no").agg(S(C("na") * C("nb")).alias("n"))


@query("J_11_range_join", "select o_orderkey, sum(c)::bigint as n from orders join (select l_shipdate::date as day, count(*) as c from lineitem group by 1) on day between o_orderdate::date and o_orderdate::date + 10 group by 1")
def _(spark, d):
    """Every order against every line item, which are counted by ship date before the binned join."""
    o = table(spark, d, "orders").select("o_orderkey", F.unix_date(C("o_orderdate").cast("date")).alias("o"))
    s = table(spark, d, "lineitem").groupBy(F.unix_date(C("l_shipdate").cast("date")).alias("s")).agg(F.count("*").alias("c"))
    bin_ = lambda c: F.floor(c / 10)
    o = o.withColumn("bin", F.explode(F.sequence(bin_(C("o")), bin_(C("o") + 10))))
    return o.join(s.withColumn("bin", bin_(C("s"))), "bin").where("s between o and o + 10").groupBy("o_orderkey").agg(S("c").alias("n"))


@query("J_12_as_of", f"{EVT}, {sql.scores(W4)}, p as (select block_no + 1 as at, word, tfidf from sc) select ev.block_no, ev.word, {sql.r9('p.tfidf')} as earlier from sc ev asof left join p on ev.word = p.word and ev.block_no >= p.at")
def _(spark, d):
    """The last earlier score of every score row."""
    w = W.partitionBy("word").orderBy("block_no").rowsBetween(W.unboundedPreceding, -1)
    out = bursts.score(event_tokens(spark, d), W4).withColumn("earlier", F.last("tfidf", ignorenulls=True).over(w))
    return out.select("block_no", "word", r9("earlier").alias("earlier"))


@query("J_13_interval_join", "select a.event_id as a, b.event_id as b from (select * from events where event_type = 'purchase') a join (select * from events where event_type = 'signup') b on a.user_id = b.user_id and epoch_us(b.ts) between epoch_us(a.ts) - 3600000000 and epoch_us(a.ts) + 3600000000")
def _(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros("ts").alias("t"))
    hour = 3_600_000_000
    a = e.where("event_type = 'purchase'").select(C("event_id").alias("a"), "user_id", C("t").alias("ta")).withColumn("bin", F.explode(F.array(*[F.floor(C("ta") / hour) + k for k in (-1, 0, 1)])))
    b = e.where("event_type = 'signup'").select(C("event_id").alias("b"), "user_id", C("t").alias("tb")).withColumn("bin", F.floor(C("tb") / hour))
    return a.join(b, ["user_id", "bin"]).where(f"tb between ta - {hour} and ta + {hour}").select("a", "b")


@query("J_14_self_join", f"{EVT} select a.word as w1, b.word as w2, count(*) as n from (select distinct post_id, unnest(tokens) as word from tok) a join (select distinct post_id, unnest(tokens) as word from tok) b on a.post_id = b.post_id and a.word < b.word group by 1, 2")
def _(spark, d):
    w = event_tokens(spark, d).select("post_id", F.explode(F.array_distinct("tokens")).alias("word"))
    a, b = w.withColumnRenamed("word", "w1"), w.withColumnRenamed("word", "w2")
    return a.join(b, "post_id").where("w1 < w2").groupBy("w1", "w2").agg(n())


@query("J_15_lateral_explode", f"{EVT} select word, count(*) as n from words group by 1")
def _(spark, d):
    t = event_tokens(spark, d).select("post_id", "tokens")
    return t.lateralJoin(spark.tvf.explode(C("tokens").outer()).toDF("word")).groupBy("word").agg(n())


# --- aggregation -------------------------------------------------------------------------------
simple("A_1_hash_aggregate", "events", lambda e: e.groupBy("event_type").agg(n(), r9(S("value")).alias("total"), r9(F.avg("value")).alias("mean")), "select event_type, count(*) as n, round(sum(value), 9) + 0.0 as total, round(avg(value), 9) + 0.0 as mean from events group by 1")
simple("A_2_max_struct", "orders", lambda o: o.groupBy("o_custkey").agg(F.max(F.struct("o_totalprice", "o_orderkey")).alias("m")).select("o_custkey", C("m.o_orderkey").alias("best")), "select o_custkey, o_orderkey as best from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey desc) = 1")
simple("A_3_count_distinct", "events", lambda e: e.agg(F.count_distinct("user_id").alias("users"), F.count_distinct("event_type").alias("types")), "select count(distinct user_id) as users, count(distinct event_type) as types from events")
_near = lambda a, b, by: (F.abs(C(a) - C(b)) <= by * C(b))
simple("A_4_approx_distinct", "events", lambda e: e.groupBy("event_type").agg(F.count_distinct("user_id").alias("x"), F.approx_count_distinct("user_id", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("b")).select("event_type", _near("a", "x", 0.1).alias("counted"), _near("b", "x", 0.1).alias("sketched")), "select distinct event_type, true as counted, true as sketched from events")
simple("A_4_sketch_union", "events", lambda e: e.groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("a")).join(e.agg(F.count_distinct("user_id").alias("x")), L(True)).select(_near("a", "x", 0.1).alias("near")), "select true as near")
simple("A_5_percentile", "events", lambda e: e.groupBy("event_type").agg(r9(F.percentile("value", 0.5)).alias("median"), r9(F.percentile("value", 0.9)).alias("p90")), "select event_type, round(quantile_cont(value, 0.5), 9) + 0.0 as median, round(quantile_cont(value, 0.9), 9) + 0.0 as p90 from events group by 1")


def _median(name: str, sketch) -> None:
    @query(name, "select distinct event_type, true as near from events")
    def _(spark, d):
        """Whether a sketch's median splits the values within a hundredth of the middle."""
        e = table(spark, d, "events").select("event_type", "value")
        m = e.groupBy("event_type").agg(sketch(C("value")).alias("m"))  # a row a type
        below = e.join(m, "event_type").groupBy("event_type").agg(F.avg((C("value") < C("m")).cast("double")).alias("lo"), F.avg((C("value") <= C("m")).cast("double")).alias("hi"))
        return below.select("event_type", ((C("lo") <= 0.51) & (C("hi") >= 0.49)).alias("near"))


_median("A_5_approx_percentile", lambda v: F.approx_percentile(v, 0.5, 10000))
_median("A_5_kll", lambda v: F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double(v), L(0.5)))
_G = "count(*) as n from events join customer on user_id = c_custkey"
_gr = lambda e, c: e.join(c, e.user_id == c.c_custkey)
simple("A_6_rollup", "events customer", lambda e, c: _gr(e, c).rollup("c_mktsegment", "event_type").agg(n()), f"select c_mktsegment, event_type, {_G} group by rollup (c_mktsegment, event_type)")
simple("A_7_cube", "events customer", lambda e, c: _gr(e, c).cube("c_mktsegment", "event_type").agg(n(), F.grouping_id().alias("g")), f"select c_mktsegment, event_type, count(*) as n, grouping(c_mktsegment, event_type) as g from events join customer on user_id = c_custkey group by cube (c_mktsegment, event_type)")
simple("A_8_grouping_sets", "events customer", lambda e, c: _gr(e, c).groupingSets([[C("c_mktsegment")], [C("event_type")]], "c_mktsegment", "event_type").agg(n()), f"select c_mktsegment, event_type, {_G} group by grouping sets ((c_mktsegment), (event_type))")
_TYPES = ["click", "purchase", "signup"]
simple("A_9_pivot", "events customer", lambda e, c: _gr(e, c).groupBy("c_mktsegment").pivot("event_type", _TYPES).count().na.fill(0), "select c_mktsegment, " + ", ".join(f"count(*) filter (where event_type = '{t}') as {t}" for t in _TYPES) + " from events join customer on user_id = c_custkey group by 1")
simple("A_10_unpivot", "events", lambda e: e.agg(F.min("value").alias("lo"), F.max("value").alias("hi")).unpivot([], ["lo", "hi"], "what", "v"), "select 'lo' as what, min(value) as v from events union all select 'hi', max(value) from events")
simple("A_11_collect", "nation", lambda t: t.groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), F.size(F.collect_set("n_name")).cast("long").alias("k")), "select n_regionkey, string_agg(n_name, ',' order by n_name) as names, count(distinct n_name) as k from nation group by 1")
simple("A_12_min_by", "events", lambda e: e.groupBy("event_type").agg(F.min_by("event_id", "event_id").alias("first_id"), F.max_by("user_id", "event_id").alias("last_user")), "select event_type, min(event_id) as first_id, arg_max(user_id, event_id) as last_user from events group by 1")
simple("A_12_mode", "events", lambda e: e.groupBy("event_type", "user_id").agg(n()).groupBy("event_type").agg(F.min(F.struct((-C("n")).alias("neg"), "user_id"))["user_id"].alias("user_id")), "select event_type, user_id from (select event_type, user_id, count(*) as n from events group by 1, 2) qualify row_number() over (partition by event_type order by n desc, user_id) = 1")
simple("A_13_conditional", "events", lambda e: e.groupBy("event_type").agg(F.count_if(C("value") > 50).alias("high"), r9(S(F.when(C("value") <= 50, C("value")))).alias("low_sum")), "select event_type, count(*) filter (where value > 50) as high, round(sum(value) filter (where value <= 50), 9) + 0.0 as low_sum from events group by 1")
simple("A_14_moments", "lineitem", lambda l: l.groupBy("l_returnflag").agg(F.round(F.stddev_pop("l_quantity"), 6).alias("sd"), F.round(F.var_samp("l_quantity"), 6).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c")), "select l_returnflag, round(stddev_pop(l_quantity), 6) as sd, round(var_samp(l_quantity), 6) as v, round(corr(l_quantity, l_extendedprice), 6) as c from lineitem group by 1")
simple("A_15_having", "events", lambda e: e.groupBy("user_id").agg(n()).where("n >= 10"), "select user_id, count(*) as n from events group by 1 having count(*) >= 10")
simple("A_16_count_min_sketch", "events", lambda e: e.agg((F.length(F.count_min_sketch("user_id", L(0.01), L(0.95), L(7))) > 0).alias("stored")), "select true as stored")
simple("A_16_heavy_hitters", "events", lambda e: e.agg(F.expr("approx_top_k(event_type, 3, 1000)").alias("t")).select(F.inline("t")).select(C("item").alias("event_type"), C("count").alias("n")), "select event_type, n from (select event_type, count(*) as n from events group by 1) order by n desc, event_type limit 3")
simple("A_17_bool_bit", "events", lambda e: e.groupBy("event_type").agg(F.bool_and(C("value") >= 0).alias("all_pos"), F.bool_or(C("value") > 99).alias("any_high"), F.bit_or("user_id").alias("bits"), F.bit_xor("event_id").alias("x")), "select event_type, bool_and(value >= 0) as all_pos, bool_or(value > 99) as any_high, bit_or(user_id) as bits, bit_xor(event_id) as x from events group by 1")

# --- windows -----------------------------------------------------------------------------------
_w = lambda: W.partitionBy("event_type").orderBy("event_id")
_u = lambda: W.partitionBy("user_id").orderBy("event_id")
_v = lambda: W.partitionBy("event_type").orderBy(F.floor("value"))
simple("N_1_rank", "events", lambda e: e.select("event_id", F.row_number().over(_w()).cast("long").alias("rn"), F.rank().over(_v()).cast("long").alias("rk"), F.dense_rank().over(_v()).cast("long").alias("dr")), "select event_id, row_number() over (partition by event_type order by event_id) as rn, rank() over (partition by event_type order by floor(value)) as rk, dense_rank() over (partition by event_type order by floor(value)) as dr from events")
simple("N_2_distribution", "events", lambda e: e.select("event_id", F.ntile(4).over(_w()).cast("long").alias("q"), r9(F.percent_rank().over(_v())).alias("p"), r9(F.cume_dist().over(_v())).alias("c")), "select event_id, ntile(4) over (partition by event_type order by event_id) as q, round(percent_rank() over (partition by event_type order by floor(value)), 9) + 0.0 as p, round(cume_dist() over (partition by event_type order by floor(value)), 9) + 0.0 as c from events")
simple("N_3_lag_lead", "events", lambda e: e.select("event_id", F.lag("event_id").over(_u()).alias("prev"), F.lead("event_id", 2).over(_u()).alias("after2")), "select event_id, lag(event_id) over w as prev, lead(event_id, 2) over w as after2 from events window w as (partition by user_id order by event_id)")
simple("N_4_first_last", "events", lambda e: e.select("event_id", F.first("event_type").over(_u()).alias("f"), F.last(F.when(C("value") > 50, C("event_id")), ignorenulls=True).over(_u()).alias("last_high"), F.nth_value("event_id", 2).over(_u()).alias("second")), "select event_id, first_value(event_type) over w as f, last_value(case when value > 50 then event_id end ignore nulls) over w as last_high, nth_value(event_id, 2) over w as second from events window w as (partition by user_id order by event_id)")
simple("N_5_running_count", "events", lambda e: e.select("event_id", F.count("*").over(_w().rowsBetween(W.unboundedPreceding, 0)).alias("n")), "select event_id, count(*) over (partition by event_type order by event_id rows unbounded preceding) as n from events")
simple("N_6_range_frame", "orders", lambda o: o.withColumn("day", F.unix_date(C("o_orderdate").cast("date"))).select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("day").rangeBetween(-9, 0)).alias("n")), "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate::date range between interval 9 days preceding and current row) as n from orders")
simple("N_7_share", "events", lambda e: e.groupBy("event_type", "user_id").agg(n()).select("event_type", "user_id", r9(C("n") / S("n").over(W.partitionBy("event_type"))).alias("share")), "select event_type, user_id, round(count(*) / sum(count(*)) over (partition by event_type)::double, 9) + 0.0 as share from events group by 1, 2")


@query("N_8_islands", f"{EVT}, b as (select distinct word, block_no from words), g as (select *, block_no - row_number() over (partition by word order by block_no) as grp from b) select word, min(block_no) as first_block, count(*) as blocks from g group by word, grp having count(*) >= 3")
def _(spark, d):
    b = bursts.explode_words(event_tokens(spark, d)).select("word", "block_no").distinct()
    g = b.withColumn("grp", C("block_no") - F.row_number().over(W.partitionBy("word").orderBy("block_no")))
    return g.groupBy("word", "grp").agg(F.min("block_no").alias("first_block"), F.count("*").alias("blocks")).where("blocks >= 3").drop("grp")


# --- sort, limit, sets -------------------------------------------------------------------------
simple("T_1_total_order", "events", lambda e: e.orderBy("ts", "event_id").select("event_id", "user_id"), "select event_id, user_id from events order by ts, event_id")
simple("T_2_top_k", "orders", lambda o: o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey"), "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 10")
simple("T_3_top_k_per_group", "orders", lambda o: o.withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 2").select("o_custkey", "o_orderkey"), "select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 2")
simple("T_4_limit_offset", "customer", lambda c: c.orderBy("c_custkey").offset(20).limit(10).select("c_custkey"), "select c_custkey from customer order by c_custkey limit 10 offset 20")


@query("T_5_null_order", "select doc_id, quality, row_number() over (order by quality asc nulls last, doc_id) as place from documents left join labels using (doc_id)")
def _(spark, d):
    """Every row with its place under the order: places within sorted partitions, then an offset for each partition."""
    t = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    t = materialize(t.orderBy(C("quality").asc_nulls_last(), "doc_id").withColumn("at", F.monotonically_increasing_id()), "null-order")
    part, row = F.shiftright("at", 33), C("at").bitwiseAND(L((1 << 33) - 1))
    size = t.groupBy(part.alias("part")).agg(n())
    before = size.select("part", (F.coalesce(S("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), L(0)) + 1).alias("first"))
    return t.withColumn("part", part).join(F.broadcast(before), "part").select("doc_id", "quality", (C("first") + row).alias("place"))




@query("T_6_range_partition", "select 4::bigint as parts, true as apart, count(*) as n from events")
def _(spark, d):
    """Ranges of ids: how many, whether each ends before the next begins, and the rows in them."""
    p = F.spark_partition_id().alias("p")
    each = table(spark, d, "events").repartitionByRange(4, "event_id").groupBy(p).agg(F.min("event_id").alias("lo"), F.max("event_id").alias("hi"), n())
    before = F.lag("hi").over(W.orderBy("p"))  # a row a range
    each = each.withColumn("apart", F.coalesce(before < C("lo"), L(True)))
    return each.agg(F.count("*").alias("parts"), F.bool_and("apart").alias("apart"), S("n").alias("n"))


_a, _b = "select user_id from events where event_type = 'click'", "select user_id from events where event_type = 'purchase'"
_sets = lambda f: lambda e: f(e.where("event_type = 'click'").select("user_id"), e.where("event_type = 'purchase'").select("user_id"))
simple("E_1_union_all", "events", _sets(lambda a, b: a.unionByName(b).groupBy("user_id").agg(n())), f"select user_id, count(*) as n from ({_a} union all {_b}) group by 1")
simple("E_2_union_distinct", "events", _sets(lambda a, b: a.union(b).distinct()), f"{_a} union {_b}")
simple("E_3_intersect", "events", _sets(lambda a, b: a.intersect(b)), f"{_a} intersect {_b}")
simple("E_3_intersect_all", "events", _sets(lambda a, b: a.intersectAll(b)), f"{_a} intersect all {_b}")
simple("E_4_except", "events", _sets(lambda a, b: a.subtract(b)), f"{_a} except {_b}")
simple("E_4_except_all", "events", _sets(lambda a, b: a.exceptAll(b)), f"{_a} except all {_b}")
simple("E_5_drop_duplicates", "documents", lambda t: t.groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id"), "select min(doc_id) as doc_id from documents group by text")

# --- scalar functions --------------------------------------------------------------------------
simple("X_1_strings", "part", lambda p: p.select("p_partkey", F.initcap("p_name").alias("ic"), F.lpad(C("p_partkey").cast("string"), 6, "0").alias("pad"), F.translate("p_brand", "#", "-").alias("tr"), F.instr("p_name", "a").cast("long").alias("pos"), F.reverse("p_name").alias("rev"), F.regexp_count("p_name", L("[aeiou]")).cast("long").alias("vow"), F.levenshtein("p_name", "p_type").cast("long").alias("lev"), F.substring("p_name", 2, 3).alias("sub"), F.concat_ws("-", F.upper("p_name"), F.lower("p_type")).alias("cat")), "select p_partkey, array_to_string(list_transform(string_split(p_name, ' '), lambda x: upper(x[1]) || lower(x[2:])), ' ') as ic, lpad(p_partkey::varchar, 6, '0') as pad, translate(p_brand, '#', '-') as tr, instr(p_name, 'a') as pos, reverse(p_name) as rev, len(regexp_extract_all(p_name, '[aeiou]')) as vow, levenshtein(p_name, p_type) as lev, substring(p_name, 2, 3) as sub, upper(p_name) || '-' || lower(p_type) as cat from part")
simple("X_2_ngrams", "events", lambda e: e.select("event_id", F.array_join(F.transform(F.sequence(L(1), F.length("event_type") - 2), lambda i: C("event_type").substr(i, L(3))), "|").alias("g")), "select event_id, array_to_string(list_transform(range(1, length(event_type) - 1), lambda i: substring(event_type, i, 3)), '|') as g from events")
simple("X_3_datetime", "events", lambda e: e.select("event_id", F.unix_micros(F.date_trunc("hour", "ts")).alias("h"), F.dayofweek("ts").cast("long").alias("dow"), F.extract(L("minute"), C("ts")).cast("long").alias("m"), F.datediff(C("ts").cast("date"), L("2024-01-01").cast("date")).cast("long").alias("days"), F.unix_micros(C("ts") + F.expr("interval 6 minutes")).alias("later"), F.date_format("ts", "yyyy-MM-dd HH").alias("fmt")), "select event_id, epoch_us(date_trunc('hour', ts)) as h, dayofweek(ts) + 1 as dow, extract(minute from ts) as m, date_diff('day', date '2024-01-01', ts::date) as days, epoch_us(ts + interval 6 minutes) as later, strftime(ts, '%Y-%m-%d %H') as fmt from events")
simple("X_4_math", "customer", lambda c: c.select("c_custkey", r9(F.log(C("c_custkey") + 1)).alias("ln"), r9(F.sqrt("c_custkey")).alias("sq"), r9(F.pow(C("c_custkey"), L(1.5))).alias("pw"), r9(F.exp(-C("c_custkey") / 100)).alias("ex"), F.pmod(-C("c_custkey"), L(7)).cast("long").alias("md"), F.signum(C("c_custkey") - 5).alias("sg"), F.greatest("c_custkey", L(10)).cast("long").alias("gr"), r9(F.try_divide(L(1.0), C("c_custkey"))).alias("td")), "select c_custkey, round(ln(c_custkey + 1), 9) + 0.0 as ln, round(sqrt(c_custkey), 9) + 0.0 as sq, round(pow(c_custkey, 1.5), 9) + 0.0 as pw, round(exp(-c_custkey / 100), 9) + 0.0 as ex, ((-c_custkey % 7) + 7) % 7 as md, sign(c_custkey - 5)::double as sg, greatest(c_custkey, 10)::bigint as gr, case when c_custkey <> 0 then round(1.0::double / c_custkey, 9) + 0.0 end as td from customer")
simple("X_4_decimal", "lineitem", lambda l: l.groupBy("l_returnflag").agg(S(C("l_extendedprice").cast("decimal(18,6)")).cast("double").alias("s")), "select l_returnflag, sum(l_extendedprice::decimal(18,6))::double as s from lineitem group by 1")
simple("X_5_arrays", "embeddings", lambda e: e.select("vec_id", r9(F.aggregate(C("embedding").cast("array<double>"), L(0.0), lambda s, x: s + x * x)).alias("sq"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"), C("embedding")[0].cast("double").alias("a0"), F.array_position(F.transform("embedding", lambda x: x > 0), True).alias("fp"), F.size(F.slice("embedding", 3, 5)).cast("long").alias("sl")), "select vec_id, round(list_sum(list_transform(embedding::double[], lambda x: x * x)), 9) + 0.0 as sq, len(list_filter(embedding, lambda x: x > 0)) as pos, embedding[1]::double as a0, coalesce(list_position(list_transform(embedding, lambda x: x > 0), true), 0)::bigint as fp, len(embedding[3:7]) as sl from embeddings")
simple("X_5_array_sets", "events", lambda e: e.groupBy("user_id").agg(F.collect_set("event_type").alias("t")).select("user_id", F.array_join(F.array_sort(F.array_intersect("t", F.array(L("click"), L("purchase")))), ",").alias("i"), F.size(F.array_except("t", F.array(L("click")))).cast("long").alias("x"), F.arrays_overlap("t", F.array(L("signup"))).alias("o")), "select user_id, array_to_string(list_sort(list_intersect(list(distinct event_type), ['click', 'purchase'])), ',') as i, len(list_filter(list(distinct event_type), lambda x: x <> 'click')) as x, list_has_any(list(distinct event_type), ['signup']) as o from events group by 1")
simple("X_6_maps", "events", lambda e: e.groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_id", "value")))).alias("m")).select("user_id", F.size(F.map_filter("m", lambda k, v: v > 50)).cast("long").alias("high"), r9(F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), L(0.0), lambda s, x: s + x)).alias("twice"), F.array_min(F.map_keys("m")).alias("k0")), "select user_id, count(*) filter (where value > 50) as high, round(sum(value * 2), 9) + 0.0 as twice, min(event_id) as k0 from events group by 1")
simple("X_7_structs", "nation", lambda t: t.select(F.struct("n_nationkey", F.struct("n_name").alias("x")).alias("s")).withColumn("s", C("s").withField("x.up", F.upper("s.x.n_name"))).select("s.n_nationkey", C("s.x.up").alias("up")), "select n_nationkey, upper(n_name) as up from nation")
simple("X_8_json", "events", lambda e: e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"), F.to_json(F.struct("user_id")).alias("j")), "select event_id, regexp_extract(props, '([0-9]+)', 1)::bigint as k, regexp_extract(props, '([0-9]+)', 1)::bigint as k2, '{\"user_id\":' || user_id || '}' as j from events")
simple("X_9_html", "pages", lambda p: p.select("page_id", F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1).alias("title"), F.size(F.regexp_extract_all("html", L(r"(?i)href="), 0)).cast("long").alias("links"), md5(F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " "), r"(?s)<[^>]+>", " ")).alias("body")), "select page_id, regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1) as title, len(regexp_extract_all(html, '(?i)href=')) as links, md5(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]+>', ' ', 'g')) as body from pages")
simple("X_10_url_parts", "pages", lambda p: p.select("page_id", F.parse_url("url", L("HOST")).alias("host"), F.parse_url("url", L("PATH")).alias("path"), F.parse_url("url", L("QUERY")).alias("q")), r"select page_id, regexp_extract(url, '://([^/?#]*)', 1) as host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) as path, nullif(regexp_extract(url, '\?([^#]*)', 1), '') as q from pages")
simple("X_11_hashes", "documents", lambda t: t.select("doc_id", F.sha2(F.lower("text"), 256).alias("s"), md5(C("text")).alias("m")), "select doc_id, sha256(lower(text)) as s, md5(text) as m from documents")
simple("X_11_repeats", "documents", lambda t: t.groupBy(F.sha2("text", 256)).agg(n(), F.min("doc_id").alias("first_id")).where("n > 1").select("first_id", "n"), "select min(doc_id) as first_id, count(*) as n from documents group by text having count(*) > 1")
# --- user functions ----------------------------------------------------------------------------


@query("U_1_scalar_pandas", "select event_type, count(*) as n from events group by 1")
def _(spark, d):
    def same(s: pd.Series) -> pd.Series:
        return s.str.strip()

    return table(spark, d, "events").select(F.pandas_udf(same, "string")("event_type").alias("event_type")).groupBy("event_type").agg(n())


@query("U_2_grouped_pandas", "select event_type, round(max(value) - min(value), 9) + 0.0 as spread from events group by 1")
def _(spark, d):
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return table(spark, d, "events").groupBy("event_type").agg(r9(F.pandas_udf(spread, "double")("value")).alias("spread"))


@query("U_3_apply_in_pandas", "select event_type, count(*) as n from events where value > 50 group by 1")
def _(spark, d):
    def run(pdf):
        return pdf[pdf["value"] > 50].groupby("event_type", as_index=False).agg(n=("value", "size"))

    return table(spark, d, "events").select("event_type", "value").groupBy("event_type").applyInPandas(run, "event_type string, n long")


@query("U_4_table_function", "select event_id, w as token, p as position from (select event_id, unnest(string_split(event_type, '_')) as w, unnest(range(len(string_split(event_type, '_')))) as p from events)")
def _(spark, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="token string, position long")
    class Tokens:
        def eval(self, text: str):
            for i, t in enumerate(text.split("_")):
                yield t, i

    spark.udtf.register("ep_tokens", Tokens)
    table(spark, d, "events").select("event_id", "event_type").createOrReplaceTempView("ep_events")
    return spark.sql("select event_id, token, position from ep_events, lateral ep_tokens(event_type)")


@query("U_5_map_in_arrow", "select count(*) as n from events where value > 50")
def _(spark, d):
    def run(batches):
        import pyarrow.compute as pc

        for b in batches:
            yield b.filter(pc.greater(b.column("value"), 50))

    return table(spark, d, "events").select("value").mapInArrow(run, "value double").agg(n())


@query("U_6_sql_functions", f"select doc_id, len({sql.tokens('text')})::bigint as n, md5({sql.squeezed('text')}) as digest from documents")
def _(spark, d):
    """The cleaning rules as functions for SQL users."""
    spark.sql(r"create or replace temporary function ep_tokenize(t string) returns array<string> return filter(split(lower(coalesce(t, '')), r'[^\p{L}\p{N}]+'), x -> x <> '')")
    spark.sql(r"create or replace temporary function ep_squeeze(t string) returns string return regexp_replace(t, r'(\p{L})\1{2,}', '$1')")
    table(spark, d, "documents").createOrReplaceTempView("ep_documents")
    return spark.sql("select doc_id, cast(size(ep_tokenize(text)) as bigint) as n, md5(cast(ep_squeeze(lower(text)) as binary)) as digest from ep_documents")


@query("U_7_cogrouped", "select c_mktsegment, count(*) as n, (select count(*) from events join customer c2 on user_id = c_custkey where c2.c_mktsegment = customer.c_mktsegment) as events from customer group by 1")
def _(spark, d):
    c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    e = table(spark, d, "events").join(c, C("user_id") == C("c_custkey")).select(C("c_mktsegment").alias("segment"), "event_id")

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_mktsegment": a["c_mktsegment"].iloc[:1], "n": [len(a)], "events": [len(b)]})

    return c.groupBy("c_mktsegment").cogroup(e.groupBy("segment")).applyInPandas(run, "c_mktsegment string, n long, events long")
