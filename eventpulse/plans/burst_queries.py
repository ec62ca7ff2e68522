"""Queries of ingest, cleaning and the word-burst detector, with their SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from eventpulse.config import BurstConfig, PrepConfig
from eventpulse.functions import clean, stem
from eventpulse.operators import blocks, bursts, packed, routing
from eventpulse.plans import sql
from eventpulse.plans.scratch import materialize, new_dir
from eventpulse.sources import posts as P
from eventpulse.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: The flagship run: sentences of documents in six-minute blocks.
W1 = BurstConfig(rate=2.0, min_count=10)
W4 = BurstConfig(rate=1.5, min_count=2)
W9 = BurstConfig(rate=1.5, min_count=3)
W10 = BurstConfig(rate=2.0, min_count=5)
PLANT = BurstConfig(rate=1.5, min_count=10)
RAW = PrepConfig(False, False, False, False)


def query(name: str, oracle: str | None = None):
    """Register a query and its SQL."""

    def put(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return put


def r9(c: str | Column) -> Column:
    """Nine digits, and no negative zero."""
    return F.round(c, 9) + F.lit(0.0)


def md5(c: Column) -> Column:
    return F.md5(c.cast("binary"))


def docs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents")


def doc_tokens(spark: SparkSession, d: str, prep: PrepConfig = PrepConfig(), region: str | None = None) -> DataFrame:
    return blocks.tokened(P.posts_from_documents(docs(spark, d), region=region), "6 minutes", prep, P.START_US)


def event_tokens(spark: SparkSession, d: str, length: str = "1 hour", located: bool = False) -> DataFrame:
    dims = [table(spark, d, n) for n in ("customer", "nation", "region")] if located else []
    events = table(spark, d, "events")
    return blocks.tokened(P.posts_from_events(events, *dims), length, RAW, blocks.first_time(events))


def order_tokens(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders")
    return blocks.tokened(P.posts_from_order_lines(orders, table(spark, d, "lineitem"), table(spark, d, "part")), "30 days", RAW, blocks.first_time(orders, "o_orderdate"))


def conv_tokens(spark: SparkSession, d: str) -> DataFrame:
    return blocks.tokened(P.posts_from_conversations(table(spark, d, "conversations")), "30 minutes", RAW, P.START_US)


def plant_tokens(spark: SparkSession, d: str) -> DataFrame:
    return blocks.tokened(P.planted_burst_posts(table(spark, d, "benchmark")), "6 minutes", RAW, P.START_US)


def events_out(ev: DataFrame) -> DataFrame:
    return ev.select("region", "block_no", "word", "cnt", r9("tfidf").alias("tfidf"), r9("prev_tfidf").alias("prev_tfidf"), r9("rate").alias("rate"), "reason")


DOC = f"with {sql.doc_posts()},\n{sql.tokened(sql.MINUTES6)}"
DOC_LANG = f"with {sql.doc_posts('lang')},\n{sql.tokened(sql.MINUTES6)}"
EVT = f"with {sql.event_posts()},\n{sql.tokened(sql.HOUR, RAW)}"
EVT_PLACE = f"with {sql.located_event_posts()},\n{sql.tokened(sql.HOUR, RAW)}"
ORD = f"with {sql.ORDER_POSTS},\n{sql.tokened(sql.DAYS30, RAW)}"
CONV = f"with {sql.CONV_POSTS},\n{sql.tokened(sql.HALF_HOUR, RAW)}"
PLANTED = f"with {sql.PLANT_WORDS}"


def bursts_sql(base: str, cfg: BurstConfig) -> str:
    return f"{base},\n{sql.scores(cfg)},\n{sql.detected(cfg)}\n{sql.EVENTS_OUT}"


# --- ingest and cleaning -----------------------------------------------------------------------

BOXES = [(-130.0, 20.0, -60.0, 70.0), (5.0, 40.0, 20.0, 60.0)]
_LON, _LAT = "cast((c_custkey % 360) - 180 as double)", "cast(((c_nationkey * 7) % 180) - 90 as double)"


@query("M_P1_bbox_filter", f"select c_custkey, {_LON} as lon, {_LAT} as lat from customer where " + " or ".join(f"({_LON} between {w} and {e} and {_LAT} between {s} and {n})" for w, s, e, n in BOXES))
def _(spark, d):
    c = table(spark, d, "customer").select("c_custkey", F.expr(_LON).alias("lon"), F.expr(_LAT).alias("lat"))
    return P.bbox_filter(c, BOXES)


@query("M_P2_with_region", "select r_name, n_name, count(*) as posts from events join customer on user_id = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def _(spark, d):
    dims = [table(spark, d, n) for n in ("customer", "nation", "region")]
    return P.with_region(table(spark, d, "events"), *dims).groupBy("r_name", "n_name").agg(F.count("*").alias("posts"))


@query("M_P3_assign_block", f"with {sql.event_posts()}, {sql.blocked(sql.HOUR)} select post_id, block_no, ts // {sql.HOUR} * {sql.HOUR} as block_start_us from blocked")
def _(spark, d):
    b = blocks.assign_block(P.posts_from_events(table(spark, d, "events")), "1 hour")
    return b.select("post_id", "block_no", F.unix_micros("block_start").alias("block_start_us"))


@query("M_P4_block_calendar", f"""{CONV},
held as (select region, block_no, count(*) as posts, sum(len(tokens)) as terms from tok group by 1, 2),
span as (select region, unnest(generate_series(min(block_no), max(block_no))) as block_no from held group by region)
select region, block_no, coalesce(posts, 0)::bigint as posts, coalesce(terms, 0)::bigint as terms from span left join held using (region, block_no)""")
def _(spark, d):
    return blocks.block_calendar(conv_tokens(spark, d))


def _token_digest(name: str, tokens: Callable[[], Column], expr: str) -> None:
    @query(name, f"select doc_id, len(t)::bigint as n_tokens, md5(array_to_string(t, ' ')) as digest from (select doc_id, {expr} as t from documents)")
    def _(spark, d):
        t = docs(spark, d).select("doc_id", tokens().alias("t"))
        return t.select("doc_id", F.size("t").cast("long").alias("n_tokens"), md5(F.array_join("t", " ")).alias("digest"))


_token_digest("M_P5_tokenize", lambda: clean.tokenize(F.col("text")), sql.tokens("text"))
_token_digest("M_P6_drop_stopwords", lambda: clean.drop_stopwords(clean.tokenize(F.col("text"))), sql.without_stopwords(sql.tokens("text")))
_token_digest("M_P11_preprocess", lambda: clean.clean_tokens(F.col("text"), PrepConfig(stem="light")), sql.cleaned("text", PrepConfig(stem="light")))


@query("M_P7_stem_light", f"select word, {sql.light('word')} as stem from (select distinct unnest({sql.tokens('text')}) as word from documents)")
def _(spark, d):
    w = docs(spark, d).select(F.explode(clean.tokenize(F.col("text"))).alias("word")).distinct()
    return w.select("word", clean.stem_light(F.col("word")).alias("stem"))


@query("M_P7_stem_porter")
def _(spark, d):
    return stem.stem_dictionary(docs(spark, d).select(F.explode(clean.tokenize(F.col("text"))).alias("word")))


@query("M_P7_stem_none", f"select count(distinct word) as words from (select unnest({sql.tokens('text')}) as word from documents)")
def _(spark, d):
    return clean.preprocess(docs(spark, d), replace(RAW, stem="none")).select(F.explode("tokens").alias("word")).agg(F.count_distinct("word").alias("words"))


_AUG_VOWELS = "regexp_replace(regexp_extract(text, '^(\\S+)', 1), '([^aeiou])([aeiou])([^aeiou])', '\\1\\2\\2\\2\\2\\2\\3', 'g')"
_AUG = f"""with aug as (select doc_id, text as original, case doc_id % 10 when 0 then 'I am at the harbour. ' || text when 1 then url || ' ' || text
  when 2 then {_AUG_VOWELS} || substring(text, length(regexp_extract(text, '^(\\S+)', 1)) + 1) else text end as text
  from documents left join pages on page_id = doc_id % (select count(*) from pages))"""


def _aug(spark, d, undoable: bool = False):
    return P.augmented_texts(docs(spark, d), table(spark, d, "pages"), undoable)


@query("M_P8_drop_checkins", f"{_AUG} select doc_id, md5({sql.checkins('text')}) as digest from aug")
def _(spark, d):
    return _aug(spark, d).select("doc_id", md5(clean.drop_checkins(F.col("text"))).alias("digest"))


@query("M_P9_strip_urls", f"{_AUG} select doc_id, md5({sql.urls('text')}) as digest from aug")
def _(spark, d):
    return _aug(spark, d).select("doc_id", md5(clean.strip_urls(F.col("text"))).alias("digest"))


@query("M_P10_squeeze_runs", f"{_AUG} select doc_id, md5({sql.squeezed('text')}) as digest from aug")
def _(spark, d):
    return _aug(spark, d).select("doc_id", md5(clean.squeeze_runs(F.lower("text"))).alias("digest"))


@query("W_AUG_round_trip", "select count(*) as documents, count(*) as restored from documents")
def _(spark, d):
    """Cleaning undoes the augmentation: tokens as those of the original text, its runs squeezed."""
    same = clean.clean_tokens(F.col("text")) == clean.clean_tokens(F.col("original"))
    return _aug(spark, d, True).agg(F.count("*").alias("documents"), F.count_if(same).alias("restored"))


@query("M_P12_ablation", " union all ".join(f"select '{k}' as config, count(*) as tokens, count(distinct word) as distinct_tokens from (select unnest({sql.cleaned('text', c)}) as word from documents)" for k, c in clean.ablation_configs().items()))
def _(spark, d):
    return clean.preprocess_ablation(docs(spark, d))


@query("M_P13_materialize_posts", f"with {sql.doc_posts('lang')} select region, ts // 86400000000 as day, count(*) as posts from posts group by 1, 2")
def _(spark, d):
    from eventpulse.sinks import materialize_posts

    stored = materialize_posts(P.posts_from_documents(docs(spark, d), region="lang"), new_dir(spark, "posts"))
    return stored.groupBy("region", F.col("day").cast("long").alias("day")).agg(F.count("*").alias("posts"))


@query("M_P14_track", "select event_id, event_type from events where event_type in ('purchase', 'click') and value > 50")
def _(spark, d):
    return P.track(table(spark, d, "events"), F.col("event_type").isin("purchase", "click") & (F.col("value") > 50)).select("event_id", "event_type")


# --- the word-burst detector -------------------------------------------------------------------


@query("M_K1_count_words", f"{DOC}, {sql.COUNTS} select region, block_no, word, cnt from wc")
def _(spark, d):
    return bursts.count_words(doc_tokens(spark, d))


@query("M_K2_common_words", f"{DOC}, {sql.COUNTS} select region, block_no, word, cnt from wc where cnt >= 10")
def _(spark, d):
    return bursts.common_words(bursts.count_words(doc_tokens(spark, d)), 10)


def _tf(kind: str) -> None:
    of = "block_terms" if kind == "total" else "block_distinct"

    @query(f"M_K3_term_frequency_{kind}", f"{EVT}, {sql.COUNTS} select wc.region, wc.block_no, word, cnt, block_terms, block_distinct, {sql.r9(f'cnt / {of}::double')} as tf from wc join tot using (region, block_no)")
    def _(spark, d):
        out = bursts.term_frequency(bursts.count_words(event_tokens(spark, d)), kind)
        return out.select("region", "block_no", "word", "cnt", "block_terms", "block_distinct", r9("tf").alias("tf"))


_tf("total")
_tf("distinct")


def _df(name: str, cfg: BurstConfig) -> None:
    @query(f"M_K4_document_frequency_{name}", f"{EVT}, {sql.scores(cfg)} select region, block_no, word, df from sc")
    def _(spark, d):
        return bursts.document_frequency(bursts.count_words(event_tokens(spark, d)), cfg).select("region", "block_no", "word", "df")


_df("prefix", W4)
_df("full", replace(W4, corpus="full"))
_df("common", replace(W4, scope="common"))


def _idf(name: str, cfg: BurstConfig) -> None:
    @query(f"M_K5_idf_{name}", f"{CONV}, {sql.scores(cfg)} select region, block_no, word, n_blocks, df, {sql.r9('idf')} as idf from sc")
    def _(spark, d):
        return bursts.score(conv_tokens(spark, d), cfg).select("region", "block_no", "word", "n_blocks", "df", r9("idf").alias("idf"))


_idf("elapsed", W10)
_idf("nonempty", replace(W10, blocks="nonempty"))
_idf("full", replace(W10, corpus="full"))


@query("M_K6_tfidf", f"{CONV}, {sql.scores(W10)} select region, block_no, word, {sql.r9('tfidf')} as tfidf from sc")
def _(spark, d):
    return bursts.score(conv_tokens(spark, d), W10).select("region", "block_no", "word", r9("tfidf").alias("tfidf"))


def _prev(kind: str) -> None:
    cfg = replace(W4, previous=kind)

    @query(f"M_K7_previous_{kind}", f"{EVT}, {sql.scores(cfg)} select region, block_no, word, {sql.r9('prev_tfidf')} as prev_tfidf from sc where prev_tfidf is not null")
    def _(spark, d):
        ws = bursts.score(event_tokens(spark, d), cfg)
        return ws.where("prev_tfidf is not null").select("region", "block_no", "word", r9("prev_tfidf").alias("prev_tfidf"))


_prev("raw")
_prev("common")


@query("M_K8_score_ratio", f"{EVT}, {sql.scores(W4)} select region, block_no, word, {sql.r9('case when prev_tfidf > 1e-12 then tfidf / prev_tfidf end')} as rate from sc where cnt >= 2")
def _(spark, d):
    ws = bursts.score(event_tokens(spark, d), W4).where("cnt >= 2")
    return ws.select("region", "block_no", "word", r9(F.when(F.col("prev_tfidf") > 1e-12, bursts.score_ratio(F.col("tfidf"), F.col("prev_tfidf")))).alias("rate"))


def _detect(name: str, base: str, tokens: Callable[[SparkSession, str], DataFrame], cfg: BurstConfig) -> None:
    @query(name, bursts_sql(base, cfg))
    def _(spark, d):
        return events_out(bursts.detect_bursts(tokens(spark, d), cfg))


_detect("M_K9_detect_event", EVT, event_tokens, W4)
_detect("M_K9_detect_skip", EVT, event_tokens, replace(W4, prev_zero="skip"))
_detect("M_K9_detect_floor", EVT, event_tokens, replace(W4, prev_zero="floor", floor=0.001))
_detect("M_K10_quiet_window", EVT, event_tokens, replace(W4, quiet_window=5))
_detect("M_K16_detect_barrier_W1", DOC, doc_tokens, W1)
_detect("M_K16_detect_common_scope", DOC, doc_tokens, replace(W1, scope="common", previous="common"))
_detect("M_K16_detect_distinct_terms", DOC, doc_tokens, replace(W1, denominator="distinct"))
_detect("M_K16_detect_full_corpus", EVT, event_tokens, replace(W4, corpus="full"))
_detect("W_9_order_lines", ORD, order_tokens, W9)
_detect("W_10_conversations", CONV, conv_tokens, W10)
_detect("W_PLANT_bursts", PLANTED, plant_tokens, PLANT)
_detect("W_5_bursts_by_language", DOC_LANG, lambda s, d: doc_tokens(s, d, region="lang"), replace(W1, min_count=5))
_detect("W_5_bursts_by_region", EVT_PLACE, lambda s, d: event_tokens(s, d, located=True), W4)


@query("W_12_bursts_of_good_documents", bursts_sql(DOC.replace("from documents)", "from documents join (select doc_id from labels where quality = 1) using (doc_id))"), replace(W1, min_count=5)))
def _(spark, d):
    good = table(spark, d, "labels").where("quality = 1").select("doc_id")
    tokens = blocks.tokened(P.posts_from_documents(docs(spark, d).join(good, "doc_id", "left_semi")), "6 minutes")
    return events_out(bursts.detect_bursts(tokens, replace(W1, min_count=5)))


@query("W_8_stopwords_kept", f"with {sql.doc_posts()},\n{sql.tokened(sql.MINUTES6, replace(PrepConfig(), stopwords=False))},\n{sql.scores(W1)},\n{sql.detected(W1)}\nselect reason, count(*) as events from ev group by 1")
def _(spark, d):
    """Events when function words stay: many of them are function words."""
    return bursts.detect_bursts(doc_tokens(spark, d, replace(PrepConfig(), stopwords=False)), W1).groupBy("reason").agg(F.count("*").alias("events"))


@query("W_8_pages", f"with {sql.PAGE_POSTS}, {sql.tokened(sql.MINUTES6)} select block_no, count(*) as tokens, count(distinct word) as distinct_tokens from words group by 1")
def _(spark, d):
    t = blocks.tokened(P.posts_from_pages(table(spark, d, "pages")), "6 minutes", origin=P.START_US)
    return bursts.explode_words(t).groupBy("block_no").agg(F.count("*").alias("tokens"), F.count_distinct("word").alias("distinct_tokens"))


@query("M_K11_steady_words", f"{CONV}, {sql.scores(W10)} select region, word, count(*) as n_blocks, {sql.r9('avg(tfidf)')} as mean_tfidf, {sql.r9('stddev_pop(tfidf)')} as sd_tfidf from sc group by 1, 2 having count(*) >= 0.9 * (select max(block_no) from tot)")
def _(spark, d):
    return bursts.steady_words(bursts.score(conv_tokens(spark, d), W10)).select("region", "word", "n_blocks", r9("mean_tfidf").alias("mean_tfidf"), r9("sd_tfidf").alias("sd_tfidf"))


@query("M_K12_trend", f"""{EVT}, {sql.scores(W4)}, {sql.detected(W4)},
span as (select region, word, block_no as event_block, unnest(generate_series(block_no - 9, block_no)) as block_no from ev)
select region, word, event_block, block_no, {sql.r9('coalesce(tfidf, 0.0)')} as tfidf from span left join (select region, word, block_no, tfidf from sc) using (region, word, block_no)""")
def _(spark, d):
    ws = materialize(bursts.score(event_tokens(spark, d), W4), "scores")
    return bursts.trend(ws, bursts.detect(ws, W4)).select("region", "word", "event_block", "block_no", r9("tfidf").alias("tfidf"))


@query("M_K13_render_trend", f"{EVT}, {sql.scores(W4)}, {sql.detected(W4)} select word, block_no, 10::bigint as points from ev order by round(tfidf, 9) desc, word, block_no limit 5")
def _(spark, d):
    """Charts of the five strongest events, and the points on their lines (the drawing itself is held to a test)."""
    ws = materialize(bursts.score(event_tokens(spark, d), W4), "scores")
    top = bursts.detect(ws, W4).orderBy(F.round("tfidf", 9).desc(), "word", "block_no").limit(5)
    rows = bursts.trend_arrays(ws, top).collect()  # five rows
    charts = [(r["word"], r["block_no"], bursts.render_trend([(p["block_no"], p["tfidf"]) for p in r["trend"]])) for r in rows]
    drawn = spark.createDataFrame(charts, "word string, block_no long, svg string")
    return drawn.select("word", "block_no", F.size(F.split(F.regexp_extract("svg", 'points="([^"]*)"', 1), " ")).cast("long").alias("points"))


@query("M_K14_write_events", f"{EVT_PLACE}, {sql.scores(W4)}, {sql.detected(W4)} select region, count(*) as events from ev group by 1")
def _(spark, d):
    from eventpulse.sinks import write_events

    stored = write_events(bursts.detect_bursts(event_tokens(spark, d, located=True), W4), new_dir(spark, "events"))
    return stored.groupBy("region").agg(F.count("*").alias("events"))


def eager_sql(base: str, cfg: BurstConfig) -> str:
    return f"""{base},
seqd as (select region, block_no, tokens, row_number() over (partition by region, block_no order by ts, post_id) - 1 as seq from tok),
run as (select *, coalesce(sum(len(tokens)) over (partition by region, block_no order by seq rows between unbounded preceding and 1 preceding), 0) as before from seqd),
occ as (select region, block_no, seq, before, unnest(tokens) as word, unnest(range(len(tokens))) as pos from run),
nth as (select *, row_number() over (partition by region, block_no, word order by seq, pos) as nth from occ),
hit as (select region, block_no, word, max(case when nth = {cfg.min_count} then before + pos + 1 end) as terms from nth where nth in (1, {cfg.min_count}) group by 1, 2, 3),
d0 as (select *, row_number() over (partition by region, word order by block_no) as df from hit),
d1 as (select region, block_no, word, {cfg.min_count}::bigint as cnt, case when terms is not null then {cfg.min_count} / terms::double * ln(block_no / (1 + df)) end as tfidf from d0),
sc as (select *, case when lag(block_no) over win = block_no - 1 then lag(tfidf) over win end as prev_tfidf from d1 window win as (partition by region, word order by block_no)),
{sql.detected(cfg)}
{sql.EVENTS_OUT}"""


@query("M_K15_detect_eager", eager_sql(EVT, W4))
def _(spark, d):
    return events_out(bursts.detect_bursts_eager(event_tokens(spark, d), W4))


@query("W_2_eager_documents", eager_sql(DOC, W1))
def _(spark, d):
    return events_out(bursts.detect_bursts_eager(doc_tokens(spark, d), W1))


@query("M_K18_leaked_blocks", "with " + ", ".join([sql.event_posts(), sql.tokened(sql.HOUR, RAW)]) + f""",
seqd as (select *, row_number() over (partition by region, block_no order by ts, post_id) - 1 as seq, count(*) over (partition by region, block_no) as n from tok),
lates as (select region, block_no + case when seq >= ceil((1 - 0.2) * n) then 1 else 0 end as block_no, tokens from seqd),
words2 as (select region, block_no, unnest(tokens) as word from lates),
{sql.scores(W4).replace('from words group', 'from words2 group')}, {sql.detected(W4)} {sql.EVENTS_OUT}""")
def _(spark, d):
    return events_out(bursts.detect_bursts(blocks.leak_blocks(event_tokens(spark, d), 0.2), W4))


@query("W_LEAK_changed_events", None)
def _(spark, d):
    """Events that differ from the synchronised run, by the share of posts that leak."""
    tokens = materialize(event_tokens(spark, d), "event-tokens")
    keys = ["region", "block_no", "word"]
    right = bursts.detect_bursts(tokens, W4).select(*keys).withColumn("_r", F.lit(1))
    out = None
    for share in (0.0, 0.05, 0.2):
        own = bursts.detect_bursts(blocks.leak_blocks(tokens, share), W4).select(*keys).withColumn("_o", F.lit(1))
        one = own.join(right, keys, "full").agg(F.count_if(F.col("_r").isNull()).alias("added"), F.count_if(F.col("_o").isNull()).alias("lost")).select(F.lit(share).alias("leaked"), "added", "lost")
        out = one if out is None else out.unionByName(one)
    return out


RATES, COUNTS = [1.5, 2.0, 3.0], [2, 3, 5]


@query("M_K20_sweep", f"""{EVT}, {sql.scores(W4)},
grid as (select r::double as rate, k::bigint as min_count from (select unnest({RATES}) as r), (select unnest({COUNTS}) as k))
select g.rate, g.min_count, count(*) filter (where coalesce(prev_tfidf > 1e-12, false) and tfidf / prev_tfidf > g.rate + 1e-9) as ratio_events,
  count(*) filter (where not coalesce(prev_tfidf > 1e-12, false)) as new_events
from sc, grid g where cnt >= g.min_count and tfidf > 1e-12 group by 1, 2""")
def _(spark, d):
    return bursts.burst_sweep(bursts.score(event_tokens(spark, d), W4), RATES, COUNTS)


@query("B_7_top_tfidf", f"""{CONV}, {sql.scores(W10)} select region, block_no, word, {sql.r9('tfidf')} as tfidf, rank from (
select *, row_number() over (partition by region, block_no order by round(tfidf, 9) desc, word) as rank from sc) where rank <= 5""")
def _(spark, d):
    return bursts.top_tfidf(bursts.score(conv_tokens(spark, d), W10), 5).select("region", "block_no", "word", r9("tfidf").alias("tfidf"), "rank")


@query("B_8_count_ratio", f"""{EVT}, {sql.COUNTS}, p as (select *, case when lag(block_no) over w = block_no - 1 then lag(cnt) over w end as prev_cnt from wc window w as (partition by region, word order by block_no))
select region, block_no, word, cnt, prev_cnt from p where cnt >= 2 and cnt > 1.5 * prev_cnt""")
def _(spark, d):
    return bursts.count_ratio(bursts.count_words(event_tokens(spark, d)), 1.5, 2)


# --- routing -----------------------------------------------------------------------------------

_SUMS = "count(*) as n, sum(event_id)::bigint as ids"


def _multiset(name: str, route: Callable[[DataFrame], DataFrame]) -> None:
    @query(name, f"select event_type, {_SUMS} from events group by 1")
    def _(spark, d):
        return route(table(spark, d, "events").select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


_multiset("M_R1_route_shuffle", lambda df: routing.route_shuffle(df, 4))
_multiset("M_R3_route_fields", lambda df: routing.route_fields(df, 4, "event_type"))

@query("M_R4_route_global", f"select event_type, {_SUMS} from events group by 1")
def _(spark, d):
    """A small result in one task: the sums of each type, not the rows behind them."""
    sums = table(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))
    return routing.route_global(sums)


@query("M_R2_route_all", f"select task::bigint as task, {_SUMS} from events, (select unnest(range(4)) as task) group by 1")
def _(spark, d):
    return routing.route_all(table(spark, d, "events").select("event_id"), 4).groupBy(F.col("task").cast("long").alias("task")).agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@query("M_R5_route_direct", "select (event_id % 4)::bigint as task, count(*) as n from events group by 1")
def _(spark, d):
    df = routing.route_direct(table(spark, d, "events").select("event_id"), 4, "event_id")
    return df.groupBy(F.spark_partition_id().cast("long").alias("task")).agg(F.count("*").alias("n"))


@query("M_R6_routing_skew", "select count(*) as tasks, sum(n)::bigint as total_rows, round(max(n) / avg(n), 9) + 0.0 as skew from (select event_id % 4 as task, count(*) as n from events group by 1)")
def _(spark, d):
    out = routing.routing_skew(routing.route_direct(table(spark, d, "events").select("event_id"), 4, "event_id"))
    return out.select("tasks", "total_rows", r9("skew").alias("skew"))


@query("W_6_bursts_by_parallelism", f"{DOC}, {sql.scores(W1)}, {sql.detected(W1)} select s::bigint as shards, (select count(*) from ev) as events from (select unnest([1, 2, 4, 8]) as s)")
def _(spark, d):
    """The same events whatever the number of tasks that words are dealt to."""
    tokens = materialize(packed.pack(doc_tokens(spark, d)), "doc-tokens", "zstd")  # cleaned once
    out = None
    for s in (1, 2, 4, 8):  # one after the other: what a run has shuffled goes before the next
        found = bursts.detect_bursts(routing.route_direct(tokens, s, "post_id"), W1)
        one = materialize(found.agg(F.lit(s).cast("long").alias("shards"), F.count("*").alias("events")), "bursts-by-tasks")
        out = one if out is None else out.unionByName(one)
    return out
