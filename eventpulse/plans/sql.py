"""DuckDB SQL of the detectors' steps, as common table expressions."""

from __future__ import annotations

from eventpulse.config import BurstConfig, PrepConfig
from eventpulse.functions.clean import LIGHT_SUFFIX
from eventpulse.functions.stopwords import stopwords

T0 = 1_704_067_200_000_000  # 2024-01-01 in microseconds
GAP = r"[^\p{L}\p{N}]+"
LETTERS = "abcdefghijklmnopqrstuvwxyzàáâãäåæçèéêëìíîïñòóôöùúûüÿßœ"
MINUTES6, HOUR, DAYS30 = 360_000_000, 3_600_000_000, 2_592_000_000_000
HALF_HOUR = 1_800_000_000


def r9(x: str) -> str:
    """Rounded as the queries round."""
    return f"round({x}, 9) + 0.0"


def tokens(text: str) -> str:
    return f"list_filter(string_split_regex(lower(coalesce({text}, '')), '{GAP}'), lambda x: x <> '')"


def without_stopwords(toks: str, langs: tuple[str, ...] = ("en", "fr", "de", "es")) -> str:
    words = ", ".join(f"'{w}'" for w in stopwords(langs))
    return f"list_filter({toks}, lambda x: x not in ({words}))"


def urls(text: str) -> str:
    return rf"regexp_replace({text}, '(https?://|www\.)\S+', '', 'g')"


def checkins(text: str) -> str:
    return rf"array_to_string(list_filter(string_split_regex({text}, '[.!?\n]+'), lambda s: not starts_with(lower(ltrim(s)), 'i am at')), '. ')"


def squeezed(text: str) -> str:
    out = f"lower({text})"
    for ch in LETTERS:
        out = f"regexp_replace({out}, '{ch}{{3,}}', '{ch}', 'g')"
    return out


def light(word: str) -> str:
    cut = f"regexp_replace({word}, '{LIGHT_SUFFIX}', '')"
    return f"(case when length({cut}) >= 4 then {cut} else {word} end)"


def cleaned(text: str, cfg: PrepConfig = PrepConfig()) -> str:
    """The tokens of a text under the cleaning rules. Runs are squeezed before the split: no run crosses a gap."""
    t = f"coalesce({text}, '')"
    t = urls(t) if cfg.urls else t
    t = checkins(t) if cfg.checkins else t
    t = squeezed(t) if cfg.squeeze else t
    out = tokens(t)
    out = without_stopwords(out, cfg.langs) if cfg.stopwords else out
    return f"list_transform({out}, lambda x: {light('x')})" if cfg.stem == "light" else out


def doc_posts(region: str = "'ALL'") -> str:
    return rf"""posts as (
  select doc_id * 1000000 + pos as post_id, {T0} + doc_id * 36000000 as ts, {region} as region, s as text, doc_id, lang
  from (select doc_id, lang, unnest(parts) as s, unnest(range(len(parts))) as pos
        from (select doc_id, lang, string_split_regex(text, '[.!?\n]+') as parts from documents))
  where trim(s) <> '')"""


EVENT_TEXT = r"event_type || ' k' || regexp_extract(props, '([0-9]+)', 1) || ' ' || replace(event_type, '_', '') || 'k' || regexp_extract(props, '([0-9]+)', 1)"


def event_posts(region: str = "'ALL'") -> str:
    return f"posts as (select event_id as post_id, epoch_us(ts) as ts, {region} as region, {EVENT_TEXT} as text, user_id from events)"


def located_event_posts() -> str:
    return f"""posts as (select event_id as post_id, epoch_us(ts) as ts, r_name as region, n_name as place, {EVENT_TEXT} as text, user_id
  from events join customer on user_id = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"""


ORDER_POSTS = """posts as (select l_orderkey * 10 + l_linenumber as post_id, epoch_us(o_orderdate::timestamp) as ts, 'ALL' as region,
  p_name || ' ' || replace(p_brand, '#', '') || ' part' || p_partkey as text
  from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey)"""
CONV_POSTS = f"posts as (select conv_id * 1000 + turn as post_id, {T0} + (conv_id * 360 + turn * 20) * 1000000 as ts, 'ALL' as region, coalesce(text, '') as text from conversations)"
PAGE_POSTS = rf"posts as (select page_id as post_id, {T0} + page_id * 36000000 as ts, 'ALL' as region, regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1) || ' ' || url as text from pages)"


def blocked(length: int) -> str:
    return f"blocked as (select posts.*, ((ts - (select min(ts) // {length} * {length} from posts)) // {length} + 1)::bigint as block_no from posts)"


def tokened(length: int, cfg: PrepConfig = PrepConfig()) -> str:
    return f"{blocked(length)},\ntok as (select * exclude (text), {cleaned('text', cfg)} as tokens from blocked),\nwords as (select region, block_no, unnest(tokens) as word from tok)"


PLANT_ITEMS = f"""bench as (select row_number() over (order by item_id) - 1 as item, {without_stopwords(tokens('text'))} as toks from benchmark),
firsts as (select item, word, min(p) as p from (select item, unnest(toks) as word, unnest(range(len(toks))) as p from bench) group by item, word),
ranked as (select item, word, row_number() over (partition by item order by p) - 1 as rk from firsts)"""
PLANT_WORDS = f"""{PLANT_ITEMS},
spec as (select * from (values (0, 30), (1, 40), (2, 10)) as t(d, n)),
planted as (select item, d, k from (select item, d, unnest(range(n)) as k from bench, spec)),
words as (select 'P' as region, (2 * item + d + 1)::bigint as block_no, word from planted join ranked using (item) where rk < 8 and rk <> k % 8)"""

COUNTS = """wc as (select region, block_no, word, count(*) as cnt from words group by 1, 2, 3),
tot as (select region, block_no, sum(cnt)::bigint as block_terms, count(*) as block_distinct from wc group by 1, 2)"""


def scores(cfg: BurstConfig = BurstConfig()) -> str:
    """wc to sc: one row for each word and block with tf, idf, tfidf and the previous score."""
    denominator = "block_terms" if cfg.denominator == "total" else "block_distinct"
    seen = "1" if cfg.scope == "all" else f"case when cnt >= {cfg.min_count} then 1 else 0 end"
    frame = "order by w.block_no rows unbounded preceding" if cfg.corpus == "prefix" else ""
    if cfg.corpus == "prefix":
        n = "w.block_no" if cfg.blocks == "elapsed" else "(select count(*) from tot t where t.region = w.region and t.block_no <= w.block_no)"
    else:
        n = "(select max(block_no) from tot t where t.region = w.region)" if cfg.blocks == "elapsed" else "(select count(*) from tot t where t.region = w.region)"
    known = "lag(block_no) over win = block_no - 1" + (f" and lag(cnt) over win >= {cfg.min_count}" if cfg.previous == "common" else "")
    quiet = f", coalesce(max(tfidf) over (partition by region, word order by block_no range between {cfg.quiet_window} preceding and 1 preceding), 0.0) as quiet_max" if cfg.quiet_window else ""
    return f"""{COUNTS},
d0 as (select w.region, w.block_no, w.word, cnt, block_terms, block_distinct, cnt / {denominator}::double as tf, ({n})::bigint as n_blocks,
  sum({seen}) over (partition by w.region, w.word {frame})::bigint as df from wc w join tot on w.region = tot.region and w.block_no = tot.block_no),
d1 as (select *, ln(n_blocks / (1 + df)) as idf, tf * ln(n_blocks / (1 + df)) as tfidf from d0),
sc as (select *, case when {known} then lag(tfidf) over win end as prev_tfidf{quiet} from d1 window win as (partition by region, word order by block_no))"""


def detected(cfg: BurstConfig = BurstConfig(), source: str = "sc") -> str:
    """ev: the burst events of the scores."""
    prev = "coalesce(prev_tfidf > 1e-12, false)"
    base = f"case when {prev} then tfidf / prev_tfidf end" if cfg.prev_zero != "floor" else f"tfidf / (case when {prev} then prev_tfidf else {cfg.floor} end)"
    new = f"when not {prev} then 'new'" if cfg.prev_zero == "event" else ""
    quiet = f" and tfidf > {cfg.rate} * quiet_max + 1e-9" if cfg.quiet_window else ""
    return f"""rated as (select *, {base} as rate from {source} where cnt >= {cfg.min_count} and tfidf > 1e-12),
ev as (select region, block_no, word, cnt, tfidf, prev_tfidf, rate, reason from (
  select *, case when coalesce(rate > {cfg.rate} + 1e-9, false) then 'ratio' {new} end as reason from rated) where reason is not null{quiet})"""


EVENTS_OUT = f"select region, block_no, word, cnt, {r9('tfidf')} as tfidf, {r9('prev_tfidf')} as prev_tfidf, {r9('rate')} as rate, reason from ev"
