"""Post streams made from the tables: post_id, ts, region, text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from eventpulse.functions.clean import SENTENCE_END, drop_stopwords, tokenize

#: Microseconds of 2024-01-01, whatever the session's zone.
START_US = 1_704_067_200_000_000
#: Room in the ids of posts: sentences of a document, turns of a conversation, lines of an order.
IDS_PER_DOC, IDS_PER_CONVERSATION, IDS_PER_ORDER = 1_000_000, 1_000, 10


def _at(seconds: Column) -> Column:
    return F.timestamp_micros((F.lit(START_US) + seconds * 1_000_000).cast("long"))


def two_part_id(of: Column, part: Column, room: int) -> Column:
    """One id of two; a part that has no room fails the job, as its post would pass for another's."""
    full = F.raise_error(F.concat(F.lit("no room for part "), part.cast("string"), F.lit(f" of {room}")))
    return F.when((part < 0) | (part >= room), full.cast("long")).otherwise((of * room + part).cast("long"))


def posts_from_documents(docs: DataFrame, seconds: int = 36, sentence: bool = True, region: str | None = None) -> DataFrame:
    """Sentences, or whole documents, as posts; one document every ``seconds``. Blank sentences are dropped."""
    place = F.col(region) if region else F.lit("ALL")
    ts = _at(F.col("doc_id") * seconds)
    if not sentence:
        return docs.select(F.col("doc_id").alias("post_id"), ts.alias("ts"), place.alias("region"), F.coalesce("text", F.lit("")).alias("text"))
    parts = docs.select("doc_id", ts.alias("ts"), place.alias("region"), F.posexplode(F.split("text", SENTENCE_END)).alias("_n", "text"))
    return parts.where(F.trim("text") != "").select(two_part_id(F.col("doc_id"), F.col("_n"), IDS_PER_DOC).alias("post_id"), "ts", "region", "text")


def with_region(df: DataFrame, customer: DataFrame, nation: DataFrame, region: DataFrame, user: str = "user_id") -> DataFrame:
    """``df`` with nation and region names of the user: three dimension joins that size statistics broadcast."""
    c = customer.select(F.col("c_custkey").alias("_c"), "c_nationkey")
    n = nation.select("n_nationkey", "n_name", "n_regionkey")
    r = region.select("r_regionkey", "r_name")
    out = df.join(c, df[user] == c["_c"]).join(n, F.col("c_nationkey") == n["n_nationkey"]).join(r, F.col("n_regionkey") == r["r_regionkey"])
    return out.drop("_c", "c_nationkey", "n_nationkey", "n_regionkey", "r_regionkey")


def event_text() -> Column:
    """Type, key and both together, blank-separated."""
    k = F.concat(F.lit("k"), F.get_json_object("props", "$.k"))
    return F.concat_ws(" ", "event_type", k, F.concat_ws("", F.regexp_replace("event_type", "_", ""), k))


def posts_from_events(events: DataFrame, customer: DataFrame | None = None, nation: DataFrame | None = None, region: DataFrame | None = None) -> DataFrame:
    """Events as posts at their own time; the region of the user if the dimensions are given."""
    df = with_region(events, customer, nation, region) if customer is not None else events.withColumn("r_name", F.lit("ALL"))
    return df.select(F.col("event_id").alias("post_id"), "ts", F.col("r_name").alias("region"), event_text().alias("text"))


def posts_from_order_lines(orders: DataFrame, lines: DataFrame, part: DataFrame) -> DataFrame:
    """Order lines as posts: words of the part, its brand and its number, at the order's date."""
    text = F.concat_ws(" ", "p_name", F.regexp_replace("p_brand", "#", ""), F.concat(F.lit("part"), F.col("p_partkey")))
    df = lines.select("l_orderkey", "l_linenumber", "l_partkey").join(orders.select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    df = df.join(part.select("p_partkey", "p_name", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return df.select(two_part_id(F.col("l_orderkey"), F.col("l_linenumber"), IDS_PER_ORDER).alias("post_id"), F.col("o_orderdate").cast("timestamp").alias("ts"), F.lit("ALL").alias("region"), text.alias("text"))


def posts_from_conversations(c: DataFrame) -> DataFrame:
    """Turns as posts: a conversation every six minutes, a turn every twenty seconds."""
    return c.select(two_part_id(F.col("conv_id"), F.col("turn"), IDS_PER_CONVERSATION).alias("post_id"), _at(F.col("conv_id") * 360 + F.col("turn") * 20).alias("ts"), F.lit("ALL").alias("region"), F.coalesce("text", F.lit("")).alias("text"))


def page_title(html: Column) -> Column:
    """What stands in the title element."""
    return F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title>", 1)


def posts_from_pages(p: DataFrame) -> DataFrame:
    """Title and address of each page; one page every 36 seconds."""
    return p.select(F.col("page_id").alias("post_id"), _at(F.col("page_id") * 36).alias("ts"), F.lit("ALL").alias("region"), F.concat_ws(" ", page_title(F.col("html")), "url").alias("text"))


def _content_words(bench: DataFrame) -> DataFrame:
    """(item, words): the items numbered from 0 with their distinct content words in order."""
    words = F.array_distinct(drop_stopwords(tokenize(F.col("text"))))
    nth = F.row_number().over(Window.orderBy("item_id")) - 1  # a few hundred rows of a fixture
    return bench.select(nth.cast("long").alias("item"), words.alias("words"))


def planted_burst_posts(bench: DataFrame) -> DataFrame:
    """Known bursts: item i has 30 posts in block 1 + 2i, 40 in the next and 10 in the one after.

    A post is the item's first eight distinct content words but one, in turn.
    """
    items = _content_words(bench).select("item", F.slice("words", 1, 8).alias("words"))
    spec = F.array(*[F.struct(F.lit(d).alias("d"), F.lit(n).alias("n")) for d, n in ((0, 30), (1, 40), (2, 10))])
    posts = items.select("item", "words", F.explode(spec).alias("s")).select("item", "words", "s.d", F.explode(F.sequence(F.lit(0), F.col("s.n") - 1)).alias("k"))
    kept = F.filter("words", lambda w, i: i != F.pmod(F.col("k"), F.lit(8)))
    block0 = 2 * F.col("item") + F.col("d")  # from 0
    return posts.select((F.col("item") * 1000 + F.col("d") * 100 + F.col("k")).alias("post_id"), _at(block0 * 360 + F.col("k")).alias("ts"), F.lit("P").alias("region"), F.array_join(kept, " ").alias("text"))


def chain_posts(bench: DataFrame, posts: int = 60) -> DataFrame:
    """Posts whose clustering depends on their order: windows of four words that slide over an item's
    distinct words, in blocks i div 4 and the next."""
    items = _content_words(bench)
    rows = items.select("item", "words", F.explode(F.array(F.lit(0), F.lit(1))).alias("d"), F.sequence(F.lit(0), F.lit(posts - 1)).alias("ks"))
    rows = rows.select("item", "words", "d", F.explode("ks").alias("k"))
    n = F.size("words")
    window = F.transform(F.sequence(F.lit(0), F.lit(3)), lambda j: F.element_at("words", (F.pmod(F.col("k") + j, n) + 1).cast("int")))
    block0 = F.floor(F.col("item") / 4) + F.col("d")
    second = F.pmod(F.col("item"), F.lit(4)) * 60 + F.col("k")
    return rows.select((F.col("item") * 1000 + F.col("d") * 100 + F.col("k")).alias("post_id"), _at(block0 * 360 + second).alias("ts"), F.lit("C").alias("region"), F.array_join(window, " ").alias("text"))


def augmented_texts(docs: DataFrame, pages: DataFrame, undoable: bool = False) -> DataFrame:
    """Documents with something for the cleaning rules to undo: a check-in sentence, an address or a
    stretched word, by doc_id mod 10 (0, 1, 2). Without a page of the number sought there is no text, and a stretched
    vowel may stand beside itself in capitals. ``undoable``: neither; such documents stay as they are, each once."""
    n = pages.agg(F.count("*").alias("_pages"))
    p = pages.select(F.col("page_id").alias("_p"), "url")
    p = p.groupBy("_p").agg(F.min("url").alias("url")) if undoable else p
    n = n.withColumn("_pages", F.greatest("_pages", F.lit(1))) if undoable else n
    df = docs.crossJoin(F.broadcast(n)).join(p, F.pmod("doc_id", "_pages") == F.col("_p"), "left")  # a single row
    first = F.regexp_extract("text", r"^(\S+)", 1)
    near = "([^aeiouAEIOU])" if undoable else "([^aeiou])"
    long = F.concat(F.regexp_replace(first, f"{near}([aeiou]){near}", "$1$2$2$2$2$2$3"), F.substring("text", F.length(first) + 1, F.length("text")))
    kind = F.pmod("doc_id", F.lit(10))
    text = F.when(kind == 0, F.concat(F.lit("I am at the harbour. "), F.col("text"))).when(kind == 1, F.concat(F.col("url"), F.lit(" "), F.col("text"))).when(kind == 2, long).otherwise(F.col("text"))
    text = F.coalesce(text, "text") if undoable else text
    return df.select("doc_id", F.col("text").alias("original"), text.alias("text"))


def bbox_filter(df: DataFrame, boxes: list[tuple[float, float, float, float]], lon: str = "lon", lat: str = "lat") -> DataFrame:
    """Rows inside one of the boxes (west, south, east, north): a filter that reaches the scan."""
    inside = F.lit(False)
    for w, s, e, n in boxes:
        inside = inside | (F.col(lon).between(w, e) & F.col(lat).between(s, n))
    return df.where(inside)


def track(df: DataFrame, predicate: Column) -> DataFrame:
    """The part of the stream that a criterion selects."""
    return df.where(predicate)


def by_authors(df: DataFrame, authors: DataFrame, user: str = "user_id") -> DataFrame:
    """Posts of the given authors."""
    return df.join(authors.select(F.col(user)).distinct(), user, "left_semi")
