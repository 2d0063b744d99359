"""Plain relational queries around the methods, each over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lexnorm.functions import tokens
from lexnorm.sources.store import table

REVENUE = "cast(round(sum(l_extendedprice * (1 - l_discount)), 2) as double)"


def _flat(spark: SparkSession, d: str, name: str = "documents", *cols: str) -> DataFrame:
    return table(spark, d, name).select(*cols, F.explode(tokens.words(F.col("text"))).alias("word"))


def _freq(spark: SparkSession, d: str, name: str = "documents") -> DataFrame:
    return tokens.vocabulary(table(spark, d, name))


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', {ts})")


def seconds(ts: str) -> Column:
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', {ts}) div 1000000")


def tokens_by_lang(spark: SparkSession, d: str) -> DataFrame:
    return _flat(spark, d, "documents", "lang").groupBy("lang").agg(F.count("*").alias("tokens"), F.countDistinct("word").alias("words"))


def word_freq(spark: SparkSession, d: str) -> DataFrame:
    return _freq(spark, d)


def vocab_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    _flat(spark, d, "documents", "lang", "source").groupBy("lang", "source").agg(F.count("*").alias("n")).createOrReplaceTempView("lexnorm_counts")
    return spark.sql("SELECT lang, source, sum(n) AS tokens, cast(grouping_id(lang, source) as bigint) AS gid FROM lexnorm_counts GROUP BY GROUPING SETS ((lang, source), (lang), (source), ())")


def rollup_cube(spark: SparkSession, d: str) -> DataFrame:
    o, c, n, r = (table(spark, d, t) for t in ("orders", "customer", "nation", "region"))
    dims = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_nationkey", "n_name", "r_name")
    flat = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey"))
    roll = flat.rollup("r_name", "n_name").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total")).select("r_name", "n_name", F.lit(None).cast("string").alias("c_mktsegment"), "orders", "total")
    cube = flat.cube("r_name", "c_mktsegment").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total")).select("r_name", F.lit(None).cast("string").alias("n_name"), "c_mktsegment", "orders", "total")
    return roll.unionByName(cube)


LANGS = ("de", "en", "es", "fr")


def pivot_tokens(spark: SparkSession, d: str) -> DataFrame:
    counts = _flat(spark, d, "documents", "lang", "source").groupBy("source", "lang").count()
    return counts.groupBy("source").pivot("lang", list(LANGS)).agg(F.sum("count")).na.fill(0)


def approx_vocab(spark: SparkSession, d: str) -> DataFrame:
    """Words by sketches of fixed size, beside the exact count and the relative error."""
    flat = _flat(spark, d, "documents", "lang")
    about = flat.groupBy("lang").agg(F.hll_sketch_estimate(F.hll_sketch_agg("word")).alias("about"), F.percentile_approx(F.length("word"), 0.5).alias("median_length"))
    out = about.join(flat.distinct().groupBy("lang").agg(F.count("*").alias("words")), "lang")
    return out.withColumn("error", F.abs(F.col("about") - F.col("words")) / F.col("words"))


def zipf_curve(spark: SparkSession, d: str) -> DataFrame:
    """Words by rank of frequency class: a class has all words of one count, so no window spans all words."""
    classes = _freq(spark, d).groupBy("freq").agg(F.count("*").alias("words"))
    order = Window.orderBy(F.desc("freq"))
    cum = Window.orderBy(F.desc("freq")).rowsBetween(Window.unboundedPreceding, 0)
    total = F.sum(F.col("freq") * F.col("words")).over(Window.partitionBy())
    return classes.select("freq", "words", (F.sum("words").over(cum) - F.col("words") + 1).alias("first_rank"), F.dense_rank().over(order).cast("long").alias("class_rank"), F.round(F.sum(F.col("freq") * F.col("words")).over(cum) / total, 8).alias("share"))


def rank_windows(spark: SparkSession, d: str) -> DataFrame:
    freq = tokens.vocabulary(table(spark, d, "documents"), by=["lang"])
    w = Window.partitionBy("lang").orderBy(F.desc("freq"))
    strict = Window.partitionBy("lang").orderBy(F.desc("freq"), "word")
    return freq.select("lang", "word", "freq", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dense"), F.ntile(4).over(strict).cast("long").alias("quarter"), F.round(F.percent_rank().over(w), 8).alias("pct"), F.round(F.cume_dist().over(w), 8).alias("cume"))


def topk_per_lang(spark: SparkSession, d: str) -> DataFrame:
    freq = tokens.vocabulary(table(spark, d, "documents"), by=["lang"])
    w = Window.partitionBy("lang").orderBy(F.desc("freq"), "word")
    return freq.withColumn("rk", F.row_number().over(w)).where("rk <= 10").select("lang", "word", "freq", F.col("rk").cast("long").alias("rk"))


def lag_lead_events(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_id", "user_id", seconds("ts").alias("s"))
    w = Window.partitionBy("user_id").orderBy("s", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return e.select("event_id", (F.col("s") - F.lag("s").over(w)).alias("since"), (F.lead("s").over(w) - F.col("s")).alias("until"), F.first("event_id").over(whole).alias("first_id"), F.last("event_id").over(whole).alias("last_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


def range_frame_events(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_id", "user_id", "value", seconds("ts").alias("s"))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"), F.round(F.sum("value").over(w), 6).alias("total"))


def setops_vocab(spark: SparkSession, d: str) -> DataFrame:
    a, b = _freq(spark, d).select("word"), _freq(spark, d, "conversations").select("word")
    ta, tb = _flat(spark, d).select("word"), _flat(spark, d, "conversations").select("word")
    rows = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b), "union_all": ta.unionAll(tb), "intersect_all": ta.intersectAll(tb), "except_all": ta.exceptAll(tb)}
    out = None
    for name, frame in rows.items():
        one = frame.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def known_semi(spark: SparkSession, d: str) -> DataFrame:
    return _freq(spark, d, "conversations").join(_freq(spark, d).select("word"), "word", "left_semi")


def unseen_anti(spark: SparkSession, d: str) -> DataFrame:
    return _freq(spark, d, "conversations").join(_freq(spark, d).select("word"), "word", "left_anti")


def full_outer_vocab(spark: SparkSession, d: str) -> DataFrame:
    a, b = _freq(spark, d).withColumnRenamed("freq", "in_documents"), _freq(spark, d, "conversations").withColumnRenamed("freq", "in_conversations")
    return a.join(b, "word", "full").na.fill(0)


def theta_join_lengths(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of frequent words with equal first letter and lengths that differ by one at most."""
    f = _freq(spark, d).where("freq >= 400").select("word", F.length("word").alias("n"), F.substring("word", 1, 1).alias("c"))
    a, b = f.alias("a"), f.alias("b")
    return a.join(b, (F.col("a.c") == F.col("b.c")) & (F.abs(F.col("a.n") - F.col("b.n")) <= 1) & (F.col("a.word") < F.col("b.word"))).select(F.col("a.word").alias("left_word"), F.col("b.word").alias("right_word"))


def interval_join_events(spark: SparkSession, d: str) -> DataFrame:
    """Clicks and purchases of a user within the next hour: an equi-join on hour buckets, then the exact bound."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", seconds("ts").alias("s"))
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("s").alias("cs"), F.explode(F.array(F.expr("s div 3600"), F.expr("s div 3600 + 1"))).alias("hour"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("s").alias("ps"), F.expr("s div 3600").alias("hour"))
    return c.join(p, ["user_id", "hour"]).where((F.col("ps") >= F.col("cs")) & (F.col("ps") <= F.col("cs") + 3600)).select("click_id", "purchase_id")


def asof_events(spark: SparkSession, d: str) -> DataFrame:
    """Each purchase with the user's latest earlier click: one sort by user, no join."""
    e = table(spark, d, "events").where("event_type in ('click', 'purchase')").select("event_id", "user_id", "event_type", micros("ts").alias("t"))
    w = Window.partitionBy("user_id").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", last).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "click_id")


def star_join_revenue(spark: SparkSession, d: str) -> DataFrame:
    li, o, c, n, r = (table(spark, d, t) for t in ("lineitem", "orders", "customer", "nation", "region"))
    dims = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_nationkey", "n_name", "r_name")
    flat = li.select("l_orderkey", "l_extendedprice", "l_discount").join(o.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    flat = flat.join(c.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey"))
    return flat.groupBy("r_name", "n_name").agg(F.expr(REVENUE).alias("revenue"), F.count("*").alias("items"))


def part_title_vocab(spark: SparkSession, d: str) -> DataFrame:
    p, li = table(spark, d, "part"), table(spark, d, "lineitem")
    sold = li.groupBy("l_partkey").agg(F.sum(F.expr("l_extendedprice * (1 - l_discount)")).alias("r"), F.count("*").alias("n"))
    titles = p.select("p_partkey", F.explode(F.array_distinct(tokens.words(F.col("p_name")))).alias("word"))
    return titles.join(sold, titles.p_partkey == sold.l_partkey, "left").groupBy("word").agg(F.count("*").alias("titles"), F.sum(F.coalesce("n", F.lit(0))).alias("items"), F.round(F.sum(F.coalesce("r", F.lit(0.0))), 2).alias("revenue"))


def html_text_tokens(spark: SparkSession, d: str) -> DataFrame:
    pages = table(spark, d, "pages")
    text = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " "), r"(?s)<[^>]*>", " ")
    return pages.select("page_id", F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1).alias("title"), F.size(tokens.words(text)).cast("long").alias("n_words"), F.size(F.regexp_extract_all("html", F.lit(r"(href=)"), F.lit(1))).cast("long").alias("links"))


def json_props(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_type", F.from_json("props", "k bigint").alias("p"))
    return e.groupBy("event_type").agg(F.count("p.k").alias("n"), F.sum("p.k").alias("total"), F.min("p.k").alias("least"), F.max("p.k").alias("most"))


def date_buckets(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders")
    return o.groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month")).agg(F.count("*").alias("orders"), F.max(F.quarter("o_orderdate")).cast("long").alias("quarter"), F.max(F.datediff("o_orderdate", F.date_trunc("month", "o_orderdate"))).cast("long").alias("last_day"), F.max(F.add_months(F.date_trunc("month", "o_orderdate").cast("date"), 1)).alias("next_month"))


def dedup_exact(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents")
    return docs.groupBy(F.md5("text").alias("key")).agg(F.count("*").alias("copies"), F.min("doc_id").alias("first_id")).where("copies > 1").select("first_id", "copies")


def tumbling_counts(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(seconds("w.start").alias("start_s"), "event_type", "n")


def sliding_counts(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(seconds("w.start").alias("start_s"), "n")


def session_windows(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.groupBy("user_id", F.session_window("ts", "4 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", micros("w.start").alias("start_us"), "n")


def map_functions(spark: SparkSession, d: str) -> DataFrame:
    """Counts by language as a map, filtered and looked up."""
    counts = _flat(spark, d, "documents", "lang", "source").groupBy("source", "lang").count()
    m = counts.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "count"))).alias("m"))
    big = F.map_filter("m", lambda k, v: v >= 1000)
    return m.select("source", F.size(big).cast("long").alias("big"), F.coalesce(F.element_at("m", F.lit("en")), F.lit(0)).alias("en"))


def sampled_documents(spark: SparkSession, d: str) -> DataFrame:
    """A sampling operator: a tenth of the documents by hash, the same on any plan."""
    return table(spark, d, "documents").where(F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("long") % 10 == 0).select("doc_id", "lang")


def string_agg_words(spark: SparkSession, d: str) -> DataFrame:
    freq = tokens.vocabulary(table(spark, d, "documents"), by=["lang"])
    return freq.groupBy("lang").agg(F.array_join(F.array_sort(F.collect_list("word")), ",").alias("words"))


_W = r"[\p{L}\p{N}]+"


def _tok(cols: str, source: str) -> str:
    return f"SELECT {cols}unnest(regexp_extract_all(lower(text), '{_W}')) AS word FROM {source}"


_DOC, _CON = _tok("", "documents"), _tok("", "conversations")
_LANG, _BOTH = _tok("lang, ", "documents"), _tok("lang, source, ", "documents")
_FD, _FC = (f"SELECT word, count(*) AS freq FROM ({x}) GROUP BY word" for x in (_DOC, _CON))
_FL = f"SELECT lang, word, count(*) AS freq FROM ({_LANG}) GROUP BY ALL"
_STAR = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"

ORACLES: dict[str, str] = {
    "tokens_by_lang": f"SELECT lang, count(*) AS tokens, count(DISTINCT word) AS words FROM ({_LANG}) GROUP BY lang",
    "word_freq": _FD,
    "vocab_grouping_sets": f"SELECT lang, source, count(*) AS tokens, grouping(lang, source) AS gid FROM ({_BOTH}) GROUP BY GROUPING SETS ((lang, source), (lang), (source), ())",
    "rollup_cube": f"SELECT r_name, n_name, NULL::VARCHAR AS c_mktsegment, count(*) AS orders, round(sum(o_totalprice), 2) AS total {_STAR} GROUP BY ROLLUP (r_name, n_name) UNION ALL SELECT r_name, NULL, c_mktsegment, count(*), round(sum(o_totalprice), 2) {_STAR} GROUP BY CUBE (r_name, c_mktsegment)",
    "pivot_tokens": "SELECT source, " + ", ".join(f"count(*) FILTER (lang = '{x}') AS {x}" for x in LANGS) + f" FROM ({_BOTH}) GROUP BY source",
    "zipf_curve": f"WITH f AS (SELECT freq, count(*) AS words FROM ({_FD}) GROUP BY freq) SELECT freq, words, (sum(words) OVER w - words + 1)::BIGINT AS first_rank, dense_rank() OVER (ORDER BY freq DESC) AS class_rank, round(sum(freq * words) OVER w / (SELECT sum(freq * words) FROM f), 8) AS share FROM f WINDOW w AS (ORDER BY freq DESC ROWS UNBOUNDED PRECEDING)",
    "rank_windows": f"WITH f AS (SELECT * FROM ({_FL})) SELECT lang, word, freq, rank() OVER w AS rk, dense_rank() OVER w AS dense, ntile(4) OVER (PARTITION BY lang ORDER BY freq DESC, word) AS quarter, round(percent_rank() OVER w, 8) AS pct, round(cume_dist() OVER w, 8) AS cume FROM f WINDOW w AS (PARTITION BY lang ORDER BY freq DESC)",
    "topk_per_lang": f"SELECT lang, word, freq, row_number() OVER (PARTITION BY lang ORDER BY freq DESC, word) AS rk FROM ({_FL}) QUALIFY rk <= 10",
    "lag_lead_events": "SELECT event_id, s - lag(s) OVER w AS since, lead(s) OVER w - s AS until, first_value(event_id) OVER a AS first_id, last_value(event_id) OVER a AS last_id, nth_value(event_id, 2) OVER a AS second_id FROM (SELECT event_id, user_id, epoch_us(ts) // 1000000 AS s FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY s, event_id), a AS (PARTITION BY user_id ORDER BY s, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "range_frame_events": "SELECT event_id, count(*) OVER w AS n, round(sum(value) OVER w, 6) AS total FROM (SELECT event_id, user_id, value, epoch_us(ts) // 1000000 AS s FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)",
    "setops_vocab": f"WITH ta AS ({_DOC}), tb AS ({_CON}), a AS (SELECT DISTINCT word FROM ta), b AS (SELECT DISTINCT word FROM tb) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'union_all', count(*) FROM (SELECT * FROM ta UNION ALL SELECT * FROM tb) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM ta INTERSECT ALL SELECT * FROM tb) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM ta EXCEPT ALL SELECT * FROM tb)",
    "known_semi": f"SELECT * FROM ({_FC}) WHERE word IN (SELECT word FROM ({_DOC}))",
    "unseen_anti": f"SELECT * FROM ({_FC}) WHERE word NOT IN (SELECT word FROM ({_DOC}))",
    "full_outer_vocab": f"SELECT coalesce(a.word, b.word) AS word, coalesce(a.freq, 0) AS in_documents, coalesce(b.freq, 0) AS in_conversations FROM ({_FD}) a FULL JOIN ({_FC}) b ON a.word = b.word",
    "theta_join_lengths": f"WITH f AS (SELECT word FROM ({_FD}) WHERE freq >= 400) SELECT a.word AS left_word, b.word AS right_word FROM f a JOIN f b ON a.word < b.word AND left(a.word, 1) = left(b.word, 1) AND abs(length(a.word) - length(b.word)) <= 1",
    "interval_join_events": "WITH e AS (SELECT *, epoch_us(ts) // 1000000 AS s FROM events) SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM e c JOIN e p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.s BETWEEN c.s AND c.s + 3600",
    "asof_events": "SELECT event_id AS purchase_id, click_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click_id FROM events WHERE event_type IN ('click', 'purchase')) WHERE event_type = 'purchase'",
    "star_join_revenue": "SELECT r_name, n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS items FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
    "part_title_vocab": f"WITH s AS (SELECT l_partkey, sum(l_extendedprice * (1 - l_discount)) AS r, count(*) AS n FROM lineitem GROUP BY 1), t AS (SELECT p_partkey, unnest(list_distinct(regexp_extract_all(lower(p_name), '{_W}'))) AS word FROM part) SELECT word, count(*) AS titles, sum(coalesce(n, 0))::BIGINT AS items, round(sum(coalesce(r, 0)), 2) AS revenue FROM t LEFT JOIN s ON p_partkey = l_partkey GROUP BY word",
    "html_text_tokens": f"SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, len(regexp_extract_all(lower(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')), '{_W}')) AS n_words, len(regexp_extract_all(html, 'href=')) AS links FROM pages",
    "json_props": "SELECT event_type, count(k) AS n, sum(k)::BIGINT AS total, min(k) AS least, max(k) AS most FROM (SELECT event_type, (props::JSON ->> 'k')::BIGINT AS k FROM events) GROUP BY event_type",
    "date_buckets": "SELECT date_trunc('month', o_orderdate)::DATE AS month, count(*) AS orders, max(quarter(o_orderdate)) AS quarter, max(date_diff('day', date_trunc('month', o_orderdate), date_trunc('day', o_orderdate))) AS last_day, max((date_trunc('month', o_orderdate) + INTERVAL 1 MONTH)::DATE) AS next_month FROM orders GROUP BY 1",
    "dedup_exact": "SELECT min(doc_id) AS first_id, count(*) AS copies FROM documents GROUP BY text HAVING count(*) > 1",
    "tumbling_counts": "SELECT epoch_us(ts) // 3600000000 * 3600 AS start_s, event_type, count(*) AS n FROM events GROUP BY ALL",
    "sliding_counts": "SELECT start_s, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 3600000000 * 3600, epoch_us(ts) // 3600000000 * 3600 - 3600]) AS start_s FROM events) GROUP BY start_s",
    "session_windows": "WITH g AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 14400000000 THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t) AS k FROM g) SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, k",
    "map_functions": f"WITH c AS (SELECT source, lang, count(*) AS n FROM ({_BOTH}) GROUP BY ALL) SELECT source, count(*) FILTER (n >= 1000) AS big, coalesce(max(n) FILTER (lang = 'en'), 0) AS en FROM c GROUP BY source",
    "sampled_documents": "SELECT doc_id, lang FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 4))::BIGINT % 10 = 0",
    "string_agg_words": f"SELECT lang, string_agg(word, ',' ORDER BY word) AS words FROM ({_FL}) GROUP BY lang",
}

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        tokens_by_lang, word_freq, vocab_grouping_sets, rollup_cube, pivot_tokens, approx_vocab, zipf_curve, rank_windows, topk_per_lang, lag_lead_events, range_frame_events,
        setops_vocab, known_semi, unseen_anti, full_outer_vocab, theta_join_lengths, interval_join_events, asof_events, star_join_revenue, part_title_vocab, html_text_tokens,
        json_props, date_buckets, dedup_exact, tumbling_counts, sliding_counts, session_windows, map_functions, sampled_documents, string_agg_words,
    )
}
