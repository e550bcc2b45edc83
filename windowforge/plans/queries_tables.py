"""Relational, scalar and streaming operators a user of the method needs, over the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from windowforge.functions import sql as registered
from windowforge.functions.tokens import count_tokens, tokenize
from windowforge.sources.corpus import corpus, strip_html, table
from windowforge.streaming import stream

QUERIES, ORACLE_SQL = {}, {}
TOKENS = r"regexp_extract_all(text, '\S+')"
N = f"len({TOKENS})"


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return add


def counted(spark, d, *columns: str):
    return table(spark, d, "documents").select("doc_id", *columns, count_tokens(F.col("text")).alias("n"))


# projections, filters


@query(f"SELECT doc_id, lang, {N} AS n FROM documents WHERE lang = 'en' AND doc_id BETWEEN 100 AND 400 AND {N} > 50")
def filter_domain(spark, d):
    rows = table(spark, d, "documents").filter((F.col("lang") == "en") & F.col("doc_id").between(100, 400))
    return rows.select("doc_id", "lang", count_tokens(F.col("text")).alias("n")).filter("n > 50")


@query(f"SELECT doc_id, {N} AS n FROM documents WHERE {N} >= 256 AND {N} < 1024 AND lang IN ('fr', 'de')")
def filter_length_interval(spark, d):
    return counted(spark, d, "lang").filter("n >= 256 AND n < 1024").filter(F.col("lang").isin("fr", "de")).select("doc_id", "n")


@query(f"SELECT CASE WHEN {N} < 100 THEN 'short' WHEN {N} < 1000 THEN 'middle' ELSE 'long' END AS size, count(*) AS documents FROM documents GROUP BY 1")
def case_buckets(spark, d):
    return counted(spark, d).groupBy(F.when(F.col("n") < 100, "short").when(F.col("n") < 1000, "middle").otherwise("long").alias("size")).agg(F.count(F.lit(1)).alias("documents"))


@query("SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 0")
def null_safe_filter(spark, d):
    rows = table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left")
    return rows.filter(F.col("quality").eqNullSafe(F.lit(None)) | (F.col("quality") == 0)).select("doc_id", "quality")


# joins


@query("SELECT o_orderkey, c_name, n_name, round(o_totalprice, 2) AS price FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_totalprice > 400000")
def join_broadcast(spark, d):
    o = table(spark, d, "orders").filter("o_totalprice > 400000")
    return o.join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("o_orderkey", "c_name", "n_name", F.round("o_totalprice", 2).alias("price"))


@query("SELECT l_orderkey, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 4) AS revenue, max(o_custkey) AS o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_totalprice < 20000 GROUP BY 1")
def join_shuffle(spark, d):
    l, o = table(spark, d, "lineitem"), table(spark, d, "orders").filter("o_totalprice < 20000")
    return l.join(o.hint("merge"), l.l_orderkey == o.o_orderkey).groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 4).alias("revenue"), F.max("o_custkey").alias("o_custkey"))


@query("SELECT DISTINCT d.doc_id FROM documents d JOIN labels l USING (doc_id) WHERE l.toxic = 1")
def join_semi(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").filter("toxic = 1"), "doc_id", "left_semi").distinct()


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@query("SELECT coalesce(d.doc_id, v.vec_id) AS id, d.lang, v.label FROM documents d FULL JOIN embeddings v ON d.doc_id = v.vec_id")
def join_full(spark, d):
    a, b = table(spark, d, "documents"), table(spark, d, "embeddings")
    return a.join(b, a.doc_id == b.vec_id, "full").select(F.coalesce("doc_id", "vec_id").alias("id"), "lang", "label")


@query(
    f"""WITH o AS (SELECT doc_id, {N} AS n, sum({N}) OVER (ORDER BY doc_id) - {N} AS b FROM documents WHERE {N} > 0)
    SELECT doc_id, unnest(range((b // 4096)::BIGINT, ((b + n - 1) // 4096)::BIGINT + 1)) AS slot FROM o"""
)
def join_interval(spark, d):
    """Which of the equal slots of a line of tokens each document touches: its slots are written out, so the join is by key."""
    from windowforge.operators.prefix import running

    rows = running(counted(spark, d).filter("n > 0"), F.col("doc_id"), "n", ["doc_id"])
    touched = rows.select("doc_id", F.explode(F.sequence(F.floor(F.col("before") / 4096), F.floor((F.col("before") + F.col("n") - 1) / 4096))).alias("slot"))
    slots = touched.select("slot").distinct()
    return touched.join(slots, "slot").select("doc_id", "slot")


@query("SELECT e.event_id, p.event_id AS last_purchase FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts WHERE e.event_type <> 'purchase'")
def join_asof(spark, d):
    """The latest purchase of the user not after each event: both sides in one line per user, the last one seen carried on."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    p = e.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("p"))
    line = e.filter("event_type <> 'purchase'").select("user_id", "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("long").alias("p")).unionByName(p.select("user_id", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), "p"))
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return line.withColumn("last_purchase", F.last("p", ignorenulls=True).over(w)).filter("side = 1").select("event_id", "last_purchase")


@query(f"SELECT doc_id, w, c FROM (SELECT doc_id, w, count(*) AS c FROM (SELECT doc_id, lower(unnest({TOKENS})) AS w FROM documents WHERE doc_id < 50) GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY c DESC, w) <= 3")
def join_lateral(spark, d):
    table(spark, d, "documents").filter("doc_id < 50").select("doc_id", tokenize(F.lower("text")).alias("ws")).createOrReplaceTempView("_wf_lateral")
    return spark.sql("SELECT doc_id, w, c FROM _wf_lateral, LATERAL (SELECT w, count(*) AS c FROM (SELECT explode(ws) AS w) GROUP BY w ORDER BY c DESC, w LIMIT 3)")


# aggregations


@query(f"SELECT lang, source, count(*) AS documents, sum({N})::BIGINT AS tokens FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup_domain(spark, d):
    return counted(spark, d, "lang", "source").rollup("lang", "source").agg(F.count(F.lit(1)).alias("documents"), F.sum("n").alias("tokens"))


@query("SELECT quality, toxic, count(*) AS documents FROM labels GROUP BY CUBE (quality, toxic)")
def agg_cube(spark, d):
    return table(spark, d, "labels").cube("quality", "toxic").agg(F.count(F.lit(1)).alias("documents"))


@query("SELECT lang, source, count(*) AS documents FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark, d):
    rows = table(spark, d, "documents").select("lang", "source")
    return rows.groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(F.count(F.lit(1)).alias("documents"))


@query("SELECT lang, count(*) AS documents, count(DISTINCT text) AS texts FROM documents GROUP BY 1")
def agg_distinct_text(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("documents"), F.count_distinct(F.sha2("text", 256)).alias("texts"))


@query(f"SELECT lang, round(quantile_cont({N}, 0.5), 6) AS p50, round(quantile_cont({N}, 0.9), 6) AS p90, max({N}) AS longest, arg_max(doc_id, ({N}, -doc_id)) AS longest_doc, round(stddev_samp({N}), 6) AS spread FROM documents GROUP BY 1")
def agg_percentiles(spark, d):
    return counted(spark, d, "lang").groupBy("lang").agg(F.round(F.percentile("n", 0.5), 6).alias("p50"), F.round(F.percentile("n", 0.9), 6).alias("p90"), F.max("n").alias("longest"), F.max_by("doc_id", F.struct("n", -F.col("doc_id"))).alias("longest_doc"), F.round(F.stddev("n"), 6).alias("spread"))


@query()
def agg_approximate(spark, d):
    rows = table(spark, d, "documents")
    n = count_tokens(F.col("text"))
    return rows.groupBy("lang").agg(F.approx_count_distinct("text").alias("texts"), F.percentile_approx(n, 0.5).alias("p50"), F.round(F.skewness(n), 3).alias("skewness"))


# windows


@query(f"SELECT doc_id, row_number() OVER w AS place, rank() OVER w AS rank_, dense_rank() OVER w AS dense, round(percent_rank() OVER w, 6) AS share FROM (SELECT doc_id, lang, {N} AS n FROM documents) WINDOW w AS (PARTITION BY lang ORDER BY n DESC, doc_id)")
def win_rank_tokens(spark, d):
    w = Window.partitionBy("lang").orderBy(F.desc("n"), "doc_id")
    return counted(spark, d, "lang").select("doc_id", F.row_number().over(w).alias("place"), F.rank().over(w).alias("rank_"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("share"))


@query(f"SELECT doc_id, (sum({N}) OVER (PARTITION BY lang ORDER BY doc_id))::BIGINT AS running FROM documents")
def win_running_tokens(spark, d):
    w = Window.partitionBy("lang").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return counted(spark, d, "lang").select("doc_id", F.sum("n").over(w).alias("running"))


@query(f"WITH t AS (SELECT doc_id, unnest(x) AS w, unnest(range(len(x))) AS i FROM (SELECT doc_id, list_transform({TOKENS}, lambda t: lower(t)) AS x FROM documents)) SELECT a, b, count(*) AS c FROM (SELECT lag(w) OVER (PARTITION BY doc_id ORDER BY i) AS a, w AS b FROM t) WHERE a IS NOT NULL GROUP BY ALL HAVING count(*) >= 5")
def win_lag_bigram(spark, d):
    words = table(spark, d, "documents").select("doc_id", F.posexplode(F.transform(tokenize(F.col("text")), lambda x: F.lower(x))).alias("i", "b"))
    w = Window.partitionBy("doc_id").orderBy("i")
    return words.select(F.lag("b").over(w).alias("a"), "b").filter("a IS NOT NULL").groupBy("a", "b").agg(F.count(F.lit(1)).alias("c")).filter("c >= 5")


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) AS hour_value FROM events")
def win_range_events(spark, d):
    """Seconds are rounded, halves to even, as the cast of the SQL rounds them; cutting them off moves events over the edge of the hour."""
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return table(spark, d, "events").withColumn("s", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")).select("event_id", F.round(F.sum("value").over(w), 4).alias("hour_value"))


@query(f"SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n, doc_id) AS quarter FROM (SELECT doc_id, lang, {N} AS n FROM documents)")
def win_ntile_length(spark, d):
    return counted(spark, d, "lang").select("doc_id", F.ntile(4).over(Window.partitionBy("lang").orderBy("n", "doc_id")).alias("quarter"))


@query(f"SELECT doc_id, round({N} / sum({N}) OVER (PARTITION BY source), 6) AS share FROM documents")
def win_share(spark, d):
    return counted(spark, d, "source").select("doc_id", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("source")), 6).alias("share"))


# order, top-k


@query(f"SELECT doc_id, {N} AS n FROM documents ORDER BY n DESC, doc_id LIMIT 10")
def top_longest(spark, d):
    return counted(spark, d).orderBy(F.desc("n"), "doc_id").limit(10)


@query(f"SELECT lang, doc_id, {N} AS n FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY {N} DESC, doc_id) <= 5")
def top_k_per_domain(spark, d):
    return counted(spark, d, "lang").withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "doc_id"))).filter("k <= 5").select("lang", "doc_id", "n")


@query("SELECT doc_id, lang FROM documents ORDER BY doc_id OFFSET 20")
def sort_offset(spark, d):
    return table(spark, d, "documents").select("doc_id", "lang").orderBy("doc_id").offset(20)


@query("SELECT lang, count(*) AS documents, min(doc_id) AS first FROM documents GROUP BY 1")
def sort_within(spark, d):
    rows = table(spark, d, "documents").select("lang", "doc_id").repartition("lang").sortWithinPartitions("lang", "doc_id")
    return rows.groupBy("lang").agg(F.count(F.lit(1)).alias("documents"), F.min("doc_id").alias("first"))


# sets


@query("SELECT 'documents' AS domain, count(*) AS rows_ FROM documents UNION ALL SELECT 'pages', count(*) FROM pages UNION ALL SELECT 'conversations', count(DISTINCT conv_id) FROM conversations UNION ALL SELECT 'benchmark', count(*) FROM benchmark")
def set_union_corpus(spark, d):
    return corpus(spark, d).groupBy("domain").agg(F.count(F.lit(1)).alias("rows_"))


@query("SELECT doc_id FROM documents EXCEPT SELECT vec_id FROM embeddings")
def set_except_coverage(spark, d):
    return table(spark, d, "documents").select("doc_id").exceptAll(table(spark, d, "embeddings").select(F.col("vec_id").alias("doc_id")))


@query(f"SELECT w FROM (SELECT unnest({TOKENS}) AS w FROM benchmark) INTERSECT SELECT w FROM (SELECT unnest({TOKENS}) AS w FROM documents)")
def set_intersect_benchmark(spark, d):
    words = lambda name: table(spark, d, name).select(F.explode(tokenize(F.col("text"))).alias("w"))
    return words("benchmark").intersect(words("documents"))


# functions


@query(r"SELECT doc_id, md5(trim(regexp_replace(lower(text), '[^a-z0-9]+', ' ', 'g'))) AS clean, length(text) AS chars, instr(text, 'e') AS first_e, replace(substr(text, 1, 5), chr(10), '_') AS head FROM documents")
def fn_string_clean(spark, d):
    text = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.md5(F.trim(F.regexp_replace(F.lower(text), "[^a-z0-9]+", " "))).alias("clean"), F.length(text).cast("long").alias("chars"), F.instr(text, "e").cast("long").alias("first_e"), F.translate(F.substr(text, F.lit(1), F.lit(5)), "\n", "_").alias("head"))


@query(
    r"""SELECT page_id, length(t) AS chars, md5(t) AS digest FROM (SELECT page_id, trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''),
    '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g')) AS t FROM pages)"""
)
def fn_html_strip(spark, d):
    return table(spark, d, "pages").select("page_id", strip_html(F.col("html")).alias("t")).select("page_id", F.length("t").cast("long").alias("chars"), F.md5("t").alias("digest"))


@query("SELECT event_type, count(*) AS events, sum((props->>'$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY 1")
def fn_json_props(spark, d):
    return table(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).groupBy("event_type").agg(F.count(F.lit(1)).alias("events"), F.sum("k").alias("k"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_trunc('month', o_orderdate)::DATE AS month_, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate::TIMESTAMP) AS days FROM orders")
def fn_date_parts(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.year(o).cast("long").alias("y"), F.month(o).cast("long").alias("m"), F.trunc(o, "month").alias("month_"), F.datediff(o, F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("SELECT vec_id, round(list_sum(embedding::DOUBLE[]), 6) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_max(embedding)::DOUBLE, 6) AS largest, round((embedding[1] + embedding[2])::DOUBLE, 5) AS head FROM embeddings")
def fn_array_fold(spark, d):
    v = F.col("embedding")
    return table(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x), 6).alias("total"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.array_max(v).cast("double"), 6).alias("largest"), F.round((v[0] + v[1]).cast("double"), 5).alias("head"))


@query("SELECT n_nationkey, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def fn_map_pairs(spark, d):
    regions = table(spark, d, "region").agg(F.map_from_entries(F.collect_list(F.struct("r_regionkey", "r_name"))).alias("m"))
    return table(spark, d, "nation").crossJoin(F.broadcast(regions)).select("n_nationkey", F.element_at("m", F.col("n_regionkey")).alias("r_name"))


@query("SELECT o_orderkey, step, round(CASE WHEN step < 1000 THEN step * 3e-7 ELSE 1.5e-4 * (1 + cos(pi() * least(1, (step - 1000) / 3087.0))) END, 12) AS lr FROM (SELECT o_orderkey::BIGINT AS o_orderkey, o_orderkey::BIGINT % 4200 AS step FROM orders)")
def fn_sql_registered(spark, d):
    registered.register_all(spark)
    steps = table(spark, d, "orders").select(F.col("o_orderkey").cast("long").alias("o_orderkey"), (F.col("o_orderkey").cast("long") % 4200).alias("step"))
    return spark.sql("SELECT o_orderkey, step, round(wf_lr(step, 4087), 12) AS lr FROM {steps}", steps=steps)


@query(
    f"""WITH t AS (SELECT doc_id, {TOKENS} AS x FROM documents), s AS (SELECT doc_id, x, unnest(range(greatest(1, ceil(len(x) / 512.0)::BIGINT))) AS seg_no FROM t)
    SELECT doc_id, seg_no, seg_no * 512 AS start, len(list_slice(x, seg_no * 512 + 1, seg_no * 512 + 512)) AS n FROM s"""
)
def fn_segments_udtf(spark, d):
    registered.register_all(spark)
    table(spark, d, "documents").select("doc_id", tokenize(F.col("text")).alias("x")).createOrReplaceTempView("_wf_tokens")
    return spark.sql("SELECT doc_id, seg_no, start, size(tokens) AS n FROM _wf_tokens, LATERAL wf_segments(x, 512)")


# batch twins of the streams


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS events, round(sum(value), 4) AS value FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return stream.tumbling(table(spark, d, "events")).withColumn("value", F.round("value", 4))


@query("SELECT s AS start, event_type, count(*) AS events FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS s, event_type FROM events) GROUP BY ALL")
def stream_sliding(spark, d):
    return stream.sliding(table(spark, d, "events"))


@query(
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS n FROM events),
    s AS (SELECT user_id, ts, sum(n) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
    SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS end_, count(*) AS events FROM s GROUP BY user_id, k"""
)
def stream_session(spark, d):
    return stream.sessions(table(spark, d, "events")).withColumnRenamed("end", "end_")


@query("SELECT event_type, count(DISTINCT event_id) AS events FROM events GROUP BY 1")
def stream_dedup(spark, d):
    e = table(spark, d, "events")
    return stream.deduplicated(e.unionByName(e.filter("event_id % 3 = 0"))).groupBy("event_type").agg(F.count(F.lit(1)).alias("events"))


@query("SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_join(spark, d):
    e = table(spark, d, "events")
    views = e.filter("event_type = 'view'").select("user_id", F.col("ts").alias("lts"), F.col("event_id").alias("view_id"))
    buys = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("rts"), F.col("event_id").alias("purchase_id"))
    return stream.interval_join(views, buys, "user_id").select("view_id", "purchase_id")
