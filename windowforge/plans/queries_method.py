"""Queries of the method and its baselines over the given tables, with the SQL they are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.functions import vec as V
from windowforge.functions.schedule import batch, learning_rate
from windowforge.functions.tokens import count_tokens, segment
from windowforge.operators import assign as A
from windowforge.operators import baselines as B
from windowforge.operators import density as D
from windowforge.operators import embed, isodata, materialize, mixture, objective, pack, project, stats
from windowforge.plans import organize as P
from windowforge.session import settled
from windowforge.sources.corpus import corpus, table

L, SEED, DELTA = 1024, 7, 0.25
QUERIES, ORACLE_SQL = {}, {}


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return add


def docs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents")


def embeddings(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.col("vec_id").cast("string").alias("seg_id"), F.col("embedding").alias("vec"))


def segments(spark: SparkSession, d: str, window: int = L, overlong: str = "split") -> DataFrame:
    return segment(docs(spark, d).select("doc_id", "text", "lang"), window, overlong)


def r6(c, name: str):
    return F.round(c, 6).alias(name)


TOKENS = r"regexp_extract_all(text, '\S+')"
SEG = f"""tk AS (SELECT doc_id, lang, {TOKENS} AS tokens FROM documents),
    sg AS (SELECT doc_id, lang, tokens, unnest(range(greatest(1, ceil(len(tokens) / {L}.0)::BIGINT))) AS seg_no FROM tk),
    seg AS (SELECT doc_id || ':' || seg_no AS seg_id, doc_id, lang, seg_no, list_slice(tokens, seg_no * {L} + 1, (seg_no + 1) * {L}) AS toks,
                   len(list_slice(tokens, seg_no * {L} + 1, (seg_no + 1) * {L})) AS n_tokens FROM sg)"""
EMB = "e AS (SELECT vec_id::VARCHAR AS seg_id, embedding::DOUBLE[] AS v FROM embeddings)"
UNIT = f"{EMB}, u AS (SELECT seg_id, list_transform(v, lambda x: x / sqrt(list_sum(list_transform(v, lambda y: y * y)))) AS v FROM e)"
SUBSET = "('0x' || substr(md5('7:' || seg_id), 1, 7))::BIGINT % {n}"


def seeds_sql(k: int) -> str:
    return f"c AS (SELECT seg_id AS cluster_id, v AS cv FROM u ORDER BY md5('{SEED}:' || seg_id), seg_id LIMIT {k})"


ASSIGN = "a AS (SELECT seg_id, cluster_id, round(list_dot_product(v, cv), 12) AS cos FROM u, c QUALIFY row_number() OVER (PARTITION BY seg_id ORDER BY round(list_dot_product(v, cv), 12) DESC, cluster_id) = 1)"


# tokens and segments


@query(f"SELECT doc_id, len({TOKENS}) AS n_tokens, len(regexp_extract_all(text, '[\\p{{L}}\\p{{N}}]+')) AS n_words FROM documents")
def token_counts(spark, d):
    return docs(spark, d).select("doc_id", count_tokens(F.col("text")).alias("n_tokens"), count_tokens(F.col("text"), "word").alias("n_words"))


@query(f"WITH {SEG} SELECT seg_id, doc_id, seg_no, seg_no * {L} AS start, n_tokens, md5(array_to_string(toks, ' ')) AS digest FROM seg")
def segment_split(spark, d):
    return segments(spark, d).select("seg_id", "doc_id", "seg_no", "start", "n_tokens", F.md5(F.array_join("tokens", " ")).alias("digest"))


@query(f"SELECT doc_id, least(len({TOKENS}), {L}) AS n_tokens, greatest(len({TOKENS}) - {L}, 0) AS lost FROM documents")
def segment_truncate(spark, d):
    return segments(spark, d, overlong="truncate").select("doc_id", "n_tokens", (F.col("doc_tokens") - F.col("n_tokens")).alias("lost"))


@query(
    " UNION ALL ".join(
        f"SELECT {w} AS window, sum(len({TOKENS}))::BIGINT AS tokens, sum(greatest(len({TOKENS}) - {w}, 0))::BIGINT AS lost, count(*) FILTER (len({TOKENS}) > {w}) AS documents_cut, round(sum(greatest(len({TOKENS}) - {w}, 0)) / sum(len({TOKENS})), 6) AS share FROM documents"
        for w in (1024, 2048, 4096)
    )
)
def truncation_loss(spark, d):
    rows = docs(spark, d).select(count_tokens(F.col("text")).alias("n"), F.explode(F.array(*[F.lit(w) for w in (1024, 2048, 4096)])).alias("window"))
    lost = F.greatest(F.col("n") - F.col("window"), F.lit(0))
    return rows.groupBy("window").agg(F.sum("n").alias("tokens"), F.sum(lost).alias("lost"), F.count_if(lost > 0).alias("documents_cut"), r6(F.sum(lost) / F.sum("n"), "share"))


# domains


def domain_sql(rows: str, domain: str) -> str:
    return f"SELECT {domain} AS domain, max(n)::BIGINT AS max_len, min(n)::BIGINT AS min_len, round(avg(n), 6) AS avg_len, count(*) AS documents, sum(n)::BIGINT AS tokens FROM ({rows}) GROUP BY 1"


def _counted(spark, d):
    return docs(spark, d).select("lang", "source", count_tokens(F.col("text")).alias("n_tokens"))


@query(domain_sql(f"SELECT lang, len({TOKENS}) AS n FROM documents", "lang"))
def domain_stats_lang(spark, d):
    return stats.domain_stats(_counted(spark, d), "lang").withColumn("avg_len", F.round("avg_len", 6))


@query(domain_sql(f"SELECT source, len({TOKENS}) AS n FROM documents", "source"))
def domain_stats_source(spark, d):
    return stats.domain_stats(_counted(spark, d), "source").withColumn("avg_len", F.round("avg_len", 6))


STRIPPED = r"""trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g'))"""
CORPUS = f"""SELECT 'documents' AS domain, text FROM documents UNION ALL SELECT 'pages', {STRIPPED} FROM pages
    UNION ALL SELECT 'conversations', string_agg(role || ': ' || text, chr(10) ORDER BY turn) FROM conversations GROUP BY conv_id UNION ALL SELECT 'benchmark', text FROM benchmark"""


@query(domain_sql(f"SELECT domain, len({TOKENS}) AS n FROM ({CORPUS})", "domain"))
def domain_stats_corpus(spark, d):
    return stats.domain_stats(corpus(spark, d).select("domain", count_tokens(F.col("text")).alias("n_tokens")), "domain").withColumn("avg_len", F.round("avg_len", 6))


EDGES = [256, 1024, 2048, 4096]
INTERVAL = "CASE WHEN n < 256 THEN '<256' WHEN n < 1024 THEN '256-1024' WHEN n < 2048 THEN '1024-2048' WHEN n < 4096 THEN '2048-4096' ELSE '>=4096' END"


@query(
    f"""WITH t AS (SELECT lang AS domain, {INTERVAL} AS interval, count(*) AS documents FROM (SELECT lang, len({TOKENS}) AS n FROM documents) GROUP BY ALL)
    SELECT domain, interval, documents, round(documents / sum(documents) OVER (PARTITION BY domain), 6) AS share,
           round(sum(CASE WHEN interval = '>=4096' THEN documents ELSE 0 END) OVER (PARTITION BY domain) / sum(documents) OVER (PARTITION BY domain), 6) AS longest_share FROM t"""
)
def length_mix(spark, d):
    return stats.length_mix(_counted(spark, d), "lang", EDGES).withColumns({c: F.round(c, 6) for c in ("share", "longest_share")})


@query(f"SELECT lang AS domain, sum(len({TOKENS}))::BIGINT AS tokens, round(sum(len({TOKENS})) / sum(sum(len({TOKENS}))) OVER (), 6) AS share FROM documents GROUP BY 1")
def domain_share(spark, d):
    return stats.domain_share(_counted(spark, d), "lang").withColumn("share", F.round("share", 6))


@query(f"SELECT e AS edge, round(avg((len({TOKENS}) < e)::INT), 6) AS share FROM documents, (SELECT unnest([256, 1024, 2048, 4096, 16384]) AS e) GROUP BY 1")
def short_doc_share(spark, d):
    rows = _counted(spark, d).select("n_tokens", F.explode(F.array(*[F.lit(e) for e in [*EDGES, 16384]])).alias("edge"))
    return rows.groupBy("edge").agg(r6(F.avg((F.col("n_tokens") < F.col("edge")).cast("double")), "share"))


# vectors

BUCKET = "('0x' || substr(md5(lower(t)), 1, 7))::BIGINT % 1024"


@query(f"WITH {SEG}, t AS (SELECT seg_id, unnest(toks) AS t FROM seg) SELECT seg_id, {BUCKET} AS b, count(*) AS tf FROM t GROUP BY ALL")
def hash_buckets(spark, d):
    return embed.hash_sparse(segments(spark, d)).select("seg_id", "b", "tf")


WEIGHTED = f"""{SEG}, t AS (SELECT seg_id, unnest(toks) AS t FROM seg), tf AS (SELECT seg_id, {BUCKET} AS b, count(*) AS tf FROM t GROUP BY ALL),
    df AS (SELECT b, count(*) AS df FROM tf GROUP BY b), w AS (SELECT seg_id, b, tf * (1 + ln(((SELECT count(*) FROM seg) + 1) / (df + 1))) AS w FROM tf JOIN df USING (b)),
    hv AS (SELECT seg_id, b, w / sqrt(sum(w * w) OVER (PARTITION BY seg_id)) AS w FROM w)"""


@query(f"WITH {WEIGHTED} SELECT seg_id, count(*) AS nonzero, round(max(w), 4) AS largest, round(sum(w), 3) AS total FROM hv GROUP BY 1")
def hash_norms(spark, d):
    v = embed.hash_embed(segments(spark, d)).filter(F.exists("vec", lambda x: x != 0))
    return v.select("seg_id", F.size(F.filter("vec", lambda x: x != 0)).cast("long").alias("nonzero"), F.round(F.array_max("vec").cast("double"), 4).alias("largest"), F.round(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double")), 3).alias("total"))


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm, round(list_dot_product(embedding::DOUBLE[], (SELECT embedding::DOUBLE[] FROM embeddings WHERE vec_id = 0)), 6) AS to_first FROM embeddings")
def embedding_norms(spark, d):
    e = table(spark, d, "embeddings")
    first = e.filter("vec_id = 0").select(F.col("embedding").alias("f"))
    return e.crossJoin(F.broadcast(first)).select("vec_id", r6(V.norm(F.col("embedding")), "norm"), r6(V.dot(F.col("embedding"), F.col("f")), "to_first"))


@query(f"WITH {SEG} SELECT seg_id, doc_id, label, round(list_sum(embedding::DOUBLE[]), 6) AS total FROM seg JOIN embeddings ON doc_id = vec_id")
def doc_vec_join(spark, d):
    s, e = segments(spark, d).select("seg_id", "doc_id"), table(spark, d, "embeddings")
    v = embed.given(s, e).select("seg_id", r6(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x.cast("double")), "total"))
    return s.join(v, "seg_id").join(e.select(F.col("vec_id").alias("doc_id"), "label"), "doc_id").select("seg_id", "doc_id", "label", "total")


@query("SELECT label, i AS at, round(avg(x::DOUBLE), 6) AS mean FROM (SELECT label, unnest(embedding) AS x, unnest(range(64)) AS i FROM embeddings) GROUP BY ALL")
def agg_vector_mean(spark, d):
    rows = table(spark, d, "embeddings").select(F.col("label").cast("string").alias("label"), "embedding")
    s = V.sum_native(rows, ["label"], "embedding").select("label", F.posexplode("vec").alias("at", "x"), "n")
    return s.select(F.col("label").cast("int").alias("label"), F.col("at").cast("long").alias("at"), r6(F.col("x") / F.col("n"), "mean"))


# density


def density_sql(mode: str, n: int) -> str:
    mean = "(list_sum(list_transform(s, lambda x: x * x)) - m) / (m * (m - 1))"
    rho = {"printed": f"2 * {mean}", "mean_cosine": mean, "mean_dissimilarity": f"1 - {mean}"}[mode]
    return f"""{UNIT}, s AS (SELECT seg_id, {SUBSET.format(n=n)} AS subset_id, v FROM u), x AS (SELECT subset_id, i, sum(y) AS y FROM (SELECT subset_id, unnest(v) AS y, unnest(range(len(v))) AS i FROM s) GROUP BY ALL),
        z AS (SELECT subset_id, list(y) AS s FROM x GROUP BY 1), r AS (SELECT subset_id, m, {rho} AS rho FROM z JOIN (SELECT subset_id, count(*) AS m FROM s GROUP BY 1) USING (subset_id))"""


def _density(mode: str, n: int):
    def run(spark, d):
        return D.subset_density(D.split(embeddings(spark, d), n, SEED), mode).select("subset_id", "m", r6(F.col("rho"), "rho"))

    def count(spark, d):
        return D.initial_clusters(embeddings(spark, d), n, mode, SEED).select("documents", r6(F.col("mean_rho"), "mean_rho"), "raw", "n_clusters")

    run.__name__, count.__name__ = f"subset_density_{mode}_{n}", f"initial_clusters_{mode}_{n}"
    query(f"WITH {density_sql(mode, n)} SELECT subset_id, m, round(rho, 6) AS rho FROM r")(run)
    query(
        f"WITH {density_sql(mode, n)} SELECT sum(m)::BIGINT AS documents, round(avg(rho), 6) AS mean_rho, floor(round(sum(m) * avg(rho), 9))::BIGINT AS raw, greatest(1, least(floor(round(sum(m) * avg(rho), 9))::BIGINT, sum(m)::BIGINT)) AS n_clusters FROM r"
    )(count)


for _mode in ("printed", "mean_cosine", "mean_dissimilarity"):
    for _n in (4, 10, 20):
        _density(_mode, _n)


@query(
    f"""WITH {UNIT}, s AS (SELECT seg_id, {SUBSET.format(n=10)} AS subset_id, v FROM u)
    SELECT subset_id, m, round(coalesce(2 * p / (m * (m - 1)), 0), 6) AS rho FROM (SELECT subset_id, count(*) AS m FROM s GROUP BY 1)
    LEFT JOIN (SELECT a.subset_id, sum(list_dot_product(a.v, b.v)) AS p FROM s a JOIN s b ON a.subset_id = b.subset_id AND a.seg_id < b.seg_id GROUP BY 1) USING (subset_id)"""
)
def subset_density_pairs(spark, d):
    return D.subset_density_pairs(D.split(embeddings(spark, d), 10, SEED)).select("subset_id", "m", r6(F.col("rho"), "rho"))


TEXT_SUBSET = "('0x' || substr(md5('7:' || seg_id), 1, 7))::BIGINT % 4"


@query(
    f"""WITH {WEIGHTED}, s AS (SELECT {TEXT_SUBSET} AS subset_id, b, sum(w) AS w FROM hv GROUP BY ALL), m AS (SELECT {TEXT_SUBSET} AS subset_id, count(*) AS m FROM seg GROUP BY 1)
    SELECT subset_id, m, round((q - nz) / (m * (m - 1)), 5) AS rho FROM (SELECT subset_id, sum(w * w) AS q FROM s GROUP BY 1) JOIN m USING (subset_id) JOIN (SELECT {TEXT_SUBSET} AS subset_id, count(DISTINCT seg_id) AS nz FROM hv GROUP BY 1) USING (subset_id)"""
)
def subset_density_text(spark, d):
    v = embed.hash_embed(segments(spark, d))
    return D.subset_density(D.split(v, 4, SEED)).select("subset_id", "m", F.round("rho", 5).alias("rho"))


# clustering, a round at a time over the given vectors


@query(f"WITH {UNIT}, {seeds_sql(20)} SELECT cluster_id, round(list_sum(cv), 6) AS total FROM c")
def seed_sample(spark, d):
    return isodata.seed(embeddings(spark, d), 20, SEED).select("cluster_id", r6(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x), "total"))


def _assigned(spark, d, how="exact", k=20):
    e = embeddings(spark, d)
    return e, isodata.seed(e, k, SEED), A.assign(e, isodata.seed(e, k, SEED), how)


@query(f"WITH {UNIT}, {seeds_sql(20)}, {ASSIGN} SELECT seg_id, cluster_id, round(cos, 6) AS cos FROM a")
def assign_exact(spark, d):
    return _assigned(spark, d)[2].select("seg_id", "cluster_id", r6(F.col("cos"), "cos"))


@query(ORACLE_SQL["assign_exact"])
def assign_nested_loop(spark, d):
    e = embeddings(spark, d)
    return A.exact_sql(e, isodata.seed(e, 20, SEED)).select("seg_id", "cluster_id", r6(F.col("cos"), "cos"))


def _text_vectors(spark, d):
    return settled(embed.hash_embed(segments(spark, d), 256), "text-vectors")


def _approximate(how: str):
    def run(spark, d):
        v = _text_vectors(spark, d)
        c = settled(isodata.seed(v, 64, SEED), "text-centres")
        found = settled(A.assign(v, c, how), "approximate")
        return A.recall(found, A.exact(v, c)).crossJoin(found.agg(r6(F.avg("evals"), "evals"))).select("documents", r6(F.col("recall"), "recall"), "never_above", "evals")

    run.__name__ = f"assign_{how}"
    query()(run)


for _how in ("hnsw", "cells", "lsh"):
    _approximate(_how)

SPAWNED = f"{UNIT}, {seeds_sql(20)}, {ASSIGN}, m AS (SELECT seg_id, CASE WHEN cos > {DELTA} THEN cluster_id ELSE 'r1/' || seg_id END AS cluster_id, CASE WHEN cos > {DELTA} THEN cos ELSE 1.0 END AS cos, NOT cos > {DELTA} AS spawned FROM a)"


@query(f"WITH {SPAWNED} SELECT seg_id, cluster_id, round(cos, 6) AS cos, spawned FROM m")
def spawned(spark, d):
    return isodata.spawn(_assigned(spark, d)[2], DELTA, False, "r1").select("seg_id", "cluster_id", r6(F.col("cos"), "cos"), "spawned")


CENTRED = f"""{SPAWNED}, x AS (SELECT cluster_id, i, avg(y) AS y, count(*) AS n FROM (SELECT cluster_id, unnest(v) AS y, unnest(range(len(v))) AS i FROM m JOIN e USING (seg_id)) GROUP BY ALL),
    k AS (SELECT cluster_id, list(y ORDER BY i) AS kv, max(n) AS n FROM x GROUP BY 1)"""


@query(
    f"""WITH {CENTRED} SELECT cluster_id, n, round(coalesce(sqrt(list_sum(list_transform(list_zip(kv, o.v), lambda p: (p[1] - p[2]) * (p[1] - p[2])))), 0), 6) AS shift, round(list_sum(kv), 6) AS total
    FROM k LEFT JOIN (SELECT c.cluster_id, e.v FROM c JOIN e ON c.cluster_id = e.seg_id) o USING (cluster_id)"""
)
def recenter(spark, d):
    e, c, a = _assigned(spark, d)
    out = isodata.recenter(isodata.spawn(a, DELTA, False, "r1"), e, c)
    return out.select("cluster_id", "n", r6(F.col("shift"), "shift"), r6(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x), "total"))


NORMED = f"{CENTRED}, q AS (SELECT cluster_id, list_transform(kv, lambda x: x / sqrt(list_dot_product(kv, kv))) AS qv FROM k), g AS (SELECT a.cluster_id AS a, b.cluster_id AS b, round(list_dot_product(a.qv, b.qv), 12) AS cos FROM q a JOIN q b ON a.cluster_id < b.cluster_id AND round(list_dot_product(a.qv, b.qv), 12) > 0.35)"


def _centred(spark, d):
    e, c, a = _assigned(spark, d)
    return settled(isodata.recenter(settled(isodata.spawn(a, DELTA, False, "r1"), "spawned"), e, c), "centred")


@query(f"WITH {NORMED} SELECT a, b, round(cos, 6) AS cos FROM g")
def merge_edges(spark, d):
    return isodata.merge_edges(_centred(spark, d), 0.35).select("a", "b", r6(F.col("cos"), "cos"))


@query(
    f"""WITH RECURSIVE {NORMED}, h AS (SELECT a, b FROM g UNION ALL SELECT b, a FROM g), w(n, r) AS (SELECT cluster_id, cluster_id FROM k UNION SELECT h.b, w.r FROM w JOIN h ON w.n = h.a)
    SELECT n AS cluster_id, min(r) AS root FROM w GROUP BY 1"""
)
def merge_components(spark, d):
    c = _centred(spark, d)
    return isodata.components(isodata.merge_edges(c, 0.35), c)


@query(
    f"""WITH {NORMED}, h AS (SELECT a, b, cos FROM g UNION ALL SELECT b, a, cos FROM g), f AS (SELECT a, b FROM h QUALIFY row_number() OVER (PARTITION BY a ORDER BY cos DESC, b) = 1)
    SELECT cluster_id, coalesce(least(x.a, x.b), cluster_id) AS root FROM k LEFT JOIN (SELECT x.a, x.b FROM f x JOIN f y ON x.a = y.b AND x.b = y.a) x ON x.a = cluster_id"""
)
def merge_mutual_best(spark, d):
    c = _centred(spark, d)
    return isodata.mutual_best(isodata.merge_edges(c, 0.35), c)


def _clustered(spark, d, **changes):
    done = isodata.fit(embeddings(spark, d), Config(delta=DELTA, n_clusters=20, rounds=3, assign="exact").with_(**changes))
    return done


@query()
def isodata_clusters(spark, d):
    return _clustered(spark, d).membership.select("seg_id", "cluster_id", r6(F.col("cos"), "cos"))


@query()
def isodata_trace(spark, d):
    return _clustered(spark, d).trace


@query()
def isodata_mutual_best(spark, d):
    return _clustered(spark, d, merge="mutual_best", delta=0.35, finalize=True).trace


@query()
def isodata_classic(spark, d):
    return isodata.classic(embeddings(spark, d), 20, rounds=3, seed_=SEED).trace


# packing


def text_config(**changes) -> Config:
    """Hashed text vectors: many seeds, mergers without chains, a last pass that gives every document its nearest centre."""
    return Config(window=L, delta=0.2, dim=256, rounds=3, assign="exact", merge="mutual_best", n_clusters=30, finalize=True).with_(**changes)


def _by_lang(spark, d):
    """Members with the language as the cluster: a clustering that SQL can follow."""
    s = segments(spark, d)
    v = embed.hash_embed(s, 256)
    return s.select(F.col("lang").alias("cluster_id"), "seg_id", "doc_id", "seg_no", "n_tokens").join(v, "seg_id")


@query(f"WITH {SEG} SELECT lang AS cluster_id, sum(n_tokens)::BIGINT AS tokens, greatest(1, ceil(sum(n_tokens) / {L}.0)::BIGINT) AS n_windows FROM seg GROUP BY 1")
def window_budget(spark, d):
    return pack.window_budget(segments(spark, d).withColumnRenamed("lang", "cluster_id"), L)


@query(f"WITH {SEG} SELECT lang AS cluster_id, seg_id, row_number() OVER (PARTITION BY lang ORDER BY n_tokens DESC, doc_id, seg_no) AS place FROM seg")
def pack_order(spark, d):
    return pack.order(segments(spark, d).withColumnRenamed("lang", "cluster_id")).select("cluster_id", "seg_id", "place")


@query(
    f"""WITH {SEG}, t AS (SELECT seg_id, n_tokens, doc_id % 1200 - 100 AS remaining, (doc_id % 7) / 7.0 AS cos FROM seg)
    SELECT seg_id, round(cos + remaining / {L}.0 + CASE WHEN n_tokens <= remaining THEN 1.0 ELSE {L}.0 / ({L} + n_tokens - remaining) END, 6) AS score FROM t"""
)
def pack_score(spark, d):
    rows = segments(spark, d).select("seg_id", "n_tokens", (F.col("doc_id") % 1200 - 100).alias("remaining"), ((F.col("doc_id") % 7) / 7.0).alias("cos"))
    return rows.select("seg_id", r6(pack.score(F.col("cos"), F.col("remaining"), F.col("n_tokens"), L), "score"))


@query(
    f"""WITH RECURSIVE {SEG}, o AS (SELECT seg_id, n_tokens, row_number() OVER (ORDER BY n_tokens DESC, doc_id, seg_no) AS k FROM seg WHERE lang = 'es'),
    s(k, seg_id, slot, rem, sc) AS (
        SELECT 0::BIGINT, '', 0::BIGINT, list_transform(range((SELECT greatest(1, ceil(sum(n_tokens) / {L}.0)::BIGINT) FROM o)), lambda i: {L}::BIGINT), 0.0::DOUBLE
        UNION ALL
        SELECT k, seg_id, slot, list_transform(range(len(rem)), lambda i: CASE WHEN i + 1 = slot THEN rem[i + 1] - n ELSE rem[i + 1] END), f[slot]
        FROM (SELECT *, list_position(f, list_max(f)) AS slot FROM (
            SELECT o.k, o.seg_id, s.rem, o.n_tokens AS n, list_transform(s.rem, lambda r: CASE WHEN r < 0 THEN -1.0 ELSE round(r / {L}.0 + {L}.0 / ({L} + greatest(o.n_tokens - r, 0)), 12) END) AS f FROM s JOIN o ON o.k = s.k + 1)))
    SELECT seg_id, slot - 1 AS window_no, round(sc, 6) AS score FROM s WHERE k > 0"""
)
def pack_by_size(spark, d):
    """alpha = 0: free share and penalty alone, on one cluster."""
    m = pack.pack(_by_lang(spark, d).filter("cluster_id = 'es'"), text_config(alpha=0.0))
    return m.select("seg_id", F.substring_index("window_id", "|", -1).cast("long").alias("window_no"), r6(F.col("score"), "score"))


@query()
def pack_manifest(spark, d):
    return pack.pack(_by_lang(spark, d), text_config()).withColumn("score", F.round("score", 6))


@query(f"WITH {SEG} SELECT lang AS cluster_id, count(*) AS placed, sum(n_tokens)::BIGINT AS tokens, count(DISTINCT seg_id) AS distinct_segments FROM seg GROUP BY 1")
def pack_coverage(spark, d):
    return pack.pack(_by_lang(spark, d), text_config()).groupBy("cluster_id").agg(F.count(F.lit(1)).alias("placed"), (F.sum("used") + F.sum("cut")).alias("tokens"), F.count_distinct("seg_id").alias("distinct_segments"))


def _manifest_row(spark, d, label: str, manifest: DataFrame):
    return objective.counts(objective.per_window(manifest, L), L).select(F.lit(label).alias("variant"), *[F.round(c, 6).alias(c) for c in ("members", "single_share", "fill", "cross_attention", "cut_share", "homogeneity")], "windows", "violating")


@query()
def weight_sweep(spark, d):
    """All on or off combinations of the three weights over clusters by language."""
    m, out = settled(_by_lang(spark, d), "sweep"), None
    for a in (0.0, 1.0):
        for b in (0.0, 1.0):
            for c in (0.0, 1.0):
                row = _manifest_row(spark, d, f"{a:.0f}{b:.0f}{c:.0f}", pack.pack(m, text_config(alpha=a, beta=b, lam=c)))
                out = row if out is None else out.unionByName(row)
    return out


@query()
def pack_without_clusters(spark, d):
    """One cluster of everything: what the coarse step saves."""
    m = _by_lang(spark, d).withColumn("cluster_id", F.lit("all"))
    return _manifest_row(spark, d, "one cluster", pack.pack(m, text_config()))


@query()
def pack_backfilled(spark, d):
    return _manifest_row(spark, d, "backfilled", pack.pack(_by_lang(spark, d), text_config(backfill=True)))


@query()
def window_first(spark, d):
    return _manifest_row(spark, d, "window first", B.window_first(_by_lang(spark, d).filter("cluster_id = 'es'"), text_config()))


# baselines

CHOPPED = f"""{SEG}, o AS (SELECT seg_id, doc_id, n_tokens, sum(n_tokens) OVER (ORDER BY md5('{SEED}:' || seg_id), seg_id) - n_tokens AS b FROM seg WHERE n_tokens > 0),
    p AS (SELECT *, unnest(range((b // {L})::BIGINT, ((b + n_tokens - 1) // {L})::BIGINT + 1)) AS w FROM o),
    rm AS (SELECT 'random|' || lpad(w::VARCHAR, 12, '0') AS window_id, seg_id, doc_id, n_tokens, greatest(w * {L} - b, 0)::BIGINT AS start, greatest(b - w * {L}, 0)::BIGINT AS off, (least((w + 1) * {L} - b, n_tokens) - greatest(w * {L} - b, 0))::BIGINT AS used FROM p)"""


def _random(spark, d):
    s = segments(spark, d)
    return s, B.random_windows(s, L, SEED)


@query(f"WITH {CHOPPED} SELECT window_id, row_number() OVER (PARTITION BY window_id ORDER BY off) - 1 AS pos, seg_id, start, off AS offset_, n_tokens, used FROM rm")
def random_manifest(spark, d):
    return _random(spark, d)[1].select("window_id", "pos", "seg_id", "start", F.col("offset").alias("offset_"), "n_tokens", "used")


@query(
    f"""WITH {SEG}, o AS (SELECT seg_id, lang, n_tokens, sum(n_tokens) OVER (PARTITION BY lang ORDER BY md5('{SEED}:' || seg_id), seg_id) - n_tokens AS b FROM seg WHERE n_tokens > 0),
    p AS (SELECT *, unnest(range((b // {L})::BIGINT, ((b + n_tokens - 1) // {L})::BIGINT + 1)) AS w FROM o)
    SELECT 'random|' || lang || '|' || lpad(w::VARCHAR, 12, '0') AS window_id, seg_id, (least((w + 1) * {L} - b, n_tokens) - greatest(w * {L} - b, 0))::BIGINT AS used FROM p"""
)
def random_by_domain(spark, d):
    return B.random_windows(segments(spark, d), L, SEED, within="lang").select("window_id", "seg_id", "used")


@query(f"WITH {SEG} SELECT 'single|' || seg_id AS window_id, seg_id, n_tokens AS used, {L} - n_tokens AS pad FROM seg")
def single_manifest(spark, d):
    return B.single_windows(segments(spark, d), L).select("window_id", "seg_id", "used", (F.lit(L) - F.col("used")).alias("pad"))


@query(
    f"""WITH {UNIT}, x AS (SELECT a.seg_id AS src, b.seg_id AS dst, round(list_dot_product(a.v, b.v), 12) AS w FROM u a JOIN u b ON a.seg_id <> b.seg_id)
    SELECT src, dst, round(w, 6) AS w FROM x QUALIFY row_number() OVER (PARTITION BY src ORDER BY x.w DESC, dst) <= 20"""
)
def knn_graph_exact(spark, d):
    return B.knn_graph(embeddings(spark, d), 20, "exact").select("src", "dst", r6(F.col("w"), "w"))


def _knn(how: str):
    def run(spark, d):
        v = _text_vectors(spark, d)
        truth, found = B.knn_graph(v, 20, "exact"), B.knn_graph(v, 20, how)
        hit = truth.select("src", "dst").join(found.select("src", "dst", F.lit(1).alias("hit")), ["src", "dst"], "left")
        return hit.agg(F.count(F.lit(1)).alias("edges"), r6(F.avg(F.coalesce("hit", F.lit(0))), "recall"))

    run.__name__ = f"knn_graph_{how}"
    query()(run)


for _how in ("cells", "lsh"):
    _knn(_how)


def _text_prepared(spark, d, config: Config = None, where: str | None = None) -> P.Prepared:
    rows = docs(spark, d)
    return P.prepare(rows.filter(where) if where else rows, config or text_config())


@query()
def graph_paths(spark, d):
    return P.graph_paths(_text_prepared(spark, d))


@query()
def graph_manifest(spark, d):
    p = _text_prepared(spark, d)
    return B.graph_windows(p.segments, P.graph_paths(p), L)


@query()
def retrieval_manifest(spark, d):
    p = _text_prepared(spark, d)
    return B.retrieval_windows(p.segments, settled(B.knn_graph(p.vectors, 20), "edges"), L)


def _fit(rule: str):
    def run(spark, d):
        return _manifest_row(spark, d, rule, B.fit_decreasing(segments(spark, d), L, rule))

    run.__name__ = f"fit_{rule}"
    query()(run)


for _rule in ("first", "best", "worst"):
    _fit(_rule)


# windows and steps


@query(
    f"""WITH {CHOPPED} SELECT window_id, count(DISTINCT doc_id) AS n_docs, sum(used)::BIGINT AS n_tokens, {L} - sum(used)::BIGINT AS pad,
    md5(string_agg(array_to_string(list_slice(toks, start + 1, start + used), ' '), ' ' ORDER BY off)) AS digest FROM rm JOIN (SELECT seg_id, toks FROM seg) USING (seg_id) GROUP BY 1"""
)
def windows_materialized(spark, d):
    s, m = _random(spark, d)
    return materialize.windows(m, s, L).select("window_id", "n_docs", F.col("n_tokens").cast("long").alias("n_tokens"), F.col("pad").cast("long").alias("pad"), F.md5(F.array_join("tokens", " ")).alias("digest"))


@query(f"WITH {CHOPPED}, w AS (SELECT DISTINCT window_id FROM rm) SELECT window_id, (row_number() OVER (ORDER BY md5('{SEED}:' || window_id), window_id) - 1) // 28 AS step FROM w")
def training_steps(spark, d):
    return batch(_random(spark, d)[1].select("window_id").distinct(), L, 28 * L, SEED).select("window_id", "step")


@query(
    """SELECT o_orderkey, step, round(CASE WHEN step < 1000 THEN step * 3e-7 ELSE 1.5e-4 * (1 + cos(pi() * least((step - 1000) / (4087.0 - 1000), 1))) END, 12) AS lr
    FROM (SELECT o_orderkey::BIGINT AS o_orderkey, o_orderkey::BIGINT % 4200 AS step FROM orders)"""
)
def lr_schedule(spark, d):
    """The rate of the step that an order's number falls on."""
    rows = table(spark, d, "orders").select(F.col("o_orderkey").cast("long").alias("o_orderkey"), (F.col("o_orderkey").cast("long") % 4200).alias("step"))
    return rows.select("o_orderkey", "step", F.round(learning_rate(F.col("step"), 4087), 12).alias("lr"))


@query(
    f"""WITH {SEG}, o AS (SELECT lang, seg_id, n_tokens, sum(n_tokens) OVER (PARTITION BY lang ORDER BY md5('{SEED}:' || seg_id), seg_id) - n_tokens AS b FROM seg)
    SELECT lang, seg_id, n_tokens FROM o WHERE b < 50000 * CASE lang WHEN 'en' THEN 0.6 WHEN 'fr' THEN 0.2 WHEN 'de' THEN 0.1 WHEN 'es' THEN 0.1 END"""
)
def domain_mix(spark, d):
    return mixture.mix(segments(spark, d), "lang", {"en": 0.6, "fr": 0.2, "de": 0.1, "es": 0.1}, 50_000, seed=SEED).select("lang", "seg_id", "n_tokens")


@query()
def organize_one_domain(spark, d):
    return P.organize_domain(docs(spark, d), "lang", "fr", text_config())


# measures

WINDOWS = f"{CHOPPED}, pw AS (SELECT window_id, count(*) AS members, sum(used)::BIGINT AS used, sum(used * (used + 1))::BIGINT AS sq FROM rm GROUP BY 1)"


@query(
    f"""WITH {WINDOWS} SELECT count(*) AS windows, round(avg(members), 6) AS members, max(members) AS most_members, round(avg((members = 1)::INT), 6) AS single_share, round((sum(used) / ({L}.0 * count(*)))::DOUBLE, 6) AS fill,
    round(avg(1 - sq / (used::DOUBLE * (used + 1))), 6) AS cross_attention, round(sum({L}.0::DOUBLE / members), 6) AS homogeneity, round((count(*) * {L}.0 * {L})::DOUBLE, 6) AS attention_padded, round(sum(used::DOUBLE * (used + 1) / 2), 6) AS attention_causal,
    round(sum((used::DOUBLE * (used + 1) - sq) / 2), 6) AS attention_across FROM pw"""
)
def measures_random(spark, d):
    row = objective.counts(objective.per_window(_random(spark, d)[1], L), L)
    return row.select("windows", r6(F.col("members"), "members"), "most_members", *[r6(F.col(c), c) for c in ("single_share", "fill", "cross_attention", "homogeneity", "attention_padded", "attention_causal", "attention_across")])


@query(
    f"""WITH {UNIT}, s AS (SELECT seg_id, {SUBSET.format(n=50)} AS w, v FROM u) SELECT w AS window_id, docs, round(coalesce(r, 0), 6) AS relevance FROM (SELECT w, count(*) AS docs FROM s GROUP BY 1)
    LEFT JOIN (SELECT a.w, sum(list_dot_product(a.v, b.v)) AS r FROM s a JOIN s b ON a.w = b.w AND a.seg_id <> b.seg_id GROUP BY 1) USING (w)"""
)
def relevance_pairs(spark, d):
    rows = embeddings(spark, d).select(D.subset(F.col("seg_id"), 50, SEED).alias("window_id"), "vec")
    return objective.relevance(rows).select("window_id", "docs", r6(F.col("relevance"), "relevance"))


@query(
    f"""WITH {UNIT}, s AS (SELECT seg_id, {SUBSET.format(n=50)} AS w, v FROM u), p AS (SELECT a.w, sum(list_dot_product(a.v, b.v)) AS r, count(*) AS n FROM s a JOIN s b ON a.w = b.w AND a.seg_id <> b.seg_id GROUP BY 1)
    SELECT round(avg(r / n), 6) AS window_mean, round(sum(r) / sum(n), 6) AS pair_mean FROM p"""
)
def mean_cosine_pairs(spark, d):
    rows = embeddings(spark, d).select(D.subset(F.col("seg_id"), 50, SEED).alias("window_id"), "vec")
    return objective.mean_cosine(objective.relevance(rows)).select(r6(F.col("window_mean"), "window_mean"), r6(F.col("pair_mean"), "pair_mean"))


@query(
    f"""WITH {SEG}, g AS (SELECT doc_id // 5 AS w, count(*) AS members, sum(n_tokens)::BIGINT AS total FROM seg GROUP BY 1)
    SELECT 'printed' AS mode, round({L}.0 / sum(members) - 1, 6) AS penalty FROM g UNION ALL SELECT 'per_window_length', round(sum(CASE WHEN total <= {L} THEN 1.0 ELSE {L}.0 / total - 1 END), 6) FROM g"""
)
def penalty_modes(spark, d):
    m = segments(spark, d).select((F.floor(F.col("doc_id") / 5)).cast("string").alias("window_id"), F.col("n_tokens").alias("used"), F.lit(0).alias("cut"))
    w = objective.per_window(m, L)
    rows = [objective.penalty_of(w, L, mode).select(F.lit(mode).alias("mode"), r6(F.col("penalty"), "penalty")) for mode in ("printed", "per_window_length")]
    return rows[0].unionByName(rows[1])


@query(f"WITH {SEG} SELECT doc_id // 5 AS w, sum(n_tokens)::BIGINT AS total, sum(n_tokens)::BIGINT - {L} AS excess FROM seg GROUP BY 1 HAVING sum(n_tokens) > {L} + 64")
def violations(spark, d):
    m = segments(spark, d).select(F.floor(F.col("doc_id") / 5).alias("window_id"), F.col("n_tokens").alias("used"), F.lit(0).alias("cut"))
    return objective.violations(objective.per_window(m, L), L, 64).select(F.col("window_id").alias("w"), "total", "excess")


@query(f"WITH {SEG} SELECT doc_id, round((0.5 * (doc_id % 10) + 2.0 * count(*) + 0.25 * max(n_tokens))::DOUBLE, 6) AS objective FROM seg GROUP BY 1")
def scalarised(spark, d):
    rows = segments(spark, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("segments"), F.max("n_tokens").alias("longest")).withColumn("r", F.col("doc_id") % 10)
    return objective.scalarise(rows, {"r": 0.5, "segments": 2.0, "longest": 0.25}).select("doc_id", r6(F.col("objective"), "objective"))


@query(
    """WITH s AS (SELECT label, count(*) AS size FROM embeddings GROUP BY 1) SELECT count(*) AS clusters, max(size) AS largest, min(size) AS smallest, round(avg(size), 6) AS mean, round(median(size), 6) AS median,
    count(*) FILTER (size < 100) AS below, count(*) FILTER (size = 1) AS single, round(count(*) FILTER (size < 100) / count(*), 6) AS below_share, round(count(*) FILTER (size = 1) / count(*), 6) AS single_share FROM s"""
)
def cluster_stats_labels(spark, d):
    t = stats.cluster_table(stats.cluster_sizes(table(spark, d, "embeddings"), "label"))
    return t.withColumns({c: F.round(c, 6) for c in ("mean", "median", "below_share", "single_share")})


@query()
def cluster_stats_framework(spark, d):
    done = isodata.fit(_text_prepared(spark, d).vectors, text_config())
    return stats.cluster_table(stats.cluster_sizes(done.membership))


@query()
def cluster_stats_graph(spark, d):
    return stats.cluster_table(stats.cluster_sizes(P.graph_paths(_text_prepared(spark, d)), "path_id"))


@query()
def window_report(spark, d):
    return P.compared(docs(spark, d), text_config())


def _report(window: int):
    def run(spark, d):
        return P.compared(docs(spark, d), text_config(window=window))

    run.__name__ = f"window_report_{window}"
    query()(run)


for _w in (2048, 4096):
    _report(_w)


@query()
def delta_sweep(spark, d):
    p, out = _text_prepared(spark, d), None
    for delta in (0.3, 0.5):
        for how in ("components", "mutual_best"):
            c = text_config(delta=delta, merge=how)
            done = P.organize(docs(spark, d), c, p)
            row = objective.counts(objective.per_window(done.manifest, L), L).select(F.lit(delta).alias("delta"), F.lit(how).alias("merge"), "windows", "members", "fill").crossJoin(stats.cluster_table(stats.cluster_sizes(done.clustering.membership)).select("clusters", "largest", "single"))
            out = row if out is None else out.unionByName(row)
    return out


@query()
def cohesion_framework(spark, d):
    p = _text_prepared(spark, d)
    return stats.cohesion(p.vectors, isodata.fit(p.vectors, text_config()).centroids)


@query()
def cohesion_graph(spark, d):
    """The same with the graph's paths as clusters."""
    p = _text_prepared(spark, d)
    sums = D.vector_sums(P.graph_paths(p).select("seg_id", F.col("path_id").cast("string").alias("cluster_id")).join(p.vectors, "seg_id"), "cluster_id", unit=False)
    return stats.cohesion(p.vectors, settled(sums.select("cluster_id", V.scale(F.col("vec"), 1 / F.col("n")).alias("vec"), "n"), "path-centres"))


@query()
def isolation_framework(spark, d):
    done = P.organize(docs(spark, d), text_config())
    return stats.isolation(stats.cluster_sizes(done.clustering.membership), done.manifest, done.clustering.membership)


@query()
def isolation_graph(spark, d):
    p = _text_prepared(spark, d)
    paths = P.graph_paths(p)
    return stats.isolation(stats.cluster_sizes(paths, "path_id"), B.graph_windows(p.segments, paths, L), paths, "path_id")


@query()
def tsne_framework(spark, d):
    p = _text_prepared(spark, d, where="lang = 'en'")
    done = isodata.fit(p.vectors, text_config())
    return project.tsne(p.vectors, 300, iters=150).join(done.membership.select("seg_id", "cluster_id"), "seg_id")


@query()
def tsne_graph(spark, d):
    """The map of all English segments, each with the path that it lies on."""
    p = _text_prepared(spark, d, where="lang = 'en'")
    return project.tsne_whole(p.vectors).join(P.graph_paths(p).select("seg_id", "path_id"), "seg_id")


@query()
def pca_map(spark, d):
    return project.pca(embeddings(spark, d), 500).select("seg_id", r6(F.col("x"), "x"), r6(F.col("y"), "y"))
