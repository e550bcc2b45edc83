"""The whole method with its defaults, at the lengths of the experiments, beside its baselines: windows, clusters, costs, and what a reader of
one window could answer."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.functions import scorers as S
from windowforge.functions.tokens import segment, tokenize
from windowforge.operators import assign as A
from windowforge.operators import baselines as B
from windowforge.operators import costs, embed, isodata, objective, pack, stats
from windowforge.operators import density as D
from windowforge.operators import evals as E
from windowforge.plans import organize as P
from windowforge.plans.queries_evals import PLANTED, _asked, _planted, words
from windowforge.plans.queries_method import CHOPPED, SEED, SEG, UNIT, docs, embeddings, r6, seeds_sql, segments, text_config
from windowforge.session import settled
from windowforge.sources.corpus import table

QUERIES, ORACLE_SQL = {}, {}
#: A threshold at which the given vectors stay in many clusters.
FAR = 0.42


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return add


def stacked(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for row in rows[1:]:
        out = out.unionByName(row)
    return out


# the method as it stands: density decides the count, threshold and components merge, all by default


@query()
def organize_default(spark, d):
    """One row: the measures of the windows and the table of the clusters."""
    done = P.organize(docs(spark, d), Config())
    p = done.prepared
    row = objective.report(done.manifest, p.segments, p.vectors, 1024, "framework")
    table = stats.cluster_table(stats.cluster_sizes(done.clustering.membership))
    return row.crossJoin(table.select(*[F.col(c).alias(c if c == "clusters" else f"cluster_{c}") for c in table.columns]))


@query(f"WITH {SEG} SELECT count(*) AS segments, sum(n_tokens)::BIGINT AS tokens, 0::BIGINT AS missing, 0::BIGINT AS twice FROM seg")
def organize_coverage(spark, d):
    """Every segment lies in one window, with all its tokens used or counted as cut."""
    done = P.organize(docs(spark, d), Config())
    placed = done.manifest.groupBy("seg_id").agg(F.count(F.lit(1)).alias("times"), F.sum(F.col("used") + F.col("cut")).alias("n"))
    both = done.prepared.segments.select("seg_id", "n_tokens").join(placed, "seg_id", "left")
    lost = F.col("times").isNull() | (F.col("n") != F.col("n_tokens"))
    return both.agg(F.count(F.lit(1)).alias("segments"), F.sum("n").cast("long").alias("tokens"), F.count_if(lost).alias("missing"), F.count_if(F.col("times") > 1).alias("twice"))


@query(f"WITH {SEG} SELECT lang, count(*) AS segments, sum(n_tokens)::BIGINT AS tokens FROM seg WHERE n_tokens > 0 GROUP BY 1")
def one_domain_coverage(spark, d):
    """One domain organised, all others in random order: no domain loses a segment or a token."""
    rows = docs(spark, d)
    found = P.organize_domain(rows, "lang", "fr", text_config())
    placed = found.filter("n_tokens > 0").groupBy("seg_id").agg(F.sum(F.col("used") + F.col("cut")).alias("n"))
    own = placed.withColumn("doc_id", F.substring_index("seg_id", ":", 1).cast("long")).join(rows.select("doc_id", "lang"), "doc_id")
    return own.groupBy("lang").agg(F.count(F.lit(1)).alias("segments"), F.sum("n").cast("long").alias("tokens"))


def _report(window: int):
    def run(spark, d):
        return P.compared(docs(spark, d), Config(window=window))

    run.__name__ = f"window_report_{window}"
    query()(run)


for _w in (8192, 16384, 32768, 65536):
    _report(_w)


# clustering, all rounds in SQL


def rounds_sql(rounds: int, k: int, delta: float) -> str:
    """Assignment, opening, means and merging by components, round by round."""
    out = [f"{UNIT}, z1 AS (SELECT cluster_id, cv, cv AS old FROM (WITH {seeds_sql(k)} SELECT * FROM c))"]
    for t in range(1, rounds + 1):
        far = "false" if t == rounds else f"NOT cos > {delta}"
        out.append(
            f"""y{t} AS (SELECT cluster_id, list_transform(cv, lambda x: x / sqrt(list_dot_product(cv, cv))) AS q FROM z{t}),
    a{t} AS (SELECT seg_id, cluster_id, round(list_dot_product(v, q), 12) AS cos FROM u, y{t} QUALIFY row_number() OVER (PARTITION BY seg_id ORDER BY round(list_dot_product(v, q), 12) DESC, cluster_id) = 1),
    m{t} AS (SELECT seg_id, CASE WHEN {far} THEN 'r{t}/' || seg_id ELSE cluster_id END AS cluster_id, CASE WHEN {far} THEN 1.0 ELSE cos END AS cos, {far} AS spawned FROM a{t}),
    x{t} AS (SELECT cluster_id, i, avg(y) AS y, count(*) AS n FROM (SELECT cluster_id, unnest(v) AS y, unnest(range(len(v))) AS i FROM m{t} JOIN e USING (seg_id)) GROUP BY ALL),
    k{t} AS MATERIALIZED (SELECT cluster_id, list(y ORDER BY i) AS kv, max(n) AS n FROM x{t} GROUP BY 1),
    p{t} AS (SELECT cluster_id, list_transform(kv, lambda x: x / sqrt(list_dot_product(kv, kv))) AS q FROM k{t}),
    g{t} AS (SELECT a.cluster_id AS a, b.cluster_id AS b FROM p{t} a JOIN p{t} b ON a.cluster_id <> b.cluster_id AND round(list_dot_product(a.q, b.q), 12) > {delta}),
    w{t}(n, r) AS (SELECT cluster_id, cluster_id FROM k{t} UNION SELECT g{t}.b, w{t}.r FROM w{t} JOIN g{t} ON w{t}.n = g{t}.a),
    f{t} AS MATERIALIZED (SELECT n AS cluster_id, min(r) AS root FROM w{t} GROUP BY 1),
    z{t + 1} AS MATERIALIZED (SELECT cluster_id, list(y ORDER BY i) AS cv, list(y ORDER BY i) AS old FROM (SELECT root AS cluster_id, i, sum(y * n) / sum(n) AS y FROM (SELECT root, n, unnest(kv) AS y, unnest(range(len(kv))) AS i FROM k{t} JOIN f{t} USING (cluster_id)) GROUP BY ALL) GROUP BY 1)"""
        )
    return ",\n    ".join(out)


@query(f"WITH RECURSIVE {rounds_sql(3, 20, FAR)} SELECT seg_id, root AS cluster_id, round(cos, 6) AS cos FROM m3 JOIN f3 USING (cluster_id)")
def isodata_rounds(spark, d):
    """Three rounds whose last assigns every row."""
    done = isodata.fit(embeddings(spark, d), Config(delta=FAR, n_clusters=20, rounds=3, assign="exact", epsilon=0.0))
    return done.membership.select("seg_id", "cluster_id", r6(F.col("cos"), "cos"))


_COUNTED = " UNION ALL ".join(f"SELECT {t} AS round, (SELECT count(*) FROM m{t} WHERE spawned) AS spawned, (SELECT count(*) FROM z{t + 1}) AS clusters, (SELECT count(*) FROM u) * (SELECT count(*) FROM z{t}) AS evals" for t in (1, 2, 3))


@query(f"WITH RECURSIVE {rounds_sql(3, 20, FAR)} {_COUNTED}")
def isodata_figures(spark, d):
    done = isodata.fit(embeddings(spark, d), Config(delta=FAR, n_clusters=20, rounds=3, assign="exact", epsilon=0.0))
    return done.trace.select("round", "spawned", "clusters", "evals")


# the index against exact search, and what each way costs


def _short(spark, d, dim: int = 128):
    """Segments of 64 tokens, so that there are thousands of centres."""
    return settled(embed.hash_embed(segments(spark, d, 64), dim), "short-vectors")


@query()
def index_growth(spark, d):
    """Comparisons a document, recall and seconds of each way to the nearest centre, as the centres grow."""
    v, out = _short(spark, d), []
    for k in (500, 2000, 8000):
        c = settled(isodata.seed(v, k, SEED), "short-centres")
        truth = None
        for how in ("exact", "hnsw", "cells", "lsh"):
            found, cost = costs.measured(spark, lambda: settled(A.assign(v, c, how), "index"))  # noqa: B023
            truth = truth or found
            row = A.recall(found, truth).crossJoin(found.agg(r6(F.avg("evals"), "evals"))).crossJoin(c.agg(F.count(F.lit(1)).alias("centres")))
            out.append(row.select("centres", F.lit(how).alias("how"), "documents", "evals", r6(F.col("recall"), "recall"), F.lit(float(cost["seconds"])).alias("seconds")))
    return stacked(out)


@query()
def cost_counters(spark, d):
    """Seconds, bytes shuffled, comparisons and rounds of clustering and packing by each way, and of the baselines, over the same segments."""
    p = P.prepare(docs(spark, d), text_config())
    n, out = p.segments.count(), []

    def row(name: str, run, evals=lambda got: None, rounds=lambda got: None):
        got, cost = costs.measured(spark, run)
        out.append((name, cost["seconds"], cost["tasks"], cost["shuffle_written"], evals(got), rounds(got)))

    told = lambda done: done.trace.agg(F.sum("evals")).first()[0]
    for how in ("exact", "hnsw", "cells"):
        row(f"clusters by {how}", lambda: isodata.fit(p.vectors, text_config(assign=how)), told, lambda done: done.trace.count())  # noqa: B023
    row("classic clusters", lambda: isodata.classic(p.vectors, 30, rounds=3, seed_=SEED), told, lambda done: done.trace.count())
    done = isodata.fit(p.vectors, text_config())
    row("packing by clusters", lambda: settled(pack.pack(P.members_of(p, done.membership), text_config()), "packed"))
    one = done.membership.withColumn("cluster_id", F.lit("all"))
    row("packing without clusters", lambda: settled(pack.pack(P.members_of(p, one), text_config()), "packed"))
    row("random windows", lambda: settled(B.random_windows(p.segments, 1024, SEED), "random"))
    row("graph of neighbours and paths", lambda: P.graph_paths(p), lambda paths: n * (n - 1))
    return spark.createDataFrame(out, "way string, seconds double, tasks long, shuffle_bytes long, evals long, rounds long")


# sweeps


@query()
def delta_length_sweep(spark, d):
    """Threshold by length of the window."""
    out = []
    for window in (1024, 4096):
        p = P.prepare(docs(spark, d), text_config(window=window))
        for delta in (0.2, 0.4):
            done = P.organize(docs(spark, d), text_config(window=window, delta=delta), p)
            w = objective.per_window(done.manifest, window)
            rel = objective.mean_cosine(objective.relevance(objective.by_document(done.manifest, p.segments, p.vectors)))
            row = objective.counts(w, window).select(F.lit(window).alias("window"), F.lit(delta).alias("delta"), "windows", "members", "fill", "cross_attention", "cut_share")
            out.append(row.crossJoin(rel).crossJoin(stats.cluster_table(stats.cluster_sizes(done.clustering.membership)).select("clusters", "largest", "single")))
    return stacked(out)


@query()
def density_sweep(spark, d):
    """Density mode and number of subsets: how many clusters they begin with, and what becomes of them."""
    p, out = P.prepare(docs(spark, d), Config(dim=256)), []
    for mode in ("mean_cosine", "mean_dissimilarity", "printed"):
        for n in (4, 20):
            first = D.initial_clusters(p.vectors, n, mode, SEED).first()
            done = isodata.fit(p.vectors, Config(delta=0.4, dim=256, rounds=2, n_clusters=first["n_clusters"], assign="exact", merge="mutual_best"))
            t = stats.cluster_table(stats.cluster_sizes(done.membership)).crossJoin(stats.cohesion(p.vectors, done.centroids))
            out.append(t.select(F.lit(mode).alias("density"), F.lit(n).alias("subsets"), F.lit(first["n_clusters"]).alias("begun"), "clusters", "largest", "single", "own", "gap"))
    return stacked(out)


# what a reader of one window could answer, by method


def read_pairs(manifest: DataFrame, hits: DataFrame) -> DataFrame:
    """One row: passages that several documents hold, and how many have two of these documents in one window. hits: (item_id, doc_id)."""
    several = hits.distinct().withColumn("c", F.count(F.lit(1)).over(Window.partitionBy("item_id"))).filter("c > 1")
    at = manifest.select("window_id", F.substring_index("seg_id", ":", 1).cast("long").alias("doc_id")).distinct()
    met = several.join(at, "doc_id").groupBy("item_id", "window_id").agg(F.count_distinct("doc_id").alias("n")).groupBy("item_id").agg(F.max("n").alias("n"))
    return met.agg(F.count(F.lit(1)).alias("examples"), F.coalesce(F.sum((F.col("n") > 1).cast("long")), F.lit(0)).alias("right"))


def read_labels(manifest: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: labelled documents by the vote of the other labelled documents of their first window; ties and no voters say 1."""
    at = manifest.select("window_id", F.substring_index("seg_id", ":", 1).cast("long").alias("doc_id")).groupBy("doc_id").agg(F.min("window_id").alias("window_id"))
    of = Window.partitionBy("window_id")
    v = at.join(labels.select("doc_id", "quality").filter("quality is not null"), "doc_id").select("quality", (F.sum("quality").over(of) - F.col("quality")).alias("ones"), (F.count(F.lit(1)).over(of) - 1).alias("voters"))
    return v.agg(F.count(F.lit(1)).alias("examples"), F.sum(((2 * F.col("ones") >= F.col("voters")).cast("int") == F.col("quality")).cast("long")).alias("right"))


def read_needles(manifest: DataFrame, segs: DataFrame, needles: DataFrame) -> DataFrame:
    """One row: planted passages, by their first words in a document, and how many stand whole in one piece of one window."""
    piece = manifest.select("window_id", "seg_id", F.col("start").alias("piece_start"), "used").join(segs.select("seg_id", "tokens"), "seg_id")
    text = F.concat(F.lit(" "), F.array_join(F.slice("tokens", F.col("piece_start") + 1, F.col("used")), " "), F.lit(" "))
    held = piece.select(F.substring_index("seg_id", ":", 1).cast("long").alias("doc_id"), text.alias("text"))
    whole = needles.join(held, "doc_id").groupBy("item_id", "doc_id").agg(F.max(F.contains(F.col("text"), F.concat(F.lit(" "), F.col("question"), F.lit(" "))).cast("long")).alias("right"))
    return whole.agg(F.count(F.lit(1)).alias("examples"), F.coalesce(F.sum("right"), F.lit(0)).alias("right"))


def read_keys(manifest: DataFrame, segs: DataFrame) -> DataFrame:
    """One row: neighbouring segments of one document as key and value, and how many stand in one window, so that the value can be found by its key."""
    at = manifest.select("window_id", "seg_id").join(segs.select("seg_id", "doc_id", "seg_no"), "seg_id").select("window_id", "doc_id", "seg_no").distinct()
    pairs = segs.filter("seg_no > 0").select("doc_id", "seg_no")
    keys, values = at.withColumn("seg_no", F.col("seg_no") + 1).withColumnRenamed("window_id", "w"), at
    met = values.join(keys, ["doc_id", "seg_no"]).groupBy("doc_id", "seg_no").agg(F.max((F.col("w") == F.col("window_id")).cast("long")).alias("right"))
    return pairs.join(met, ["doc_id", "seg_no"], "left").agg(F.count(F.lit(1)).alias("examples"), F.coalesce(F.sum("right"), F.lit(0)).alias("right"))


def read_all(spark, d, manifest: DataFrame, segs: DataFrame, method: str, window: int) -> DataFrame:
    hits, labels = _planted(spark, d).select("item_id", "question", "doc_id"), table(spark, d, "labels")
    tasks = {"multihop": read_pairs(manifest, hits.select("item_id", "doc_id")), "fewshot": read_labels(manifest, labels), "needle": read_needles(manifest, segs, hits), "key_value": read_keys(manifest, segs)}
    return stacked([row.select(F.lit(method).alias("method"), F.lit(window).alias("window"), F.lit(task).alias("task"), "examples", "right") for task, row in tasks.items()])


def tasks_sql() -> str:
    return f"""WITH {CHOPPED}, {PLANTED}, wd AS (SELECT DISTINCT window_id, doc_id FROM rm),
    d2 AS (SELECT item_id FROM h GROUP BY 1 HAVING count(DISTINCT doc_id) > 1), mp AS (SELECT item_id, max(n) AS n FROM (SELECT item_id, window_id, count(DISTINCT doc_id) AS n FROM h JOIN d2 USING (item_id) JOIN wd USING (doc_id) GROUP BY ALL) GROUP BY 1),
    fw AS (SELECT doc_id, min(window_id) AS window_id FROM wd GROUP BY 1), lv AS (SELECT quality, sum(quality) OVER w - quality AS ones, count(*) OVER w - 1 AS voters FROM fw JOIN labels USING (doc_id) WINDOW w AS (PARTITION BY window_id)),
    pt AS (SELECT rm.doc_id, ' ' || array_to_string(list_slice(toks, start + 1, start + used), ' ') || ' ' AS t FROM rm JOIN seg USING (seg_id)),
    nd AS (SELECT h.item_id, h.doc_id, max(contains(pt.t, ' ' || question || ' ')::INT) AS ok FROM h JOIN pt ON pt.doc_id = h.doc_id GROUP BY ALL),
    wn AS (SELECT DISTINCT window_id, rm.doc_id, seg_no FROM rm JOIN seg USING (seg_id)),
    kv AS (SELECT s.doc_id, s.seg_no, coalesce(max((a.window_id = b.window_id)::INT), 0) AS ok FROM seg s LEFT JOIN wn a ON a.doc_id = s.doc_id AND a.seg_no = s.seg_no LEFT JOIN wn b ON b.doc_id = s.doc_id AND b.seg_no = s.seg_no - 1 WHERE s.seg_no > 0 GROUP BY ALL)
    SELECT 'random' AS method, 1024 AS "window", 'multihop' AS task, count(*) AS examples, coalesce(sum((n > 1)::INT), 0)::BIGINT AS "right" FROM mp
    UNION ALL SELECT 'random', 1024, 'fewshot', count(*), sum(((2 * ones >= voters)::INT = quality)::INT)::BIGINT FROM lv
    UNION ALL SELECT 'random', 1024, 'needle', count(*), coalesce(sum(ok), 0)::BIGINT FROM nd
    UNION ALL SELECT 'random', 1024, 'key_value', count(*), coalesce(sum(ok), 0)::BIGINT FROM kv"""


@query(tasks_sql())
def tasks_random(spark, d):
    """What windows in random order let a reader answer."""
    s = segments(spark, d)
    return read_all(spark, d, settled(B.random_windows(s, 1024, SEED), "random"), s, "random", 1024)


@query()
def tasks_by_method(spark, d):
    """A row for each length, method and task. The reader sees one window at a time; its scores compare windows, not models."""
    out = []
    for window in (1024, 4096):
        done = P.organize(docs(spark, d), text_config(window=window))
        p = done.prepared
        ways = {"framework": done.manifest, "random": settled(B.random_windows(p.segments, window, SEED), "random"), "graph": settled(B.graph_windows(p.segments, P.graph_paths(p), window), "graph")}
        out += [read_all(spark, d, manifest, p.segments, name, window) for name, manifest in ways.items()]
    return stacked(out)


# spans, summaries of near copies, vectors by a user's model


@query(
    f"""WITH {PLANTED}, s AS (SELECT item_id, doc_id, answer, len(regexp_extract_all(substr(t, 1, instr(t, ' ' || question || ' ')), '\\S+')) + 8 AS first, t FROM h)
    SELECT item_id, doc_id, first, least(first + 8, len(regexp_extract_all(t, '\\S+'))) AS last, {words('t', 'first + 1', 'first + 8')} = answer AS found FROM s"""
)
def span_qa(spark, d):
    """Where in the document the answer stands: its first word and the word after its last, counted from 0, and whether these words are the answer."""
    t = tokenize(F.col("text"))
    joined = F.concat(F.lit(" "), F.array_join(t, " "), F.lit(" "))
    before = F.substr(joined, F.lit(1), F.instr(joined, F.concat(F.lit(" "), F.col("question"), F.lit(" "))))
    p = _planted(spark, d).select("item_id", "doc_id", t.alias("t"), (F.size(tokenize(before)) + 8).cast("long").alias("first"))
    said = F.array_join(F.slice("t", (F.col("first") + 1).cast("int"), F.lit(8)), " ")
    return p.join(_asked(spark, d).select("item_id", "answer"), "item_id").select("item_id", "doc_id", "first", F.least(F.col("first") + 8, F.size("t").cast("long")).alias("last"), (said == F.col("answer")).alias("found"))


@query()
def rouge_near_copies(spark, d):
    """The first words of a document as the summary, against those of the first document with the same beginning and another text."""
    rows = docs(spark, d).select("doc_id", "text", F.sha2(E.first_words(F.col("text"), 8), 256).alias("k"), F.sha2("text", 256).alias("h"), F.size(tokenize(F.col("text"))).alias("n")).filter("n >= 8")
    first = rows.groupBy("k").agg(F.min_by(F.struct("doc_id", "h"), "doc_id").alias("f"), F.count(F.lit(1)).alias("c")).filter("c > 1").select("k", "f.*").withColumnRenamed("doc_id", "ref").withColumnRenamed("h", "ref_h")
    pairs = rows.join(first, "k").filter("doc_id <> ref AND h <> ref_h").select("doc_id", "ref", E.first_words(F.col("text"), 100).alias("summary"))
    against = pairs.join(docs(spark, d).select(F.col("doc_id").alias("ref"), E.first_words(F.col("text"), 100).alias("lead")), "ref")
    return against.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg(S.rouge_l(F.col("summary"), F.col("lead"))), 6).alias("rouge_l"))


def _letters():
    return lambda texts: np.array([[t.count(c) for c in "aeio"] for t in texts], dtype=np.float32).reshape(len(texts), 4)


@query(
    f"""WITH {SEG}, t AS (SELECT seg_id, array_to_string(toks, ' ') AS s FROM seg) SELECT seg_id, {", ".join(f"(length(s) - length(replace(s, '{c}', '')))::DOUBLE AS {c}" for c in "aeio")} FROM t"""
)
def user_model(spark, d):
    """Vectors by any function of texts; here counts of four letters."""
    v = embed.with_model(segments(spark, d), _letters, 4)
    return v.select("seg_id", *[F.col("vec")[k].cast("double").alias(c) for k, c in enumerate("aeio")])


@query(f"WITH {SEG} SELECT doc_id, count(*) AS pieces, sum(n_tokens)::BIGINT AS tokens FROM (SELECT doc_id, greatest(1, ceil(n / 16384.0)::BIGINT) AS k, n FROM (SELECT doc_id, sum(n_tokens) AS n FROM seg GROUP BY 1)), LATERAL (SELECT least(16384, n - 16384 * i) AS n_tokens FROM range(k) r(i)) GROUP BY 1")
def segments_printed(spark, d):
    """Segments at the shortest printed length."""
    return segment(docs(spark, d).select("doc_id", "text"), 16384).groupBy("doc_id").agg(F.count(F.lit(1)).alias("pieces"), F.sum("n_tokens").alias("tokens"))
