"""Tasks after training, re-expressed on the given tables: generators, the stand-in reader, scorers, and the published scores.

The stand-in reader is no model; its scores test generators and scorers and are never the method's.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from windowforge.functions import scorers as S
from windowforge.functions import sql as registered
from windowforge.functions.tokens import segment, tokenize
from windowforge.operators import evals as E
from windowforge.operators.prefix import running
from windowforge.plans.scores import METHODS
from windowforge.sources import examples as source
from windowforge.sources.corpus import corpus, table

QUERIES, ORACLE_SQL = {}, {}
X = r"regexp_extract_all(text, '\S+')"
LIMITS = [16384, 32768, 65536]


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return add


def words(text: str, first: int, last: int) -> str:
    return f"array_to_string(list_slice(regexp_extract_all({text}, '\\S+'), {first}, {last}), ' ')"


# key-value retrieval: an example for each supplier


def _suppliers(spark, d):
    """Numbers of the suppliers, dealt over all cores: the table is one small file, what is made from a row is large."""
    return table(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("example_id")).repartition(4 * spark.sparkContext.defaultParallelism, "example_id")


PLACES = "(SELECT 140 AS n_pairs, unnest([1, 35, 70, 105, 140]) AS position UNION ALL SELECT 300, unnest([1, 50, 100, 150, 200, 250, 300]))"


@query(
    f"""SELECT example_id, n_pairs, position,
    array_to_string(list_transform(range(1, n_pairs + 1), lambda i: md5('k:' || example_id || ':' || n_pairs || ':' || i) || ': ' || md5('v:' || example_id || ':' || n_pairs || ':' || i)), ' ') AS context,
    md5('k:' || example_id || ':' || n_pairs || ':' || position) AS key, md5('v:' || example_id || ':' || n_pairs || ':' || position) AS answer
    FROM (SELECT s_suppkey::BIGINT AS example_id FROM supplier), {PLACES}"""
)
def kv_examples(spark, d):
    """Whole examples: the dictionary in which to look, the key asked for, the answer."""
    out = None
    for pairs, positions in E.KV_POSITIONS.items():
        rows = E.kv_examples(spark, pairs, positions, _suppliers(spark, d)).select("example_id", "n_pairs", "position", "context", "key", "answer")
        out = rows if out is None else out.unionByName(rows)
    return out


@query(f"SELECT w AS window, n_pairs, position, count(*) AS examples, avg(CASE WHEN n_pairs * 80 <= w THEN 1.0::DOUBLE END) AS accuracy FROM supplier, (SELECT unnest([16384, 32768, 65536]) AS w), {PLACES} GROUP BY ALL")
def kv_accuracy(spark, d):
    """Accuracy by position and window; null where the prompt does not fit, as the printed dash."""
    out = None
    for pairs, positions in E.KV_POSITIONS.items():
        made = E.kv_examples(spark, pairs, positions, _suppliers(spark, d))
        for window in LIMITS:
            rows = E.accuracy(E.kv_read(made, window).withColumn("window", F.lit(window)), ["window", "n_pairs", "position"])
            out = rows if out is None else out.unionByName(rows)
    return out


@query("SELECT w AS window, n_pairs, avg(CASE WHEN n_pairs * 80 <= w THEN 1.0::DOUBLE END) AS accuracy FROM supplier, (SELECT unnest([16384, 32768, 65536]) AS w), (SELECT unnest([140, 300]) AS n_pairs) GROUP BY ALL")
def kv_average(spark, d):
    return kv_accuracy(spark, d).groupBy("window", "n_pairs").agg(F.avg("accuracy").alias("accuracy"))


@query("SELECT s_suppkey::BIGINT AS example_id, md5('k:' || s_suppkey || ':140:70') AS question, md5('v:' || s_suppkey || ':140:70') AS answer, sum(CASE WHEN i = 1 THEN 66 ELSE 67 END)::BIGINT AS chars FROM supplier, range(1, 141) r(i) GROUP BY ALL")
def kv_data_source(spark, d):
    """The source makes examples up to the largest supplier's number; each supplier takes its own."""
    source.register(spark)
    ids = _suppliers(spark, d)
    last = ids.agg(F.max("example_id")).first()[0]
    rows = spark.read.format("windowforge_examples").option("pairs", 140).option("position", 70).option("examples", 0 if last is None else last + 1).option("block", 1000).load()
    return rows.select("example_id", "question", "answer", F.length("context").cast("long").alias("chars")).join(ids, "example_id")


@query("SELECT s_suppkey::BIGINT AS example_id, i AS place, md5('k:' || s_suppkey || ':140:' || i) AS key, md5('v:' || s_suppkey || ':140:' || i) AS value, i = 35 AS asked FROM supplier, range(1, 141) r(i)")
def kv_table_function(spark, d):
    registered.register_all(spark)
    return spark.sql("SELECT s.example_id, t.* FROM {ids} s, LATERAL wf_kv_example(s.example_id, 140, 35) t", ids=_suppliers(spark, d))


@query(f"SELECT event_id, (props->>'$.k')::BIGINT AS answer, '{{\"' || event_id || '\": ' || (props->>'$.k') || '}}' AS pair FROM events WHERE event_id % 100 = 7")
def kv_events(spark, d):
    """Pairs from the events' own numbers."""
    e = table(spark, d, "events").filter("event_id % 100 = 7").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    return e.select("event_id", F.col("k").alias("answer"), F.to_json(F.map_from_arrays(F.array(F.col("event_id").cast("string")), F.array("k"))).alias("p")).select("event_id", "answer", F.regexp_replace("p", ":", ": ").alias("pair"))


# needle in a haystack


def _needles(spark, d):
    text = F.array_join(F.slice(tokenize(F.col("text")), 1, 12), " ")
    return table(spark, d, "benchmark").select(F.col("item_id").alias("needle_id"), text.alias("text")).filter(F.size(tokenize(F.col("text"))) == 12)


def _haystack(spark, d, length: int = 65_536):
    """The first words of the documents in the order of their numbers, as many as the longest grid needs: a bounded row."""
    rows = table(spark, d, "documents").select("doc_id", "text", F.size(tokenize(F.col("text"))).alias("n"))
    kept = running(rows.filter("n > 0"), F.col("doc_id"), "n", []).filter(F.col("before") < length).select("doc_id", tokenize(F.col("text")).alias("t"))
    return kept.agg(F.flatten(F.sort_array(F.collect_list(F.struct("doc_id", "t")))["t"]).alias("tokens"))


GRID_LENGTHS, GRID_DEPTHS = [1024, 4096, 16384, 32768, 65536], [0, 25, 50, 75, 100]


@query(
    f"""WITH n AS (SELECT count(*) AS c FROM benchmark WHERE len({X}) >= 12), h AS (SELECT least(65536 + 30000, sum(len({X}))) AS total FROM documents),
    g AS (SELECT l, p, floor((l - 12) * p / 100)::BIGINT AS place FROM (SELECT unnest({GRID_LENGTHS}) AS l), (SELECT unnest({GRID_DEPTHS}) AS p))
    SELECT l AS length, p AS depth, greatest(1, round(greatest(least(least(l, 32768) - place, 12), 0) / 12.0 * 10))::DOUBLE AS score FROM g"""
)
def needle_grid(spark, d):
    return E.needle_grid(_needles(spark, d), _haystack(spark, d), GRID_LENGTHS, GRID_DEPTHS, 32_768)


@query(
    f"""SELECT w AS window, round(avg(greatest(1, round(greatest(least(least(l, w) - floor((l - 12) * p / 100)::BIGINT, 12), 0) / 12.0 * 10)))::DOUBLE * 10, 6) AS score
    FROM (SELECT unnest({LIMITS}) AS w), (SELECT unnest({GRID_LENGTHS}) AS l), (SELECT unnest({GRID_DEPTHS}) AS p) GROUP BY 1"""
)
def needle_mean(spark, d):
    out, needles, hay = None, _needles(spark, d), _haystack(spark, d)
    for window in LIMITS:
        row = E.needle_grid(needles, hay, GRID_LENGTHS, GRID_DEPTHS, window).agg(F.round(F.avg("score") * 10, 6).alias("score")).select(F.lit(window).alias("window"), "score")
        out = row if out is None else out.unionByName(row)
    return out


# questions


def _asked(spark, d, skip: int = 8, n: int = 8):
    """Benchmark passages as questions (their first words) with answers (the next words)."""
    b = table(spark, d, "benchmark")
    return b.select("item_id", E.first_words(F.col("text"), skip).alias("question"), E.next_words(F.col("text"), skip, n).alias("answer"), F.sha2("text", 256).alias("key"))


def _planted(spark, d, skip: int = 8):
    """(item_id, doc_id, text): documents that hold a passage's first words. A document's runs of that many words meet the questions by key: nothing is compared pair by pair."""
    words_ = table(spark, d, "documents").select("doc_id", tokenize(F.col("text")).alias("t"))
    runs = words_.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("t") - skip + 1, F.lit(1))), lambda i: F.array_join(F.slice("t", i, F.lit(skip)), " ")))).alias("question"))
    hits = runs.join(F.broadcast(_asked(spark, d, skip).select("item_id", "question").filter("question <> ''")), "question")  # the benchmark is a fixed table of a few hundred rows
    return hits.select("item_id", "question", "doc_id").distinct().join(table(spark, d, "documents").select("doc_id", "text"), "doc_id")


PLANTED = f"""j AS (SELECT doc_id, ' ' || array_to_string({X}, ' ') || ' ' AS t FROM documents), q AS (SELECT item_id, {words('text', 1, 8)} AS question, {words('text', 9, 16)} AS answer FROM benchmark WHERE len({X}) >= 8),
    h AS (SELECT item_id, question, answer, doc_id, t FROM j, q WHERE contains(t, ' ' || question || ' '))"""


@query(f"WITH {PLANTED} SELECT item_id, doc_id, {words('substr(t, instr(t, question) + length(question))', 1, 8)} AS prediction, answer FROM h")
def qa_single(spark, d):
    """Question and answer in one document."""
    p = _planted(spark, d).join(_asked(spark, d).select("item_id", "answer"), "item_id")
    return p.select("item_id", "doc_id", E.answer_after(F.col("text"), F.col("question"), 8).alias("prediction"), "answer")


@query(f"WITH {PLANTED} SELECT count(*) AS examples, round(avg(({words('substr(t, instr(t, question) + length(question))', 1, 8)} = answer)::INT), 6) AS exact FROM h")
def qa_single_exact(spark, d):
    return qa_single(spark, d).agg(F.count(F.lit(1)).alias("examples"), F.round(F.avg(S.exact_match(F.col("prediction"), F.col("answer"))), 6).alias("exact"))


@query()
def qa_single_f1(spark, d):
    return qa_single(spark, d).agg(F.count(F.lit(1)).alias("examples"), F.round(F.avg(S.token_f1(F.col("prediction"), F.col("answer"))), 6).alias("f1"))


@query()
def trivia_f1(spark, d):
    """Open questions: the best over all documents that hold the passage, by window: the reader sees the first tokens alone."""
    p, a, out = _planted(spark, d), _asked(spark, d).select("item_id", "answer"), None
    for window in (256, 1024, 4096):
        read = p.select("item_id", E.answer_after(F.col("text"), F.col("question"), 8, window).alias("prediction")).join(a, "item_id")
        best = read.groupBy("item_id").agg(F.max(S.token_f1(F.col("prediction"), F.col("answer"))).alias("f1"))
        row = best.agg(F.count(F.lit(1)).alias("questions"), F.round(F.avg("f1"), 6).alias("f1")).select(F.lit(window).alias("window"), "questions", "f1")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"WITH {PLANTED}, d AS (SELECT item_id, list(DISTINCT doc_id ORDER BY doc_id) AS docs FROM h GROUP BY 1 HAVING count(DISTINCT doc_id) > 1) SELECT item_id, docs[1] AS first_doc, docs[2] AS second_doc, len(docs) AS documents FROM d")
def multihop_pairs(spark, d):
    """Passages that two documents share: a question over both."""
    docs = F.sort_array(F.collect_set("doc_id"))
    per = _planted(spark, d).groupBy("item_id").agg(docs.alias("docs")).filter(F.size("docs") > 1)
    return per.select("item_id", F.col("docs")[0].alias("first_doc"), F.col("docs")[1].alias("second_doc"), F.size("docs").cast("long").alias("documents"))


@query()
def qa_multihop_f1(spark, d):
    """The answer joins what follows the passage in two documents; seen only if both lie in one window of 4096 tokens."""
    p, pairs = _planted(spark, d), multihop_pairs(spark, d)
    after = p.select("item_id", "doc_id", F.size(tokenize(F.col("text"))).alias("n"), E.answer_after(F.col("text"), F.col("question"), 12).alias("a"))
    a, b = after.select("item_id", F.col("doc_id").alias("first_doc"), F.col("n").alias("n1"), F.col("a").alias("a1")), after.select("item_id", F.col("doc_id").alias("second_doc"), F.col("n").alias("n2"), F.col("a").alias("a2"))
    both = pairs.join(a, ["item_id", "first_doc"]).join(b, ["item_id", "second_doc"])
    seen = F.when(F.col("n1") + F.col("n2") <= 4096, F.concat_ws(" ", "a1", "a2")).otherwise(F.col("a1"))
    return both.agg(F.count(F.lit(1)).alias("examples"), F.round(F.avg(S.token_f1(seen, F.concat_ws(" ", "a1", "a2"))), 6).alias("f1"))


@query("SELECT o_orderkey, c_name || ' of ' || n_name || ' ordered ' || o_orderkey AS fact, n_name AS answer FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_orderkey % 50 = 1")
def multihop_facts(spark, d):
    """Facts chained by key: an order's customer, the customer's nation."""
    o, c, n = table(spark, d, "orders").filter("o_orderkey % 50 = 1"), table(spark, d, "customer"), table(spark, d, "nation")
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.select("o_orderkey", F.concat("c_name", F.lit(" of "), "n_name", F.lit(" ordered "), F.col("o_orderkey").cast("string")).alias("fact"), F.col("n_name").alias("answer"))


# choices and classes


@query(
    f"""WITH b AS (SELECT item_id, {X} AS t, row_number() OVER (ORDER BY item_id) - 1 AS k, count(*) OVER () AS n FROM benchmark), o AS (SELECT item_id, k, n, t, i FROM b, (SELECT unnest([0, 1, 2, 3]) AS i)),
    x AS (SELECT o.item_id, i, len(list_intersect(list_distinct(list_slice(o.t, 1, len(o.t) // 2)), list_distinct(list_slice(c.t, len(c.t) // 2 + 1, len(c.t))))) AS overlap FROM o JOIN b c ON c.k = (o.k + i) % o.n)
    SELECT item_id, arg_max(i, (overlap, -i)) AS choice, max(overlap) AS overlap FROM x GROUP BY 1"""
)
def multiple_choice(spark, d):
    """First half of a passage, four second halves, one of them its own; the reader picks by common words."""
    t = tokenize(F.col("text"))
    b = table(spark, d, "benchmark").select("item_id", t.alias("t"))
    numbered = b.withColumn("k", F.row_number().over(Window.orderBy("item_id")) - 1)  # a fixed table of a few hundred rows
    n = numbered.agg(F.count(F.lit(1)).alias("n"))
    left = numbered.crossJoin(F.broadcast(n)).select("item_id", F.slice("t", F.lit(1), F.floor(F.size("t") / 2).cast("int")).alias("head"), "k", "n", F.explode(F.array(*[F.lit(i) for i in range(4)])).alias("i"))
    right = numbered.select(F.col("k").alias("rk"), F.slice("t", (F.floor(F.size("t") / 2) + 1).cast("int"), F.size("t")).alias("tail"))
    pairs = left.join(right, (F.col("k") + F.col("i")) % F.col("n") == F.col("rk"))
    scored = pairs.select("item_id", "i", F.size(F.array_intersect("head", "tail")).cast("long").alias("overlap"))
    return scored.groupBy("item_id").agg(F.max_by("i", F.struct("overlap", -F.col("i"))).alias("choice"), F.max("overlap").alias("overlap"))


@query(
    """WITH x AS (SELECT d.doc_id, d.lang, l.quality, d.doc_id // 8 AS w FROM documents d JOIN labels l USING (doc_id)),
    v AS (SELECT a.doc_id, a.quality, coalesce(sum(b.quality), 0) AS ones, count(b.doc_id) AS voters FROM x a LEFT JOIN x b ON a.w = b.w AND a.doc_id <> b.doc_id AND a.lang = b.lang GROUP BY ALL)
    SELECT voters, count(*) AS documents, round(avg(((2 * ones >= voters)::INT = quality)::INT), 6) AS accuracy FROM v GROUP BY 1"""
)
def fewshot_classify(spark, d):
    """Labelled neighbours in the same window vote; by their number."""
    x = table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels"), "doc_id").select("doc_id", "lang", "quality", F.floor(F.col("doc_id") / 8).alias("w"))
    of = Window.partitionBy("w", "lang")
    v = x.select("quality", (F.sum("quality").over(of) - F.col("quality")).alias("ones"), (F.count(F.lit(1)).over(of) - 1).alias("voters"))
    return v.groupBy("voters").agg(F.count(F.lit(1)).alias("documents"), F.round(F.avg(((2 * F.col("ones") >= F.col("voters")).cast("int") == F.col("quality")).cast("double")), 6).alias("accuracy"))


# summaries


@query()
def rouge_documents(spark, d):
    """The first lines of a document against those of the next document of its source."""
    lead = F.array_join(F.slice(F.split("text", "\n"), 1, 3), " ")
    rows = table(spark, d, "documents").select("doc_id", "source", E.first_words(lead, 100).alias("lead"))
    pairs = rows.withColumn("ref", F.lead("lead").over(Window.partitionBy("source").orderBy("doc_id"))).filter("ref IS NOT NULL")
    return pairs.groupBy("source").agg(F.round(F.avg(S.rouge_l(F.col("lead"), F.col("ref"))), 6).alias("rouge_l"))


@query()
def rouge_dialogues(spark, d):
    """What was asked against what was answered, as the summary of a dialogue."""
    c = table(spark, d, "conversations")
    said = lambda role: F.array_join(F.sort_array(F.collect_list(F.when(F.col("role") == role, F.struct("turn", "text"))))["text"], " ")
    both = c.groupBy("conv_id").agg(said("user").alias("asked"), said("assistant").alias("answered")).filter("asked <> '' AND answered <> ''")
    return both.agg(F.count(F.lit(1)).alias("dialogues"), F.round(F.avg(S.rouge_l(E.first_words(F.col("asked"), 200), E.first_words(F.col("answered"), 200))), 6).alias("rouge_l"))


# completion


ELEMENTS = r"list_filter(string_split_regex(coalesce(html, ''), '>'), lambda x: x <> '')"


@query(
    f"""WITH e AS (SELECT page_id, {ELEMENTS} AS e FROM pages), p AS (SELECT page_id, unnest(range(2, len(e) + 1)) AS i, e FROM e), c AS (SELECT page_id, e[i - 1] AS a, e[i] AS b FROM p)
    SELECT page_id, count(*) AS n, round(avg(1 - levenshtein(a, b) / greatest(length(a), length(b))), 6) AS edit_sim FROM c WHERE length(a) = octet_length(encode(a)) AND length(b) = octet_length(encode(b)) AND length(a) < 200 AND length(b) < 200 GROUP BY 1"""
)
def edit_sim_pages(spark, d):
    """Next element of a page, guessed to be the one before: ASCII elements alone, as edit distances of other engines count bytes."""
    e = table(spark, d, "pages").select("page_id", F.filter(F.split(F.coalesce("html", F.lit("")), ">"), lambda x: x != "").alias("e"))
    pairs = e.select("page_id", F.explode(F.arrays_zip(F.slice("e", F.lit(1), F.greatest(F.size("e") - 1, F.lit(0))).alias("a"), F.slice("e", F.lit(2), F.greatest(F.size("e") - 1, F.lit(0))).alias("b"))).alias("p")).select("page_id", F.col("p.a").alias("a"), F.col("p.b").alias("b"))
    plain = [(F.length(c) == F.octet_length(c)) & (F.length(c) < 200) for c in (F.col("a"), F.col("b"))]
    return pairs.filter(plain[0] & plain[1]).groupBy("page_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(S.edit_sim(F.col("a"), F.col("b"))), 6).alias("edit_sim"))


def pass_sql(k: int) -> str:
    return f"""WITH t AS (SELECT doc_id % 40 AS task, count(*) AS n, sum(quality)::BIGINT AS c FROM labels GROUP BY 1)
    SELECT task, n, c, round(CASE WHEN c = 0 THEN 0 WHEN n - c < {k} THEN 1 ELSE 1 - exp(list_sum(list_transform(range(n - c + 1, n + 1), lambda i: ln(1 - {k}.0 / i)))) END, 6) AS pass_at_k FROM t"""


def _pass(k: int):
    def run(spark, d):
        rows = table(spark, d, "labels").select((F.col("doc_id") % 40).alias("task"), F.col("quality").alias("passed"))
        return S.pass_at_k(rows, ["task"], k=k).withColumn("pass_at_k", F.round("pass_at_k", 6))

    run.__name__ = f"pass_at_{k}"
    query(pass_sql(k))(run)


for _k in (1, 3):
    _pass(_k)


# likelihood


def likelihood_sql(order: int) -> str:
    before = "''" if order == 1 else "coalesce(lag(t) OVER (PARTITION BY doc_id ORDER BY i), '<s>')"
    return f"""WITH w AS (SELECT doc_id, unnest(x) AS t, unnest(range(len(x))) AS i FROM (SELECT doc_id, {X} AS x FROM documents)), g AS (SELECT doc_id, {before} AS b, t FROM w),
    tr AS (SELECT * FROM g WHERE doc_id % 5 <> 0), p AS (SELECT b, t, count(*) AS c FROM tr GROUP BY ALL), h AS (SELECT b, count(*) AS h FROM tr GROUP BY 1), v AS (SELECT count(DISTINCT t) AS v FROM tr)
    SELECT doc_id, count(*) AS n, round(sum(ln((coalesce(c, 0) + 1) / (coalesce(h, 0) + v + 1))), 3) AS log_likelihood FROM g LEFT JOIN p USING (b, t) LEFT JOIN h USING (b), v WHERE doc_id % 5 = 0 GROUP BY 1"""


def _likelihood(order: int):
    def run(spark, d):
        rows = table(spark, d, "documents").select(F.col("doc_id"), tokenize(F.col("text")).alias("tokens"))
        out = E.ngram_likelihood(rows.filter("doc_id % 5 <> 0"), rows.filter("doc_id % 5 = 0"), order, key="doc_id")
        return out.select("doc_id", "n", F.round("log_likelihood", 3).alias("log_likelihood"))

    run.__name__ = f"likelihood_{'unigram' if order == 1 else 'bigram'}"
    query(likelihood_sql(order))(run)


for _o in (1, 2):
    _likelihood(_o)


# scores by category, task, window and method: mean prices of orders in cents, as sums of whole numbers

CELLS = """v AS (SELECT o_orderpriority AS category, o_orderstatus AS task, CASE o_orderkey % 3 WHEN 0 THEN 16384 WHEN 1 THEN 32768 ELSE 65536 END AS "window",
    CASE o_custkey % 3 WHEN 0 THEN 'random' WHEN 1 THEN 'graph' ELSE 'framework' END AS method, sum(round(o_totalprice * 100)::BIGINT)::DOUBLE / count(*) AS score FROM orders GROUP BY ALL)"""


def _scores(spark, d):
    of = lambda key, values: F.when(F.col(key) % 3 == 0, values[0]).when(F.col(key) % 3 == 1, values[1]).otherwise(values[2])
    rows = table(spark, d, "orders").select(F.col("o_orderpriority").alias("category"), F.col("o_orderstatus").alias("task"), of("o_orderkey", LIMITS).alias("window"), of("o_custkey", METHODS).alias("method"), F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    return rows.groupBy("category", "task", "window", "method").agg((F.sum("cents").cast("double") / F.count(F.lit(1))).alias("score"))


@query(f"WITH {CELLS} SELECT category, \"window\", method, round(avg(score), 4) AS score FROM v GROUP BY ALL")
def radar_averages(spark, d):
    return E.radar(_scores(spark, d)).withColumn("score", F.round("score", 4))


@query(
    f"""WITH {CELLS}, c AS (SELECT category, task, "window", max(score) FILTER (method = 'framework') AS o, max(score) FILTER (method = 'random') AS r, max(score) FILTER (method = 'graph') AS g FROM v GROUP BY ALL)
    SELECT category, 'random' AS base, round((sum(o) / sum(r) - 1) * 100, 4) AS improvement FROM c WHERE o IS NOT NULL AND r IS NOT NULL GROUP BY 1
    UNION ALL SELECT category, 'graph', round((sum(o) / sum(g) - 1) * 100, 4) FROM c WHERE o IS NOT NULL AND g IS NOT NULL GROUP BY 1"""
)
def improvement_claims(spark, d):
    out = None
    for base in ("random", "graph"):
        rows = E.improvement(_scores(spark, d), base).select("category", F.lit(base).alias("base"), F.round("improvement", 4).alias("improvement"))
        out = rows if out is None else out.unionByName(rows)
    return out


@query(f"WITH {CELLS} SELECT category, task, method, max(score) FILTER (\"window\" = 16384) AS w16384, max(score) FILTER (\"window\" = 32768) AS w32768, max(score) FILTER (\"window\" = 65536) AS w65536 FROM v GROUP BY ALL")
def agg_pivot_scores(spark, d):
    p = _scores(spark, d).groupBy("category", "task", "method").pivot("window", LIMITS).agg(F.max("score"))
    return p.select("category", "task", "method", *[F.col(str(w)).alias(f"w{w}") for w in LIMITS])


@query(f"SELECT domain, doc_id, greatest(1, ceil(len({X}) / 2048.0)::BIGINT) AS segments FROM (SELECT 'benchmark' AS domain, item_id AS doc_id, text FROM benchmark UNION ALL SELECT 'documents', doc_id, text FROM documents)")
def corpus_segments(spark, d):
    rows = corpus(spark, d).filter(F.col("domain").isin("benchmark", "documents"))
    return segment(rows, 2048, prefix=F.col("domain")).groupBy("domain", "doc_id").agg(F.count(F.lit(1)).alias("segments"))
