"""Surrounding operators on the given tables: sources, joins, aggregates, windows, functions, SQL forms and Python forms, each with a DuckDB twin where SQL can say it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evigraph.functions import sqlfuncs
from evigraph.operators import packed, retrieval, textprep
from evigraph.operators.measures import lcs_fold, lcs_ratio
from evigraph.queries.method import QV, chunk_sql, count_sql, score_sql
from evigraph.runtime import scratch
from evigraph.sources.corpora import documents, html_text, table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
W = r"'[\p{L}\p{N}]+'"


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def by_sql(name: str, sql: str, spark_sql: str | None = None, tables: str = "") -> None:
    """A query whose Spark form is SQL text over the same tables."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        # CTEs over the files: no view outlives the query.
        used = tables.split() or TABLES
        heads = ", ".join(f"{t} AS (SELECT * FROM parquet.`{d}/{t}.parquet`)" for t in used)
        text = (spark_sql or sql).strip()
        return spark.sql(f"WITH {heads}, {text[5:]}" if text.upper().startswith("WITH ") else f"WITH {heads} {text}")

    QUERIES[name], ORACLES[name] = run, sql


TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

# ---- sources and sinks ----


@query("SELECT doc_id, lang, n_chars FROM documents WHERE lang = 'de'")
def src_parquet_scan(spark, d):
    return table(spark, d, "documents").where("lang = 'de'").select("doc_id", "lang", "n_chars")


@query("SELECT doc_id, n_chars FROM documents WHERE lang = 'fr'")
def src_partitioned_roundtrip(spark, d):
    path = scratch(spark, "by_lang")
    table(spark, d, "documents").select("doc_id", "n_chars", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).where("lang = 'fr'").select("doc_id", "n_chars")


@query("SELECT o_custkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY o_custkey")
def src_bucketed_edges(spark, d):
    """Both sides bucketed by the key, so the join needs no exchange."""
    import uuid

    names = [f"b{uuid.uuid4().hex}" for _ in range(2)]
    table(spark, d, "orders").select("o_custkey").write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", scratch(spark, "orders")).saveAsTable(names[0])
    table(spark, d, "customer").select("c_custkey").write.bucketBy(8, "c_custkey").sortBy("c_custkey").option("path", scratch(spark, "customer")).saveAsTable(names[1])
    a, b = (spark.table(n) for n in names)
    return a.hint("merge").join(b, a["o_custkey"] == b["c_custkey"]).groupBy("o_custkey").agg(F.count("*").alias("n"))


@query("SELECT event_id, len(json_keys(props)) AS n_keys FROM events")
def src_json_props(spark, d):
    return table(spark, d, "events").select("event_id", F.size(F.json_object_keys("props")).cast("long").alias("n_keys"))


def _roundtrip(fmt, **options):
    def run(spark, d):
        path = scratch(spark, fmt)
        rows = table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
        rows.write.format(fmt).options(**options).save(path)
        return spark.read.schema(rows.schema).format(fmt).options(**options).load(path)

    return run


for _f in ("csv", "orc", "json"):
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation", f"src_{_f}_roundtrip")(_roundtrip(_f))


@query("SELECT doc_id, CAST(len(string_split(text, chr(10))) AS INTEGER) AS n_lines FROM documents WHERE text IS NOT NULL")
def src_text_lines(spark, d):
    return table(spark, d, "documents").where("text is not null").select("doc_id", F.size(F.split("text", "\n")).alias("n_lines"))


HTML_SQL = r"""trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '[ \t\r\n]+', ' ', 'g'))"""


@query(f"SELECT page_id, md5({HTML_SQL}) AS digest FROM pages")
def src_html_text(spark, d):
    return table(spark, d, "pages").select("page_id", F.md5(html_text(F.col("html")).cast("binary")).alias("digest"))


# ---- projection, filters ----


@query("SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS band FROM documents")
def op_project_case(spark, d):
    return table(spark, d, "documents").select("doc_id", F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long").alias("band"))


by_sql("op_filter_lang", "SELECT doc_id, source FROM documents WHERE lang <> 'en' AND n_chars > 1000", tables="documents")
by_sql("op_filter_in_between", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 100000", tables="orders")


@query(r"SELECT doc_id FROM documents WHERE text LIKE '%licens%' OR regexp_matches(text, '[0-9]{3}-[0-9]{4}')")
def op_like_regex(spark, d):
    return table(spark, d, "documents").where(F.col("text").like("%licens%") | F.col("text").rlike("[0-9]{3}-[0-9]{4}")).select("doc_id")


@query("SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM l.toxic")
def op_null_safe(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left").where(F.col("quality").eqNullSafe(F.col("toxic"))).select("doc_id", "quality")


@query("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text)")
def op_dedup_exact(spark, d):
    return table(spark, d, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("m")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("m")


# ---- joins ----

DF_SQL = "WITH " + count_sql(1) + ", freq AS (SELECT term, count(*) AS df FROM counts GROUP BY term) SELECT chunk_key, sum(df)::BIGINT AS dfs FROM counts JOIN freq USING (term) GROUP BY chunk_key"


def _counts(spark, d):
    return textprep.term_counts(textprep.ngrams(textprep.chunk(documents(spark, d)), 1))


def _df_join(hint):
    def run(spark, d):
        c = _counts(spark, d)
        return c.join(textprep.doc_freq(c).hint(hint), "term").groupBy("chunk_key").agg(F.sum("df").alias("dfs"))

    return run


query(DF_SQL, "join_broadcast_df")(_df_join("broadcast"))
query(DF_SQL, "join_sortmerge_postings")(_df_join("merge"))


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_shuffle_hash(spark, d):
    o, li = table(spark, d, "orders").select("o_orderkey", "o_orderpriority"), table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    return li.join(o.hint("shuffle_hash"), li["l_orderkey"] == o["o_orderkey"]).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("SELECT a.vec_id AS u, b.vec_id AS v FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) > 0.4")
def join_theta_pairs(spark, d):
    from evigraph.operators.synonyms import pairs_exact

    return pairs_exact(table(spark, d, "embeddings").select("vec_id", F.col("embedding").alias("vec")), 0.4, "vec_id").select("u", "v")


@query(
    "WITH " + chunk_sql() + ", pos AS (SELECT DISTINCT doc_key, unnest(range(0, len(t), 100)) AS p FROM tok), own AS (SELECT chunk_key, doc_key, chunk_no * 224 AS a, chunk_no * 224 + len(tokens) AS z FROM chunks) SELECT chunk_key, count(*) AS hits FROM own JOIN pos ON pos.doc_key = own.doc_key AND p >= a AND p < z GROUP BY chunk_key"
)
def join_range_offsets(spark, d):
    """Positions to the chunks that cover them: an equi-join on the cell of the start, as a position's chunks start in two cells at most."""
    docs = documents(spark, d)
    c = textprep.chunk(docs).select("chunk_key", "doc_key", (F.col("chunk_no") * 224).alias("a"), (F.col("chunk_no") * 224 + F.col("n_tok")).alias("z")).withColumn("cell", F.expr("a div 224"))
    n = F.size(textprep.tokens(F.col("text")))
    p = docs.where("text is not null").select("doc_key", n.alias("n")).where("n > 0").select("doc_key", F.explode(F.expr("sequence(0, n - 1, 100)")).alias("p")).distinct()
    p = p.select("doc_key", "p", F.explode(F.array(F.expr("p div 224"), F.expr("p div 224 - 1"))).alias("cell"))
    return p.join(c, ["doc_key", "cell"]).where("p >= a and p < z").groupBy("chunk_key").agg(F.count("*").alias("hits"))


@query("SELECT o_orderkey, event_id FROM orders ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY user_id, ts) e ON o_custkey = e.user_id AND o_orderdate >= e.ts")
def join_asof_events(spark, d):
    """Latest event at or before each order of a customer: one union, one window; no row meets all others."""
    e = table(spark, d, "events").groupBy("user_id", "ts").agg(F.max("event_id").alias("event_id")).select(F.col("user_id").alias("k"), "ts", F.lit(None).cast("long").alias("o_orderkey"), "event_id", F.lit(0).alias("side"))
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), "o_orderkey", F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("side"))
    w = Window.partitionBy("k").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    both = e.unionByName(o).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w))
    return both.where("side = 1 and event_id is not null").select("o_orderkey", "event_id")


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def join_interval(spark, d):
    """Bounded time condition as an equi-join on user and hour cell."""
    e = table(spark, d, "events").select("user_id", "event_id", "ts", "event_type").withColumn("cell", F.expr("unix_seconds(cast(ts as timestamp)) div 3600"))
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t0"), F.explode(F.array(F.col("cell"), F.col("cell") + 1)).alias("cell"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("t1"), "cell")
    return a.join(b, ["user_id", "cell"]).where("t1 >= t0 and t1 <= t0 + interval 1 hour").select("click", "purchase")


by_sql("join_left_labels", "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id", tables="documents labels")
by_sql("join_full_fuse", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS orders, coalesce(b.n, 0) AS events FROM (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY o_custkey) a FULL JOIN (SELECT user_id AS k, count(*) AS n FROM events GROUP BY user_id) b ON a.k = b.k", tables="orders events")
by_sql("join_semi_dict", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)", tables="documents labels")
by_sql("join_anti_outlabel", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", tables="documents labels")


@query("SELECT item_id FROM benchmark b WHERE NOT EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text))")
def join_anti_negatives(spark, d):
    items, docs = table(spark, d, "benchmark"), table(spark, d, "documents").select(F.col("text").alias("t"))
    hit = docs.join(F.broadcast(items), F.contains("t", "text")).select("item_id").distinct()
    return items.select("item_id").join(hit, "item_id", "left_anti")


#: Sizes and thresholds of the grid are the odd line numbers and ten times the odd discounts under 0.08 that occur in the line items.
by_sql("join_cross_grid", "SELECT n, tau FROM (SELECT DISTINCT l_linenumber AS n FROM lineitem WHERE l_linenumber % 2 = 1) a CROSS JOIN (SELECT DISTINCT round(10 * l_discount, 1) AS tau FROM lineitem WHERE l_discount < 0.075 AND round(100 * l_discount) % 2 = 1) b", tables="lineitem")
by_sql("join_self_twohop", "SELECT a.o_custkey AS customer, count(DISTINCT l.l_partkey) AS parts FROM orders a JOIN lineitem l ON l.l_orderkey = a.o_orderkey GROUP BY a.o_custkey", tables="orders lineitem")

# ---- aggregates ----


@query("WITH " + count_sql(1) + " SELECT term, count(*) AS df FROM counts GROUP BY term")
def agg_df(spark, d):
    return textprep.doc_freq(_counts(spark, d))


@query("WITH " + count_sql(1) + " SELECT term, sum(cnt)::BIGINT AS total FROM counts GROUP BY term HAVING sum(cnt) >= 3")
def agg_term_totals(spark, d):
    return _counts(spark, d).groupBy("term").agg(F.sum("cnt").alias("total")).where("total >= 3")


@query(f"SELECT lang, count(DISTINCT w) AS words FROM (SELECT lang, unnest(regexp_extract_all(lower(text), {W})) AS w FROM documents) GROUP BY lang")
def agg_distinct_exact(spark, d):
    return table(spark, d, "documents").select("lang", F.explode(textprep.tokens(F.col("text"))).alias("w")).groupBy("lang").agg(F.countDistinct("w").alias("words"))


@query()
def agg_distinct_approx(spark, d):
    rows = table(spark, d, "documents").select("lang", F.explode(textprep.tokens(F.col("text"))).alias("w"))
    return rows.groupBy("lang").agg(F.approx_count_distinct("w", 0.02).alias("words"), F.hll_sketch_estimate(F.hll_sketch_agg("w", F.lit(12))).alias("sketch"))


by_sql("agg_minby_relax", "SELECT l_orderkey, min_by(l_partkey, l_extendedprice * 1000 + l_linenumber) AS cheapest FROM lineitem GROUP BY l_orderkey", tables="lineitem")


@query("SELECT conv_id, array_to_string(list(role ORDER BY turn), '>') AS roles FROM conversations GROUP BY conv_id")
def agg_collect_sorted(spark, d):
    c = table(spark, d, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("x"))
    return c.select("conv_id", F.array_join(F.transform("x", lambda r: r["role"]), ">").alias("roles"))


by_sql("agg_cube_lang_source", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", tables="documents")
by_sql("agg_rollup_region", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)", tables="customer nation region")
by_sql("agg_grouping_sets", "SELECT lang, source, sum(n_chars) AS chars FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", "SELECT lang, source, sum(n_chars) AS chars FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", tables="documents")


@query("SELECT lang, count(*) FILTER (quality = 0 AND toxic = 0) AS q0t0, count(*) FILTER (quality = 0 AND toxic = 1) AS q0t1, count(*) FILTER (quality = 1 AND toxic = 0) AS q1t0, count(*) FILTER (quality = 1 AND toxic = 1) AS q1t1 FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def agg_pivot_quality(spark, d):
    rows = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select("lang", F.concat(F.lit("q"), "quality", F.lit("t"), "toxic").alias("c"))
    return rows.groupBy("lang").pivot("c", ["q0t0", "q0t1", "q1t0", "q1t1"]).count().na.fill(0)


by_sql("agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.25) AS q1, quantile_cont(n_chars, 0.5) AS q2, quantile_cont(n_chars, 0.75) AS q3 FROM documents GROUP BY lang", "SELECT lang, percentile(n_chars, 0.25) AS q1, percentile(n_chars, 0.5) AS q2, percentile(n_chars, 0.75) AS q3 FROM documents GROUP BY lang", tables="documents")


@query("WITH " + count_sql(2) + " SELECT term, count(*) AS df FROM counts WHERE n = 2 GROUP BY term HAVING count(*) >= 5")
def agg_having(spark, d):
    c = textprep.term_counts(textprep.ngrams(textprep.chunk(documents(spark, d)), 2)).where("n = 2")
    return textprep.doc_freq(c).where("df >= 5")


# ---- windows, sorting, sets ----

by_sql("win_topk", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 7", tables="documents")
by_sql("win_rank_family", "SELECT doc_id, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS nt, round(cume_dist() OVER w, 6) AS cd FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars)", tables="documents")
by_sql("win_lead_relation", "SELECT conv_id, turn, role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next_role FROM conversations", tables="conversations")
by_sql("win_lag_turns", "SELECT conv_id, turn, prev FROM (SELECT conv_id, turn, role, lag(turn) OVER w AS prev, lag(role) OVER w AS before FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'assistant' AND before = 'user'", tables="conversations")
by_sql("win_running_budget", "SELECT source, doc_id FROM (SELECT source, doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING) AS used FROM documents) WHERE used <= 20000", tables="documents")
by_sql("win_sliding_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS mean3 FROM events", tables="events")
by_sql("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events", tables="events")
by_sql("win_max_norm", "SELECT doc_id, round(n_chars / max(n_chars) OVER (PARTITION BY lang), 6) AS v FROM documents", tables="documents")
by_sql("sort_global_limit", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20", tables="documents")
by_sql("sort_offset_page", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 30", tables="orders")
by_sql("topk_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, rank() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3", tables="customer")
by_sql("set_union_edges", "SELECT n_name AS x FROM nation UNION SELECT r_name FROM region UNION SELECT n_name FROM nation", tables="nation region")


@query("SELECT s_suppkey AS k, s_acctbal AS bal, NULL::VARCHAR AS seg FROM supplier UNION ALL SELECT c_custkey, c_acctbal, c_mktsegment FROM customer")
def set_union_by_name(spark, d):
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("k"), F.col("s_acctbal").alias("bal"))
    return s.unionByName(table(spark, d, "customer").select(F.col("c_mktsegment").alias("seg"), F.col("c_acctbal").alias("bal"), F.col("c_custkey").alias("k")), allowMissingColumns=True)


by_sql("set_except_omega", "SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels", tables="documents labels")
by_sql("set_intersect_terms", f"SELECT w FROM (SELECT unnest(regexp_extract_all(lower(text), {W})) AS w FROM documents WHERE lang = 'fr') INTERSECT SELECT w FROM (SELECT unnest(regexp_extract_all(lower(text), {W})) AS w FROM documents WHERE lang = 'es')", r"SELECT w FROM (SELECT explode(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+', 0)) AS w FROM documents WHERE lang = 'fr') INTERSECT SELECT w FROM (SELECT explode(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+', 0)) AS w FROM documents WHERE lang = 'es')", tables="documents")

# ---- functions ----


@query(f"SELECT doc_id, CAST(len(regexp_extract_all(lower(text), {W})) AS INTEGER) AS n FROM documents")
def fn_tokens(spark, d):
    return table(spark, d, "documents").select("doc_id", F.size(textprep.tokens(F.col("text"))).alias("n"))


by_sql("fn_string_family", "SELECT n_nationkey, lower(n_name) AS lo, substring(n_name, 2, 3) AS mid, concat_ws('-', n_name, n_regionkey) AS cat, translate(n_name, 'AEI', '431') AS tr, levenshtein(n_name, 'FRANCE') AS lev, lpad(n_name, 12, '*') AS pad, reverse(n_name) AS rev, length(trim(n_name)) AS len FROM nation", tables="nation")
by_sql("fn_date_family", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS mon, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS mon, datediff(CAST(o_orderdate AS DATE), DATE '1992-01-01') AS days FROM orders", tables="orders")
by_sql("fn_math_family", "SELECT c_custkey, round(ln(1 + abs(c_acctbal)), 5) AS l, round(sqrt(abs(c_acctbal)), 5) AS s, round(power(c_custkey, 0.5), 5) AS p, CAST(floor(c_acctbal) AS BIGINT) AS f, c_custkey % 7 AS m, greatest(c_custkey, 50) AS g FROM customer", tables="customer")


@query("SELECT vec_id, round(list_cosine_similarity(embedding::DOUBLE[], (SELECT embedding::DOUBLE[] FROM embeddings WHERE vec_id = 0)), 4) AS cos FROM embeddings")
def fn_array_cosine(spark, d):
    e = table(spark, d, "embeddings")
    return e.join(F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("z")))).select("vec_id", F.round(retrieval.cosine(F.col("embedding"), F.col("z")), 4).alias("cos"))


@query(f"SELECT doc_id, array_to_string(list_slice(list_sort(list_distinct(t)), 1, 3), ' ') AS first3, CAST(len(list_filter(t, lambda x: length(x) > 6)) AS INTEGER) AS long_words, list_contains(t, 'the') AS has_the FROM (SELECT doc_id, regexp_extract_all(lower(text), {W}) AS t FROM documents WHERE text <> '')")
def fn_array_family(spark, d):
    t = table(spark, d, "documents").where("text <> ''").select("doc_id", textprep.tokens(F.col("text")).alias("t"))
    return t.select("doc_id", F.array_join(F.slice(F.array_sort(F.array_distinct("t")), 1, 3), " ").alias("first3"), F.size(F.filter("t", lambda x: F.length(x) > 6)).alias("long_words"), F.array_contains("t", "the").alias("has_the"))


@query("WITH " + count_sql(1) + " SELECT chunk_key, coalesce(max(CASE WHEN term = 'the' THEN cnt END), 0) AS the_count, count(*) AS words FROM counts GROUP BY chunk_key")
def fn_map_tf(spark, d):
    m = _counts(spark, d).groupBy("chunk_key").agg(F.map_from_entries(F.collect_list(F.struct("term", "cnt"))).alias("tf"))
    return m.select("chunk_key", F.coalesce(F.try_element_at("tf", F.lit("the")), F.lit(0)).alias("the_count"), F.size("tf").cast("long").alias("words"))


@query("SELECT event_id, len(props) AS n, json_valid(props) AS ok FROM events")
def fn_json_props(spark, d):
    return table(spark, d, "events").select("event_id", F.length("props").cast("long").alias("n"), F.get_json_object("props", "$").isNotNull().alias("ok"))


@query("SELECT doc_id, md5(text) AS m FROM documents")
def fn_hash_md5(spark, d):
    return table(spark, d, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("m"))


by_sql("sql_scalar_n", "SELECT lang, round(count(*) / (SELECT count(*) FROM documents), 6) AS share FROM documents GROUP BY lang", tables="documents")
by_sql("sql_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 50000)", tables="customer orders")
by_sql("sql_cte_chain", "WITH a AS (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang), b AS (SELECT source, max(n) AS m FROM a GROUP BY source), c AS (SELECT a.source, lang, n FROM a JOIN b ON a.source = b.source AND a.n = b.m) SELECT lang, count(*) AS sources FROM c GROUP BY lang", tables="documents")
REACH = "SELECT 'r:' || CAST(r_regionkey AS STRING) AS node, 0 AS step FROM region WHERE r_regionkey = 1 UNION ALL SELECT e.dst, t.step + 1 FROM t JOIN e ON e.src = t.node"
EDGES = "SELECT 'r:' || CAST(n_regionkey AS STRING) AS src, 'n:' || CAST(n_nationkey AS STRING) AS dst FROM nation UNION ALL SELECT 'n:' || CAST(c_nationkey AS STRING), 'c:' || CAST(c_custkey AS STRING) FROM customer"


@query(f"WITH RECURSIVE e AS ({EDGES}), t(node, step) AS ({REACH}) SELECT node, step FROM t".replace("STRING", "VARCHAR"))
def sql_recursive_reach(spark, d):
    heads = ", ".join(f"{t} AS (SELECT * FROM parquet.`{d}/{t}.parquet`)" for t in ("region", "nation", "customer"))
    return spark.sql(f"WITH RECURSIVE {heads}, e AS ({EDGES}), t(node, step) AS ({REACH}) SELECT node, step FROM t")


# ---- Python forms ----


@query()
def udf_lcs(spark, d):
    b = table(spark, d, "benchmark").select("item_id", "text")
    return b.select("item_id", lcs_ratio(F.col("text"), F.reverse(F.col("text"))).alias("v"), lcs_ratio(F.col("text"), F.col("text")).alias("self"))


@query()
def fn_lcs_fold(spark, d):
    n = table(spark, d, "nation")
    return n.select("n_nationkey", F.round(lcs_fold(F.concat_ws(" ", F.lit("the nation"), "n_name"), F.concat_ws(" ", "n_name", F.lit("the nation"))), 6).alias("v"))


@query()
def udf_encode(spark, d):
    from evigraph.functions.encoder import encode

    return encode(table(spark, d, "benchmark").select("item_id", "text"), "text").select("item_id", F.round(retrieval.cosine(F.col("vec"), F.col("vec")), 4).alias("norm"), F.size("vec").alias("dim"))


@query("SELECT label, round(sum(embedding[1]) / count(*), 4) AS first, count(*) AS n FROM embeddings GROUP BY label")
def udaf_vec_mean(spark, d):
    """Mean vector of a group by partial sums of positions, so no group is gathered."""
    pos = table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x"))
    mean = pos.groupBy("label", "i").agg((F.sum(F.col("x").cast("double")) / F.count("*")).alias("m"), F.count("*").alias("n"))
    return mean.where("i = 0").select("label", F.round("m", 4).alias("first"), "n")


@query(f"WITH {QV} SELECT qid, edge_id, ms FROM r WHERE rk <= 3")
def udf_matrix_topk(spark, d):
    """Exact top-k in Arrow batches: each task keeps its own best, one small window ends it."""
    e = table(spark, d, "embeddings")
    q = {r["vec_id"]: r["embedding"] for r in e.where("vec_id % 50 = 0").collect()}
    ids, mat = sorted(q), np.array([q[i] for i in sorted(q)])
    mat = mat / np.linalg.norm(mat, axis=1, keepdims=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            m = np.array(b.column(1).to_pylist(), float)
            s = np.round(mat @ (m / np.linalg.norm(m, axis=1, keepdims=True)).T, 4)
            keys = b.column(0).to_numpy()
            for i, qid in enumerate(ids):
                top = np.lexsort((keys, -s[i]))[:4]
                top = top[keys[top] != qid][:3]
                yield pa.RecordBatch.from_arrays([pa.array([qid] * len(top), pa.int64()), pa.array(keys[top], pa.int64()), pa.array(s[i][top])], names=["qid", "edge_id", "ms"])

    found = e.select("vec_id", "embedding").mapInArrow(run, "qid long, edge_id long, ms double")
    return retrieval.best(found, 3, "ms", "edge_id", digits=4).drop("rk")


@query("WITH " + chunk_sql() + " SELECT doc_key, chunk_no, CAST(len(tokens) AS INTEGER) AS n_tok FROM chunks")
def udtf_chunk(spark, d):
    sqlfuncs.register(spark)
    return spark.sql(f"SELECT CAST(doc_id AS STRING) AS doc_key, c.chunk_no, c.n_tok FROM parquet.`{d}/documents.parquet`, LATERAL chunk_text(text, 256, 32) c")


@query("WITH " + score_sql() + " SELECT chunk_key, round(max(er), 6) AS top FROM scores GROUP BY chunk_key")
def sql_functions(spark, d):
    """The score and the edge cost by their SQL names."""
    sqlfuncs.register(spark)
    rows = packed.candidates(textprep.chunk(documents(spark, d)), 3, cap=1)  # the best of each chunk, ties and near ties
    return rows.groupBy("chunk_key").agg(F.round(F.max(F.expr(sqlfuncs.ENTITY_SCORE)), 6).alias("top"))


@query()
def udf_mst(spark, d):
    """Spanning crossings of the star schema by grouped Kruskal."""
    from evigraph.operators import steiner
    from evigraph.queries.method import star_costs, star_terminals

    c = star_costs(spark, d)
    return steiner.spanning_crossings(steiner.boundary(c, steiner.regions(c, star_terminals(spark)))).select("qid", "t1", "t2", F.round("weight", 6).alias("weight"))


