"""Operators that users of the methods need, each a query with its DuckDB twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import register
from ..experiments.sql import sentences, with_
from ..functions import text as t
from ..models.lexical import is_positive
from ..sources import corpora
from ..sources.corpora import table


def op(key: str, sql: str | None = None, **tables: str):
    """Register a builder that takes the named tables as DataFrames."""

    def enter(f):
        def build(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(*(table(spark, sf_dir, n) for n in tables.values()))

        build.__doc__ = f.__doc__
        build.__name__ = f.__name__
        register(key, sql)(build)
        return f

    return enter


# -- scans, projections, filters -------------------------------------------------------------------


@op("scan_parquet", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_quantity > 45", a="lineitem")
def scan_parquet(l):
    """Two columns, two filters: both reach the scan."""
    return l.where("l_shipdate >= timestamp '1997-01-01' and l_quantity > 45").select("l_orderkey", "l_quantity")


@op("proj_case", "SELECT o_orderkey, CASE WHEN o_totalprice >= 200000 THEN 'high' WHEN o_totalprice >= 50000 THEN 'mid' ELSE 'low' END AS band, round(o_totalprice * 2, 2) AS twice FROM orders", a="orders")
def proj_case(o):
    return o.select("o_orderkey", F.when(F.col("o_totalprice") >= 200000, "high").when(F.col("o_totalprice") >= 50000, "mid").otherwise("low").alias("band"), F.round(F.col("o_totalprice") * 2, 2).alias("twice"))


@op("filter_mix", "SELECT event_id, event_type, value FROM events WHERE value BETWEEN 6 AND 20 AND event_type IN ('click', 'view', 'purchase') AND props LIKE '{%' AND NOT (event_type IS NOT DISTINCT FROM 'none')", a="events")
def filter_mix(e):
    """BETWEEN, IN, LIKE and null-safe equality in one predicate."""
    return e.where(F.col("value").between(6, 20) & F.col("event_type").isin("click", "view", "purchase") & F.col("props").like("{%") & ~F.col("event_type").eqNullSafe("none")).select("event_id", "event_type", "value")


EDGES = """WITH e AS (SELECT CASE event_id % 5 WHEN 0 THEN 'half' WHEN 1 THEN 'above' WHEN 2 THEN 'nan' WHEN 3 THEN 'null' ELSE 'one' END AS name,
CASE event_id % 5 WHEN 0 THEN 0.5::DOUBLE WHEN 1 THEN 0.500001::DOUBLE WHEN 2 THEN 'nan'::DOUBLE WHEN 3 THEN NULL ELSE 1.0::DOUBLE END AS prob FROM events)
SELECT name, CASE WHEN NOT isnan(prob) THEN prob END AS prob, coalesce(NOT isnan(prob) AND prob > 0.5, false) AS is_boundary, count(*)::BIGINT AS events FROM e GROUP BY ALL"""


@op("threshold_edge", EDGES, a="events")
def threshold_edge(e):
    """Strictly more than one half; null and NaN are negative (NaN is shown as null). Events get the edges in turn."""
    edges = (("half", F.lit(0.5)), ("above", F.lit(0.500001)), ("nan", F.lit(float("nan"))), ("null", F.lit(None).cast("double")), ("one", F.lit(1.0)))
    turn = F.array(*(F.struct(F.lit(n).alias("name"), p.alias("prob")) for n, p in edges))
    x = e.select(F.get(turn, (F.col("event_id") % 5).cast("int")).alias("x")).select("x.*")
    rows = x.select("name", F.when(F.isnan("prob"), None).otherwise(F.col("prob")).alias("prob"), is_positive(F.col("prob")).alias("is_boundary"))
    return rows.groupBy("name", "prob", "is_boundary").agg(F.count("*").alias("events"))


# -- joins -----------------------------------------------------------------------------------------


@op("join_inner", "SELECT o_orderstatus, count(*)::BIGINT AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus", a="orders", b="lineitem")
def join_inner(o, l):
    return o.join(l.hint("merge"), o.o_orderkey == l.l_orderkey).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@op("join_hash", "SELECT c_mktsegment, count(*)::BIGINT AS n FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_mktsegment", a="customer", b="orders")
def join_hash(c, o):
    return o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@op("join_broadcast", "SELECT r_name, count(*)::BIGINT AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name", a="customer", b="nation", c="region")
def join_broadcast(c, n, r):
    """Nations and regions are of fixed size."""
    small = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return c.join(F.broadcast(small), c.c_nationkey == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("customers"))


@op("join_full", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS has_doc, l.doc_id IS NOT NULL AS has_label FROM (SELECT doc_id FROM documents WHERE doc_id % 2 = 0) d FULL JOIN labels l ON d.doc_id = l.doc_id", a="documents", b="labels")
def join_full(d, l):
    a, b = d.where("doc_id % 2 = 0").select(F.col("doc_id").alias("x")), l.select(F.col("doc_id").alias("y"))
    return a.join(b, F.col("x") == F.col("y"), "full").select(F.coalesce("x", "y").alias("doc_id"), F.col("x").isNotNull().alias("has_doc"), F.col("y").isNotNull().alias("has_label"))


@op("join_left", "SELECT s_suppkey, count(l_orderkey)::BIGINT AS lines FROM supplier LEFT JOIN lineitem ON s_suppkey = l_suppkey AND l_quantity > 49 GROUP BY s_suppkey", a="supplier", b="lineitem")
def join_left(s, l):
    return s.join(l.where("l_quantity > 49"), s.s_suppkey == l.l_suppkey, "left").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("lines"))


@op("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)", a="customer", b="orders")
def join_semi(c, o):
    return c.join(o.where("o_totalprice > 300000"), c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@op("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)", a="documents", b="labels")
def join_anti(d, l):
    return d.select("doc_id").join(l, "doc_id", "left_anti")


RANGE_SQL = with_(sentences("F-INT")) + ", w AS (SELECT DISTINCT doc_id, s AS first, least(s + 4, n_sent - 1) AS last FROM (SELECT doc_id, n_sent, unnest(range(0, n_sent, 3)) AS s FROM (SELECT DISTINCT doc_id, n_sent FROM sents))) SELECT w.doc_id, w.first::INT AS first, count(*)::BIGINT AS n, sum(n_tok)::BIGINT AS tokens FROM w JOIN sents ON sents.doc_id = w.doc_id AND idx BETWEEN w.first AND w.last GROUP BY ALL"


@register("join_range", RANGE_SQL)
def join_range(spark, sf_dir):
    """Sentences within windows: equality on the document, then the interval."""
    docs = corpora.interviews(spark, sf_dir)
    w = docs.where("n_sent > 0").select("doc_id", "n_sent", F.explode(F.sequence(F.lit(0), F.col("n_sent") - 1, F.lit(3))).alias("first")).select("doc_id", "first", F.least(F.col("first") + 4, F.col("n_sent") - 1).alias("last"))
    s = t.exploded(docs).alias("s")
    return s.join(w.alias("w"), (F.col("s.doc_id") == F.col("w.doc_id")) & F.col("s.idx").between(F.col("w.first"), F.col("w.last"))).groupBy("w.doc_id", "w.first").agg(F.count("*").alias("n"), F.sum(F.col("n_tok").cast("long")).alias("tokens"))


ASOF_SQL = with_(sentences("F-INT")) + " SELECT doc_id, idx, (SELECT max(b.idx) FROM sents b WHERE b.doc_id = a.doc_id AND b.ends_para AND b.idx <= a.idx)::INT AS boundary FROM sents a"


@register("join_asof", ASOF_SQL)
def join_asof(spark, sf_dir):
    """The latest boundary at or before each sentence, by one running window."""
    w = Window.partitionBy("doc_id").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", F.last(F.when(F.col("ends_para"), F.col("idx")), True).over(w).alias("boundary"))


@op("join_cross", "SELECT n_name, r_name FROM nation, region WHERE n_regionkey <> r_regionkey", a="nation", b="region")
def join_cross(n, r):
    """Two tables of fixed size."""
    return n.crossJoin(F.broadcast(r)).where("n_regionkey <> r_regionkey").select("n_name", "r_name")


@register("join_lateral", "SELECT c_custkey, x.o_orderkey, x.o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) x")
def join_lateral(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    best = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey", "o_totalprice")
    return c.lateralJoin(best).select("c_custkey", "o_orderkey", "o_totalprice")


@op("join_skew", "SELECT a.source, count(*)::BIGINT AS pairs FROM documents a JOIN labels b ON a.doc_id = b.doc_id GROUP BY a.source", a="documents", b="labels")
def join_skew(d, l):
    """Salted join: the hot side is dealt over salts, the other side is repeated for each."""
    salts = 4
    a = d.select("doc_id", "source").withColumn("salt", F.pmod(F.xxhash64("source", "doc_id"), F.lit(salts)).cast("int"))
    b = l.select("doc_id").withColumn("salt", F.explode(F.array(*map(F.lit, range(salts)))))
    return a.join(b, ["doc_id", "salt"]).groupBy("source").agg(F.count("*").alias("pairs"))


# -- aggregation -----------------------------------------------------------------------------------


@op("agg_distinct", "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY event_type", a="events")
def agg_distinct(e):
    return e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@op("agg_approx_distinct", a="events")
def agg_approx_distinct(e):
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@op("agg_rollup", "SELECT lang, source, count(*)::BIGINT AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)", a="documents")
def agg_rollup(d):
    return d.rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@op("agg_cube", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, grouping(l_returnflag)::INT AS g FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", a="lineitem")
def agg_cube(l):
    return l.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping("l_returnflag").cast("int").alias("g"))


@op("agg_grouping_sets", "SELECT lang, source, count(*)::BIGINT AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", a="documents")
def agg_grouping_sets(d):
    return d.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"))


@op("agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, min(n_chars) AS least, max(n_chars) AS most, round(avg(n_chars), 4) AS mean, round(stddev_samp(n_chars), 4) AS dev FROM documents GROUP BY lang", a="documents")
def agg_percentile(d):
    return d.groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.min("n_chars").alias("least"), F.max("n_chars").alias("most"), F.round(F.avg("n_chars"), 4).alias("mean"), F.round(F.stddev_samp("n_chars"), 4).alias("dev"))


@op("agg_percentile_approx", a="documents")
def agg_percentile_approx(d):
    return d.groupBy("lang").agg(F.percentile_approx("n_chars", [0.25, 0.5, 0.75], 10000).alias("quartiles"))


@op("agg_ordered_text", "SELECT conv_id, md5(string_agg(role || ':' || text, chr(10) ORDER BY turn)) AS digest, arg_max(role, turn) AS last_role FROM conversations GROUP BY conv_id", a="conversations")
def agg_ordered_text(c):
    """Documents rebuilt in order from their turns."""
    lists = c.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("x"), F.max_by("role", "turn").alias("last_role"))
    return lists.select("conv_id", F.md5(F.array_join(F.transform("x", lambda s: F.concat(s["role"], F.lit(":"), s["text"])), "\n").cast("binary")).alias("digest"), "last_role")


@op("agg_listagg", "SELECT r_name, string_agg(n_name, ',' ORDER BY n_name) AS nations FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY r_name", a="nation", b="region")
def agg_listagg(n, r):
    lists = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).groupBy("r_name").agg(F.sort_array(F.collect_list("n_name")).alias("x"))
    return lists.select("r_name", F.array_join("x", ",").alias("nations"))


@op("pivot_results", "SELECT lang, count(*) FILTER (quality = 1)::BIGINT AS good, count(*) FILTER (quality = 0)::BIGINT AS bad FROM documents JOIN labels USING (doc_id) GROUP BY lang", a="documents", b="labels")
def pivot_results(d, l):
    x = d.select("doc_id", "lang").join(l, "doc_id").groupBy("lang").pivot("quality", [1, 0]).count()
    return x.select("lang", F.coalesce(F.col("1"), F.lit(0)).alias("good"), F.coalesce(F.col("0"), F.lit(0)).alias("bad"))


@op("unpivot_labels", "SELECT doc_id, 'quality' AS name, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels", a="labels")
def unpivot_labels(l):
    return l.unpivot("doc_id", ["quality", "toxic"], "name", "v")


@op("agg_having", "SELECT l_suppkey, count(*)::BIGINT AS n FROM lineitem GROUP BY l_suppkey HAVING count(*) > 600", a="lineitem")
def agg_having(l):
    return l.groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600")


# -- window functions ------------------------------------------------------------------------------


@op("win_rank", "SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000)) AS rk, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000)) AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(3) OVER w AS nt FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)", a="supplier")
def win_rank(s):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    band = Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_acctbal") / 1000))
    return s.select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(band).alias("rk"), F.dense_rank().over(band).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(3).over(w).alias("nt"))


@op("win_lag_boundary", "SELECT vec_id, label IS DISTINCT FROM lead(label) OVER (PARTITION BY vec_id // 100 ORDER BY vec_id) AS boundary, lag(label, 1, -1) OVER (PARTITION BY vec_id // 100 ORDER BY vec_id) AS before FROM embeddings", a="embeddings")
def win_lag_boundary(e):
    """A boundary is where the label changes."""
    w = Window.partitionBy(F.floor(F.col("vec_id") / 100)).orderBy("vec_id")
    return e.select("vec_id", (~F.col("label").eqNullSafe(F.lead("label").over(w))).alias("boundary"), F.lag("label", 1, -1).over(w).alias("before"))


PARA_SQL = with_(sentences("F-INT")) + " SELECT doc_id, idx, coalesce(sum(ends_para::INT) OVER (PARTITION BY doc_id ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS para, sum(n_tok) OVER (PARTITION BY doc_id ORDER BY idx)::BIGINT AS upto FROM sents"


@register("win_para_id", PARA_SQL)
def win_para_id(spark, sf_dir):
    w = Window.partitionBy("doc_id").orderBy("idx")
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    return t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", F.coalesce(F.sum(F.col("ends_para").cast("long")).over(before), F.lit(0)).alias("para"), F.sum(F.col("n_tok").cast("long")).over(w).alias("upto"))


@op("win_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING), 4) AS before, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN CURRENT ROW AND 2 FOLLOWING)::BIGINT AS after FROM events", a="events")
def win_rows(e):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return e.select("event_id", F.round(F.avg("value").over(w.rowsBetween(-3, -1)), 4).alias("before"), F.count("*").over(w.rowsBetween(0, 2)).alias("after"))


@op("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)::BIGINT AS last_hour FROM events", a="events")
def win_range(e):
    """Events of a user within an hour before each; times count as the nearest second, halves as the even one."""
    second = F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")
    w = Window.partitionBy("user_id").orderBy(second).rangeBetween(-3600, 0)
    return e.select("event_id", F.count("*").over(w).alias("last_hour"))


@op("win_last", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER w AS last_buy, first_value(event_id) OVER w AS first_event, nth_value(event_id, 2) OVER w AS second_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)", a="events")
def win_last(e):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(w).alias("last_buy"), F.first("event_id").over(w).alias("first_event"), F.nth_value("event_id", 2).over(w).alias("second_event"))


ISLANDS_SQL = with_(sentences("F-INT")) + ", p AS (SELECT *, coalesce(sum(ends_para::INT) OVER (PARTITION BY doc_id ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS para FROM sents) SELECT doc_id, min(idx)::INT AS first, max(idx)::INT AS last FROM p GROUP BY doc_id, para"


@register("segments_islands", ISLANDS_SQL)
def segments_islands(spark, sf_dir):
    """Segments from boundary flags, inside the document's arrays."""
    docs = corpora.interviews(spark, sf_dir).where("n_sent > 0")
    return docs.select("doc_id", F.inline(t.segments(F.transform("sents", lambda s: s["ends_para"]))))


# -- order, sets -----------------------------------------------------------------------------------


@op("sort_total", "SELECT c_custkey, c_acctbal, row_number() OVER (ORDER BY c_acctbal DESC, c_custkey) AS place FROM customer QUALIFY place <= 100", a="customer")
def sort_total(c):
    """A total order; the place is counted on the first hundred rows alone."""
    top = c.select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey").limit(100)
    return top.withColumn("place", F.row_number().over(Window.orderBy(F.desc("c_acctbal"), "c_custkey")))


@op("topk", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20", a="documents")
def topk(d):
    return d.select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


@op("topk_group", "SELECT source, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3", a="documents")
def topk_group(d):
    """Best three of each source; Spark limits each task's groups before the shuffle."""
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return d.select("source", "doc_id", "n_chars").withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


@op("paging", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 50 OFFSET 200", a="orders")
def paging(o):
    return o.select("o_orderkey").orderBy("o_orderkey").offset(200).limit(50)


@op("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", a="customer", b="supplier")
def set_union(c, s):
    return c.select(F.col("c_nationkey").alias("k")).unionByName(s.select(F.col("s_nationkey").alias("k"))).distinct()


@op("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier", a="customer", b="supplier")
def set_intersect(c, s):
    return c.select(F.col("c_nationkey").alias("k")).intersectAll(s.select("s_nationkey"))


@op("set_except", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier", a="customer", b="supplier")
def set_except(c, s):
    return c.select(F.col("c_nationkey").alias("k")).exceptAll(s.select("s_nationkey"))


# -- functions -------------------------------------------------------------------------------------


@op("fn_string", "SELECT doc_id, lower(substr(text, 1, 5)) AS head, len(string_split(text, ' ')) AS parts, regexp_extract(text, '([a-z]+)', 1) AS word, translate(substr(text, 1, 9), 'aeiou', '12345') AS coded, md5(text) AS digest, levenshtein('kitten', 'sitting')::INT AS d, lpad(doc_id::VARCHAR, 6, '0') AS padded, reverse(lang) AS rev FROM documents", a="documents")
def fn_string(d):
    return d.select("doc_id", F.lower(F.substring("text", 1, 5)).alias("head"), F.size(F.split("text", " ")).cast("long").alias("parts"), F.regexp_extract("text", "([a-z]+)", 1).alias("word"), F.translate(F.substring("text", 1, 9), "aeiou", "12345").alias("coded"), F.md5(F.col("text").cast("binary")).alias("digest"), F.levenshtein(F.lit("kitten"), F.lit("sitting")).alias("d"), F.lpad(F.col("doc_id").cast("string"), 6, "0").alias("padded"), F.reverse("lang").alias("rev"))


@op("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding[1:4], lambda x: x::DOUBLE * 2)), 4) AS s, len(list_filter(embedding, lambda x: x > 0))::INT AS pos, len(embedding)::INT AS n, list_contains(range(label), 3) AS has3, array_to_string(range(label), ',') AS seq FROM embeddings", a="embeddings")
def fn_array(e):
    ints = F.when(F.col("label") > 0, F.sequence(F.lit(0), F.col("label") - 1)).otherwise(F.array().cast("array<int>"))
    return e.select("vec_id", F.round(F.aggregate(F.transform(F.slice("embedding", 1, 4), lambda x: x.cast("double") * 2), F.lit(0.0), lambda a, x: a + x), 4).alias("s"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.size("embedding").alias("n"), F.array_contains(ints, 3).alias("has3"), F.array_join(ints.cast("array<string>"), ",").alias("seq"))


@op("fn_map", "SELECT n_nationkey, CASE n_regionkey WHEN 0 THEN 'a' WHEN 1 THEN 'b' END AS letter, 2 AS entries FROM nation", a="nation")
def fn_map(n):
    m = F.map_from_entries(F.array(F.struct(F.lit(0), F.lit("a")), F.struct(F.lit(1), F.lit("b"))))
    return n.select("n_nationkey", F.try_element_at(m, F.col("n_regionkey")).alias("letter"), F.size(m).alias("entries"))


@op("fn_json", "SELECT event_id, (props::JSON->>'$.k')::INT AS k, '{\"e\":' || event_id || '}' AS again FROM events", a="events")
def fn_json(e):
    return e.select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.to_json(F.struct(F.col("event_id").alias("e"))).alias("again"))


@op("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, year(o_orderdate)::INT AS y, (o_orderdate + INTERVAL 36 HOUR)::DATE AS later FROM orders", a="orders")
def fn_date(o):
    return o.select("o_orderkey", F.trunc("o_orderdate", "month").alias("month"), F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("y"), F.to_date(F.col("o_orderdate") + F.expr("INTERVAL 36 HOURS")).alias("later"))


@op("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, floor(p_retailprice / 7)::BIGINT AS f, p_size // 5 AS q, round(exp(-p_size / 10.0), 6) AS e FROM part", a="part")
def fn_math(p):
    return p.select("p_partkey", F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("s"), F.floor(F.col("p_retailprice") / 7).alias("f"), F.floor(F.col("p_size") / 5).cast("int").alias("q"), F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("e"))


@op("fn_vector", "SELECT a.vec_id, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS dot, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1", a="embeddings")
def fn_vector(e):
    v = e.select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    b = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("u"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
    return v.join(b, "vec_id").select("vec_id", F.round(dot("v", "u"), 4).alias("dot"), F.round(dot("v", "u") / F.sqrt(dot("v", "v") * dot("u", "u")), 4).alias("cosine"))


# -- subqueries ------------------------------------------------------------------------------------


@register("subquery_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c.c_custkey AND o_orderstatus = 'F') AND c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
def subquery_exists(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    mean = c.agg(F.avg("c_acctbal")).scalar()
    own = o.where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_orderstatus") == "F")).exists()
    return c.where(own & (F.col("c_acctbal") > mean)).select("c_custkey")


RECURSIVE = "WITH RECURSIVE m AS (SELECT DISTINCT CAST(month(o_orderdate) AS INT) AS k FROM {orders}), r(n, f) AS (SELECT k, CAST(k AS BIGINT) FROM m WHERE k = 1 UNION ALL SELECT m.k, f * m.k FROM r JOIN m ON m.k = r.n + 1) SELECT n, f FROM r"


@register("cte_recursive", RECURSIVE.format(orders="orders"))
def cte_recursive(spark, sf_dir):
    """Factorials along the months of the orders: each step joins the table's next month."""
    return spark.sql(RECURSIVE, orders=table(spark, sf_dir, "orders"))


# -- sampling and hygiene --------------------------------------------------------------------------


@op("sample_hash", "SELECT doc_id FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 10 = 0", a="documents")
def sample_hash(d):
    """A tenth of the rows, by the id's hash: no sort, the same rows in every run."""
    return d.where(t.h(F.col("doc_id")) % 10 == 0).select("doc_id")


@op("sample_stratified", a="documents")
def sample_stratified(d):
    return d.sampleBy("lang", {"en": 0.1, "de": 0.5, "fr": 0.5, "es": 0.5}, seed=3).groupBy("lang").count()


@op("dedup_exact", "SELECT min(doc_id) AS doc_id, count(*)::BIGINT AS copies FROM documents GROUP BY md5(text)", a="documents")
def dedup_exact(d):
    return d.groupBy(F.md5(F.col("text").cast("binary")).alias("m")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("m")


@op("dedup_near", a="documents")
def dedup_near(d):
    """Near copies by banded min-hash signatures of word sets: (doc_id, group), group by the smallest id of a shared band."""
    words = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1)))
    low = lambda k: F.array_min(F.transform("w", lambda x: F.xxhash64(x, F.lit(k))))
    sig = d.select("doc_id", words.alias("w")).where(F.size("w") > 0).select("doc_id", *(low(k).alias(f"m{k}") for k in range(12)))
    bands = sig.select("doc_id", F.explode(F.array(*(F.xxhash64(F.lit(b), *(f"m{k}" for k in range(4 * b, 4 * b + 4))) for b in range(3)))).alias("band"))
    least = bands.groupBy("band").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")).where("n > 1")
    return bands.join(least, "band").groupBy("doc_id").agg(F.min("least").alias("group"))


@op("quality_filter", "SELECT d.doc_id, d.lang FROM documents d WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)", a="documents", b="labels")
def quality_filter(d, l):
    return d.select("doc_id", "lang").join(l.where("quality = 1"), "doc_id", "left_semi")


@register("html_paragraphs")
def html_paragraphs(spark, sf_dir):
    """Paragraph strings of every page."""
    return table(spark, sf_dir, "pages").select("page_id", F.posexplode(t.html_paragraphs(F.col("html"))).alias("i", "paragraph"))
