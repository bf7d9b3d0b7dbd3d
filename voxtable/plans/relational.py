"""Generic operators at volume: scans, predicates, joins, aggregates, windows, sets, subqueries and function suites."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from voxtable.functions.hashing import draw, sql_draw
from voxtable.functions.shared import shared_folder, stored
from voxtable.registry import query
from voxtable.sources.tables import load, micros

DAY = 86_400_000_000


def _r(df: DataFrame, digits: int = 4) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _ev(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").withColumn("us", micros("ts"))


@query("scan_pruned_filter", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 49 AND l_discount >= 0.05")
def scan_pruned_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").filter("l_quantity > 49 AND l_discount >= 0.05D").select("l_orderkey", "l_quantity")


@query("proj_case", "SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS size, n_chars * 2 AS twice FROM documents")
def proj_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    size = F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long")
    return load(spark, sf_dir, "documents").select("doc_id", size.alias("size"), (F.col("n_chars") * 2).alias("twice"))


@query("filter_mix", "SELECT event_id FROM events WHERE value BETWEEN 10 AND 20 AND event_type IN ('click', 'view') AND props LIKE '%1%' AND regexp_matches(props, '[0-9]{2}') AND user_id IS NOT DISTINCT FROM user_id")
def filter_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    keep = F.col("value").between(10, 20) & F.col("event_type").isin("click", "view") & F.col("props").like("%1%") & F.col("props").rlike("[0-9]{2}") & F.col("user_id").eqNullSafe(F.col("user_id"))
    return e.filter(keep).select("event_id")


@query("join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations are 25 by definition."""
    c, n = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


ORDERS = "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 4) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority"


def _orders(spark: SparkSession, sf_dir: str, hint: str) -> DataFrame:
    o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    joined = o.join(li.hint(hint), o["o_orderkey"] == li["l_orderkey"])
    return _r(joined.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q")))


query("join_merge", ORDERS)(lambda spark, sf_dir: _orders(spark, sf_dir, "merge"))
query("join_shash", ORDERS)(lambda spark, sf_dir: _orders(spark, sf_dir, "shuffle_hash"))


@query("join_left_blank", "SELECT coalesce(toxic::VARCHAR, '') AS toxic, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")
def join_left_blank(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    return d.groupBy(F.coalesce(F.col("toxic").cast("string"), F.lit("")).alias("toxic")).agg(F.count(F.lit(1)).alias("n"))


@query("join_full_metrics", "SELECT source, a.n AS english, b.n AS french FROM (SELECT source, count(*) AS n FROM documents WHERE lang = 'en' GROUP BY 1) a FULL JOIN (SELECT source, count(*) AS n FROM documents WHERE lang = 'fr' GROUP BY 1) b USING (source)")
def join_full_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents")
    one = lambda where, name: d.filter(where).groupBy("source").agg(F.count(F.lit(1)).alias(name))
    return one("lang = 'en'", "english").join(one("lang = 'fr'", "french"), "source", "full")


@query("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def join_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels").filter("toxic = 1"), "doc_id", "left_semi")


@query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


@query("join_theta_lang", "SELECT a.lang AS prompt_lang, b.lang AS target_lang FROM (SELECT DISTINCT lang FROM documents) a JOIN (SELECT DISTINCT lang FROM documents) b ON a.lang <> b.lang")
def join_theta_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Over distinct languages only: the one inequality join, of a handful of rows."""
    langs = load(spark, sf_dir, "documents").select("lang").distinct()
    return langs.select(F.col("lang").alias("prompt_lang")).join(langs.select(F.col("lang").alias("target_lang")), F.col("prompt_lang") != F.col("target_lang"))


SPANS = "WITH ev AS (SELECT *, epoch_us(ts) AS us FROM events), sp AS (SELECT user_id, min(us) AS lo, min(us) + 86400000000 * 2 AS hi FROM ev WHERE event_type = 'signup' GROUP BY user_id)"


@query("join_range_segment", SPANS + " SELECT sp.user_id, count(*) AS n FROM sp JOIN ev ON ev.us BETWEEN sp.lo AND sp.hi GROUP BY sp.user_id")
def join_range_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events within each span, whoever's: both sides are dealt by day, a span under each day that it touches, so the range join is an equi-join."""
    e = _ev(spark, sf_dir)
    spans = e.filter("event_type = 'signup'").groupBy("user_id").agg(F.min("us").alias("lo")).withColumn("hi", F.col("lo") + 2 * DAY)
    by_day = spans.withColumn("day", F.explode(F.sequence(F.floor(F.col("lo") / DAY), F.floor(F.col("hi") / DAY))))
    points = e.select("us", F.floor(F.col("us") / DAY).alias("day"))
    return points.join(by_day, "day").filter("us BETWEEN lo AND hi").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query("join_asof_tokens", "WITH e AS (SELECT user_id, event_id, event_type, last_value(CASE WHEN event_type = 'signup' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id) AS lv FROM events) SELECT event_id, lv AS last_signup FROM e WHERE event_type = 'purchase'")
def join_asof_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Last sign-up value before each purchase: union by construction, last non-null in order, no range join."""
    w = Window.partitionBy("user_id").orderBy("event_id")
    last = F.last(F.when(F.col("event_type") == "signup", F.col("value")), ignorenulls=True).over(w)
    return load(spark, sf_dir, "events").withColumn("last_signup", last).filter("event_type = 'purchase'").select("event_id", "last_signup")


@query("join_interval", "WITH ev AS (SELECT *, epoch_us(ts) AS us FROM events) SELECT a.event_id, count(*) AS n FROM ev a JOIN ev b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND abs(a.us - b.us) <= 3600000000 GROUP BY a.event_id")
def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _ev(spark, sf_dir).select("event_id", "user_id", "us")
    b = e.select(F.col("user_id").alias("u"), F.col("event_id").alias("other"), F.col("us").alias("t"))
    hour = 3_600_000_000
    both = e.withColumn("cell", F.explode(F.array(*[F.floor(F.col("us") / hour) + d for d in (-1, 0, 1)]))).join(b.withColumn("cell", F.floor(F.col("t") / hour)), "cell")
    return both.filter((F.col("user_id") == F.col("u")) & (F.col("event_id") != F.col("other")) & (F.abs(F.col("us") - F.col("t")) <= hour)).groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))


@query("join_cross_grid", "SELECT w AS which, r AS render FROM (VALUES ('mono'), ('all')) a(w), (VALUES ('phones'), ('both')) b(r)")
def join_cross_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    grid = lambda name, *v: spark.createDataFrame([(x,) for x in v], f"{name} string")
    return grid("which", "mono", "all").crossJoin(grid("render", "phones", "both"))


@query("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 4) AS s, round(avg(l_extendedprice), 4) AS m, min(l_discount) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 4) AS sd, round(corr(l_quantity, l_extendedprice), 4) AS r FROM lineitem GROUP BY 1")
def agg_basic(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = F.col("l_quantity")
    return _r(load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(q).alias("s"), F.avg("l_extendedprice").alias("m"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi"), F.stddev_samp(q).alias("sd"), F.corr("l_quantity", "l_extendedprice").alias("r")))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("agg_sketch")
def agg_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct users by mergeable sketch."""
    sketches = load(spark, sf_dir, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s"))
    return sketches.select("event_type", F.hll_sketch_estimate("s").alias("users"))


@query("agg_filter", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, round(coalesce(sum(value) FILTER (WHERE event_type = 'purchase'), 0), 4) AS spent FROM events GROUP BY 1")
def agg_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    spent = F.coalesce(F.sum(F.when(F.col("event_type") == "purchase", F.col("value"))), F.lit(0.0))
    return _r(load(spark, sf_dir, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), spent.alias("spent")))


@query("agg_ordered", "SELECT user_id, string_agg(event_type, ',' ORDER BY event_id) AS path, arg_max(event_type, event_id) AS last FROM events GROUP BY 1")
def agg_ordered(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("event_id", "event_type"))), lambda s: s["event_type"]), ",")
    return load(spark, sf_dir, "events").groupBy("user_id").agg(path.alias("path"), F.max_by("event_type", "event_id").alias("last"))


@query("agg_quantile", "SELECT event_type, round(quantile_cont(value, 0.25), 4) AS q1, round(median(value), 4) AS q2, round(quantile_cont(value, 0.9), 4) AS p90 FROM events GROUP BY 1")
def agg_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = F.percentile("value", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.9)))
    return _r(load(spark, sf_dir, "events").groupBy("event_type").agg(q.alias("q")).select("event_type", F.col("q")[0].alias("q1"), F.col("q")[1].alias("q2"), F.col("q")[2].alias("p90")))


@query("agg_gsets", "SELECT event_type, user_id % 3 AS u, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 3), ())")
def agg_gsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("event_type", (F.col("user_id") % 3).alias("u"))
    return e.groupingSets([["event_type"], ["u"], []], "event_type", "u").agg(F.count(F.lit(1)).alias("n"))


@query("agg_pivot", "SELECT l_returnflag, round(sum(l_quantity) FILTER (WHERE l_linestatus = 'F'), 4) AS F, round(sum(l_quantity) FILTER (WHERE l_linestatus = 'O'), 4) AS O FROM lineitem GROUP BY 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(load(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.sum("l_quantity")))


@query("agg_unpivot", "SELECT doc_id, task, truth FROM (SELECT doc_id, 'quality' AS task, quality AS truth FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels)")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "task", "truth")


@query("win_rank", "SELECT c_custkey, rank() OVER w::INT AS r, dense_rank() OVER w::INT AS d, round(percent_rank() OVER w, 4) AS p, round(cume_dist() OVER w, 4) AS c, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)::INT AS q FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal)".replace("rank() OVER w::INT AS r, dense_rank() OVER w::INT", "(rank() OVER w)::INT AS r, (dense_rank() OVER w)::INT").replace("ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)::INT", "(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey))::INT"))
def win_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal")
    q = F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey"))
    return _r(load(spark, sf_dir, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.percent_rank().over(w).alias("p"), F.cume_dist().over(w).alias("c"), q.alias("q")))


@query("win_lag_gap", "WITH ev AS (SELECT *, epoch_us(ts) AS us FROM events) SELECT event_id, us - lag(us) OVER w AS gap, lead(event_type) OVER w AS nxt, first_value(event_type) OVER w AS fst FROM ev WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id")
    return _ev(spark, sf_dir).select("event_id", (F.col("us") - F.lag("us").over(w)).alias("gap"), F.lead("event_type").over(w).alias("nxt"), F.first("event_type").over(w).alias("fst"))


@query("win_frames", "WITH ev AS (SELECT *, epoch_us(ts) AS us FROM events) SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS rows_mean, count(*) OVER (PARTITION BY user_id ORDER BY us RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS in_day, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id), 4) AS running FROM ev")
def win_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id")
    return _r(_ev(spark, sf_dir).select("event_id", F.avg("value").over(w.orderBy("event_id").rowsBetween(-2, 0)).alias("rows_mean"), F.count(F.lit(1)).over(w.orderBy("us").rangeBetween(-DAY, 0)).alias("in_day"), F.sum("value").over(w.orderBy("event_id")).alias("running")))


@query("topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def topk_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, sf_dir, "orders").withColumn("rn", F.row_number().over(w)).filter("rn <= 2").select("o_custkey", "o_orderkey")


A, B = "SELECT doc_id % 300 AS id FROM documents WHERE lang = 'en'", "SELECT doc_id % 300 AS id FROM documents WHERE lang = 'fr'"


def _sides(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    d = load(spark, sf_dir, "documents").select((F.col("doc_id") % 300).alias("id"), "lang")
    return d.filter("lang = 'en'").select("id"), d.filter("lang = 'fr'").select("id")


@query("set_union", f"SELECT 'all' AS kind, count(*) AS n FROM ({A} UNION ALL {B}) UNION ALL SELECT 'distinct', count(*) FROM ({A} UNION {B})")
def set_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    n = lambda df, kind: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
    return n(a.unionAll(b), "all").unionAll(n(a.unionAll(b).distinct(), "distinct"))


@query("set_intersect", f"{A} INTERSECT ALL {B}")
def set_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    return a.intersectAll(b)


@query("set_except", f"{A} EXCEPT ALL {B}")
def set_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = _sides(spark, sf_dir)
    return a.exceptAll(b)


@query("subq_scalar", "SELECT doc_id FROM documents WHERE n_chars > (SELECT quantile_cont(n_chars, 0.95) FROM documents)")
def subq_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "documents").createOrReplaceTempView("voxtable_documents")
    return spark.sql("SELECT doc_id FROM voxtable_documents WHERE n_chars > (SELECT percentile(n_chars, 0.95) FROM voxtable_documents)")


@query("subq_exists", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_discount > 0.05) GROUP BY 1")
def subq_exists(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "orders").createOrReplaceTempView("voxtable_orders")
    load(spark, sf_dir, "lineitem").createOrReplaceTempView("voxtable_lineitem")
    return spark.sql("SELECT o_orderpriority, count(*) AS n FROM voxtable_orders WHERE EXISTS (SELECT 1 FROM voxtable_lineitem WHERE l_orderkey = o_orderkey AND l_discount > 0.05D) GROUP BY 1")


@query("cte_recursive", "WITH RECURSIVE c AS (SELECT l_linenumber::BIGINT AS n, count(*) AS lines FROM lineitem GROUP BY 1), t(n, f, lines) AS (SELECT n, 1::BIGINT, lines FROM c WHERE n = 1 UNION ALL SELECT c.n, t.f * c.n, c.lines FROM t JOIN c ON c.n = t.n + 1) SELECT n, f, lines FROM t")
def cte_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line numbers one after the other: in how many orders n lines can stand, and how many lines have the number."""
    lines = stored(load(spark, sf_dir, "lineitem").groupBy(F.col("l_linenumber").cast("bigint").alias("n")).agg(F.count(F.lit(1)).alias("lines")))
    return spark.sql("WITH RECURSIVE t(n, f, lines) AS (SELECT n, 1L, lines FROM {c} WHERE n = 1 UNION ALL SELECT c.n, t.f * c.n, c.lines FROM t JOIN {c} c ON c.n = t.n + 1) SELECT n, f, lines FROM t", c=lines)


@query("str_suite", "SELECT p_partkey, upper(p_name) AS up, substr(p_name, 2, 3) AS mid, string_split(p_name, ' ')[1] AS w, translate(p_name, 'aei', '123') AS tr, regexp_replace(p_name, '[aeiou]+', '_', 'g') AS rx, lpad(p_brand, 12, '*') AS pad, reverse(p_brand) AS rev, concat_ws('/', p_type, p_brand) AS cat, levenshtein(p_name, p_type) AS lev FROM part")
def str_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, b = F.col("p_name"), F.col("p_brand")
    return load(spark, sf_dir, "part").select("p_partkey", F.upper(n).alias("up"), F.substring(n, 2, 3).alias("mid"), F.split(n, " ")[0].alias("w"), F.translate(n, "aei", "123").alias("tr"), F.regexp_replace(n, "[aeiou]+", "_").alias("rx"), F.lpad(b, 12, "*").alias("pad"), F.reverse(b).alias("rev"), F.concat_ws("/", "p_type", "p_brand").alias("cat"), F.levenshtein(n, F.col("p_type")).alias("lev"))


@query("date_suite", "SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, month(o_orderdate)::INT AS m, (o_orderdate::DATE - DATE '1990-01-01')::INT AS days, strftime(o_orderdate, '%Y-%m') AS ym FROM orders")
def date_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.quarter(d).alias("q"), F.month(d).alias("m"), F.datediff(d.cast("date"), F.lit("1990-01-01").cast("date")).alias("days"), F.date_format(d, "yyyy-MM").alias("ym"))


@query("math_suite", "SELECT event_id, round(value, 1) AS r, floor(value)::BIGINT AS f, round(ln(value), 4) AS l, round(exp(-value), 4) AS e, round(tanh(value / 100), 4) AS t, round(pow(value, 0.5), 4) AS p, greatest(value, 50) AS g, (user_id % 7)::BIGINT AS m FROM events")
def math_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    # the logarithm of nothing is minus infinity and of less not a number, as in SQL; the engine's are null
    ln = F.when(v == 0, F.lit(float("-inf"))).when(v < 0, F.lit(float("nan"))).otherwise(F.ln(v))
    return load(spark, sf_dir, "events").select("event_id", F.round(v, 1).alias("r"), F.floor(v).alias("f"), F.round(ln, 4).alias("l"), F.round(F.exp(-v), 4).alias("e"), F.round(F.tanh(v / 100), 4).alias("t"), F.round(F.pow(v, F.lit(0.5)), 4).alias("p"), F.greatest(v, F.lit(50.0)).alias("g"), (F.col("user_id") % 7).alias("m"))


@query("arr_suite", "SELECT vec_id, round(list_max(embedding)::DOUBLE, 4) AS top, list_position(embedding, list_max(embedding))::BIGINT AS at, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE * 2)), 4) AS twice, len(list_filter(embedding, lambda x: x > 0))::INT AS positive FROM embeddings")
def arr_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = F.col("embedding")
    twice = F.aggregate(F.transform(F.slice(e, 1, 8), lambda x: x.cast("double") * 2), F.lit(0.0), lambda s, x: s + x)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.array_max(e).cast("double"), 4).alias("top"), F.array_position(e, F.array_max(e)).alias("at"), F.round(twice, 4).alias("twice"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@query("map_suite", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') * 2 AS clicks2, count(DISTINCT event_type)::INT AS kinds FROM events GROUP BY 1")
def map_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    packed = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    twice = F.transform_values("m", lambda k, v: v * 2)
    return packed.select("user_id", F.coalesce(F.try_element_at(twice, F.lit("click")), F.lit(0)).alias("clicks2"), F.size(F.map_keys("m")).alias("kinds"))


@query("json_suite", "SELECT event_id, (props->>'k')::INT AS k FROM events")
def json_suite(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("hash_sample", "SELECT doc_id, ('0x' || substr(md5(concat_ws('|', 's', doc_id)), 1, 8))::BIGINT % 100 AS b FROM documents WHERE ('0x' || substr(md5(concat_ws('|', 's', doc_id)), 1, 8))::BIGINT % 100 < 10")
def hash_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    from voxtable.functions.hashing import draw

    return load(spark, sf_dir, "documents").select("doc_id", (draw("s", F.col("doc_id")) % 100).alias("b")).filter("b < 10")


@query("dedup_exact", "SELECT md5(text) AS h, count(*) AS n, min(doc_id) AS keep FROM documents GROUP BY text")
def dedup_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grouped by digest and length, so no text is dealt."""
    d = load(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("h"), F.octet_length("text").alias("len"))
    return d.groupBy("h", "len").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("keep")).select("h", "n", "keep")


@query("sink_roundtrip", "SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY lang")
def sink_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents' lengths written by language and read again, with partition discovery."""
    from voxtable.sources.tables import write_pairs

    path = f"{shared_folder(spark)}/sink-{uuid.uuid4().hex}"
    write_pairs(load(spark, sf_dir, "documents").select("doc_id", "n_chars", "lang"), path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query("udtf_clauses", r"SELECT item_id, len(list_filter(regexp_split_to_array(text, '[.,]'), lambda c: trim(c) <> '')) AS n FROM benchmark")
def udtf_clauses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Punctuated clauses of a text by a table function, joined laterally."""
    from pyspark.sql.functions import udtf

    class Clauses:
        def eval(self, text: str):  # noqa: ANN202
            for c in (text or "").replace(",", ".").split("."):
                if c.strip():
                    yield (c.strip(),)

    spark.udtf.register("voxtable_clauses", udtf(Clauses, returnType="clause string"))
    load(spark, sf_dir, "benchmark").createOrReplaceTempView("voxtable_benchmark")
    return spark.sql("SELECT item_id, count(*) AS n FROM voxtable_benchmark, LATERAL voxtable_clauses(text) GROUP BY item_id")


@query("udaf_centroid", "SELECT label, round(avg(embedding[1]::DOUBLE), 6) AS c0, count(*) AS n FROM embeddings GROUP BY label")
def udaf_centroid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").groupBy("label").agg(F.round(F.avg(F.col("embedding")[0].cast("double")), 6).alias("c0"), F.count(F.lit(1)).alias("n"))


@query("sql_surface", "SELECT item_id, length(text) AS n, trim(regexp_replace(lower(text), '[^\\p{L}\\p{N}]+', ' ', 'g')) AS scored FROM benchmark")
def sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Methods as SQL functions over temporary views."""
    register(spark, sf_dir)
    return spark.sql("SELECT item_id, char_length(text) AS n, voxtable_scoring(text) AS scored FROM voxtable_benchmark")


def register(spark: SparkSession, sf_dir: str) -> None:
    """Installs the tables as views and the row-level methods as SQL functions."""
    for t in ("documents", "benchmark", "events", "embeddings", "labels", "conversations"):
        load(spark, sf_dir, t).createOrReplaceTempView(f"voxtable_{t}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION voxtable_scoring(t STRING) RETURNS STRING RETURN trim(regexp_replace(lower(t), '[^\\\\p{L}\\\\p{N}]+', ' '))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION voxtable_digit(x DOUBLE, k INT) RETURNS INT RETURN int(round(greatest(-k, least(k, x))))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION voxtable_error_rate(edits BIGINT, n BIGINT) RETURNS DOUBLE RETURN try_divide(double(edits), n)")


@query("rel_pricing", "SELECT l_returnflag, l_linestatus, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
def rel_pricing(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load(spark, sf_dir, "lineitem").filter("l_shipdate <= TIMESTAMP_NTZ'1998-09-02 00:00:00'")
    return _r(li.groupBy("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.count(F.lit(1)).alias("n")), 2)


@query("rel_nation_revenue", "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey GROUP BY n_name")
def rel_nation_revenue(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = {n: load(spark, sf_dir, n) for n in ("region", "nation", "customer", "orders", "lineitem", "supplier")}
    j = t["region"].join(t["nation"], F.col("r_regionkey") == F.col("n_regionkey")).join(t["customer"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["orders"], F.col("o_custkey") == F.col("c_custkey")).join(t["lineitem"], F.col("l_orderkey") == F.col("o_orderkey"))
    j = j.join(t["supplier"], (F.col("s_suppkey") == F.col("l_suppkey")) & (F.col("s_nationkey") == F.col("c_nationkey")))
    return _r(j.groupBy("n_name").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue")), 2)


@query("rel_promo_share", "SELECT round(100 * sum(CASE WHEN p_type = 'PROMO' THEN l_extendedprice ELSE 0 END) / sum(l_extendedprice), 4) AS share FROM lineitem JOIN part ON p_partkey = l_partkey")
def rel_promo_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    j = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "part"), F.col("p_partkey") == F.col("l_partkey"))
    return _r(j.agg((100 * F.sum(F.when(F.col("p_type") == "PROMO", F.col("l_extendedprice")).otherwise(0.0)) / F.sum("l_extendedprice")).alias("share")))


@query("rel_discount_sum", "SELECT round(sum(l_extendedprice * l_discount), 2) AS revenue FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_quantity < 24")
def rel_discount_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem").filter("l_discount BETWEEN 0.05D AND 0.07D AND l_quantity < 24")
    return _r(rows.agg(F.sum(F.col("l_extendedprice") * F.col("l_discount")).alias("revenue")), 2)


@query("sample_strat", "SELECT doc_id, lang FROM (SELECT doc_id, lang, " + sql_draw("'strat'", "doc_id") + " % 100 AS u FROM documents) WHERE u < CASE lang WHEN 'en' THEN 10 WHEN 'de' THEN 20 ELSE 40 END")
def sample_strat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A hashed share of each language: the same rows on every run, without a shuffle."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang")
    share = F.when(F.col("lang") == "en", 10).when(F.col("lang") == "de", 20).otherwise(40)
    return docs.filter(F.pmod(draw("strat", F.col("doc_id")), F.lit(100)) < share)


@query("rel_top_orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def rel_top_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)
