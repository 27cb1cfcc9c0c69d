"""Surrounding operators on the given tables: scans, projections, joins, aggregates, windows, sets, functions. Each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import sql as macros
from ..functions.text import tokens
from ..operators import detect
from ..sources import snippets, tables
from ..sources.scratch import Scratch, folder
from ..sources.tables import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


# ---- scans, sources, sinks -----------------------------------------------------------------------------------------------------


@query("scan_parquet", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > 150000 GROUP BY 1")
def scan_parquet(spark, d):
    return table(spark, d, "orders").filter("o_totalprice > 150000").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def _round_trip(fmt: str, schema: str = "c_custkey bigint, c_name string, c_nationkey bigint"):
    def run(spark, d) -> DataFrame:
        path = folder(spark, fmt)
        table(spark, d, "customer").select(F.col("c_custkey").cast("bigint").alias("c_custkey"), "c_name", F.col("c_nationkey").cast("bigint").alias("c_nationkey")).write.format(fmt).save(path)
        return tables.read(spark, path, fmt, schema).groupBy("c_nationkey").agg(F.count("*").alias("n"), F.max("c_name").alias("last"))

    return run


for _fmt in ("csv", "json", "orc"):
    QUERIES[f"scan_roundtrip_{_fmt}"] = _round_trip(_fmt)
    SQL[f"scan_roundtrip_{_fmt}"] = "SELECT CAST(c_nationkey AS BIGINT) AS c_nationkey, count(*) AS n, max(c_name) AS last FROM customer GROUP BY 1"


@query("source_snippets", "SELECT o_orderkey AS doc_id, array_to_string(['w' || CAST('0x' || substr(md5(CAST(o_orderkey AS VARCHAR)), k, 2) AS INTEGER) FOR k IN range(1, 33, 2)], ' ') AS text FROM orders WHERE o_orderkey IS NOT NULL")
def source_snippets(spark, d):
    """The source's snippets at the numbers of the orders."""
    return snippets.of_numbers(table(spark, d, "orders").select(F.col("o_orderkey").cast("bigint")))


@query("sink_partitioned")
def sink_partitioned(spark, d):
    path = folder(spark, "bands")
    docs = tables.with_arrival(table(spark, d, "documents"), table(spark, d, "events")).select("doc_id", "lang", F.to_date("ts").alias("day"))
    tables.write(docs, path, ("lang", "day"), ("doc_id",))
    return spark.read.parquet(path).groupBy("lang", "day").agg(F.count("*").alias("n"))


# ---- projection, filter, predicate -----------------------------------------------------------------------------------------------


@query("op_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def op_project(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("op_filter_compare", "SELECT count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_shipdate < TIMESTAMP '1997-01-01'")
def op_filter_compare(spark, d):
    keep = F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_shipdate") < F.lit("1997-01-01").cast("timestamp_ntz"))
    return table(spark, d, "lineitem").filter(keep).agg(F.count("*").alias("n"))


@query("op_filter_like", "SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_name, '^[b-m]')")
def op_filter_like(spark, d):
    return table(spark, d, "part").filter(F.col("p_name").like("%a%") & F.col("p_name").rlike("^[b-m]")).select("p_partkey")


@query("op_filter_nullsafe", "SELECT count(*) AS n FROM (SELECT nullif(n_regionkey, 1) AS a, nullif(n_nationkey % 5, 1) AS b FROM nation) WHERE a IS NOT DISTINCT FROM b")
def op_filter_nullsafe(spark, d):
    both = table(spark, d, "nation").select(F.nullif("n_regionkey", F.lit(1)).alias("a"), F.nullif(F.col("n_nationkey") % 5, F.lit(1)).alias("b"))
    return both.filter(F.col("a").eqNullSafe(F.col("b"))).agg(F.count("*").alias("n"))


@query("op_nulls", "SELECT doc_id, coalesce(nullif(quality, 0), -1) AS q, CASE WHEN toxic = 1 THEN 'toxic' WHEN quality = 1 THEN 'good' ELSE 'other' END AS kind FROM labels")
def op_nulls(spark, d):
    kind = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "good").otherwise("other")
    return table(spark, d, "labels").select("doc_id", F.coalesce(F.nullif("quality", F.lit(0)), F.lit(-1)).alias("q"), kind.alias("kind"))


@query("op_hash_sample", "SELECT doc_id, CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT) % 10 AS fold FROM documents")
def op_hash_sample(spark, d):
    return table(spark, d, "documents").select("doc_id", (F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("bigint") % 10).alias("fold"))


def _views(spark, d, *names: str) -> None:
    for n in names:
        table(spark, d, n).createOrReplaceTempView(n)


def _plain(name: str, text: str, *names: str) -> None:
    """A query whose SQL both engines read."""

    def run(spark, d) -> DataFrame:
        _views(spark, d, *names)
        return spark.sql(text)

    QUERIES[name], SQL[name] = run, text


_plain("op_subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders)", "orders")
_plain("op_subquery_in", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)", "customer", "orders")
_plain("op_subquery_exists", "SELECT s_suppkey FROM supplier s WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_suppkey = s.s_suppkey AND l_quantity > 49)", "supplier", "lineitem")
_plain("op_subquery_not_exists", "SELECT count(*) AS n FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)", "customer", "orders")
_plain("op_subquery_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)", "orders")
_plain("op_cte", "WITH t AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT n, count(*) AS customers FROM t GROUP BY n", "orders")
_plain("op_cte_recursive", "WITH RECURSIVE c AS (SELECT o_orderpriority AS p, count(*) AS t FROM orders GROUP BY 1), r(p, n, f) AS (SELECT p, 1, t FROM c UNION ALL SELECT p, n + 1, f * 2 FROM r WHERE n < 12) SELECT p, n, f FROM r", "orders")


@query("op_generate", r"SELECT lang, count(*) AS n FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS t FROM documents) GROUP BY lang")
def op_generate(spark, d):
    return table(spark, d, "documents").select("lang", F.explode(tokens(F.col("text"))).alias("t")).groupBy("lang").agg(F.count("*").alias("n"))


@query("op_cast", "SELECT event_id, TRY_CAST(substr(props, 6, 2) AS INTEGER) AS k, round(value / nullif(event_id % 3, 0), 6) AS share FROM events")
def op_cast(spark, d):
    events = table(spark, d, "events")
    return events.select("event_id", F.substring("props", 6, 2).try_cast("int").alias("k"), F.round(F.try_divide("value", F.nullif(F.col("event_id") % 3, F.lit(0))), 6).alias("share"))


# ---- joins -----------------------------------------------------------------------------------------------------------------------


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_broadcast(spark, d):
    nations = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


ORDERED = "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _hinted(hint: str):
    def run(spark, d) -> DataFrame:
        lines = table(spark, d, "lineitem").select("l_orderkey", "l_quantity")
        orders = table(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
        return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))

    return run


for _name, _hint in (("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    QUERIES[_name], SQL[_name] = _hinted(_hint), ORDERED


def _outer(how: str):
    def run(spark, d) -> DataFrame:
        old = table(spark, d, "labels").filter("quality = 1").select("doc_id", F.lit(1).alias("a"))
        new = table(spark, d, "labels").filter("doc_id % 2 = 0").select("doc_id", F.lit(1).alias("b"))
        return old.join(new, "doc_id", how).groupBy(F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b")).agg(F.count("*").alias("n"))

    return run


for _how in ("left", "right", "full"):
    QUERIES[f"join_outer_{_how}"] = _outer(_how)
    SQL[f"join_outer_{_how}"] = f"SELECT coalesce(a, 0) AS a, coalesce(b, 0) AS b, count(*) AS n FROM (SELECT doc_id, 1 AS a FROM labels WHERE quality = 1) x {_how.upper()} JOIN (SELECT doc_id, 1 AS b FROM labels WHERE doc_id % 2 = 0) y USING (doc_id) GROUP BY ALL"


@query("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left_semi")


@query("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels"), "doc_id", "left_anti")


@query("join_prior", "SELECT a.o_orderkey AS q, count(*) AS earlier FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderkey < a.o_orderkey GROUP BY 1")
def join_prior(spark, d):
    a = table(spark, d, "orders").select(F.col("o_orderkey").alias("q"), "o_custkey")
    b = table(spark, d, "orders").select(F.col("o_orderkey").alias("h"), "o_custkey")
    return a.join(b, "o_custkey").filter("h < q").groupBy("q").agg(F.count("*").alias("earlier"))


@query("join_theta", "SELECT a.n_name AS a, count(*) AS n FROM nation a JOIN nation b ON a.n_name < b.n_name GROUP BY 1")
def join_theta(spark, d):
    n = table(spark, d, "nation")
    return n.select(F.col("n_name").alias("a")).join(F.broadcast(n.select(F.col("n_name").alias("b"))), F.col("a") < F.col("b")).groupBy("a").agg(F.count("*").alias("n"))


@query("join_range", "SELECT k.k, count(*) AS n FROM events e JOIN (SELECT unnest(range(20)) AS k) k ON e.value >= k.k * 17 AND e.value < k.k * 17 + 30 GROUP BY 1")
def join_range(spark, d):
    """Overlapping ranges by an equi-join on bins of both sides, then the exact test."""
    width = 30
    spans = spark.range(20).select(F.col("id").alias("k"), (F.col("id") * 17).alias("lo"), (F.col("id") * 17 + 30).alias("hi"))
    binned = spans.select("*", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))).alias("bin"))
    points = table(spark, d, "events").select("value", F.floor(F.col("value") / width).alias("bin"))
    return points.join(binned, "bin").filter("value >= lo AND value < hi").groupBy("k").agg(F.count("*").alias("n"))


@query("join_asof", "SELECT d.doc_id, max(e.event_id) AS last_click FROM documents d JOIN events x ON x.event_id = d.doc_id JOIN events e ON e.event_type = 'click' AND e.ts <= x.ts GROUP BY 1")
def join_asof(spark, d):
    """The latest click not after each document: one sorted pass over the union, a day a partition, with the day's carry-over."""
    events = table(spark, d, "events")
    left = table(spark, d, "documents").select("doc_id").join(events.select(F.col("event_id").alias("doc_id"), "ts"), "doc_id")
    clicks = events.filter("event_type = 'click'").select("ts", F.col("event_id").alias("click"))
    both = left.select("ts", "doc_id", F.lit(None).cast("bigint").alias("click"), F.lit(1).alias("side")).unionByName(clicks.select("ts", F.lit(None).cast("bigint").alias("doc_id"), "click", F.lit(0).alias("side")))
    both = both.withColumn("day", F.to_date("ts"))
    carry = both.groupBy("day").agg(F.max_by("click", F.when(F.col("side") == 0, F.struct("ts", "click"))).alias("day_last"))
    carry = carry.withColumn("before", F.last("day_last", ignorenulls=True).over(W.orderBy("day").rowsBetween(W.unboundedPreceding, -1)))
    within = W.partitionBy("day").orderBy("ts", "side", "click").rowsBetween(W.unboundedPreceding, 0)
    seen = both.withColumn("here", F.last("click", ignorenulls=True).over(within)).filter("side = 1").join(F.broadcast(carry.select("day", "before")), "day")
    return seen.select("doc_id", F.coalesce("here", "before").alias("last_click")).filter("last_click IS NOT NULL")


@query("join_interval", "SELECT a.event_id AS q, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND b.ts BETWEEN a.ts - INTERVAL 1 DAY AND a.ts GROUP BY 1")
def join_interval(spark, d):
    e = table(spark, d, "events")
    a, b = e.select(F.col("event_id").alias("q"), "user_id", F.col("ts").alias("t")), e.select(F.col("event_id").alias("h"), "user_id", F.col("ts").alias("u"))
    return a.join(b, "user_id").filter("h <> q AND u <= t AND u >= t - INTERVAL 1 DAY").groupBy("q").agg(F.count("*").alias("n"))


@query("join_recursive", """WITH RECURSIVE o AS (SELECT o_orderkey, o_orderdate, lag(o_orderkey) OVER w AS p, lag(o_orderdate) OVER w AS t FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)),
e AS (SELECT o_orderkey, CASE WHEN o_orderdate <= t + INTERVAL 180 DAY THEN p END AS up FROM o), r AS (SELECT o_orderkey, o_orderkey AS first_order FROM e WHERE up IS NULL UNION ALL SELECT e.o_orderkey, r.first_order FROM e JOIN r ON e.up = r.o_orderkey) SELECT * FROM r""")
def join_recursive(spark, d):
    """Runs of a customer's orders, each within 180 days of the one before, followed to their first by joins that double their reach."""
    by = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    near = F.col("o_orderdate") <= F.lag("o_orderdate").over(by) + F.expr("INTERVAL 180 DAY")
    links = table(spark, d, "orders").select(F.col("o_orderkey").alias("doc_id"), F.when(near, F.lag("o_orderkey").over(by)).alias("match_id"))
    return detect.chains(links, Scratch(spark, "runs").write).select(F.col("doc_id").alias("o_orderkey"), F.col("story").alias("first_order"))


@query("join_salted", ORDERED)
def join_salted(spark, d, salts: int = 8):
    """The order side is copied once a salt, so that one order's lines can be in several tasks."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_quantity", F.pmod(F.xxhash64("l_partkey", "l_linenumber"), F.lit(salts)).alias("salt"))
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderpriority", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))).alias("salt"))
    return lines.join(orders, ["l_orderkey", "salt"]).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


# ---- aggregates ------------------------------------------------------------------------------------------------------------------

_plain("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_extendedprice), 4) AS p FROM lineitem GROUP BY l_returnflag, l_linestatus", "lineitem")
_plain("agg_sort", "SELECT o_custkey, max(o_orderpriority) AS last, min(o_orderpriority) AS first FROM orders GROUP BY o_custkey", "orders")
_plain("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_orderkey) AS orders FROM lineitem", "lineitem")
_plain("agg_filtered", "SELECT o_orderstatus, count(*) FILTER (WHERE o_totalprice > 200000) AS big, round(sum(o_totalprice) FILTER (WHERE o_totalprice <= 200000), 2) AS small FROM orders GROUP BY o_orderstatus", "orders")
_plain("agg_grouping_sets", "SELECT lang, source, count(*) AS n, CAST(grouping(lang) AS INTEGER) AS g FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())", "documents")
_plain("agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)", "documents")
_plain("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)", "lineitem")
_plain("agg_having", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY l_partkey HAVING count(*) > 30", "lineitem")


@query("agg_pivot", "SELECT lang, count(*) FILTER (source = 'src0') AS src0, count(*) FILTER (source = 'src1') AS src1 FROM documents GROUP BY lang")
def agg_pivot(spark, d):
    return table(spark, d, "documents").groupBy("lang").pivot("source", ["src0", "src1"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_unpivot", "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def agg_unpivot(spark, d):
    return table(spark, d, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value")


@query("agg_approx")
def agg_approx(spark, d):
    terms = table(spark, d, "documents").select("doc_id", F.explode(tokens(F.col("text"))).alias("term"))
    return terms.agg(F.approx_count_distinct("term", 0.02).alias("distinct"), F.hll_sketch_estimate(F.hll_sketch_agg("term")).alias("hll"), F.percentile_approx("doc_id", 0.5).alias("median"), F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(doc_id), 0.5D)").alias("kll_median"))


@query("agg_stats", """WITH c AS (SELECT l_returnflag, l_quantity AS most, count(*) AS n FROM lineitem GROUP BY ALL), m AS (SELECT * FROM c QUALIFY row_number() OVER (PARTITION BY l_returnflag ORDER BY n DESC, most) = 1)
SELECT l_returnflag, any_value(most) AS most, round(quantile_cont(l_quantity, 0.5), 6) AS med, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem JOIN m USING (l_returnflag) GROUP BY 1""")
def agg_stats(spark, d):
    lines = table(spark, d, "lineitem").groupBy("l_returnflag")
    return lines.agg(F.mode("l_quantity", True).alias("most"), F.round(F.expr("percentile(l_quantity, 0.5)"), 6).alias("med"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"))


@query("agg_argmin", "SELECT o_custkey, o_orderkey, o_totalprice FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS r FROM orders) WHERE r = 1")
def agg_argmin(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.min(F.struct("o_totalprice", "o_orderkey")).alias("s")).select("o_custkey", "s.o_orderkey", "s.o_totalprice")


# ---- windows, sorts, sets ----------------------------------------------------------------------------------------------------------

_plain("win_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER w AS nt, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)", "orders")
_plain("win_analytic", "SELECT o_orderkey, lag(o_totalprice) OVER w AS prev, lead(o_totalprice) OVER w AS next, first_value(o_orderkey) OVER w AS first, nth_value(o_orderkey, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)", "orders")
_plain("win_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS three, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near, count(*) OVER (PARTITION BY user_id) AS whole FROM events", "events")
_plain("sort_multi", "SELECT o_orderkey FROM (SELECT o_orderkey FROM orders ORDER BY o_orderpriority DESC NULLS LAST, o_orderkey LIMIT 50 OFFSET 10) t", "orders")
_plain("sort_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", "orders")
_plain("sort_topk_group", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 3", "orders")
_plain("set_union", "SELECT o_custkey AS k FROM orders UNION SELECT c_custkey FROM customer", "orders", "customer")
_plain("set_union_all", "SELECT n_nationkey AS k FROM nation UNION ALL SELECT r_regionkey FROM region", "nation", "region")
_plain("set_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer WHERE c_custkey % 2 = 0", "orders", "customer")
_plain("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders", "orders", "customer")


# ---- functions -------------------------------------------------------------------------------------------------------------------


@query("fn_string", "SELECT doc_id, lower(substr(text, 1, 20)) AS low, CAST(length(text) AS BIGINT) AS n, md5(text) AS m, sha256(text) AS s, replace(source, 'src', 'S') AS r, CAST(levenshtein(lang, source) AS BIGINT) AS l FROM documents")
def fn_string(spark, d):
    docs = table(spark, d, "documents")
    return docs.select("doc_id", F.lower(F.substring("text", 1, 20)).alias("low"), F.length("text").cast("bigint").alias("n"), F.md5("text").alias("m"), F.sha2("text", 256).alias("s"), F.replace("source", F.lit("src"), F.lit("S")).alias("r"), F.levenshtein("lang", "source").cast("bigint").alias("l"))


@query("fn_date", "SELECT event_id, epoch_us(ts) AS us, CAST(date_trunc('hour', ts) AS VARCHAR) AS h, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days, epoch_us(ts + INTERVAL 90 MINUTE) AS later FROM events")
def fn_date(spark, d):
    ts = F.col("ts").cast("timestamp")
    return table(spark, d, "events").select("event_id", F.unix_micros(ts).alias("us"), F.date_format(F.date_trunc("hour", ts), "yyyy-MM-dd HH:mm:ss").alias("h"), F.date_diff(ts.cast("date"), F.lit("2024-01-01").cast("date")).cast("bigint").alias("days"), F.unix_micros(ts + F.expr("INTERVAL 90 MINUTE")).alias("later"))


@query("fn_math", "SELECT l_orderkey, l_linenumber, round(log10(l_quantity) + ln(l_quantity) + log2(l_quantity), 6) AS logs, round(sqrt(l_extendedprice) + pow(l_discount, 2), 6) AS roots, CAST(ceil(l_tax * 10) + floor(l_tax * 10) AS BIGINT) AS steps, round(acos(least(1, l_discount)), 6) AS angle FROM lineitem")
def fn_math(spark, d):
    q = F.col("l_quantity").cast("double")
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.log10(q) + F.ln(q) + F.log2(q), 6).alias("logs"), F.round(F.sqrt("l_extendedprice") + F.pow("l_discount", F.lit(2)), 6).alias("roots"), (F.ceil(F.col("l_tax") * 10) + F.floor(F.col("l_tax") * 10)).cast("bigint").alias("steps"), F.round(F.acos(F.least(F.lit(1.0), "l_discount")), 6).alias("angle"))


@query("fn_bits", "SELECT event_id, CAST(bit_count(event_id) AS BIGINT) AS ones, xor(event_id, user_id) AS x, event_id & user_id AS a, event_id | user_id AS o, event_id << 3 AS l, event_id >> 2 AS r FROM events")
def fn_bits(spark, d):
    e, u = F.col("event_id"), F.col("user_id")
    return table(spark, d, "events").select("event_id", F.bit_count(e).cast("bigint").alias("ones"), e.bitwiseXOR(u).alias("x"), e.bitwiseAND(u).alias("a"), e.bitwiseOR(u).alias("o"), F.shiftleft(e, 3).alias("l"), F.shiftright(e, 2).alias("r"))


@query("fn_array", """SELECT vec_id, CAST(len(embedding) AS BIGINT) AS n, round(list_sum([CAST(x AS DOUBLE) FOR x IN embedding IF x > 0]), 4) AS positive, round(CAST(embedding[3] AS DOUBLE), 6) AS third, round(list_max([CAST(x AS DOUBLE) FOR x IN embedding]), 6) AS top FROM embeddings""")
def fn_array(spark, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").cast("bigint").alias("n"), F.round(F.aggregate(F.filter(v, lambda x: x > 0), F.lit(0.0), lambda s, x: s + x), 4).alias("positive"), F.round(F.element_at(v, 3), 6).alias("third"), F.round(F.array_max(v), 6).alias("top"))


@query("fn_map", r"SELECT doc_id, term, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS term FROM documents) GROUP BY ALL")
def fn_map(spark, d):
    """Words counted within the row: a map is built from the sorted array's runs, each word's number being the distance of its ends."""
    terms = table(spark, d, "documents").select("doc_id", F.array_sort(tokens(F.col("text"))).alias("terms"))
    starts = F.filter(F.sequence(F.lit(0), F.size("terms") - 1), lambda i: (i == 0) | (F.get("terms", i) != F.get("terms", i - 1)))
    runs = terms.filter(F.size("terms") > 0).select("doc_id", "terms", F.concat(starts, F.array(F.size("terms"))).alias("at"))
    entries = F.zip_with(F.slice("at", F.lit(1), F.size("at") - 1), F.slice("at", F.lit(2), F.size("at") - 1), lambda a, b: F.struct(F.get("terms", a), (b - a).cast("bigint")))
    return runs.select("doc_id", F.explode(F.map_from_entries(entries)).alias("term", "n"))


@query("fn_json", "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1")
def fn_json(spark, d):
    parsed = table(spark, d, "events").select(F.from_json("props", "k string").alias("p"))
    return parsed.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


# ---- windows of time (the same plans run on streams) ---------------------------------------------------------------------------------


def _events(spark, d) -> DataFrame:
    return table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("win_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def win_tumbling(spark, d):
    return _events(spark, d).groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("start"), "event_type", "n")


@query("win_sliding", "SELECT epoch_us(time_bucket(INTERVAL 12 HOUR, ts)) - k * 43200000000 AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def win_sliding(spark, d):
    return _events(spark, d).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("start"), "n")


@query("win_session", """WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 1 DAY THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def win_session(spark, d):
    return _events(spark, d).groupBy("user_id", F.session_window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start"), "n")


# ---- functions of the user ---------------------------------------------------------------------------------------------------------------


@query("udf_sql_macro", "SELECT l_linenumber, m AS p_miss, f AS p_fa, round((0.02::DOUBLE * m + 0.098::DOUBLE * f) / 0.02, 6) AS cost FROM (SELECT l_linenumber, count(*) FILTER (l_returnflag = 'R' AND l_quantity <= 25) / count(*) FILTER (l_returnflag = 'R') AS m, count(*) FILTER (l_returnflag <> 'R' AND l_quantity > 25) / count(*) FILTER (l_returnflag <> 'R') AS f FROM lineitem GROUP BY 1)")
def udf_sql_macro(spark, d):
    macros.register(spark)
    _views(spark, d, "lineitem")
    return spark.sql("SELECT l_linenumber, m AS p_miss, f AS p_fa, round(detection_cost(m, f), 6) AS cost FROM (SELECT l_linenumber, count(*) FILTER (WHERE l_returnflag = 'R' AND l_quantity <= 25) / count(*) FILTER (WHERE l_returnflag = 'R') AS m, count(*) FILTER (WHERE l_returnflag <> 'R' AND l_quantity > 25) / count(*) FILTER (WHERE l_returnflag <> 'R') AS f FROM lineitem GROUP BY 1)")


@query("udtf_bands", "SELECT CAST(t - 1 AS INTEGER) AS table_no, bucket, count(*) AS n FROM (SELECT unnest([1, 2, 3]) AS t, unnest([CAST(c_custkey % 5 AS BIGINT), CAST(c_custkey % 7 AS BIGINT), CAST(c_nationkey AS BIGINT)]) AS bucket FROM customer) GROUP BY ALL")
def udtf_bands(spark, d):
    macros.register(spark)
    _views(spark, d, "customer")
    return spark.sql("SELECT table_no, bucket, count(*) AS n FROM customer, LATERAL explode_bands(array(CAST(c_custkey % 5 AS BIGINT), CAST(c_custkey % 7 AS BIGINT), CAST(c_nationkey AS BIGINT))) GROUP BY 1, 2")


@query("udf_sql_entry", "SELECT lang, count(*) AS n FROM documents GROUP BY lang")
def udf_sql_entry(spark, d):
    macros.register(spark, d)
    return spark.sql("SELECT lang, count(*) AS n FROM novel_docs GROUP BY lang")
