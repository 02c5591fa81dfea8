"""Relational operators, functions and streams around the methods; a query for each, with SQL beside it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lincompress.functions import linexpr, udx
from lincompress.operators import compress as C
from lincompress.plans.design import ModelSpec, num
from lincompress.sources.scratch import shared_folder
from lincompress.sources.tables import follow, load, panel_of, read_text_table, register_views, write_table
from lincompress.streaming import compress_stream as cs

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


@query("op_filter_project", "SELECT l_orderkey, l_quantity * 2 AS twice, CASE WHEN l_discount > 0.05 THEN 'high' ELSE 'low' END AS level FROM lineitem WHERE l_returnflag IN ('A', 'R') AND l_quantity BETWEEN 10 AND 20 AND l_linestatus LIKE 'F%' AND l_tax IS NOT NULL")
def _(s, d):
    rows = load(s, d, "lineitem").where(F.col("l_returnflag").isin("A", "R") & F.col("l_quantity").between(10, 20) & F.col("l_linestatus").like("F%") & F.col("l_tax").isNotNull())
    return rows.select("l_orderkey", (F.col("l_quantity") * 2).alias("twice"), F.when(F.col("l_discount") > 0.05, "high").otherwise("low").alias("level"))


def _join(name: str, hint: str | None):
    @query(name, "SELECT o_orderkey, c_mktsegment, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey")
    def run(s, d):
        right = load(s, d, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
        right = right.hint(hint) if hint else right
        return load(s, d, "orders").select("o_orderkey", "o_custkey").join(right, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment", "c_nationkey")


_join("op_join_inner", None)
_join("op_join_hash", "shuffle_hash")
_join("op_join_merge", "merge")


@query("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(s, d):
    places = load(s, d, "nation").join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))  # fixed tables of 25 and 5 rows
    return load(s, d, "customer").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@query("op_join_eager", "SELECT c_mktsegment, count(*) AS cnt, round(sum(o_totalprice), 2) AS sy FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def _(s, d):
    """Facts are summed by key before the attributes join, so the join has a row for each key."""
    facts = load(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("cnt"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).alias("sy"))
    return facts.join(load(s, d, "customer").select("c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.sum("cnt").alias("cnt"), F.round(F.sum("sy").cast("double"), 2).alias("sy"))


def _outer(how: str, sql: str):
    @query(f"op_join_{how}", f"SELECT c_custkey, count(o_orderkey) AS n FROM customer {sql} JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
    def run(s, d):
        joined = load(s, d, "customer").select("c_custkey").join(load(s, d, "orders").select("o_custkey", "o_orderkey"), F.col("o_custkey") == F.col("c_custkey"), how)
        return joined.groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


_outer("left", "LEFT")
_outer("right", "RIGHT")
_outer("full", "FULL OUTER")


@query("op_join_cross", "SELECT n_name, r_name FROM nation CROSS JOIN region")
def _(s, d):
    return load(s, d, "nation").select("n_name").crossJoin(F.broadcast(load(s, d, "region").select("r_name")))


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
def _(s, d):
    return load(s, d, "customer").select("c_custkey").join(load(s, d, "orders").where("o_orderstatus = 'P'").select("o_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_semi")


@query("op_join_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def _(s, d):
    return load(s, d, "orders").select("o_orderkey").join(load(s, d, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("op_join_asof", "WITH e AS (SELECT * FROM events) SELECT event_id, user_id, last_value FROM (SELECT event_id, user_id, event_type, max_by(CASE WHEN event_type <> 'purchase' THEN value END, CASE WHEN event_type <> 'purchase' THEN (ts, event_id) END) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND INTERVAL 1 MICROSECOND PRECEDING) AS last_value FROM e) WHERE event_type = 'purchase'")
def _(s, d):
    """The last earlier value of the same user: one sort by user instead of a join of all pairs."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    before = Window.partitionBy("user_id").orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    other = F.when(F.col("event_type") != "purchase", F.struct("us", "event_id", "value"))
    return e.withColumn("last_value", F.max(other).over(before)["value"]).where("event_type = 'purchase'").select("event_id", "user_id", "last_value")


_INTERVAL = "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 DAY GROUP BY a.user_id"


@query("op_join_interval", _INTERVAL)
def _(s, d):
    """Pairs within a day, counted by day buckets and a window over both kinds, without forming the pairs."""
    e = load(s, d, "events").where("event_type in ('click', 'purchase')").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    ahead = Window.partitionBy("user_id").orderBy("us").rangeBetween(1, 86_400_000_000)
    n = F.count_if(F.col("event_type") == "purchase").over(ahead)
    return e.withColumn("n", n).where("event_type = 'click' AND n > 0").groupBy("user_id").agg(F.sum("n").alias("pairs"))


@query("op_join_lateral", "SELECT c_custkey, x.o_totalprice AS top FROM customer, LATERAL (SELECT o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC LIMIT 1) x")
def _(s, d):
    return load(s, d, "customer").select("c_custkey").join(load(s, d, "orders").groupBy("o_custkey").agg(F.max("o_totalprice").alias("top")), F.col("o_custkey") == F.col("c_custkey")).select("c_custkey", "top")


@query("op_join_self", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _(s, d):
    n = load(s, d, "nation")
    return n.alias("a").join(n.alias("b"), (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


@query("op_agg_filtered", "SELECT l_returnflag, count(*) FILTER (l_discount > 0.05) AS high, count(DISTINCT l_suppkey) AS supps, sum(l_quantity) AS qty FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_discount") > 0.05).alias("high"), F.count_distinct("l_suppkey").alias("supps"), F.sum("l_quantity").alias("qty"))


@query("op_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS cnt, sum(l_quantity) AS sy, sum(l_quantity * l_quantity) AS syy FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def _(s, d):
    return load(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("cnt"), F.sum("l_quantity").alias("sy"), F.sum(F.col("l_quantity") * F.col("l_quantity")).alias("syy"))


@query("op_cube", "SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(s, d):
    return load(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("cnt"))


@query("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(s, d):
    register_views(s, d)
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@query("op_agg_moments", "SELECT l_returnflag, round(var_pop(l_quantity), 6) AS vp, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_tax), 8) AS co, round(covar_pop(l_quantity, l_tax), 8) AS cv, round(regr_slope(l_tax, l_quantity), 9) AS sl FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.var_pop("l_quantity"), 6).alias("vp"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_tax"), 8).alias("co"), F.round(F.covar_pop("l_quantity", "l_tax"), 8).alias("cv"), F.round(F.regr_slope("l_tax", "l_quantity"), 9).alias("sl"))


@query("op_agg_order_statistics", "SELECT o_orderpriority, round(median(o_totalprice), 4) AS md, round(quantile_cont(o_totalprice, 0.9), 4) AS p90, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top FROM orders GROUP BY o_orderpriority")
def _(s, d):
    return load(s, d, "orders").groupBy("o_orderpriority").agg(F.round(F.median("o_totalprice"), 4).alias("md"), F.round(F.percentile("o_totalprice", F.lit(0.9)), 4).alias("p90"), F.max(F.struct("o_totalprice", "o_orderkey"))["o_orderkey"].alias("top"))


@query("op_agg_approximate", "SELECT true AS distinct_close, true AS median_close, true AS sketch_close")
def _(s, d):
    rows = load(s, d, "orders")
    n, near, sketch, q, mid = rows.agg(F.count_distinct("o_custkey"), F.approx_count_distinct("o_custkey", 0.02), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey")), F.percentile_approx("o_totalprice", 0.5, 10_000), F.median("o_totalprice")).first()
    return s.createDataFrame([(abs(near - n) < 0.1 * n, abs(q - mid) < 0.02 * mid, abs(sketch - n) < 0.1 * n)], "distinct_close boolean, median_close boolean, sketch_close boolean")


@query("op_pivot", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN l_quantity END) AS \"F\", sum(CASE WHEN l_linestatus = 'O' THEN l_quantity END) AS \"O\" FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).sum("l_quantity")


@query("op_unpivot", "SELECT l_returnflag, 'qty' AS outcome, sum(l_quantity) AS total FROM lineitem GROUP BY l_returnflag UNION ALL SELECT l_returnflag, 'rows', count(*)::DOUBLE FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum("l_quantity").alias("qty"), F.count(F.lit(1)).cast("double").alias("rows")).unpivot("l_returnflag", ["qty", "rows"], "outcome", "total")


@query("op_window_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 9) AS pr, round(cume_dist() OVER v, 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def _(s, d):
    w, v = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return load(s, d, "orders").select("o_orderkey", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(v).cast("bigint").alias("rk"), F.dense_rank().over(v).cast("bigint").alias("dr"), F.round(F.percent_rank().over(v), 9).alias("pr"), F.round(F.cume_dist().over(v), 9).alias("cd"))


@query("op_window_lag", "SELECT o_orderkey, lag(o_totalprice) OVER w AS prev, lead(o_totalprice) OVER w AS next, first_value(o_totalprice) OVER w AS first, nth_value(o_totalprice, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    c = "o_totalprice"
    return load(s, d, "orders").select("o_orderkey", F.lag(c).over(w).alias("prev"), F.lead(c).over(w).alias("next"), F.first_value(c).over(w).alias("first"), F.nth_value(c, 2).over(w).alias("second"))


@query("op_window_frame", "SELECT o_orderkey, round(sum(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS last3, count(*) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("last3"), F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


@query("op_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(s, d):
    return load(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("op_top_k_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def _(s, d):
    return load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10).select("o_orderkey")


_SETS = "SELECT l_returnflag, l_linestatus, l_discount FROM lineitem WHERE l_suppkey % 2 = "


def _set(name: str, sql: str, f):
    @query(f"op_set_{name}", f"{_SETS}0 {sql} {_SETS}1")
    def run(s, d):
        rows = load(s, d, "lineitem")
        part = lambda k: rows.where(F.col("l_suppkey") % 2 == k).select("l_returnflag", "l_linestatus", "l_discount")
        return f(part(0), part(1))


_set("union_all", "UNION ALL", lambda a, b: a.unionByName(b))
_set("union", "UNION", lambda a, b: a.union(b).distinct())
_set("intersect", "INTERSECT", lambda a, b: a.intersect(b))
_set("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_set("except", "EXCEPT", lambda a, b: a.subtract(b))
_set("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))


@query("op_distinct", "SELECT DISTINCT l_returnflag, l_linestatus, l_discount, l_tax FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").select("l_returnflag", "l_linestatus", "l_discount", "l_tax").distinct()


@query("op_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
def _(s, d):
    register_views(s, d)
    return s.sql("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")


_ROOTS = """WITH RECURSIVE b AS (SELECT l_returnflag AS flag, l_linestatus AS status, sum(l_quantity * l_quantity) / count(*) - (sum(l_quantity) / count(*)) * (sum(l_quantity) / count(*)) AS x FROM lineitem GROUP BY l_returnflag, l_linestatus),
n(flag, status, x, k, v) AS (SELECT flag, status, x, 1, CAST(1.0 AS DOUBLE) FROM b UNION ALL SELECT flag, status, x, k + 1, (v + x / v) / 2 FROM n WHERE k < 8)
SELECT flag, status, k, round(v, 9) AS v FROM n"""


@query("op_recursive", _ROOTS)
def _(s, d):
    """Newton's steps from 1 to the standard deviation of the quantity in each group of line items; as many rows recur as there are groups."""
    load(s, d, "lineitem").createOrReplaceTempView("lineitem")
    return s.sql(_ROOTS)


@query("op_fn_string", "SELECT p_partkey, upper(p_type) AS up, length(p_name) AS len, substring(p_name, 1, 3) AS pre, replace(p_type, ' ', '_') AS under, lpad(p_partkey::VARCHAR, 8, '0') AS code, split_part(p_type, ' ', 1) AS head FROM part")
def _(s, d):
    return load(s, d, "part").select("p_partkey", F.upper("p_type").alias("up"), F.length("p_name").cast("bigint").alias("len"), F.substring("p_name", 1, 3).alias("pre"), F.replace("p_type", F.lit(" "), F.lit("_")).alias("under"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("code"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("head"))


@query("op_fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, quarter(o_orderdate) AS q, date_trunc('month', o_orderdate)::DATE::VARCHAR AS first, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS day FROM orders")
def _(s, d):
    c = F.col("o_orderdate")
    return load(s, d, "orders").select("o_orderkey", F.year(c).cast("bigint").alias("y"), F.month(c).cast("bigint").alias("m"), F.quarter(c).cast("bigint").alias("q"), F.trunc(c, "month").cast("string").alias("first"), F.datediff(c, F.lit("1995-01-01")).cast("bigint").alias("day"))


@query("op_fn_math", "SELECT c_custkey, round(c_acctbal, 0) AS r, floor(c_acctbal) AS f, ceil(c_acctbal) AS c, round(ln(abs(c_acctbal) + 1), 9) AS l, sign(c_acctbal)::DOUBLE AS s, greatest(c_acctbal, 0.0) AS g FROM customer")
def _(s, d):
    b = F.col("c_acctbal")
    return load(s, d, "customer").select("c_custkey", F.round(b, 0).alias("r"), F.floor(b).cast("double").alias("f"), F.ceil(b).cast("double").alias("c"), F.round(F.log1p(F.abs(b)), 9).alias("l"), F.signum(b).alias("s"), F.greatest(b, F.lit(0.0)).alias("g"))


@query("op_fn_array", "SELECT o_custkey, list_sum(list(o_totalprice::DECIMAL(12,2)))::DOUBLE AS total, len(list(o_orderkey)) AS n, list_min(list(o_orderkey)) AS least FROM orders GROUP BY o_custkey")
def _(s, d):
    g = load(s, d, "orders").groupBy("o_custkey").agg(F.collect_list(F.col("o_totalprice").cast("decimal(12,2)")).alias("p"), F.collect_list("o_orderkey").alias("k"))
    return g.select("o_custkey", F.aggregate("p", F.lit(0).cast("decimal(22,2)"), lambda a, x: (a + x).cast("decimal(22,2)")).cast("double").alias("total"), F.size("k").cast("bigint").alias("n"), F.array_min("k").alias("least"))


@query("op_fn_vector", "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS norm2 FROM embeddings")
def _(s, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return load(s, d, "embeddings").select("vec_id", F.round(linexpr.vec_dot(e, e), 6).alias("norm2"))


@query("op_fn_map_struct", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END)::BIGINT AS f, sum(CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END)::BIGINT AS o FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    g = load(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").count()
    m = g.groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "count"))).alias("m"))
    return m.select("l_returnflag", F.coalesce(F.col("m")["F"], F.lit(0)).alias("f"), F.coalesce(F.col("m")["O"], F.lit(0)).alias("o"))


@query("op_fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(s, d):
    return load(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("op_fn_variant", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(s, d):
    return load(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("op_fn_hash", "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS s FROM customer")
def _(s, d):
    return load(s, d, "customer").select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s"))


@query("op_fn_null", "SELECT l_orderkey, CASE WHEN l_tax = 0 THEN NULL ELSE l_discount / l_tax END AS ratio, coalesce(nullif(l_returnflag, 'N'), '-') AS flag FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").select("l_orderkey", F.try_divide("l_discount", "l_tax").alias("ratio"), F.coalesce(F.nullif("l_returnflag", F.lit("N")), F.lit("-")).alias("flag"))


@query("op_fn_cast", "SELECT l_orderkey, (l_extendedprice::DECIMAL(12,2))::VARCHAR AS price, l_quantity::BIGINT AS qty FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").select("l_orderkey", F.col("l_extendedprice").cast("decimal(12,2)").cast("string").alias("price"), F.col("l_quantity").cast("bigint").alias("qty"))


@query("op_udtf_fit", "SELECT round(regr_slope(l_quantity, l_discount), 6) AS slope FROM lineitem")
def _(s, d):
    udx.register_all(s)
    rows = load(s, d, "lineitem").select(F.col("l_discount").alias("disc"), F.col("l_quantity").alias("qty"))
    C.compress_stats(rows, ModelSpec("qty", (num("disc"),))).df.createOrReplaceTempView("_cf")
    return s.sql("SELECT round(coef, 6) AS slope FROM fit_linear(TABLE(_cf) WITH SINGLE PARTITION, 'qty ~ disc', 'ehw') WHERE term = 'disc'")


@query("op_udf_gram", "SELECT l_linestatus, round(sum(l_quantity), 4) AS x, round(sum(l_quantity * l_quantity), 4) AS xx FROM lineitem GROUP BY l_linestatus")
def _(s, d):
    g = load(s, d, "lineitem").groupBy("l_linestatus", "l_quantity").agg(F.count(F.lit(1)).cast("double").alias("w"))
    g = g.groupBy("l_linestatus").agg(udx.gram_agg()(F.array(F.lit(1.0), F.col("l_quantity")), F.col("w")).alias("g"))
    return g.select("l_linestatus", F.round(F.get("g", 1), 4).alias("x"), F.round(F.get("g", 2), 4).alias("xx"))


@query("op_suff_stats", "SELECT l_returnflag, count(*) AS cnt, sum(l_quantity) AS sy, sum(l_quantity * l_quantity) AS syy FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").agg(udx.suff_stats("l_quantity").alias("t")).select("l_returnflag", "t.*")


def _source(kind: str):
    @query(f"io_{kind}", "SELECT n_nationkey::BIGINT AS n_nationkey, n_name FROM nation")
    def run(s, d):
        path = shared_folder(s, kind)
        write_table(load(s, d, "nation").select(F.col("n_nationkey").cast("bigint").alias("n_nationkey"), "n_name"), path, kind)
        return read_text_table(s, path, kind, "n_nationkey bigint, n_name string")


for _kind in ("csv", "json", "orc"):
    _source(_kind)


@query("io_partitioned", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY l_returnflag")
def _(s, d):
    path = shared_folder(s, "parts")
    write_table(load(s, d, "lineitem").select("l_returnflag", "l_quantity"), path, partition_by=["l_returnflag"])
    return s.read.parquet(path).where("l_returnflag = 'A'").groupBy(F.col("l_returnflag").cast("string").alias("l_returnflag")).agg(F.count(F.lit(1)).alias("n"))


_GENERATED = "SELECT c_custkey % 2 AS arm, c_nationkey % 3 AS x1, t, floor(c_acctbal) + c_custkey % 2 + t AS y FROM customer, range(20) r(t)"


@query("io_generator", f"SELECT arm, x1, t, count(*) AS cnt, sum(y) AS sy_y, sum(y * y) AS syy_y FROM ({_GENERATED}) GROUP BY arm, x1, t")
def _(s, d):
    """A balanced panel made from the customers, 20 periods each; outcomes are whole numbers, so that sums don't depend on order."""
    rows = panel_of(load(s, d, "customer").select((F.col("c_custkey") % 2).alias("arm"), (F.col("c_nationkey") % 3).alias("x1"), F.floor("c_acctbal").cast("double").alias("base")), 20)
    return C.compress_stats(rows.withColumn("y", F.col("base") + F.col("arm") + F.col("t")), ModelSpec("y", (num("arm"), num("x1"), num("t")))).df


_EVENTS = ModelSpec("value", (num("event_type"),))


#: Watermarks need instants; wall-clock times go through the epoch, whatever the session's zone.
_INSTANT = "timestamp_ltz'1970-01-01 00:00:00Z' + (ts - timestamp_ntz'1970-01-01 00:00:00')"


def _instants(stream: DataFrame) -> DataFrame:
    return stream.withColumn("ts", F.expr(_INSTANT))


def _wall(column: str):
    return F.expr(f"timestamp_ntz'1970-01-01 00:00:00' + ({column} - timestamp_ltz'1970-01-01 00:00:00Z')")


def _drain(s, out: DataFrame, mode: str = "complete") -> DataFrame:
    """Reads a stream until nothing is left."""
    name = f"stream_{shared_folder(s, 'x').rsplit('-', 1)[1]}"
    return cs.run_available(out, name, shared_folder(s, "stream"), mode)


@query("stream_compress_parity", "SELECT event_type, count(*) AS cnt, round(sum(value), 4) AS sy_value FROM events GROUP BY event_type")
def _(s, d):
    """The events as a stream of one file, read until nothing is left."""
    return _drain(s, cs.compress_stream(follow(s, d, "events"), _EVENTS)).select("event_type", "cnt", F.round("sy_value", 4).alias("sy_value"))


@query("stream_tumbling", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS cnt FROM events GROUP BY 1, 2")
def _(s, d):
    out = cs.compress_stream(_instants(follow(s, d, "events")), _EVENTS, lambda: F.window("ts", "1 day"), ("ts", "2 days"))
    return _drain(s, out).select(_wall("window.start").alias("day"), "event_type", "cnt")


@query("stream_sliding", "SELECT date_trunc('day', ts) + INTERVAL (k) DAY AS until, event_type, count(*) AS cnt FROM events, (SELECT unnest(range(1, 8)) AS k) GROUP BY 1, 2")
def _(s, d):
    out = cs.compress_stream(_instants(follow(s, d, "events")), _EVENTS, lambda: F.window("ts", "7 days", "1 day"), ("ts", "2 days"))
    return _drain(s, out).select(_wall("window.end").alias("until"), "event_type", "cnt")


@query("stream_session", "WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS cnt FROM n GROUP BY user_id, k")
def _(s, d):
    out = cs.compress_stream(_instants(follow(s, d, "events")), ModelSpec("value", (num("user_id"),)), lambda: F.session_window("ts", "6 hours"), ("ts", "2 days"))
    return _drain(s, out).select("user_id", _wall("window.start").alias("start"), "cnt")


@query("stream_late", "WITH m AS (SELECT max(ts) AS m FROM events) SELECT count(*) FILTER (ts < m - INTERVAL 2 DAY) AS late, count(*) AS rows FROM events, m")
def _(s, d):
    e = load(s, d, "events")
    return cs.late_rows(e, "ts", "2 days", str(e.agg(F.max("ts")).first()[0]))


@query("stream_watermark", "WITH m AS (SELECT max(ts) AS m FROM events) SELECT date_trunc('day', ts) AS day, count(*) AS cnt FROM events, m WHERE day(ts) >= 10 AND date_trunc('day', ts) + INTERVAL 1 DAY <= m - INTERVAL 2 DAY GROUP BY 1")
def _(s, d):
    """Rows of the first days come last: the watermark, which holds for late rows from the second batch after it rose, drops them; closed windows are emitted once."""
    folder = shared_folder(s, "late")
    e = load(s, d, "events")
    for k, part in enumerate((e.where("day(ts) between 10 and 20"), e.where("day(ts) > 20"), e.where("day(ts) < 10"))):
        part.coalesce(1).write.mode("append").parquet(f"{folder}/events-{k}.parquet")
    stream = s.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(folder)
    out = cs.compress_stream(_instants(stream), ModelSpec("value"), lambda: F.window("ts", "1 day"), ("ts", "2 days"))
    return _drain(s, out, "append").select(_wall("window.start").alias("day"), "cnt")


@query("stream_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")
def _(s, d):
    """Every event comes twice; each is kept once. Only the id and its time go through the state's exchange."""
    once = lambda: _instants(follow(s, d, "events").select("event_id", "ts"))
    twice = once().unionAll(once())
    return _drain(s, cs.dedup(twice, "event_id", "ts", "60 days"), "append").agg(F.count(F.lit(1)).alias("n"))


@query("stream_static_join", "SELECT c_mktsegment AS segment, count(*) AS cnt, round(sum(value), 4) AS sy_value FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def _(s, d):
    """Static attributes of users join the stream before it is compressed."""
    users = load(s, d, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    out = cs.compress_stream(follow(s, d, "events").join(users, "user_id"), ModelSpec("value", (num("segment"),)))
    return _drain(s, out).select("segment", "cnt", F.round("sy_value", 4).alias("sy_value"))
