"""Surrounding operators on the given tables: scans, joins, aggregates, windows, sets, scalars, arrays, bitmaps, functions.

Each query is small in text and stands for one operator that graph work needs around it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from .functions.arrays import gini, h_index
from .functions.bits import PRIME, int_hash

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def table(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def _add(name: str, fn: Callable, oracle: str | None = None) -> None:
    QUERIES[name] = fn
    if oracle:
        ORACLES[name] = oracle


def _sql(name: str, tables: str, text: str, oracle: str | None = None) -> None:
    """A query in SQL over temporary views; the same text is the check unless another is given."""

    def run(s: SparkSession, d: str) -> DataFrame:
        for t in tables.split():
            table(s, d, t).createOrReplaceTempView(t)
        return s.sql(text)

    _add(name, run, oracle or text)


for _t in TABLES:
    _key = {"lineitem": "l_orderkey", "orders": "o_orderkey", "customer": "c_custkey", "part": "p_partkey", "supplier": "s_suppkey", "nation": "n_nationkey", "region": "r_regionkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}[_t]
    _add(f"scan_{_t}", lambda s, d, t=_t, k=_key: table(s, d, t).agg(F.count("*").alias("n"), F.sum(F.col(k).cast("long")).alias("keys")), f"SELECT count(*)::BIGINT AS n, sum({_key})::BIGINT AS keys FROM {_t}")

_add("filter_between", lambda s, d: table(s, d, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_linenumber"), "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')")
_add("filter_like", lambda s, d: table(s, d, "pages").where(F.col("url").like("http%") & F.col("url").rlike("[0-9]")).select("page_id"), "SELECT page_id FROM pages WHERE url LIKE 'http%' AND regexp_matches(url, '[0-9]')")
_add("filter_null_safe", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").where(F.col("toxic").eqNullSafe(F.lit(None))).select("doc_id"), "SELECT doc_id FROM documents LEFT JOIN labels USING (doc_id) WHERE toxic IS NOT DISTINCT FROM NULL")
_add("project_case", lambda s, d: table(s, d, "orders").select("o_orderkey", F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low").alias("band")), "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")
_co = lambda s, d: (table(s, d, "customer"), table(s, d, "orders"))
_inner = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey"
for _h, _n in (("shuffle_hash", "hash"), ("merge", "merge")):
    _add(f"join_inner_{_n}", lambda s, d, h=_h: (x := _co(s, d))[1].join(x[0].hint(h), F.col("c_custkey") == F.col("o_custkey")).select("o_orderkey", "c_mktsegment"), _inner)
_add("join_broadcast", lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name"), "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
_add("join_theta", lambda s, d: table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_nationkey") > F.col("r_regionkey") * 5).groupBy("r_regionkey").agg(F.count("*").alias("n")), "SELECT r_regionkey, count(*)::BIGINT AS n FROM nation JOIN region ON n_nationkey > r_regionkey * 5 GROUP BY r_regionkey")
_add("join_semi", lambda s, d: (x := _co(s, d))[0].join(x[1], F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
_add("join_anti", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
_add("join_left", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").select("doc_id", "quality"), "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
_add("join_full", lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).distinct().withColumn("c", F.lit(1)).join(table(s, d, "supplier").select(F.col("s_nationkey").alias("k")).distinct().withColumn("p", F.lit(1)), "k", "full_outer").select("k", "c", "p"), "SELECT coalesce(a.k, b.k) AS k, a.c, b.p FROM (SELECT DISTINCT c_nationkey AS k, 1 AS c FROM customer) a FULL JOIN (SELECT DISTINCT s_nationkey AS k, 1 AS p FROM supplier) b ON a.k = b.k")
# The price is selected too: Spark ranks by what stands right under the limit, and a projection between them would leave only the order
# that rows had before the shuffle by customer.
_sql("join_lateral", "customer orders", "SELECT c_custkey, t.o_orderkey FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t", "SELECT c_custkey, t.o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t")
_add("agg_group", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.min("l_discount").alias("low"), F.max("l_discount").alias("high"), F.round(F.avg("l_extendedprice"), 4).alias("price")), "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, round(sum(l_quantity), 2) AS quantity, min(l_discount) AS low, max(l_discount) AS high, round(avg(l_extendedprice), 4) AS price FROM lineitem GROUP BY ALL")
_add("agg_min_max_by", lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("first")), "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS top, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS first FROM orders GROUP BY o_custkey")
_add("agg_bool_bit", lambda s, d: table(s, d, "labels").groupBy("quality").agg(F.bool_or(F.col("toxic") == 1).alias("any_toxic"), F.bool_and(F.col("toxic") == 0).alias("all_clean"), F.bit_or(F.pmod("doc_id", F.lit(8))).alias("bits")), "SELECT quality, bool_or(toxic = 1) AS any_toxic, bool_and(toxic = 0) AS all_clean, bit_or(doc_id % 8)::BIGINT AS bits FROM labels GROUP BY quality")
_add("agg_collect", lambda s, d: table(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set("l_partkey")), ",").alias("parts")), "SELECT l_orderkey, array_to_string(list_sort(list_distinct(list(l_partkey))), ',') AS parts FROM lineitem GROUP BY l_orderkey")
_add("agg_median_mode", lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.round(F.median("value"), 6).alias("middle"), F.round(F.percentile("value", 0.9), 6).alias("p90"), F.mode("user_id", True).alias("busiest")), "SELECT event_type, round(median(value), 6) AS middle, round(quantile_cont(value, 0.9), 6) AS p90, (SELECT user_id FROM events y WHERE y.event_type = x.event_type GROUP BY user_id ORDER BY count(*) DESC, user_id LIMIT 1) AS busiest FROM events x GROUP BY event_type")
_add("agg_distinct", lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, count(DISTINCT l_partkey)::BIGINT AS parts, count(DISTINCT l_suppkey)::BIGINT AS suppliers FROM lineitem GROUP BY l_returnflag")
_add("agg_approx_distinct", lambda s, d: table(s, d, "lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.count_distinct("l_partkey") - 1) < 0.1).alias("near")), "SELECT true AS near")
_loads = "SELECT pmod(l_partkey, 4) AS r, pmod(l_suppkey, 4) AS c FROM lineitem"
for _n, _op in (("rollup", "ROLLUP(r, c)"), ("cube", "CUBE(r, c)"), ("grouping_sets", "GROUPING SETS ((r), (c), ())")):
    _sql(f"{_n}_block_loads", "lineitem", f"SELECT r, c, count(*) AS n FROM ({_loads}) x GROUP BY {_op}", f"SELECT r, c, count(*)::BIGINT AS n FROM (SELECT l_partkey % 4 AS r, l_suppkey % 4 AS c FROM lineitem) GROUP BY {_op}")
_add("unpivot_labels", lambda s, d: table(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "name", "value"), "SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")


def _by_cust():
    return W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_add("win_ranking", lambda s, d: table(s, d, "orders").select("o_orderkey", F.row_number().over(_by_cust()).alias("rn"), F.rank().over(W.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(W.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr"), F.ntile(3).over(_by_cust()).alias("nt"), F.round(F.percent_rank().over(_by_cust()), 6).alias("pr"), F.round(F.cume_dist().over(_by_cust()), 6).alias("cd")), "SELECT o_orderkey, row_number() OVER w::INTEGER AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)::INTEGER AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority)::INTEGER AS dr, ntile(3) OVER w::INTEGER AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)".replace("row_number() OVER w::INTEGER", "(row_number() OVER w)::INTEGER").replace("ntile(3) OVER w::INTEGER", "(ntile(3) OVER w)::INTEGER").replace("o_orderpriority)::INTEGER AS", "o_orderpriority))::INTEGER AS").replace(" rank() OVER (", " (rank() OVER (").replace("dense_rank() OVER (", "(dense_rank() OVER ("))
_add("win_lead_chain", lambda s, d: table(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(_by_cust()).alias("before"), F.lead("o_orderkey").over(_by_cust()).alias("after"), F.first("o_orderkey").over(_by_cust()).alias("first"), F.nth_value("o_orderkey", 2).over(_by_cust().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("second")), "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first, nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
_add("win_prefix_load", lambda s, d: table(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(_by_cust().rowsBetween(W.unboundedPreceding, 0)), 2).alias("so_far")), "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS so_far FROM orders")
_add("win_range_frame", lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("last_hour")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW)::BIGINT AS last_hour FROM events".replace("count(*) OVER (", "(count(*) OVER (").replace("CURRENT ROW)::BIGINT", "CURRENT ROW))::BIGINT"))
_add("topk_orders", lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
_add("topk_per_group", lambda s, d: table(s, d, "orders").withColumn("k", F.row_number().over(W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("k <= 3").select("o_orderpriority", "o_orderkey"), "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
_add("sort_offset", lambda s, d: table(s, d, "part").orderBy("p_name", "p_partkey").offset(10).limit(10).select("p_partkey"), "SELECT p_partkey FROM part ORDER BY p_name, p_partkey LIMIT 10 OFFSET 10")
_keys = lambda s, d: (table(s, d, "orders").select(F.col("o_custkey").alias("k")), table(s, d, "customer").select(F.col("c_custkey").alias("k")))
for _n, _f, _o in (("union_all", lambda a, b: a.unionAll(b), "UNION ALL"), ("union", lambda a, b: a.union(b).distinct(), "UNION"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("except", lambda a, b: b.subtract(a), None), ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL")):
    _add(f"set_{_n}", lambda s, d, f=_f: f(*_keys(s, d)), f"SELECT o_custkey AS k FROM orders {_o} SELECT c_custkey FROM customer" if _o else "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
_add("str_page_links", lambda s, d: table(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("links"), F.md5("url").alias("h"), F.lower(F.trim(F.substring("url", 1, 12))).alias("head"), F.length("html").alias("n")), "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::INTEGER AS links, md5(url) AS h, lower(trim(substring(url, 1, 12))) AS head, length(html)::INTEGER AS n FROM pages")
_add("str_split_concat", lambda s, d: table(s, d, "customer").select("c_custkey", F.concat_ws("-", "c_mktsegment", F.split("c_name", "#")[1]).alias("tag")), "SELECT c_custkey, concat_ws('-', c_mktsegment, string_split(c_name, '#')[2]) AS tag FROM customer")
_add("date_months", lambda s, d: table(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff(F.col("o_orderdate"), F.lit("1990-01-01").cast("date"))).alias("days")), "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*)::BIGINT AS n, max(date_diff('day', DATE '1990-01-01', o_orderdate::DATE))::INTEGER AS days FROM orders GROUP BY 1")
_add("math_hash", lambda s, d: table(s, d, "part").select("p_partkey", int_hash(F.col("p_partkey"), 7).alias("h"), F.shiftright("p_partkey", 2).alias("q"), F.bit_count("p_partkey").alias("ones"), F.round(F.sqrt(F.col("p_retailprice")), 6).alias("root")), f"SELECT p_partkey, (((p_partkey * 48271 + 7) % {PRIME}) * 48271 + 8) % {PRIME} AS h, p_partkey >> 2 AS q, bit_count(p_partkey)::INTEGER AS ones, round(sqrt(p_retailprice), 6) AS root FROM part")
_add("arr_kernels", lambda s, d: table(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("a")).select("l_orderkey", F.size("a").alias("n"), F.array_min("a").alias("low"), F.aggregate("a", F.lit(0).cast("long"), lambda x, y: x + y).alias("total"), F.size(F.filter("a", lambda x: x % 2 == 0)).alias("even")), "SELECT l_orderkey, len(a)::INTEGER AS n, list_min(a) AS low, list_sum(a)::BIGINT AS total, len(list_filter(a, lambda x: x % 2 = 0))::INTEGER AS even FROM (SELECT l_orderkey, list_distinct(list(l_partkey)) AS a FROM lineitem GROUP BY l_orderkey)")
_add("json_props_k", lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")), "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
_add("map_entries", lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size("m").alias("n"), F.array_max(F.map_keys("m")).alias("last")), "SELECT n_regionkey, count(*)::INTEGER AS n, max(n_nationkey) AS last FROM nation GROUP BY n_regionkey")
_add("bitmap_frontier", lambda s, d: table(s, d, "orders").select(F.bitmap_bucket_number("o_custkey").alias("b"), F.bitmap_bit_position("o_custkey").alias("p")).groupBy("b").agg(F.bitmap_count(F.bitmap_construct_agg("p")).alias("n")).agg(F.sum("n").alias("customers")), "SELECT count(DISTINCT o_custkey)::BIGINT AS customers FROM orders")
_add("sample_hash", lambda s, d: table(s, d, "part").where(int_hash(F.col("p_partkey"), 3) < PRIME // 10).select("p_partkey"), f"SELECT p_partkey FROM part WHERE (((p_partkey * 48271 + 3) % {PRIME}) * 48271 + 4) % {PRIME} < {PRIME // 10}")
_sql("sql_view_join", "nation region", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
_add("sql_view_args", lambda s, d: (table(s, d, "part").createOrReplaceTempView("part"), s.sql("SELECT p_partkey FROM part WHERE p_size > :size", args={"size": 40}))[1], "SELECT p_partkey FROM part WHERE p_size > 40")


@F.udf(T.IntegerType())
def _bits(x):
    return None if x is None else int(x).bit_count()


_add("udf_python_bits", lambda s, d: table(s, d, "region").select("r_regionkey", _bits("r_regionkey").alias("ones")), "SELECT r_regionkey, bit_count(r_regionkey)::INTEGER AS ones FROM region")
_add("udaf_gini", lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).groupBy(F.lit(1).alias("g")).agg(F.round(gini("n"), 6).alias("gini")).select("gini"), "SELECT round(sum((2 * i - n - 1) * x) / (max(n) * sum(x)), 6) AS gini FROM (SELECT x, row_number() OVER (ORDER BY x) AS i, count(*) OVER () AS n FROM (SELECT count(*) AS x FROM orders GROUP BY o_custkey))")
_add("udaf_h_index", lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n")).groupBy(F.lit(1).alias("g")).agg(h_index("n").alias("h")).select("h"), "SELECT max(least(x, i))::BIGINT AS h FROM (SELECT x, row_number() OVER (ORDER BY x DESC) AS i FROM (SELECT count(DISTINCT l_partkey) AS x FROM lineitem GROUP BY l_suppkey)) WHERE x >= i")


def _udtf(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql.functions import udtf

    @udtf(returnType="src: bigint, dst: bigint")
    class Mycielski:
        def eval(self, k: int):
            edges, n = [(0, 1)], 2
            for _ in range(k - 2):
                edges += [e for a, b in edges for e in ((a, b + n), (b, a + n))] + [(i + n, 2 * n) for i in range(n)]
                n = 2 * n + 1
            yield from edges

    return Mycielski(F.lit(5)).agg(F.count("*").alias("edges"), F.max("dst").alias("last"))


_add("udtf_mycielski", _udtf, "SELECT 71::BIGINT AS edges, 22::BIGINT AS last")
