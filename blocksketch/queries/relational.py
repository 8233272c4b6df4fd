"""Registered relational operators that graph building, reports and checks need around the sketches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..session import table

Q: dict = {}
SQL: dict = {}


def put(name: str, sql: str):
    def keep(f):
        Q[name], SQL[name] = f, sql
        return f

    return keep


t = table
n = lambda: F.count(F.lit(1)).alias("n")
put("op_filter", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R') AND l_linestatus IS NOT DISTINCT FROM 'F'")(lambda s, d: t(s, d, "lineitem").filter(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").eqNullSafe("F")).select("l_orderkey", "l_partkey", "l_quantity"))
put("op_join_inner", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")(lambda s, d: t(s, d, "orders").join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(n(), F.round(F.sum("o_totalprice"), 2).alias("total")))
put("op_join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")(lambda s, d: t(s, d, "customer").join(t(s, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
put("op_join_full", "SELECT coalesce(a.k, b.k) AS k, a.x, b.y FROM (SELECT l_partkey AS k, count(*) AS x FROM lineitem WHERE l_quantity = 1 GROUP BY 1) a FULL JOIN (SELECT l_partkey AS k, count(*) AS y FROM lineitem WHERE l_quantity = 2 GROUP BY 1) b ON a.k = b.k")(
    lambda s, d: t(s, d, "lineitem").filter("l_quantity = 1").groupBy(F.col("l_partkey").alias("k")).agg(F.count(F.lit(1)).alias("x")).join(t(s, d, "lineitem").filter("l_quantity = 2").groupBy(F.col("l_partkey").alias("k")).agg(F.count(F.lit(1)).alias("y")), "k", "full")
)
put("op_join_semi", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity = 50)")(lambda s, d: t(s, d, "orders").join(t(s, d, "lineitem").filter("l_quantity = 50"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey"))
put("op_join_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")(lambda s, d: t(s, d, "orders").join(t(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"))
put("op_join_pairs", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(lambda s, d: t(s, d, "nation").alias("a").join(t(s, d, "nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b")))


@put("op_join_range", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def _range_join(s, d):
    """Interval join: both sides meet in ten-minute buckets of a user, the later side in its own and the one before."""
    e = t(s, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 600_000_000).alias("k"))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), "k")
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), F.explode(F.array(F.col("k"), F.col("k") - 1)).alias("k"))
    return a.join(b, ["user_id", "k"]).filter((F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("interval 10 minutes"))).select("a", "b")


@put("op_join_asof", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def _asof(s, d):
    """Last view at or before each purchase: one sort of both sides' union by user and time, the last view carried forward."""
    e = t(s, d, "events").filter(F.col("event_type").isin("purchase", "view"))
    w = W.partitionBy("user_id").orderBy("ts").rowsBetween(W.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("view_id", seen).filter("event_type = 'purchase'").select("event_id", "view_id")


put("op_agg_partial", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, round(avg(l_extendedprice), 4) AS p, count(DISTINCT l_suppkey) AS suppliers, count(*) AS n FROM lineitem GROUP BY 1, 2")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.round(F.avg("l_extendedprice"), 4).alias("p"), F.countDistinct("l_suppkey").alias("suppliers"), n()))
put("op_agg_xor", "SELECT l_suppkey, bit_xor(l_partkey) AS x, arg_min(l_orderkey, (l_extendedprice, l_orderkey)) AS cheapest FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_suppkey").agg(F.bit_xor("l_partkey").alias("x"), F.min_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("cheapest")))
put("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n, grouping_id(l_returnflag, l_linestatus) AS g FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")(lambda s, d: t(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(n(), F.grouping_id().alias("g")))
put("op_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: t(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(n()))
put("op_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")(lambda s, d: t(s, d, "customer").join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(n()))
_w = lambda: W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey", "l_quantity")
_o = "PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey, l_quantity"
put("op_window_rank", f"SELECT l_suppkey, l_orderkey, l_linenumber, row_number() OVER ({_o}) AS rn, ntile(4) OVER ({_o}) AS nt FROM lineitem")(lambda s, d: t(s, d, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", F.row_number().over(_w()).alias("rn"), F.ntile(4).over(_w()).alias("nt")))
put("op_window_lag", f"SELECT l_suppkey, l_orderkey, l_linenumber, lag(l_extendedprice) OVER ({_o}) AS before, lead(l_orderkey, 2) OVER ({_o}) AS after FROM lineitem")(lambda s, d: t(s, d, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", F.lag("l_extendedprice").over(_w()).alias("before"), F.lead("l_orderkey", 2).over(_w()).alias("after")))
put("op_window_frame", "SELECT event_id, sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS s3, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS hour FROM events")(
    lambda s, d: t(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.sum("value").over(W.partitionBy("user_id").orderBy("ts").rowsBetween(-2, 0)).alias("s3"), F.count(F.lit(1)).over(W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("hour"))
)
put("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda s, d: t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice"))
put("op_topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3")(lambda s, d: t(s, d, "customer").withColumn("r", F.row_number().over(W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"))).filter("r <= 3").select("c_nationkey", "c_custkey"))
_a = lambda s, d: t(s, d, "lineitem").filter("l_quantity >= 45").select("l_partkey")
_b = lambda s, d: t(s, d, "lineitem").filter("l_quantity <= 5").select("l_partkey")
_sa, _sb = "SELECT l_partkey FROM lineitem WHERE l_quantity >= 45", "SELECT l_partkey FROM lineitem WHERE l_quantity <= 5"
put("op_union", f"SELECT l_partkey, count(*) AS n FROM ({_sa} UNION ALL {_sb}) GROUP BY 1")(lambda s, d: _a(s, d).unionByName(_b(s, d)).groupBy("l_partkey").agg(n()))
put("op_intersect", f"{_sa} INTERSECT {_sb}")(lambda s, d: _a(s, d).intersect(_b(s, d)))
put("op_except", f"{_sa} EXCEPT ALL {_sb}")(lambda s, d: _a(s, d).exceptAll(_b(s, d)))
put("op_distinct", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")(lambda s, d: t(s, d, "lineitem").select("l_partkey", "l_suppkey").distinct())
put("op_string", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, upper(substr(url, 1, 5)) AS head, length(url) AS n, md5(url) AS h, string_split(url, '/')[4] AS part FROM pages")(lambda s, d: t(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.upper(F.substring("url", 1, 5)).alias("head"), F.length("url").cast("long").alias("n"), F.md5("url").alias("h"), F.get(F.split("url", "/"), 3).alias("part")))
put("op_date", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS m, count(*) AS n, CAST(sum(date_diff('day', TIMESTAMP '1992-01-01', date_trunc('day', o_orderdate))) AS BIGINT) AS days FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("m")).agg(n(), F.sum(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).alias("days")))
put("op_math_bits", "SELECT c_custkey, c_custkey & 12 AS a, xor(c_custkey, 5) AS x, bit_count(c_custkey) AS ones, round(log2(c_custkey + 1), 6) AS l FROM customer")(lambda s, d: t(s, d, "customer").select("c_custkey", F.col("c_custkey").bitwiseAND(12).alias("a"), F.col("c_custkey").bitwiseXOR(5).alias("x"), F.bit_count("c_custkey").alias("ones"), F.round(F.log2(F.col("c_custkey") + 1), 6).alias("l")))
put("op_array", "SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_partkey)), ',') AS parts, CAST(sum(l_linenumber) AS BIGINT) AS s FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set("l_partkey")), ",").alias("parts"), F.aggregate(F.collect_list(F.col("l_linenumber").cast("long")), F.lit(0).cast("long"), lambda a, x: a + x).alias("s")))
put("op_map", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END) AS f, sum(CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END) AS o FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(n()).groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m")).select("l_returnflag", *[F.coalesce(F.col("m")[k], F.lit(0)).cast("decimal(38,0)").cast("long").alias(k.lower()) for k in ("F", "O")]))
put("op_json", "SELECT event_id, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))["k"].alias("k")))


@put("op_subquery", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part) AND NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity = 50)")
def _subquery(s, d):
    for name in ("part", "lineitem"):
        t(s, d, name).createOrReplaceTempView(f"bs_{name}")
    return s.sql("SELECT p_partkey FROM bs_part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM bs_part) AND NOT EXISTS (SELECT 1 FROM bs_lineitem WHERE l_partkey = p_partkey AND l_quantity = 50)")


put("op_pivot", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN l_quantity END) AS f, sum(CASE WHEN l_linestatus = 'O' THEN l_quantity END) AS o FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).sum("l_quantity").select("l_returnflag", F.col("F").alias("f"), F.col("O").alias("o")))
put("op_hash_sample", "SELECT count(*) AS n FROM orders WHERE (o_orderkey * 7919 + 13) % 2147483647 % 10 < 3")(lambda s, d: t(s, d, "orders").filter("(o_orderkey * 7919 + 13) % 2147483647 % 10 < 3").agg(n()))


@put("op_udf", "SELECT c_custkey, c_acctbal * 2 + 1 AS y FROM customer")
def _udf(s, d):
    @F.pandas_udf(T.DoubleType())
    def twice(x: pd.Series) -> pd.Series:
        return x * 2 + 1

    return t(s, d, "customer").select("c_custkey", twice("c_acctbal").alias("y"))


@put("op_udaf", "SELECT c_nationkey, max(c_acctbal) - min(c_acctbal) AS spread FROM customer GROUP BY 1")
def _udaf(s, d):
    @F.pandas_udf(T.DoubleType())
    def spread(x: pd.Series) -> float:
        return float(x.max() - x.min())

    return t(s, d, "customer").groupBy("c_nationkey").agg(spread("c_acctbal").alias("spread"))


@put("op_udtf", "SELECT r_regionkey, i FROM region, range(3) t(i)")
def _udtf(s, d):
    @F.udtf(returnType="i: long")
    class Numbers:
        def eval(self, count: int):
            for i in range(count):
                yield (i,)

    s.udtf.register("bs_numbers", Numbers)
    t(s, d, "region").createOrReplaceTempView("bs_region")
    return s.sql("SELECT r_regionkey, i FROM bs_region, LATERAL bs_numbers(3)")


@put("op_recursive", "WITH RECURSIVE r(i) AS (SELECT 1 UNION ALL SELECT i * 2 FROM r WHERE i < 1000) SELECT CAST(i AS BIGINT) AS i FROM r")
def _recursive(s, d):
    return s.sql("WITH RECURSIVE r(i) AS (SELECT 1L UNION ALL SELECT i * 2 FROM r WHERE i < 1000) SELECT i FROM r")


@put("op_csv_round_trip", "SELECT n_nationkey, n_name FROM nation")
def _csv(s, d):
    import uuid

    from ..session import checkpoint_dir

    path = f"{checkpoint_dir(s)}/csv-{uuid.uuid4()}"
    t(s, d, "nation").select("n_nationkey", "n_name").write.csv(path)
    return s.read.schema("n_nationkey int, n_name string").csv(path)


@put("op_json_round_trip", "SELECT r_regionkey, r_name FROM region")
def _json(s, d):
    import uuid

    from ..session import checkpoint_dir

    path = f"{checkpoint_dir(s)}/json-{uuid.uuid4()}"
    t(s, d, "region").select("r_regionkey", "r_name").write.json(path)
    return s.read.schema("r_regionkey int, r_name string").json(path)
