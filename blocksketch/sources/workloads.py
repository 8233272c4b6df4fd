"""The workload graphs, as DataFrames and as SQL over the same tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators.stream import canonical_edges, distinct_edges, encode_id, text_id, toggle_stream
from ..session import table

#: name: (SQL for rows (a, b[, w]) before canonical order, kinds)
SQL_PAIRS = {
    "w1": "SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b, l_quantity AS w FROM lineitem",
    "w1m": "SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b, l_quantity AS w FROM lineitem WHERE l_quantity >= 30",
    "w2": "SELECT l_orderkey * 2 AS a, l_partkey * 2 + 1 AS b, 1.0 AS w FROM lineitem",
    "w3": "SELECT o_custkey * 2 AS a, o_orderkey * 2 + 1 AS b, 1.0 AS w FROM orders",
    "w4": "SELECT l_orderkey * 2 AS a, l_partkey * 2 + 1 AS b, 1.0 AS w FROM lineitem WHERE l_quantity = 50",
    "w4r": "SELECT l_orderkey * 2 AS a, l_partkey * 2 + 1 AS b, 1.0 AS w FROM lineitem WHERE l_quantity = 50 AND l_returnflag = 'R'",
    "w5": "SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b, l_quantity AS w FROM lineitem WHERE l_returnflag = 'R' AND l_quantity >= 49",
    "w6": "SELECT x.l_partkey AS a, y.l_partkey AS b, 1.0 AS w FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND y.l_linenumber = x.l_linenumber + 1 WHERE x.l_quantity >= 45 AND y.l_quantity >= 40",
    "w8": "SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts) AS b, 1.0 AS w FROM events QUALIFY b IS NOT NULL",
    "w10": "SELECT doc_id * 2 AS a, CAST(('0x' || substr(md5(line), 1, 15)) AS BIGINT) * 2 + 1 AS b, 1.0 AS w FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 60",
    "w11": "SELECT page_id * 2 AS a, CAST(('0x' || substr(md5(regexp_extract(url, '^[a-z]+://([^/]+)', 1)), 1, 15)) AS BIGINT) * 2 + 1 AS b, 1.0 AS w FROM pages",
    "w12": "SELECT c_nationkey AS a, s_nationkey AS b, 1.0 AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation x ON x.n_nationkey = c_nationkey JOIN nation y ON y.n_nationkey = s_nationkey WHERE x.n_regionkey IN (0, 1) AND y.n_regionkey IN (0, 1) AND l_quantity >= 48",
    "w16": "SELECT conv_id * 2 AS a, (conv_id * 1000 + turn) * 2 + 1 AS b, 1.0 AS w FROM conversations",
}
SQL_PAIRS["w12n"] = "SELECT c_nationkey AS a, s_nationkey AS b, 1.0 AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"
SQL_PAIRS["w12b"] = SQL_PAIRS["w12"].replace("l_quantity >= 48", "l_quantity = 50 AND l_returnflag = 'R'")


def sql_edges(name: str, weight: str = "min") -> str:
    """Distinct canonical edges (u, v, w)."""
    return f"SELECT least(a, b) AS u, greatest(a, b) AS v, {weight}(CAST(w AS DOUBLE)) AS w FROM ({SQL_PAIRS[name]}) WHERE a <> b GROUP BY 1, 2"


def pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Rows (a, b, w) before canonical order."""
    t = lambda n: table(spark, sf_dir, n)
    two = lambda df, a, b, w=None: df.select(encode_id(F.col(a), 0, 2).alias("a"), encode_id(F.col(b), 1, 2).alias("b"), (F.col(w) if w else F.lit(1.0)).alias("w"))
    li = lambda: t("lineitem")
    if name in ("w1", "w1m"):
        return two(li() if name == "w1" else li().filter("l_quantity >= 30"), "l_partkey", "l_suppkey", "l_quantity")
    if name == "w2":
        return two(li(), "l_orderkey", "l_partkey")
    if name == "w3":
        return two(t("orders"), "o_custkey", "o_orderkey")
    if name == "w4":
        return two(li().filter("l_quantity = 50"), "l_orderkey", "l_partkey")
    if name == "w4r":
        return two(li().filter("l_quantity = 50 and l_returnflag = 'R'"), "l_orderkey", "l_partkey")
    if name == "w5":
        return two(li().filter("l_returnflag = 'R' and l_quantity >= 49"), "l_partkey", "l_suppkey", "l_quantity")
    if name == "w6":
        x = li().filter("l_quantity >= 45").select("l_orderkey", (F.col("l_linenumber") + 1).alias("l_linenumber"), F.col("l_partkey").alias("a"))
        y = li().filter("l_quantity >= 40").select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("b"))
        return x.join(y, ["l_orderkey", "l_linenumber"]).select("a", "b", F.lit(1.0).alias("w"))
    if name == "w8":
        # one order of all events: rank them, then join each to the next, so that no window holds the whole table
        e = t("events").select("ts", F.col("user_id").cast("long").alias("user_id"))
        r = ranked(e, "ts")
        nxt = r.select((F.col("n") - 1).alias("n"), F.col("user_id").alias("b"))
        return r.select("n", F.col("user_id").alias("a")).join(nxt, "n").select("a", "b", F.lit(1.0).alias("w"))
    if name == "w10":
        d = t("documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") > 60)
        return d.select((F.col("doc_id") * 2).alias("a"), (text_id(F.col("line")) * 2 + 1).alias("b"), F.lit(1.0).alias("w"))
    if name == "w11":
        host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
        return t("pages").select((F.col("page_id") * 2).alias("a"), (text_id(host) * 2 + 1).alias("b"), F.lit(1.0).alias("w"))
    if name in ("w12", "w12b", "w12n"):
        near = t("nation").filter(F.lit(True) if name == "w12n" else F.col("n_regionkey").isin(0, 1)).select("n_nationkey")
        c = t("customer").join(near, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("c_nationkey").cast("long").alias("a"))
        s = t("supplier").join(near, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("s_nationkey").cast("long").alias("b"))
        lines = li().filter({"w12": "l_quantity >= 48", "w12b": "l_quantity = 50 and l_returnflag = 'R'", "w12n": "true"}[name]).select("l_orderkey", "l_suppkey")
        o = t("orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
        return lines.join(o, "l_orderkey").join(c, "c_custkey").join(s, F.col("l_suppkey") == F.col("s_suppkey")).select("a", "b", F.lit(1.0).alias("w"))
    if name == "w16":
        c = t("conversations")
        return c.select((F.col("conv_id") * 2).alias("a"), ((F.col("conv_id") * 1000 + F.col("turn")) * 2 + 1).alias("b"), F.lit(1.0).alias("w"))
    raise KeyError(name)


def ranked(df: DataFrame, order: str) -> DataFrame:
    """df with n, each row's place from 0 in the order of a column of distinct values: a range exchange, then places within partitions plus the partitions' starts."""
    parts = df.repartitionByRange(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), order).withColumn("_p", F.spark_partition_id())
    inner = parts.withColumn("_i", F.row_number().over(W.partitionBy("_p").orderBy(order)) - 1)
    from ..session import cut

    inner = cut(inner)
    starts = inner.groupBy("_p").agg(F.count(F.lit(1)).alias("_c"))  # a row a partition
    starts = starts.select("_p", (F.sum("_c").over(W.orderBy("_p").rowsBetween(W.unboundedPreceding, 0)) - F.col("_c")).alias("_s"))
    return inner.join(F.broadcast(starts), "_p").withColumn("n", F.col("_s") + F.col("_i")).drop("_p", "_i", "_s")


def edges(spark: SparkSession, sf_dir: str, name: str, weight: str = "min") -> DataFrame:
    """Distinct canonical edges (u, v, w)."""
    return distinct_edges(pairs(spark, sf_dir, name), "a", "b", "w", weight)


def stream_w7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User and key of every event toggle, in time order; event_id follows ts within a pair."""
    e = table(spark, sf_dir, "events").select("event_id", "ts", encode_id(F.col("user_id"), 0, 2).alias("a"), encode_id(F.get_json_object("props", "$.k").cast("long"), 1, 2).alias("b"))
    return toggle_stream(e, "a", "b", "ts", seq="event_id")


SQL_W7 = """SELECT event_id AS seq, least(a, b) AS u, greatest(a, b) AS v, CAST(CASE WHEN row_number() OVER (PARTITION BY a, b ORDER BY ts) % 2 = 1 THEN 1 ELSE -1 END AS INTEGER) AS delta
FROM (SELECT event_id, ts, user_id * 2 AS a, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) * 2 + 1 AS b FROM events)"""


def stream_w14(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A part-supplier pair is inserted at its first line, and deleted behind its last if that line was returned."""
    li = table(spark, sf_dir, "lineitem").select(encode_id(F.col("l_partkey"), 0, 2).alias("a"), encode_id(F.col("l_suppkey"), 1, 2).alias("b"), F.struct("l_shipdate", "l_orderkey", "l_linenumber", "l_extendedprice").alias("o"), "l_returnflag")
    by = li.groupBy("a", "b").agg(F.max_by("l_returnflag", "o").alias("last"))

    both = by.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), F.explode(F.when(F.col("last") == "R", F.array(F.lit(1), F.lit(-1))).otherwise(F.array(F.lit(1)))).alias("delta"))

    return both.select(F.when(F.col("delta") == 1, 0).otherwise(1).cast("long").alias("seq"), "u", "v", "delta", F.lit(1.0).alias("w"))


SQL_W14 = "SELECT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b, arg_max(l_returnflag, (l_shipdate, l_orderkey, l_linenumber, l_extendedprice)) AS last FROM lineitem GROUP BY 1, 2) WHERE last <> 'R'"


def sql_components(edges_sql: str, pick: str = "SELECT x, label FROM cc") -> str:
    """SQL for the least vertex number of every component; pick selects from cc(x, label) and e(u, v, ...)."""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges_sql}), ends AS MATERIALIZED (SELECT u AS a, v AS b FROM e UNION SELECT v, u FROM e),
cc(x, label) USING KEY (x) AS (SELECT a, min(least(a, b)) FROM ends GROUP BY a UNION
(SELECT k.x, min(c.label) AS label FROM recurring.cc AS k JOIN ends ON ends.a = k.x JOIN cc AS c ON c.x = ends.b WHERE c.label < k.label GROUP BY k.x))
{pick}"""
