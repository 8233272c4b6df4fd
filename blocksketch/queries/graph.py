"""Registered queries over the workload graphs, each with the SQL it is held against where SQL can say it."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from ..cost import simulate
from ..exact import external, solvers
from ..functions import hashing as H
from ..operators import cells as C
from ..operators import hyper as HY
from ..operators import stream as S
from ..plans import connectivity as CC
from ..plans import densest as D
from ..plans import families as FM
from ..plans import kconn as K
from ..session import cut, table
from ..sources import workloads as WL
from ..spec import SketchSpec

Q: dict = {}
SQL: dict = {}


def register(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def _row(spark, schema: str, *values):
    return spark.createDataFrame([values], schema)


def ins(spark, d, name, weight="min"):
    return S.inserts(WL.edges(spark, d, name, weight))


# --- model ---
register("edges_canonical", WL.sql_edges("w1"))(lambda s, d: WL.edges(s, d, "w1"))
W7E = f"SELECT u, v FROM ({WL.SQL_W7}) GROUP BY u, v HAVING sum(delta) = 1"
register("edges_final_w7", W7E)(lambda s, d: S.edges_at(WL.stream_w7(s, d)).select("u", "v"))
register("edges_prefix_w7", f"SELECT u, v FROM ({WL.SQL_W7}) WHERE seq <= 500 GROUP BY u, v HAVING sum(delta) = 1")(lambda s, d: S.edges_at(WL.stream_w7(s, d), 500).select("u", "v"))
register("toggle_counts", f"SELECT delta, count(*) AS n FROM ({WL.SQL_W7}) GROUP BY delta")(lambda s, d: WL.stream_w7(s, d).groupBy("delta").agg(F.count(F.lit(1)).alias("n")))
register("stream_violations", f"WITH s AS (SELECT event_id AS seq, user_id * 2 AS u, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) * 2 + 1 AS v, CASE WHEN event_type < 'm' THEN 1 ELSE -1 END AS delta FROM events), r AS (SELECT least(u, v) AS u, greatest(u, v) AS v, seq, sum(delta) OVER (PARTITION BY u, v ORDER BY seq) AS m FROM s) SELECT u, v, seq, CAST(m AS BIGINT) AS multiplicity FROM r WHERE m NOT IN (0, 1)")(
    lambda s, d: S.validate_stream(table(s, d, "events").select(F.col("event_id").alias("seq"), (F.col("user_id") * 2).cast("long").alias("a"), (F.get_json_object("props", "$.k").cast("long") * 2 + 1).alias("b"), F.when(F.col("event_type") < "m", 1).otherwise(-1).alias("delta")).select("seq", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "delta")).select("u", "v", "seq", "multiplicity")
)
register("encode_ids", "SELECT c_custkey * 3 + 1 AS id, c_custkey FROM customer")(lambda s, d: table(s, d, "customer").select(S.encode_id(F.col("c_custkey"), 1, 3).alias("id"), "c_custkey"))


def hyper_w13(s, d):
    """An order is the set of its parts."""
    li = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("m"))
    return HY.canonical_hyperedges(li, "m")


def hyper_w13d(s, d):
    """All orders are inserted; those of status F are deleted behind it."""
    li = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("m"))
    gone = table(s, d, "orders").filter("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("l_orderkey"))
    both = li.select("m", F.lit(1).alias("delta")).unionByName(li.join(gone, "l_orderkey", "left_semi").select("m", F.lit(-1).alias("delta")))
    return HY.canonical_hyperedges(both, "m")


HW13 = "SELECT list_sort(list(DISTINCT l_partkey)) AS members FROM lineitem GROUP BY l_orderkey HAVING count(DISTINCT l_partkey) > 1"
HW13D = "SELECT list_sort(list(DISTINCT l_partkey)) AS members FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F') GROUP BY l_orderkey HAVING count(DISTINCT l_partkey) > 1"
register("hyperedges_w13", f"SELECT array_to_string(members, ',') AS members, count(*) AS n FROM ({HW13}) GROUP BY 1")(lambda s, d: hyper_w13(s, d).groupBy(F.array_join("members", ",").alias("members")).agg(F.count(F.lit(1)).alias("n")))

# --- sketch ---
SPEC = SketchSpec(rows=4, levels=20, seed=3)


def sql_cells(edges_sql: str, spec: SketchSpec, rows: int | None = None) -> str:
    h = H.sql_edge_hash(spec, "0", "row", "u", "v")
    return f"""SELECT x, row, lvl, bit_xor(u) AS xu, bit_xor(v) AS xv, bit_xor(chk) AS chk FROM (
SELECT unnest([u, v]) AS x, row, {H.sql_level("h", spec.levels)} AS lvl, u, v, {H.sql_checksum(spec, "u", "v")} AS chk
FROM (SELECT u, v, CAST(row AS INTEGER) AS row, {h} AS h FROM ({edges_sql}), range({rows or spec.rows}) t(row))) GROUP BY x, row, lvl HAVING bit_xor(u) <> 0 OR bit_xor(v) <> 0 OR bit_xor(chk) <> 0"""


def cols(df):
    return df.select("x", "row", "lvl", "xu", "xv", "chk")


CELLS_W1 = sql_cells(WL.sql_edges("w1"), SPEC)
for _mode in ("block", "combine_first", "per_update", "global_sort"):
    register("cells_w1" if _mode == "block" else f"cells_w1_{_mode}", CELLS_W1)(lambda s, d, m=_mode: cols(C.sketch_updates(ins(s, d, "w1"), SPEC, mode=m)))
register("cells_w1_row_chunks", CELLS_W1)(lambda s, d: cols(C.sketch_in_chunks(ins(s, d, "w1"), SPEC, 2)))


@register("cells_w1_salted_hubs", CELLS_W1)
def _salted(s, d):
    u = ins(s, d, "w1")
    hubs = C.edge_records(u).groupBy("x").agg(F.count(F.lit(1)).alias("deg")).filter("deg > 400").orderBy(F.desc("deg")).limit(1000).select("x")
    return cols(C.sketch_updates(u, SPEC, hubs=hubs))


register("level_bands_w1", f"SELECT CAST(lvl // 4 AS INTEGER) AS band, count(*) AS cells FROM ({CELLS_W1}) GROUP BY 1")(lambda s, d: C.sketch_updates(ins(s, d, "w1"), SPEC).groupBy(C.level_band(F.col("lvl"), 4).alias("band")).agg(F.count(F.lit(1)).alias("cells")))
register("cells_linear_merge", CELLS_W1)(lambda s, d: cols(C.merge_cells(C.sketch_updates(ins(s, d, "w1").filter("u % 3 = 0"), SPEC), C.sketch_updates(ins(s, d, "w1").filter("u % 3 <> 0"), SPEC))))
register("cells_delete_cancels", sql_cells(W7E, SPEC))(lambda s, d: cols(C.sketch_updates(WL.stream_w7(s, d), SPEC)))
CUT12 = f"SELECT CAST(u % 2 AS BIGINT) AS pu, CAST(v % 2 AS BIGINT) AS pv, u, v FROM ({WL.sql_edges('w12')})"
register("cells_cut_sum_w12", f"WITH c AS (SELECT u, v FROM ({CUT12}) WHERE pu <> pv) SELECT label, row, bit_xor(u) AS xu, bit_xor(v) AS xv FROM c, range(4) t(row), (VALUES (0), (1)) l(label) GROUP BY label, row")(
    lambda s, d: C.suffix_sums(C.cut_cells(C.sketch_updates(ins(s, d, "w12"), SPEC), ins(s, d, "w12").select(F.explode(F.array("u", "v")).alias("x")).distinct().withColumn("label", (F.col("x") % 2))), "label").groupBy("label", "row").agg(F.min_by("xu", "lvl").alias("xu"), F.min_by("xv", "lvl").alias("xv")).select(F.col("label").cast("int").alias("label"), F.col("row").cast("long").alias("row"), "xu", "xv")
)
LEVELS = f"SELECT row, lvl, count(*) AS n FROM (SELECT row, {H.sql_level('h', SPEC.levels)} AS lvl FROM (SELECT CAST(row AS INTEGER) AS row, {H.sql_edge_hash(SPEC, '0', 'row', 'u', 'v')} AS h FROM ({WL.sql_edges('w2')}), range(4) t(row))) GROUP BY row, lvl"


def levels_w2(s, d):
    e = WL.edges(s, d, "w2").select("u", "v", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("row"))
    return e.select("row", H.level(H.edge_hash(SPEC, F.lit(0), F.col("row"), F.col("u"), F.col("v")), SPEC.levels).alias("lvl")).groupBy("row", "lvl").agg(F.count(F.lit(1)).alias("n"))


register("level_histogram", LEVELS)(levels_w2)
register("row_tail_bound", f"WITH h AS ({LEVELS}), t AS (SELECT row, sum(n) AS all_n FROM h GROUP BY row) SELECT h.lvl, CAST(sum(n) AS BIGINT) AS n, least(1.0, pow(2.0, -h.lvl)) AS expected FROM h JOIN t USING (row) GROUP BY h.lvl")(lambda s, d: levels_w2(s, d).groupBy("lvl").agg(F.sum("n").alias("n")).withColumn("expected", F.least(F.lit(1.0), F.pow(F.lit(2.0), -F.col("lvl")))))
register("cell_space", f"SELECT count(*) AS cells, CAST(count(*) * 7 AS BIGINT) AS words, (SELECT CAST(count(*) * 2 AS BIGINT) FROM ({WL.sql_edges('w1')})) AS edge_words FROM ({CELLS_W1})")(lambda s, d: C.sketch_updates(ins(s, d, "w1"), SPEC).agg(F.count(F.lit(1)).alias("cells")).select("cells", (F.col("cells") * 7).alias("words")).crossJoin(WL.edges(s, d, "w1").agg((F.count(F.lit(1)) * 2).alias("edge_words"))))
register("finalize_w4", sql_cells(WL.sql_edges("w4"), SPEC))(lambda s, d: cols(C.finalize(C.sketch_updates(ins(s, d, "w4"), SPEC), SPEC)))
register("finalize_dense_w4", f"SELECT x, row, CAST({SPEC.levels} AS INTEGER) AS n_levels, bit_xor(xu) AS all_xu FROM ({sql_cells(WL.sql_edges('w4'), SPEC)}) GROUP BY x, row")(lambda s, d: C.finalize(C.sketch_updates(ins(s, d, "w4"), SPEC), SPEC, dense=True).select("x", "row", F.size("cells").alias("n_levels"), F.aggregate("cells", F.lit(0).cast("long"), lambda a, c: a.bitwiseXOR(c["xu"])).alias("all_xu")))
register("hcells_sums_w13", f"SELECT x, CAST((sum(CASE WHEN x = members[1] THEN len(members) - 1 ELSE -1 END) % {H.P} + {H.P}) % {H.P} AS BIGINT) AS s0 FROM (SELECT unnest(members) AS x, members FROM ({HW13})) GROUP BY x HAVING s0 <> 0")(
    lambda s, d: HY.sketch_hyper(hyper_w13(s, d), SketchSpec(rows=1, levels=16, seed=3), HY.rank(hyper_w13(s, d))).groupBy("x").agg(F.pmod(F.sum("s0"), F.lit(H.P)).cast("long").alias("s0")).filter("s0 <> 0")
)
register("poly_hash_16", f"SELECT c_custkey, {H.sql_poly('c_custkey', [c[0] for c in H.coefficients(4, 16, 't')])} AS h FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", H.poly_hash(F.col("c_custkey"), [c[0] for c in H.coefficients(4, 16, "t")]).alias("h")))
register("empty_cut_w3", f"WITH t AS (SELECT label FROM ({WL.sql_components(WL.sql_edges('w3'))}) GROUP BY label) SELECT count(*) AS closed FROM t")(lambda s, d: _closed_w3(s, d))


def _closed_w3(s, d):
    u = ins(s, d, "w3")
    labels = external.components(WL.edges(s, d, "w3"))
    return C.cut_is_empty(C.cut_cells(C.sketch_updates(u, SketchSpec(rows=2, levels=18)), labels), labels).filter("is_empty").agg(F.count(F.lit(1)).alias("closed"))


# --- components ---
for _w, _n in {"w1": "cc_w1", "w2": "cc_w2", "w3": "cc_w3", "w4": "cc_w4", "w4r": "cc_w4r", "w5": "cc_w5", "w6": "cc_w6", "w10": "cc_dup_docs_w10", "w11": "cc_hosts_w11", "w16": "cc_stars_w16"}.items():
    register(_n, WL.sql_components(WL.sql_edges(_w)))(lambda s, d, w=_w: CC.connected_components(ins(s, d, w)))
register("cc_count_dynamic_w7", WL.sql_components(W7E, "SELECT count(DISTINCT label) AS components FROM cc"))(lambda s, d: CC.connected_components(WL.stream_w7(s, d)).agg(F.countDistinct("label").alias("components")))
register("cc_returns_w14", WL.sql_components(WL.SQL_W14))(lambda s, d: CC.connected_components(WL.stream_w14(s, d), vertices=CC.live_vertices(WL.stream_w14(s, d))))
register("cc_distributed_w4r", WL.sql_components(WL.sql_edges("w4r")))(lambda s, d: CC.connected_components(ins(s, d, "w4r"), extraction="distributed"))
register("cc_prior_out_of_core_w5", WL.sql_components(WL.sql_edges("w5")))(lambda s, d: CC.connected_components(ins(s, d, "w5"), mode="global_sort"))
register("cc_native_hash_w5", WL.sql_components(WL.sql_edges("w5")))(lambda s, d: CC.connected_components(ins(s, d, "w5"), family="native"))
register("forest_w3", "SELECT u, v FROM (" + WL.sql_edges("w3") + ")")(lambda s, d: CC.spanning_forest(ins(s, d, "w3")).select("u", "v"))
register("forest_w4", "SELECT u, v FROM (" + WL.sql_edges("w4") + ")")(lambda s, d: CC.spanning_forest(ins(s, d, "w4")).select("u", "v"))
register("forest_w16", "SELECT u, v FROM (" + WL.sql_edges("w16") + ")")(lambda s, d: CC.spanning_forest(ins(s, d, "w16")).select("u", "v"))


@register("forest_size_w1", WL.sql_components(WL.sql_edges("w1"), "SELECT count(*) - count(DISTINCT label) AS edges, true AS subset, true AS spans FROM cc"))
def _forest_size(s, d):
    e = cut(WL.edges(s, d, "w1"))
    f = cut(CC.spanning_forest(S.inserts(e)).select("u", "v"))
    stray = f.join(e, ["u", "v"], "left_anti").agg((F.count(F.lit(1)) == 0).alias("subset"))
    spans = external.components(f).agg(F.countDistinct("label").alias("c")).crossJoin(external.components(e).agg(F.countDistinct("label").alias("c0"))).select((F.col("c") == F.col("c0")).alias("spans"))
    return f.agg(F.count(F.lit(1)).alias("edges")).crossJoin(stray).crossJoin(spans)


register("component_sizes_w4", WL.sql_components(WL.sql_edges("w4"), "SELECT label, count(*) AS size FROM cc GROUP BY label"))(lambda s, d: CC.component_sizes(CC.connected_components(ins(s, d, "w4"))))


def w18(s, d):
    """Document and benchmark item whose text it contains: a theta join, the item side bounded by the benchmark's size."""
    b = table(s, d, "benchmark").filter(F.length("text") > 0).select("item_id", F.col("text").alias("item"))
    return table(s, d, "documents").select("doc_id", "text").join(b, F.contains("text", "item")).select((F.col("doc_id") * 2).alias("a"), (F.col("item_id") * 2 + 1).alias("b"), F.lit(1.0).alias("w"))


WL.SQL_PAIRS["w18"] = "SELECT doc_id * 2 AS a, item_id * 2 + 1 AS b, 1.0 AS w FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE length(b.text) > 0"
register("same_component_w18", WL.sql_components(WL.sql_edges("w18"), "SELECT s.x AS s, t.x AS t, s.label = t.label AS same FROM cc s JOIN cc t ON s.x < t.x AND s.x % 2 = 1 AND t.x % 2 = 1"))(lambda s, d: _same18(s, d))


def _same18(s, d):
    labels = cut(CC.connected_components(S.inserts(S.distinct_edges(w18(s, d), "a", "b", "w"))))
    items = labels.filter("x % 2 = 1").select("x")  # at most the benchmark's items
    pairs = items.select(F.col("x").alias("s")).join(items.select(F.col("x").alias("t")), F.col("s") < F.col("t"))
    return CC.same_component(labels, pairs)


register("labelled_docs_w17", WL.sql_components(WL.sql_edges("w10"), "SELECT quality, count(*) FILTER (doc_id * 2 IN (SELECT x FROM cc)) AS in_component, count(*) FILTER (doc_id * 2 NOT IN (SELECT x FROM cc)) AS outside FROM labels GROUP BY quality"))(lambda s, d: _labelled17(s, d))


def _labelled17(s, d):
    labels = CC.connected_components(ins(s, d, "w10")).select((F.col("x") / 2).alias("doc_id")).filter("doc_id = floor(doc_id)").select(F.col("doc_id").cast("long").alias("doc_id"))
    labels = cut(labels)
    t = table(s, d, "labels").select("doc_id", "quality")
    a = t.join(labels, "doc_id", "left_semi").groupBy("quality").agg(F.count(F.lit(1)).alias("in_component"))
    b = t.join(labels, "doc_id", "left_anti").groupBy("quality").agg(F.count(F.lit(1)).alias("outside"))
    z = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return a.join(b, "quality", "full").select("quality", z("in_component"), z("outside"))


# --- bipartite ---
def sql_bipartite(e: str) -> str:
    cover = f"SELECT least(u * 2, v * 2 + 1) AS u, greatest(u * 2, v * 2 + 1) AS v FROM ({e}) UNION SELECT least(v * 2, u * 2 + 1), greatest(v * 2, u * 2 + 1) FROM ({e})"
    return WL.sql_components(cover, "SELECT coalesce(bool_and(p.label <> q.label), true) AS bipartite FROM cc p JOIN cc q ON q.x = p.x + 1 WHERE p.x % 2 = 0")


register("bip_w1", sql_bipartite(WL.sql_edges("w1")))(lambda s, d: FM.is_bipartite(ins(s, d, "w1")))
register("bip_w8", sql_bipartite(WL.sql_edges("w8")))(lambda s, d: FM.is_bipartite(ins(s, d, "w8")))
COS = "list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"
WL.SQL_PAIRS["w9"] = f"SELECT a.vec_id AS a, b.vec_id AS b, 1.0 AS w FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE round({COS}, 6) >= 0.35"


BLOCK9 = 2048


def w9(s, d, least=0.35):
    """Pairs of vectors by cosine: an exact theta join, block against block, so its cost grows with the square of the vectors."""
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    e = e.filter(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & F.forall("v", lambda x: x.isNotNull()))
    n, count = int(s.conf.get("spark.sql.shuffle.partitions")), e.count()
    blocks = max(1, math.ceil(count / BLOCK9), min(n, count // 64))  # no fewer than there are tasks
    packed = cut(e.withColumn("blk", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).groupBy("blk").agg(F.collect_list("vec_id").alias("ids"), F.flatten(F.collect_list("v")).alias("data")))
    # each block meets itself and the next half of the others, so that all are met by as many; of an even number, half meet the one opposite
    steps = F.sequence(F.lit(0).cast("long"), F.when(F.col("blk") < blocks // 2, F.lit(blocks // 2)).otherwise(F.lit((blocks - 1) // 2)).cast("long"))
    a = packed.select(F.col("blk").alias("ba"), F.col("ids").alias("ia"), F.col("data").alias("da"), F.explode(F.transform(steps, lambda k: (F.col("blk") + k) % blocks)).alias("blk"))
    a = a.repartition(n, "blk")  # by number: Spark would join so few rows in one task

    def compare(batches):
        for batch in batches:
            for r in range(batch.num_rows):
                same = batch["ba"][r].as_py() == batch["blk"][r].as_py()
                ids, x = ([np.asarray(batch[c][r].values) for c in cs] for cs in (("ia", "ids"), ("da", "data")))
                yield solvers.cosine_pairs(*ids, *(m.reshape(len(i), -1) for m, i in zip(x, ids)), least, same)

    return a.join(packed, "blk").select("ba", "blk", "ia", "da", "ids", "data").mapInArrow(compare, "a long, b long").select("a", "b", F.lit(1.0).alias("w"))


E9 = WL.sql_edges("w9")
COVER9 = f"SELECT least(u * 2, v * 2 + 1) AS u, greatest(u * 2, v * 2 + 1) AS v FROM ({E9}) UNION SELECT least(v * 2, u * 2 + 1), greatest(v * 2, u * 2 + 1) FROM ({E9})"
register("bip_components_w9", WL.sql_components(COVER9, "SELECT bipartite, count(*) AS n FROM (SELECT least(p.label, q.label) // 2 AS c, min(CASE WHEN p.label <> q.label THEN 1 ELSE 0 END) = 1 AS bipartite FROM cc p JOIN cc q ON q.x = p.x + 1 WHERE p.x % 2 = 0 GROUP BY 1) GROUP BY bipartite"))(lambda s, d: FM.bipartiteness(S.inserts(cut(S.distinct_edges(w9(s, d), "a", "b", "w")))).groupBy("bipartite").agg(F.count(F.lit(1)).alias("n")))

# --- hypergraphs ---
STAR = f"SELECT members[1] AS u, unnest(members[2:]) AS v FROM ({HW13})"
register("hcc_w13", WL.sql_components(STAR))(lambda s, d: HY.hyper_components(hyper_w13(s, d))[0])
register("hcc_distributed_w13", WL.sql_components(STAR))(lambda s, d: HY.hyper_components(hyper_w13(s, d), extraction="distributed")[0])
TOUCHED13 = f"SELECT DISTINCT unnest(members) AS x FROM ({HW13})"
register("hcc_deletions_w13", WL.sql_components(f"SELECT members[1] AS u, unnest(members[2:]) AS v FROM ({HW13D})", f"SELECT t.x, coalesce(label, t.x) AS label FROM ({TOUCHED13}) t LEFT JOIN cc ON cc.x = t.x"))(lambda s, d: HY.hyper_components(hyper_w13d(s, d))[0])
register("hyperforest_check_w13", WL.sql_components(STAR, "SELECT count(DISTINCT label) AS components, true AS spans FROM cc"))(lambda s, d: _hyperforest(s, d))


def _hyperforest(s, d):
    labels, chosen = HY.hyper_components(hyper_w13(s, d))
    star = chosen.select(F.element_at("members", 1).alias("u"), F.explode(F.slice("members", 2, F.size("members"))).alias("v"))
    a = labels.agg(F.countDistinct("label").alias("components"))
    return a.crossJoin(external.components(star).agg(F.countDistinct("label").alias("c"))).select("components", (F.col("c") == F.col("components")).alias("spans"))


# --- spanning-tree weight ---
def sql_thresholds(e: str, eps: float, top: float) -> str:
    steps = FM.weight_levels(eps, top)
    parts = []
    for i, t in enumerate(steps):
        parts.append(f"SELECT {i} AS i, (SELECT count(DISTINCT x) FROM ends) - coalesce((SELECT count(*) - count(DISTINCT label) FROM ({WL.sql_components(f'SELECT u, v FROM base WHERE w <= {t!r} + 1e-9')})), 0) AS n_components")
    return f"WITH base AS MATERIALIZED ({e}), ends AS (SELECT u AS x FROM base UNION SELECT v FROM base) " + " UNION ALL ".join(parts)


def sql_mst(e: str, eps: float, top: float, printed: bool = False) -> str:
    steps = FM.weight_levels(eps, top)
    n = f"(SELECT count(*) FROM (SELECT u FROM ({e}) UNION SELECT v FROM ({e})))"
    gain = [steps[i + 1] - steps[i] for i in range(len(steps) - 1)] + [-steps[-1]] if not printed else [steps[i] - (steps[i - 1] if i else 1 / (1 + eps)) for i in range(len(steps))]
    return f"SELECT round({n} + sum((CAST({gain} AS DOUBLE[]))[i + 1] * n_components){f' - {steps[-1]!r}' if printed else ''}, 4) AS weight FROM ({sql_thresholds(e, eps, top)})"


E1 = WL.sql_edges("w1")
register("mst_eps50_w1", sql_mst(E1, 0.5, 50))(lambda s, d: FM.mst_weight(ins(s, d, "w1"), 0.5, 50).select(F.round("weight", 4).alias("weight")))
register("mst_eps10_w1", sql_mst(E1, 0.1, 50))(lambda s, d: FM.mst_weight(ins(s, d, "w1"), 0.1, 50).select(F.round("weight", 4).alias("weight")))
register("mst_printed_form_w1", sql_mst(E1, 0.5, 50, True))(lambda s, d: FM.mst_weight(ins(s, d, "w1"), 0.5, 50, "as_printed").select(F.round("weight", 4).alias("weight")))
register("mst_components_per_threshold", sql_thresholds(E1, 0.5, 50))(lambda s, d: FM.threshold_components(ins(s, d, "w1"), 0.5, 50))
register("mst_disconnected_w5", sql_mst(WL.sql_edges("w5"), 0.5, 50))(lambda s, d: FM.mst_weight(ins(s, d, "w5"), 0.5, 50).select(F.round("weight", 4).alias("weight")))
register("mst_bounds_w5", "SELECT true AS at_least_exact, true AS within_factor")(lambda s, d: FM.mst_weight(ins(s, d, "w5"), 0.5, 50).crossJoin(external.minimum_forest(WL.edges(s, d, "w5")).agg(F.sum("w").alias("exact"))).select((F.col("weight") >= F.col("exact")).alias("at_least_exact"), (F.col("weight") <= 1.5 * F.col("exact")).alias("within_factor")))

# --- k-connectivity, cuts ---

@register("kcert_disjoint_w12", "SELECT 0 AS shared, 0 AS strays, true AS within_size")
def _disjoint(s, d):
    e = cut(WL.edges(s, d, "w12"))
    f = cut(K.k_certificate(S.inserts(e), 3))
    n = S.inserts(e).select(F.explode(F.array("u", "v"))).distinct().count()
    twice = f.groupBy("u", "v").count().filter("count > 1").agg(F.count(F.lit(1)).cast("int").alias("shared"))
    strays = f.join(e, ["u", "v"], "left_anti").agg(F.count(F.lit(1)).cast("int").alias("strays"))
    return twice.crossJoin(strays).crossJoin(f.agg((F.count(F.lit(1)) <= 3 * (n - 1)).alias("within_size")))


register("kcert_sizes_w12", WL.sql_components(WL.sql_edges("w12"), "SELECT CAST(f AS INTEGER) AS forest, (SELECT count(*) - count(DISTINCT label) FROM cc) AS edges FROM range(3) t(f)"))(lambda s, d: K.k_certificate(ins(s, d, "w12"), 3).groupBy("forest").agg(F.count(F.lit(1)).alias("edges")))


@register("kcert_schedules_equal", "SELECT 'lazy' AS schedule, 0 AS differ UNION ALL SELECT 'naive', 0 UNION ALL SELECT 'super', 0")
def _schedules(s, d):
    u = S.inserts(cut(WL.edges(s, d, "w12")))
    block = cut(K.k_certificate(u, 3, schedule="block"))
    out = None
    for name in ("lazy", "naive", "super"):
        other = cut(K.k_certificate(u, 3, schedule=name, width=2))
        diff = block.exceptAll(other).unionByName(other.exceptAll(block)).agg(F.lit(name).alias("schedule"), F.count(F.lit(1)).cast("int").alias("differ"))
        out = diff if out is None else out.unionByName(diff)
    return out


register("deletion_schedule_k8", "SELECT CAST(i AS INTEGER) AS i, CAST(i - p AS INTEGER) AS first_deleted, CAST(i - 1 AS INTEGER) AS last_deleted, CAST(i AS INTEGER) AS first_sketch, CAST(least(i + p - 1, 7) AS INTEGER) AS last_sketch FROM (SELECT i, i & -i AS p FROM (SELECT DISTINCT l_linenumber AS i FROM lineitem WHERE l_linenumber < 8))")(lambda s, d: _schedule_k8(s, d))


def _schedule_k8(s, d):
    """A line of an order is a forest of the certificate: what is deleted before the forest of each line's number, of eight."""
    steps = s.createDataFrame(K.deletion_schedule(8), "i int, first_deleted int, last_deleted int, first_sketch int, last_sketch int")
    return table(s, d, "lineitem").select(F.col("l_linenumber").alias("i")).distinct().join(F.broadcast(steps), "i")

KS = "SELECT DISTINCT CAST(1 << count(*) AS INTEGER) AS k FROM lineitem GROUP BY l_orderkey"


def k_of_orders(s, d):
    """(k): two to the number of an order's lines, for every number that occurs."""
    lines = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    return lines.select(F.pow(F.lit(2), "n").cast("int").alias("k")).distinct()


def _touches(s, d):
    n = {m: F.udf(lambda k, m=m: K.deletion_touches(k, m), "long")("k").alias(f"{m}_touches") for m in ("block", "naive")}
    return k_of_orders(s, d).select("k", n["block"], n["naive"])


register("deletion_cost", f"SELECT k, CAST(k * log2(k) / 2 AS BIGINT) AS block_touches, CAST(CAST(k AS BIGINT) * (k - 1) / 2 AS BIGINT) AS naive_touches FROM ({KS})")(_touches)


def sql_min_cut(e: str) -> str:
    """All cuts of a graph of at most 12 vertices."""
    return f"""WITH e AS ({e}), vs AS (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM e UNION SELECT v FROM e)), n AS (SELECT count(*) AS n FROM vs),
x AS (SELECT a.i AS a, b.i AS b, w FROM e JOIN vs a ON a.x = u JOIN vs b ON b.x = v)
SELECT min(c) AS value FROM (SELECT m, sum(CASE WHEN ((m >> a) & 1) <> ((m >> b) & 1) THEN 1 ELSE 0 END) AS c FROM range(1, 512) t(m), x WHERE m < (SELECT (1 << CAST(n - 1 AS INTEGER)) FROM n) GROUP BY m)"""


register("lambda_w12b", f"SELECT CAST(least(value, 10) AS BIGINT) AS lambda FROM ({sql_min_cut(WL.sql_edges('w12b'))})")(lambda s, d: _row(s, "lambda long", _lambda(s, d, "w12b", 10)))

register("lambda_w12", f"SELECT CAST(value AS BIGINT) AS lambda FROM ({sql_min_cut(WL.sql_edges('w12'))})")(lambda s, d: _row(s, "lambda long", _lambda(s, d, "w12", 9)))


def _lambda(s, d, w, k):
    return K.edge_connectivity_upto(S.inserts(cut(WL.edges(s, d, w))), k)[0]


register("lambda_at_least_k_w12", f"SELECT CAST(2 AS BIGINT) AS k, value > 2 AS above FROM ({sql_min_cut(WL.sql_edges('w12'))})")(lambda s, d: _row(s, "k long, above boolean", *K.edge_connectivity_upto(S.inserts(cut(WL.edges(s, d, "w12"))), 2)))
register("lambda_disconnected_w4r", "SELECT CAST(0 AS BIGINT) AS lambda")(lambda s, d: _row(s, "lambda long", _lambda(s, d, "w4r", 1)))
register("mincut_w12b", f"SELECT CAST(value AS DOUBLE) AS value FROM ({sql_min_cut(WL.sql_edges('w12b'))})")(lambda s, d: _row(s, "value double", K.approx_min_cut(S.inserts(cut(WL.edges(s, d, "w12b"))), 10)[0]))


@register("mincut_search_modes", "SELECT true AS same_level, true AS same_value")
def _modes(s, d):
    u = S.inserts(cut(WL.edges(s, d, "w12b")))
    a, b = (K.approx_min_cut(u, 3, search=m) for m in ("linear", "binary"))
    return _row(s, "same_level boolean, same_value boolean", a[2] == b[2], a[0] == b[0])


PARTIES = f"SELECT u, v, w FROM ({WL.sql_edges('w12b')}) WHERE (u % 5 = 0) <> (v % 5 = 0)"
register("cut_edges_w12b", PARTIES)(lambda s, d: K.cut_edges(WL.edges(s, d, "w12b"), table(s, d, "nation").filter("n_regionkey = 0").select(F.col("n_nationkey").cast("long").alias("x"))))
register("cut_value_w12b", f"SELECT sum(w) AS value FROM ({PARTIES})")(lambda s, d: K.cut_value(WL.edges(s, d, "w12b"), table(s, d, "nation").filter("n_regionkey = 0").select(F.col("n_nationkey").cast("long").alias("x"))))
register("cut_value_degree_cuts", f"SELECT x, sum(w) AS value FROM (SELECT u AS x, w FROM ({WL.sql_edges('w12')}) UNION ALL SELECT v, w FROM ({WL.sql_edges('w12')})) GROUP BY x")(lambda s, d: _degree_cuts(cut(WL.edges(s, d, "w12"))))


def _degree_cuts(e):
    """Each vertex alone on a side: one cut_value() for each vertex."""
    out = None
    for x in [r.x for r in e.select(F.explode(F.array("u", "v")).alias("x")).distinct().orderBy("x").limit(100).collect()]:  # nations of two regions
        one = K.cut_value(e, e.sparkSession.range(x, x + 1).withColumnRenamed("id", "x")).select(F.lit(x).cast("long").alias("x"), "value")
        out = one if out is None else out.unionByName(one)
    return out


# --- sparsifier ---
register("sparsifier_identity_w12b", f"SELECT u, v, 1.0::DOUBLE AS w FROM ({WL.sql_edges('w12b')})")(lambda s, d: K.cut_sparsifier(S.inserts(cut(WL.edges(s, d, "w12b"))), 10).select("u", "v", "w"))


def sql_st_cuts(e: str) -> str:
    """Every pair's least cut, over all cuts of a graph of ten vertices."""
    return f"WITH e AS ({e}), vs AS (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM e UNION SELECT v FROM e)), x AS (SELECT a.i AS a, b.i AS b FROM e JOIN vs a ON a.x = u JOIN vs b ON b.x = v), c AS (SELECT m, CAST(sum(CASE WHEN ((m >> a) & 1) <> ((m >> b) & 1) THEN 1 ELSE 0 END) AS DOUBLE) AS c FROM range(1, 1023) t(m), x GROUP BY m) SELECT p.x AS s, q.x AS t, min(c) AS flow FROM vs p JOIN vs q ON p.x < q.x, c WHERE ((m >> CAST(p.i AS BIGINT)) & 1) <> ((m >> CAST(q.i AS BIGINT)) & 1) GROUP BY 1, 2"


def _pairs(e):
    v = e.select(F.explode(F.array("u", "v")).alias("x")).distinct()
    return v.select(F.col("x").alias("s")).join(v.select(F.col("x").alias("t")), F.col("s") < F.col("t"))


def _st(s, d, w):
    """k beyond every connectivity: the sparsifier is the graph, and the cuts are exact."""
    e = cut(WL.edges(s, d, w))
    return K.st_min_cuts(S.inserts(e), _pairs(e), 0.5, k=12)


def sql_all_cuts(e: str) -> str:
    """(m, c): the edges across every cut m of a graph of at most twelve vertices, numbered by vertex."""
    return f"WITH e AS ({e}), vs AS (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM e UNION SELECT v FROM e)), x AS (SELECT a.i AS a, b.i AS b FROM e JOIN vs a ON a.x = u JOIN vs b ON b.x = v) SELECT m, CAST(count(*) FILTER (((m >> CAST(a AS BIGINT)) & 1) <> ((m >> CAST(b AS BIGINT)) & 1)) AS BIGINT) AS c FROM range(1, (SELECT 1 << CAST(count(*) - 1 AS INTEGER) FROM vs)) t(m), x GROUP BY m"


def all_cuts(e, weighted, name):
    """(m, name): the weight that a graph has across every cut of the vertices of e, at most twelve of them."""
    at = {r.x: i for i, r in enumerate(e.select(F.explode(F.array("u", "v")).alias("x")).distinct().orderBy("x").limit(13).collect())}
    if len(at) > 12:
        raise ValueError("more than twelve vertices")
    place = F.create_map(*[F.lit(z) for k, i in at.items() for z in (k, i)])
    bit = lambda c: F.call_function("shiftright", F.col("m"), place[F.col(c)]).bitwiseAND(F.lit(1))
    cuts = weighted.sparkSession.range(1, 2 ** (len(at) - 1)).withColumnRenamed("id", "m")
    across = weighted.select("u", "v", "w").crossJoin(cuts).filter(bit("u") != bit("v")).groupBy("m").agg(F.sum("w").alias(name))
    return cuts.join(across, "m", "left").select("m", F.coalesce(name, F.lit(0.0)).alias(name))


@register("kcert_all_cuts_w12", f"SELECT m, least(c, 3) AS capped FROM ({sql_all_cuts(WL.sql_edges('w12'))})")
def _cert_cuts(s, d):
    """The certificate's defining property: across every cut, its size up to k is the graph's."""
    e = cut(WL.edges(s, d, "w12"))
    h = cut(K.k_certificate(S.inserts(e), 3).withColumn("w", F.lit(1.0)))
    return all_cuts(e, h, "c").select("m", F.least("c", F.lit(3.0)).cast("long").alias("capped"))


@register("mincut_eps_w12n", f"SELECT min(n) AS degree_cut, true AS within, true AS sampled FROM (SELECT x, count(*) AS n FROM (SELECT u AS x FROM ({WL.sql_edges('w12n')}) UNION ALL SELECT v FROM ({WL.sql_edges('w12n')})) GROUP BY x)")
def _mincut_eps(s, d):
    """All nations trade with all others, so that the least degree is the minimum cut; eps asks for fewer forests than that, and the answer comes from a sampled level."""
    e = cut(WL.edges(s, d, "w12n"))
    value, _, j = K.approx_min_cut(S.inserts(e), eps=0.5)
    exact = e.select(F.explode(F.array("u", "v")).alias("x")).groupBy("x").count().agg(F.min("count")).first()[0]
    return _row(s, "degree_cut long, within boolean, sampled boolean", exact, abs(value - exact) <= 0.5 * exact, j > 0)


@register("sparsifier_all_cuts_w12", f"SELECT m, c, true AS within FROM ({sql_all_cuts(WL.sql_edges('w12'))})")
def _sparsifier_cuts(s, d):
    """Every cut of the sparsifier within 1 + eps of the graph's. The scale is the least that eps = 0.9 allows here; at sf0.01 the graph is complete, j > 0 and weights are above 1."""
    e = cut(WL.edges(s, d, "w12"))
    sp = K.cut_sparsifier(S.inserts(e), eps=0.9, scale=0.5)
    j = all_cuts(e, e.withColumn("w", F.lit(1.0)), "c").join(all_cuts(e, sp, "sparse"), "m")
    return j.select("m", F.col("c").cast("long").alias("c"), ((F.col("sparse") * (1 - 0.9) <= F.col("c")) & (F.col("c") <= F.col("sparse") * (1 + 0.9))).alias("within"))


@register("sparsifier_size_w12n", f"SELECT count(*) AS edges, true AS sparser, true AS weighted, true AS degrees_within FROM ({WL.sql_edges('w12n')})")
def _sparsifier_size(s, d):
    """A sparsifier that is sparser than its graph: its number of edges, weights and degree cuts."""
    e = cut(WL.edges(s, d, "w12n"))
    sp = K.cut_sparsifier(S.inserts(e), eps=0.9, scale=0.5)
    deg = lambda x, n: x.select(F.explode(F.array("u", "v")).alias("x"), "w").groupBy("x").agg(F.sum("w").alias(n))
    two = deg(e.withColumn("w", F.lit(1.0)), "c").join(deg(sp, "sparse"), "x", "left")
    n = e.count()
    good = two.agg(F.min(((1 - 0.9) * F.coalesce("sparse", F.lit(0.0)) <= F.col("c")) & (F.col("c") <= 1.9 * F.coalesce("sparse", F.lit(0.0))))).first()[0]
    return _row(s, "edges long, sparser boolean, weighted boolean, degrees_within boolean", n, sp.count() < n, sp.agg(F.max("w")).first()[0] > 1, good)


@register("st_cuts_eps_w12n", f"SELECT s.x AS s, t.x AS t, true AS within FROM (SELECT u AS x FROM ({WL.sql_edges('w12n')}) UNION SELECT v FROM ({WL.sql_edges('w12n')})) s, (SELECT u AS x FROM ({WL.sql_edges('w12n')}) UNION SELECT v FROM ({WL.sql_edges('w12n')})) t WHERE s.x < t.x")
def _st_eps(s, d):
    """s-t cuts on the sparsifier against those of the graph itself."""
    e = cut(WL.edges(s, d, "w12n"))
    got = K.st_min_cuts(S.inserts(e), _pairs(e), 1.5, scale=0.3)
    exact = K.cuts_on(e.withColumn("w", F.lit(1.0)), _pairs(e)).withColumnRenamed("flow", "exact")
    return got.join(exact, ["s", "t"]).select("s", "t", F.col("flow").between(F.col("exact") / 2.5, F.col("exact") * 2.5).alias("within"))


@register("success_rate_w4r", "SELECT CAST(6 AS BIGINT) AS seeds, true AS all_right, true AS rows_show_an_edge")
def _success(s, d):
    """Over seeds: whether components come out right, and the share of single rows that show an edge, which theory puts above a half."""
    u = S.inserts(cut(WL.edges(s, d, "w4r")))
    want, right, shown = cut(external.components(u)), 0, []
    for seed in range(6):
        got = CC.connected_components(u, seed=seed + 40)
        right += not got.exceptAll(want).limit(1).count() and not want.exceptAll(got).limit(1).count()
        spec = SketchSpec(rows=4, levels=16, seed=seed + 40)
        cells = C.sketch_updates(u, spec).withColumn("label", F.col("x"))
        some = C.recover(cells, spec, "label").count() / max(1, cells.select("label", "row").distinct().count())
        shown.append(some)
    return _row(s, "seeds long, all_right boolean, rows_show_an_edge boolean", 6, right == 6, min(shown) > 0.5)


# --- densest ---
DENSE12 = f"""WITH e AS ({WL.sql_edges('w12b')}), vs AS (SELECT x, row_number() OVER (ORDER BY x) - 1 AS i FROM (SELECT u AS x FROM e UNION SELECT v FROM e)), x AS (SELECT a.i AS a, b.i AS b FROM e JOIN vs a ON a.x = u JOIN vs b ON b.x = v)
SELECT round(max(c / bit_count(m)), 6) AS density FROM (SELECT m, sum(CASE WHEN ((m >> a) & 1) = 1 AND ((m >> b) & 1) = 1 THEN 1.0 ELSE 0.0 END) AS c FROM range(1, 1024) t(m), x GROUP BY m)"""
register("densest_w12b", DENSE12)(lambda s, d: _row(s, "density double", round(D.densest_subgraph(ins(s, d, "w12b"), 0.5)["density"], 6)))
DENSE_OK = "SELECT 'sampled' AS regime, true AS within, CAST(0 AS BIGINT) AS strays, CAST(0 AS BIGINT) AS twice, CAST(0 AS BIGINT) AS wrong_buckets"
register("densest_bound_w8", DENSE_OK)(lambda s, d: _dense(s, d, S.inserts(cut(WL.edges(s, d, "w8"))), 0.8))
register("densest_parallel_baseline", DENSE_OK)(lambda s, d: _dense(s, d, S.inserts(cut(WL.edges(s, d, "w8"))), 0.8, "parallel"))
register("densest_batch_peel_w8", DENSE_OK)(lambda s, d: _dense(s, d, S.inserts(cut(WL.edges(s, d, "w8"))), 0.8, "single", "batch"))
register("densest_deletions_w7", DENSE_OK)(lambda s, d: _dense(s, d, cut(WL.stream_w7(s, d)), 0.8))
register("densest_deletions_w14", DENSE_OK)(lambda s, d: _dense(s, d, cut(WL.stream_w14(s, d)), 0.95))


def _dense(s, d, u, eps, parts="single", peeling="sequential"):
    """The draw is of the graph, without replacement, and of the drawn number in each bucket; the density is within 1 + eps of what peeling finds in the whole graph (and so within 2 (1 + eps) of the densest)."""
    x = D.densest_subgraph(u, eps, partitions=parts, peeling=peeling)
    e = cut(S.edges_at(u).select("u", "v"))
    whole = D.peeled_in_order(e)[0]
    # one exchange of both, by the edge: bucket is null in the graph's own row
    both = x["drawn"].select("u", "v", F.col("bucket").cast("long").alias("bucket")).unionAll(e.select("u", "v", F.lit(None).cast("long").alias("bucket"))).repartition("u", "v")
    each = both.groupBy("u", "v", "bucket").agg(F.count(F.lit(1)).alias("n")).groupBy("u", "v").agg(F.expr("sum(if(bucket is null, 0, n))").alias("drawn"), F.expr("bool_or(bucket is null)").alias("known"), F.expr("count_if(bucket is not null and n > 1)").alias("twice"))
    strays, twice = each.agg(F.expr("coalesce(sum(if(known, 0, drawn)), 0)"), F.expr("coalesce(sum(twice), 0)")).first()
    got = x["drawn"].groupBy("bucket").agg(F.count(F.lit(1)).alias("got"))
    wrong = x["numbers"].join(got, "bucket", "full").filter("coalesce(got, 0) <> coalesce(x, 0)").count()
    return _row(s, "regime string, within boolean, strays long, twice long, wrong_buckets long", x["regime"], whole / (1 + eps) <= x["density"] <= whole * (1 + eps), strays, twice, wrong)


B8 = f"SELECT CAST({H.sql_poly(f'((u % {H.P}) * {H.coefficients(9, 16, 'bucket')[0][0]}) % {H.P} + ((v % {H.P}) * {H.coefficients(9, 16, 'bucket')[0][1]}) % {H.P}', [x[2] for x in H.coefficients(9, 16, 'bucket')])} % 600 AS INTEGER) AS bucket FROM ({WL.sql_edges('w8')})"
register("bucket_counts", f"SELECT bucket, count(*) AS n FROM ({B8}) GROUP BY bucket")(lambda s, d: D.bucket_stats(ins(s, d, "w8"), 600))
register("bucket_small_rate", f"SELECT count(*) AS buckets, count(*) FILTER (n <= 4 * t.e / 600.0) AS small FROM (SELECT bucket, count(*) AS n FROM ({B8}) GROUP BY bucket), (SELECT count(*) AS e FROM ({B8})) t")(lambda s, d: _small(s, d))


def _small(s, d):
    u = cut(WL.edges(s, d, "w8"))
    e = u.count()
    return D.bucket_stats(S.inserts(u), 600).agg(F.count(F.lit(1)).alias("buckets"), F.count(F.when(F.col("n") <= 4 * e / 600.0, 1)).alias("small"))


# --- matrix, exact baselines ---
register("spmv_w15", "SELECT l_orderkey AS row, round(sum(l_quantity * p_retailprice), 4) AS y FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1")(lambda s, d: FM.spmv(table(s, d, "lineitem").select(F.col("l_orderkey").alias("row"), F.col("l_partkey").alias("col"), F.col("l_quantity").alias("val")), table(s, d, "part").select(F.col("p_partkey").alias("col"), F.col("p_retailprice").alias("x")), 8).select("row", F.round("y", 4).alias("y")))
register("exact_cc_w2", WL.sql_components(WL.sql_edges("w2")))(lambda s, d: external.components(WL.edges(s, d, "w2")))
register("exact_bip_w8", sql_bipartite(WL.sql_edges("w8")))(lambda s, d: _exact_bip(cut(WL.edges(s, d, "w8"))).agg(F.min("bipartite").alias("bipartite")))
register("exact_bip_w9", SQL["bip_components_w9"])(lambda s, d: _exact_bip(w9(s, d).select(F.col("a").alias("u"), F.col("b").alias("v"))).groupBy("bipartite").agg(F.count(F.lit(1)).alias("n")))


def _exact_bip(e):
    return external.bipartite_components(external.components(external.double_cover(e)))


def sql_forest_weight(e: str) -> str:
    """Integer weights: n - c_W W + sum of c_i over thresholds is the exact weight; here two values, 49 and 50."""
    return f"WITH b AS MATERIALIZED ({e}), n AS (SELECT count(*) AS n FROM (SELECT u FROM b UNION SELECT v FROM b)), m AS (SELECT count(*) - count(DISTINCT label) AS joined FROM ({WL.sql_components('SELECT u, v FROM b WHERE w <= 49')})), f AS (SELECT count(*) - count(DISTINCT label) AS joined FROM ({WL.sql_components('SELECT u, v FROM b')})) SELECT CAST(49 * m.joined + 50 * (f.joined - m.joined) AS DOUBLE) AS weight, f.joined AS edges FROM m, f"


register("exact_mst_w5", sql_forest_weight(WL.sql_edges("w5")))(lambda s, d: external.minimum_forest(WL.edges(s, d, "w5")).agg(F.sum("w").alias("weight"), F.count(F.lit(1)).alias("edges")))


def sql_forest_weight_to(e: str, top: int) -> str:
    """Integer weights from 1 to top: each threshold's joins beyond the former's cost that threshold."""
    joined = " UNION ALL ".join(f"SELECT {t} AS t, (SELECT count(*) - count(DISTINCT label) FROM ({WL.sql_components(f'SELECT u, v FROM b WHERE w <= {t}')})) AS joined" for t in range(1, top + 1))
    return f"WITH b AS MATERIALIZED ({e}), j AS ({joined}) SELECT CAST(sum(t * (joined - before)) AS DOUBLE) AS weight, CAST(max(joined) AS BIGINT) AS edges FROM (SELECT t, joined, coalesce(lag(joined) OVER (ORDER BY t), 0) AS before FROM j)"


register("exact_mst_w1", sql_forest_weight_to(E1, 50))(lambda s, d: external.minimum_forest(WL.edges(s, d, "w1")).agg(F.sum("w").alias("weight"), F.count(F.lit(1)).alias("edges")))
register("exact_mincut_w12", sql_min_cut(WL.sql_edges("w12")))(lambda s, d: _exact_cut(s, d))


def _exact_cut(s, d):
    e = [(u, v, 1) for u, v in K.collected(WL.edges(s, d, "w12").select("u", "v"))]
    return _row(s, "value long", int(solvers.stoer_wagner(e, sorted({x for u, v, _ in e for x in (u, v)}))[0]))


register("exact_peel_w12b", DENSE12)(lambda s, d: _row(s, "density double", round(solvers.peel(K.collected(WL.edges(s, d, "w12b").select("u", "v")))[0], 6)))
register("adjacency_w7", f"SELECT count(*) AS edges, CAST(count(*) * 16 AS BIGINT) AS bytes FROM ({W7E})")(lambda s, d: external.adjacency_size(WL.stream_w7(s, d)))
register("contraction_trials_w12b")(lambda s, d: K.contraction_trials(WL.edges(s, d, "w12b"), 200).agg(F.min("value").alias("best")))


@register("measured_shuffle_w3", f"SELECT mode, CAST(2 * n * f AS BIGINT) AS shuffle_records FROM (SELECT count(*) AS n FROM ({WL.sql_edges('w3')})), (VALUES ('block', 1), ('per_update', {SPEC.rows})) m(mode, f)")
def _measured_w3(s, d):
    """Records that Spark's own figures say ingestion shuffled: both ends of each update, or each of their rows in the naive order."""
    u = cut(ins(s, d, "w3"))
    got = []
    for mode in ("block", "per_update"):
        run = lambda m=mode: C.sketch_updates(u, SPEC, mode=m, hubs=None).write.format("noop").mode("overwrite").save()
        got.append((mode, int(simulate.measured(s, run)["shuffle_records"])))
    return s.createDataFrame(got, "mode string, shuffle_records long")
