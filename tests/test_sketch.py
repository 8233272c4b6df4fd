"""The sketch substrate: linearity, locality, recovery, streams, solvers, schedules, formulas."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from blocksketch.cost import formulas, simulate
from blocksketch.exact import external, solvers
from blocksketch.operators import cells as C
from blocksketch.operators import hyper as HY
from blocksketch.operators import stream as S
from blocksketch.plans import connectivity as CC
from blocksketch.plans import families as FM
from blocksketch.plans import kconn as K
from blocksketch.spec import SketchExhausted, SketchSpec, size_spec

SPEC = SketchSpec(rows=4, levels=16, seed=2)


def updates(spark, edges, deltas=None):
    rows = [(i, min(u, v), max(u, v), d, 1.0) for i, ((u, v), d) in enumerate(zip(edges, deltas or [1] * len(edges)))]
    return spark.createDataFrame(rows, "seq long, u long, v long, delta int, w double")


def graph(n, m, seed):
    r = random.Random(seed)
    return sorted(r.sample(list(itertools.combinations(range(n), 2)), m))


def rows(df):
    return sorted(map(tuple, df.select("sk", "x", "row", "lvl", "xu", "xv", "chk").collect()))


def test_insert_and_delete_cancel_and_updates_are_local(spark):
    e = graph(20, 60, 1)
    both = updates(spark, e + [e[0]], [1] * len(e) + [-1])
    assert rows(C.sketch_updates(both, SPEC)) == rows(C.sketch_updates(updates(spark, e[1:]), SPEC))
    one = C.sketch_updates(updates(spark, e[:1]), SPEC)
    assert {r.x for r in one.collect()} == set(e[0])
    assert rows(C.merge_cells(C.sketch_updates(updates(spark, e[:30]), SPEC), C.sketch_updates(updates(spark, e[30:]), SPEC))) == rows(C.sketch_updates(updates(spark, e), SPEC))


def test_ingestion_has_one_exchange(spark):
    plan = C.sketch_updates(updates(spark, graph(10, 20, 3)), SPEC)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Python" not in plan


def test_recovered_edges_cross_the_cut(spark):
    e = graph(30, 120, 4)
    labels = spark.createDataFrame([(x, x % 3) for x in range(30)], "x long, label long")
    spec = SketchSpec(rows=12, levels=10, seed=6)
    found = C.recover_one(C.cut_cells(C.sketch_updates(updates(spark, e), spec), labels), spec, "label").collect()
    assert len(found) == 3
    assert all((r.u, r.v) in set(e) and (r.u % 3 == r.label) != (r.v % 3 == r.label) for r in found if r.u is not None)
    assert sum(r.u is not None for r in found) >= 2


@pytest.mark.parametrize("mode", ["local", "distributed"])
def test_components_of_an_odd_mix(spark, mode):
    e = [(0, 1), (1, 2), (0, 2), (10, 11), (20, 2**61)]
    labels, forest, _ = CC.extract(updates(spark, e), extraction=mode)
    got = {r.x: r.label for r in labels.collect()}
    assert got == {0: 0, 1: 0, 2: 0, 10: 10, 11: 10, 20: 20, 2**61: 20}
    assert forest.count() == 4


def test_empty_graph_and_too_few_rows(spark):
    assert CC.connected_components(updates(spark, [])).count() == 0
    with pytest.raises(SketchExhausted):
        CC.connected_components(updates(spark, graph(40, 300, 5)), SketchSpec(rows=2, levels=12))


def test_stream_checks(spark):
    bad = updates(spark, [(1, 2), (1, 2), (3, 4)], [1, 1, -1])
    assert {(r.u, r.multiplicity) for r in S.validate_stream(bad).collect()} == {(1, 2), (3, -1)}
    loops = spark.createDataFrame([(1, 1), (2, 1)], "a long, b long")
    assert [tuple(r) for r in S.canonical_edges(loops, "a", "b").select("u", "v").collect()] == [(1, 2)]
    with pytest.raises(Exception, match="null end"):
        S.canonical_edges(spark.createDataFrame([(None, 1)], "a long, b long"), "a", "b").collect()


def test_bipartite_and_lambda_of_joined_triangles(spark):
    e = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3), (1, 4)]
    assert not FM.is_bipartite(updates(spark, e)).first()[0]
    assert FM.is_bipartite(updates(spark, [(0, 1), (1, 2), (2, 3), (0, 3)])).first()[0]
    assert K.edge_connectivity_upto(updates(spark, e), 2) == (2, False)


def test_stoer_wagner_flow_peel_against_enumeration():
    for seed in range(6):
        e = graph(7, 14, seed)
        vs = list(range(7))
        best = min(sum((u in side) != (v in side) for u, v in e) for k in range(1, 7) for side in map(set, itertools.combinations(vs, k)))
        assert solvers.stoer_wagner([(u, v, 1) for u, v in e], vs)[0] == best
        near = solvers.adjacency([(u, v, 1.0) for u, v in e])
        if 0 in near and 6 in near:
            flow = min(sum((u in side) != (v in side) for u, v in e) for k in range(0, 6) for side in ({0, *x} for x in itertools.combinations(range(1, 6), k)))
            assert solvers.max_flow(near, 0, 6) == flow
        dense = max(sum(u in s and v in s for u, v in e) / len(s) for k in range(1, 8) for s in map(set, itertools.combinations(vs, k)))
        assert dense / 2 <= solvers.peel(e)[0] <= dense + 1e-9
        assert dense / 2.2 - 1e-9 <= solvers.peel_batch(e)[0] <= dense + 1e-9


@pytest.mark.parametrize("k", [1, 2, 3, 5, 8, 13, 16])
def test_every_sketch_loses_all_earlier_forests_once(k):
    gone = {i: [] for i in range(k)}
    for _, a, b, c, d in K.deletion_schedule(k):
        for i in range(c, d + 1):
            gone[i] += range(a, b + 1)
    assert all(sorted(gone[i]) == list(range(i)) for i in range(k))
    assert (K.deletion_touches(8, "block"), K.deletion_touches(8, "naive")) == (12, 28)


def test_minimum_forest_is_kruskal(spark):
    e = [(u, v, float((u * 7 + v * 3) % 5 + 1)) for u, v in graph(12, 30, 9)]
    got = external.minimum_forest(spark.createDataFrame(e, "u long, v long, w double")).agg(F.sum("w")).first()[0]
    assert got == solvers.kruskal(e)


def test_case_study_and_sizes():
    assert abs(formulas.casestudy_size(33e6) / 2**40 - 118.9) < 0.1
    assert abs(formulas.casestudy_size(33e6, log_exponent=4) / 2**40 - 176.8) < 0.2
    assert abs(formulas.adjacency_bytes(114_000) / 2**30 - 12.86) < 0.01
    assert formulas.deletion_cost(8) == 12
    assert size_spec(2100, 51731).rows == 32
    assert simulate.lru_ios([(1, 2), (1, 2), (3, 4)], 10, 10, 20) == 8


def test_hyperedges_beyond_r_are_refused_and_both_extractions_agree(spark):
    r = random.Random(8)
    sets = [sorted(r.sample(range(10 * b, 10 * b + 10), r.randint(2, 5))) for b in range(3) for _ in range(6)]
    h = HY.canonical_hyperedges(spark.createDataFrame([(m,) for m in sets], "m array<long>"), "m")
    with pytest.raises(ValueError):
        HY.hyper_components(h, 3)
    pairs = sorted({(m[0], x) for m in sets for x in m[1:]})
    want = {(x.x, x.label) for x in external.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    for how in ("local", "distributed"):
        labels, chosen = HY.hyper_components(h, extraction=how)
        assert {(x.x, x.label) for x in labels.collect()} == want
        assert {tuple(c.members) for c in chosen.collect()} <= {tuple(m) for m in sets}


def weighted(spark, edges):
    return spark.createDataFrame([(0, u, v, 1, float(w)) for u, v, w in edges], "seq long, u long, v long, delta int, w double")


def test_weights_beyond_top_and_no_integers_are_refused(spark):
    two = weighted(spark, [(0, 1, 100), (1, 2, 4)])
    assert 104 <= FM.mst_weight(two, 0.5).first()[0] <= 156
    for bad, top in ((two, 50), (weighted(spark, [(0, 1, 0)]), 50), (weighted(spark, [(0, 1, 2.5)]), 50)):
        with pytest.raises(ValueError, match="integers from 1"):
            FM.mst_weight(bad, 0.5, top)


def test_nested_thresholds_local_and_distributed(spark, monkeypatch):
    e = [(u, v, (u * 7 + v * 3) % 9 + 1) for u, v in graph(14, 30, 11)]
    want = []
    for t in FM.weight_levels(0.5, 9):
        up = {x: x for u, v, _ in e for x in (u, v)}
        for u, v, w in e:
            if w <= t + 1e-9 and up[u] != up[v]:
                a, b = up[u], up[v]
                up = {x: b if y == a else y for x, y in up.items()}
        want.append(len(set(up.values())))
    got = lambda: [r.n_components for r in FM.threshold_components(weighted(spark, e), 0.5).orderBy("i").collect()]
    assert got() == want
    monkeypatch.setattr(FM, "LOCAL", 1)
    assert got() == want


def test_connectivity_beyond_one_solver(spark, monkeypatch):
    monkeypatch.setattr(K, "LOCAL", 1)
    e = graph(6, 12, 3)
    assert K.edge_connectivity_upto(updates(spark, e + e, [1] * 12 + [-1] * 12), 1) == (0, False)
    with pytest.raises(K.TooLarge):
        K.edge_connectivity_upto(updates(spark, e), 1)
    with pytest.raises(K.TooLarge):
        K.approx_min_cut(updates(spark, e), 2)


def test_levels_that_do_not_reach_below_k_are_an_error(spark):
    nine = list(itertools.combinations(range(9), 2))
    with pytest.raises(K.LevelsExhausted):
        K.approx_min_cut(updates(spark, nine), 2, 1)
    value, side, j = K.approx_min_cut(updates(spark, nine), 9)
    assert (value, j) == (8.0, 0) and len(side) in (1, 8)


def test_rounds_read_their_rows_only(spark):
    e = graph(30, 120, 12)
    spec = SketchSpec(rows=20, levels=12, seed=8)
    stored = C.Stored(C.sketch_updates(updates(spark, e), spec))
    plan = stored.rows(0, 4, 6)._jdf.queryExecution().executedPlan().toString()
    assert "row#" in plan.split("PartitionFilters")[1][:300]
    files = {r[0] for r in stored.rows(0, 4, 6).select(F.input_file_name()).collect()}
    assert files and all("row=4" in f or "row=5" in f for f in files)
    buffers = C.Buffers(updates(spark, e), spec)
    keys = ("sk", "vg", "x", "row", "lvl")
    assert rows(C.fold(buffers.rows(0, 4, 6), *keys)) == rows(stored.rows(0, 4, 6))
    for store in ("buffers", "cells"):
        labels = CC.extract(updates(spark, e), spec, store=store)[0]
        assert {r.label for r in labels.collect()} == {min(x for p in e for x in p)}


def test_a_star_is_dealt_evenly(spark):
    leaves, n = 100_000, 4
    star = spark.range(1, leaves + 1).selectExpr("0L as u", "id as v")
    sparse = spark.range(1, 20_001).selectExpr("id * 7 + 200000 as u", "id * 7 + 200001 as v")
    u = star.union(sparse)
    spec = SketchSpec(rows=1, levels=20, seed=4)
    sizes = lambda d: sorted(r.n for r in d.select(F.spark_partition_id().alias("p")).groupBy("p").agg(F.count(F.lit(1)).alias("n")).collect())
    even, plain = sizes(C.deal(u, spec)), sizes(C.deal(u, spec, hubs=None))
    assert sum(even) == sum(plain) == 2 * (leaves + 20_000) and len(even) == n
    assert even[-1] < 3 * even[len(even) // 2] and even[-1] < 0.7 * plain[-1]
    total = lambda c: c.agg(F.count(F.lit(1)), F.sum(F.xxhash64("x", "row", "lvl", "xu", "xv", "chk").cast("decimal(38,0)"))).first()
    assert total(C.sketch_updates(u, spec)) == total(C.sketch_updates(u, spec, hubs=None))


@pytest.mark.parametrize("k, width", [(7, 2), (10, 3), (16, 4), (5, 9)])
@pytest.mark.parametrize("schedule", ["naive", "lazy", "block", "super"])
def test_every_schedule_deletes_all_former_forests_once(schedule, k, width):
    gone = {i: [] for i in range(k)}
    for i, steps in enumerate(K.deletions(k, schedule, width)):
        for which, sketches in steps:
            assert max(which) < i
            for j in sketches:
                gone[j] += which
        assert sorted(gone[i]) == list(range(i))


def test_schedule_falls_back():
    assert K.chosen_schedule(10, 1000) == "lazy"
    assert K.chosen_schedule(200, 1000) == "super"
    assert K.chosen_schedule(200, 1000, memory_words=1000) == "naive"


def test_sparsifier_is_sparse_and_whole_beyond_all_connectivity(spark):
    e = list(itertools.combinations(range(12), 2))
    sp = {(r.u, r.v): r.w for r in K.cut_sparsifier(updates(spark, e), 5).collect()}
    assert len(sp) < len(e) and max(sp.values()) > 1 and set(sp) <= set(e)
    assert {(r.u, r.v): r.w for r in K.cut_sparsifier(updates(spark, e), 12).collect()} == {p: 1.0 for p in e}


def test_bucket_draws_are_edges_without_replacement(spark):
    from blocksketch.plans import densest as D

    e = graph(24, 200, 13)
    gone = e[:60]
    u = updates(spark, e + gone, [1] * len(e) + [-1] * len(gone))
    for parts in ("single", "parallel"):
        x = D.densest_subgraph(u, 0.9, partitions=parts)
        drawn = [tuple(r) for r in x["drawn"].collect()]
        assert len(set(drawn)) == len(drawn) and {(a, b) for _, a, b in drawn} <= set(e[60:])
        asked = {r.bucket: r.x for r in x["numbers"].collect() if r.x}
        assert {b: sum(d[0] == b for d in drawn) for b in asked} == asked
    with pytest.raises(Exception, match="sketches"):
        D.bucket_sketches(spark.createDataFrame([(0, 1, 2)], "bucket long, u long, v long"), spark.createDataFrame([(0, 9, 9)], "bucket long, n long, x long"), SketchSpec(sketches=4)).collect()
    dense = list(itertools.combinations(range(8), 2)) + [(i, i + 1) for i in range(8, 30)]
    density, vertices = D.peeled(spark.createDataFrame(dense, "u long, v long"), local=10)
    assert density == 3.5 and vertices == list(range(8))


def test_hyperedge_deletions(spark):
    sets = [([1, 2, 3], 1), ([3, 4], 1), ([5, 6], 1), ([3, 4], 1), ([5, 6], -1), ([3, 4], -1), ([7, 8, 9, 1], 1), ([7, 8, 9, 1], -1)]
    h = HY.canonical_hyperedges(spark.createDataFrame(sets, "m array<long>, delta int"), "m")
    for how in ("local", "distributed"):
        labels = {r.x: r.label for r in HY.hyper_components(h, extraction=how)[0].collect()}
        assert labels == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 6: 6, 7: 7, 8: 8, 9: 9}


def test_contraction_beyond_the_limit(spark, monkeypatch):
    from blocksketch.plans import kconn

    monkeypatch.setattr(kconn, "collected", lambda edges, limit=3: (_ for _ in ()).throw(ValueError("more edges than the limit")))
    clique = lambda a: [(a + i, a + j) for i in range(5) for j in range(i)]
    edges = spark.createDataFrame(clique(0) + clique(10) + [(0, 10), (1, 11)], "u long, v long")
    values = [x.value for x in kconn.contraction_trials(edges, 8).collect()]
    assert len(values) == 8 and min(values) == 2.0 and len(set(values)) > 1


def test_contraction_stops_when_roots_rest(spark, monkeypatch):
    from blocksketch.plans import forest

    pairs = [(0, i, i ^ 1, min(i, i ^ 1), max(i, i ^ 1)) for i in range(4096)]
    done, cut = [], forest.cut
    monkeypatch.setattr(forest, "cut", lambda df: done.append(1) or cut(df))
    labels, chosen = forest.contract_functional(spark.createDataFrame(pairs, "g int, label long, to long, u long, v long"))
    assert len(done) <= 4 and all(r.root == r.label & ~1 for r in labels.collect()) and chosen.count() == 2048
    ring = [(0, i, (i * 5 + 1) % 64, min(i, (i * 5 + 1) % 64), max(i, (i * 5 + 1) % 64)) for i in range(64)]  # one cycle through all
    tail = [(0, 100 + i, 99 + i if i else 7, 99 + i if i else 7, 100 + i) for i in range(20)]
    labels, chosen = forest.contract_functional(spark.createDataFrame(ring + tail, "g int, label long, to long, u long, v long"))
    assert {r.root for r in labels.collect()} == {0} and chosen.count() == 83


@pytest.mark.parametrize("local", [0, 40, 10**6])
def test_buffers_contract_with_the_graph(spark, local):
    """Vertices beyond local: updates whose ends have met leave, and few labels are united on the driver."""
    from blocksketch.plans import forest

    e = graph(60, 80, 5) + [(u + 100, v + 100) for u, v in graph(60, 200, 6)]
    u = updates(spark, e + e[:30], [1] * len(e) + [-1] * 30)
    vs = CC.touched(u).select(F.lit(0).alias("g"), "x")
    spec = size_spec(120, len(e) + 30, seed=3)
    buffers = C.Buffers(u, spec)
    labels, chosen, _ = forest.boruvka(buffers, spec, vs, mode="distributed" if not local else "auto", local=min(local, 100))
    want = {r.x: r.label for r in external.components(S.edges_at(u)).collect()}
    assert {r.x: r.label for r in labels.collect()} == {x: want.get(x, x) for p in e for x in p}
    left = {(r.u, r.v) for r in chosen.collect()}
    assert left <= set(e[30:]) and len(left) == len(want) - len(set(want.values())) and "dealt" not in buffers.__dict__


def test_lambda_w12b_counts_up_to_the_cap_of_its_sql(spark, monkeypatch):
    """Ten vertices, all joined: beyond seven, and below the SQL's ten."""
    from blocksketch.queries import graph as GQ

    k10 = updates(spark, list(itertools.combinations(range(10), 2))).select("u", "v", "w")
    monkeypatch.setattr(GQ.WL, "edges", lambda *a: k10)
    assert GQ.Q["lambda_w12b"](spark, "").collect() == [(9,)]


def test_peeling_arrays_agrees_with_peeling_sets_beyond_one_list(spark):
    for seed in range(5):
        e = graph(40, 150 + 40 * seed, seed)
        u, v = np.array(e).T
        assert solvers.peel_arrays(u, v) == solvers.peel(e)
    many = spark.range(0, 250_000).selectExpr("id as u", "id + 1 as v")  # more than a list takes
    with pytest.raises(K.TooLarge):
        K.collected(many)
    u, v = K.collected_arrays(many)
    assert len(u) == 250_000 and solvers.peel_arrays(u, v)[0] == 250_000 / 250_001


def test_cosine_pairs_by_blocks():
    """All pairs once; a pair on the bound is summed term by term, and a vector of length zero has no pair."""
    r = np.random.default_rng(4)
    x = np.round(r.normal(size=(60, 5)), 1)
    x[7] = 0
    ids = r.permutation(60)
    dot = lambda p, q: sum(a * b for a, b in zip(p, q))
    cos = {(min(ids[i], ids[j]), max(ids[i], ids[j])): dot(x[i], x[j]) / (dot(x[i], x[i]) ** 0.5 * dot(x[j], x[j]) ** 0.5) for i in range(60) for j in range(i) if 7 not in (i, j)}
    bound = round(cos[min(cos)], 6)
    want = sorted(k for k, c in cos.items() if round(c, 6) >= bound)
    parts = [solvers.cosine_pairs(ids[a], ids[b], x[a], x[b], bound, a == b) for a, b in ((slice(0, 30), slice(0, 30)), (slice(0, 30), slice(30, 60)), (slice(30, 60), slice(30, 60)))]
    assert sorted(t for p in parts for t in zip(*p.to_pydict().values())) == want


def test_exact_components_settle_on_a_long_path(spark):
    """A thousand vertices in any order on a path, and a second path: few rounds."""
    order = random.Random(6).sample(range(1000), 1000)
    e = [(a, b) for a, b in zip(order, order[1:])] + [(a + 2000, b + 2000) for a, b in zip(range(300), range(1, 301))]
    got = external.components(updates(spark, e), limit=12).collect()
    assert len(got) == 1301 and all(r.label == (0 if r.x < 1000 else 2000) for r in got)


def test_hyperedge_cells_in_arrays_are_those_of_spark(spark):
    r, spec = 5, SketchSpec(rows=6, levels=12, seed=4)
    sets = [(sorted({(7 * i + 11 * j * j + i * j) % 60 for j in range(2 + i % 4)}), 1 if i % 5 else -1) for i in range(90)]
    h = HY.canonical_hyperedges(spark.createDataFrame(sets, "m array<long>, delta int"), "m")
    updates = HY._updates(HY.with_fingerprint(h, spec, r))
    labels = updates.select("x").distinct().withColumn("label", F.col("x") % 9)
    want = HY.fold_hyper(HY.expand_hyper(updates.join(labels, "x"), spec, r, 2, 4, "label"), r, "label", "row", "lvl")
    got = HY._by_label(updates, labels, spec, r, 1)
    assert sorted(map(tuple, got.select(want.columns).collect())) == sorted(map(tuple, want.collect()))
    plain = h.withColumn("fp", HY.fingerprint(spec, HY.digits(F.col("members"), r)))
    assert sorted(map(str, HY.with_fingerprint(h, spec, r).collect())) == sorted(map(str, plain.collect()))
    batch = updates.select(F.col("x").alias("label"), "coef", "members", "fp").orderBy("label").toArrow().combine_chunks().to_batches()[0]
    shown = []
    for chunk in (7, 10_000):  # a vertex's updates may come in several chunks
        s = HY.Sums(spec, r)
        s.chunk = chunk
        shown.append(sorted((x["label"], x["members"]) for b in s.found(0, 2)(iter([batch])) for x in b.to_pylist()))
    assert shown[0] == shown[1]
    real = {tuple(m) for m, _ in sets}
    assert all(m is None or tuple(m) in real and x in m for x, m in shown[0]) and sum(m is not None for _, m in shown[0]) > 20


def test_hyperedges_inside_a_label_are_read_no_more(spark):
    h = spark.createDataFrame([([1, 2, 3], 0), ([1, 2], 1), ([3, 4], 2)], "members array<long>, e long")
    labels = spark.createDataFrame([(1, 1), (2, 1), (3, 1), (4, 4)], "x long, label long")
    assert [row.members for row in HY.crossing(h, labels).collect()] == [[3, 4]]


def test_bucket_draws_in_arrays_are_those_of_the_cells(spark):
    """Cells made in arrays are bucket_sketches(), in pieces as well; a bucket with deletions, and a sketch that shows nothing is passed over."""
    from blocksketch.plans import densest as D

    spec = SketchSpec(rows=3, levels=9, sketches=6, seed=5)
    e = graph(30, 40, 3)
    u, v = np.array(e + e[:10]).T  # ten edges are deleted
    want = D.bucket_sketches(updates(spark, list(zip(u.tolist(), v.tolist()))).withColumn("bucket", F.lit(0)), spark.createDataFrame([(0, 30, 6)], "bucket long, n long, x long"), spec).collect()
    draw = D.Draw(spec)
    for chunk, wide in ((2**19, 100), (16, 4)):
        draw.chunk, draw.wide = chunk, wide
        sums = np.zeros((18, 9, 3), dtype=np.int64)
        draw.add(sums, u[:7], v[:7])
        draw.add(sums, u[7:], v[7:])
        cells = {(i // 3, i % 3, j): tuple(sums[i, j].tolist()) for i in range(18) for j in range(9) if sums[i, j].any()}
        assert cells == {(c.sk, c.row, c.lvl): (c.xu, c.xv, c.chk) for c in want}
    sums[:3] = 0  # a sketch without a single edge
    got = draw.edges(sums, 4)
    assert len(set(got)) == 4 and set(got) <= set(e[10:])
    with pytest.raises(SketchExhausted):
        draw.edges(np.zeros((18, 9, 3), dtype=np.int64), 1)


def test_a_bucket_is_drawn_in_one_task(spark):
    """Spark's adaptive join splits partitions; a bucket's updates must meet all the same."""
    from blocksketch.plans import densest as D
    from blocksketch.session import cut

    n = 64
    bucketed = cut(spark.range(0, 60_000).selectExpr(f"id % {n} as bucket", "id as u", "id + 100000 as v", "1 as delta"))
    numbers = cut(D.counters(bucketed).selectExpr("bucket", "n", "5L as x"))
    got = D.bucket_sample(bucketed, numbers, SketchSpec(rows=8, levels=18, sketches=5, seed=3)).collect()
    assert len(set(got)) == len(got) == 5 * n and all(r.u % n == r.bucket and r.v == r.u + 100_000 for r in got)


def test_batch_peeling_lists_any_number_of_vertices(spark):
    """The densest stage may have more vertices than the solver's limit of edges."""
    from blocksketch.plans import densest as D

    for seed in range(4):
        e = graph(30, 60 + 80 * seed, seed)
        assert solvers.peel_batch_arrays(*np.array(e).T) == solvers.peel_batch(e)
    ring = [(i, (i + d) % 60) for i in range(60) for d in (1, 2)]  # every vertex has degree 4, and all leave at once
    density, vertices = D.peeled(spark.createDataFrame(ring, "u long, v long"), local=20)
    assert density == 2.0 and type(density) is float and vertices == list(range(60))


def test_arrays_take_more_edges_than_two_million(spark):
    u, v = K.collected_arrays(spark.range(0, 2_100_000).selectExpr("id as u", "id + 1 as v"))
    assert len(u) == len(v) == 2_100_000


def test_thresholds_end_on_the_driver_once_few_components_are_left(spark, monkeypatch):
    e = [(u, v, (u * 5 + v * 11) % 12 + 1) for u, v in graph(40, 70, 21)]
    got = lambda: [r.n_components for r in FM.threshold_components(weighted(spark, e), 0.5).orderBy("i").collect()]
    want, made = got(), []
    monkeypatch.setattr(FM, "LOCAL", 30)
    few = FM.Few
    monkeypatch.setattr(FM, "Few", lambda *a: made.append(few(*a)) or made[-1])
    assert got() == want and want[0] > 30 > want[-1]
    assert len(made) == 1


def test_deleted_hyperedges_leave_the_buffers(spark, monkeypatch):
    h = spark.createDataFrame([([1, 2], 1), ([1, 2], 1), ([3, 4, 5], 1), ([3, 4, 5], -1), ([2, 6], 1), ([2, 6], -1), ([2, 6], 1)], "members array<long>, delta int")
    assert sorted((r.members, r.delta) for r in HY.net(h).collect()) == [([1, 2], 1), ([2, 6], 1)]
    seen, first = [], HY._first_round
    monkeypatch.setattr(HY, "_first_round", lambda hyper, *a: seen.append(hyper.count()) or first(hyper, *a))
    labels = {r.x: r.label for r in HY.hyper_components(h, extraction="distributed")[0].collect()}
    assert set(labels) == {1, 2, 3, 4, 5, 6} and labels[1] == labels[2] == labels[6] and len(set(labels.values())) == 4
    assert seen == [2]


def test_a_graph_whose_edges_are_all_deleted_has_an_empty_draw(spark):
    from blocksketch.queries import graph as GQ

    u = spark.createDataFrame([(0, 1, 2, 1, 1.0), (1, 1, 2, -1, 1.0), (2, 3, 4, 1, 1.0), (3, 3, 4, -1, 1.0)], "seq long, u long, v long, delta int, w double")
    row = GQ._dense(spark, None, u, 0.8).first()
    assert (row.regime, row.within, row.strays, row.twice, row.wrong_buckets) == ("exact", True, 0, 0, 0)


def test_exact_components_contract_beyond_the_driver(spark):
    """Edges reduced to stars in each partition, and contracted in Spark, give the least vertex of each component; loops and vertices beyond 2**53 stay."""
    e = graph(300, 330, 8) + [(2**61, 2**61 + 4), (900, 900)]
    want = {}
    for u, v in e:
        a, b = want.get(u, {u}), want.get(v, {v})
        want.update(dict.fromkeys(a | b, a | b))
    want = {x: min(s) for x, s in want.items()}
    df = spark.createDataFrame(e, "u long, v long").repartition(6)
    for local in (0, 40, 10**6):
        assert {r.x: r.label for r in external.components(df, local=local).collect()} == want
    star = solvers.Stars(8)
    batches = spark.createDataFrame(e, "u long, v long").toArrow().to_batches(max_chunksize=3)
    small = [p for b in star(iter(batches)) for p in zip(*b.to_pydict().values())]
    assert {r.x: r.label for r in external.components(spark.createDataFrame(small, "u long, v long")).collect()} == want


def test_bipartiteness_sketches_only_what_joins_lifted_trees(spark, monkeypatch):
    """Of an even ring, an odd one, a chord that is deleted again and a vertex left alone, only the odd ring's last edge is asked for."""
    ring = lambda a, n: [(a + i, a + (i + 1) % n) for i in range(n)]
    e = ring(0, 6) + ring(20, 5) + ring(2**55, 4) + [(0, 2), (0, 2), (40, 41), (40, 41)]
    e = [(min(p), max(p)) for p in e]
    seen, joined = [], FM._joined
    monkeypatch.setattr(FM, "_joined", lambda apart, *a: seen.append(sorted({(r.u // 2, r.v // 2) for r in apart.collect()})) or joined(apart, *a))
    got = {r.label: r.bipartite for r in FM.bipartiteness(updates(spark, e)).collect()}
    assert got == {0: True, 20: False, 40: True, 41: True, 2**55: True}
    assert len(e) > 18 and all(set(pair) <= set(range(3)) | set(range(20, 25)) | {40, 41} for pair in seen[0]) and len(seen[0]) <= 4


def test_vectors_are_compared_in_as_many_tasks_as_there_are(spark):
    from blocksketch.queries import graph as GQ

    df = GQ.w9(spark, "/root/testdata/sf0.01")
    assert df.rdd.getNumPartitions() == 4
    tasks = df.withColumn("p", F.spark_partition_id()).select("p").distinct().count()
    assert tasks > 1
    pairs = df.select("a", "b").collect()
    assert len(set(pairs)) == len(pairs) and all(r.a < r.b for r in pairs)


def test_hyperedges_are_made_once(spark):
    """The hyperedges' plan is run a single time, whatever is asked of them."""
    made = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    h = spark.createDataFrame([([1, 2, 3],), ([3, 4],), ([7, 8],)], "members array<long>").mapInArrow(count, "members array<long>")
    labels = HY.hyper_components(h, extraction="distributed")[0]
    assert {r.x: r.label for r in labels.collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 7: 7, 8: 7}
    assert made.value == 3


def test_buckets_drawn_together_are_drawn_as_alone(spark):
    """Rows made when they are asked show the edges that the cells of all rows show; deletions, a bucket beyond the room, and one of too few edges."""
    import pyarrow as pa

    from blocksketch.plans import densest as D

    rng = np.random.default_rng(8)
    rows = []
    for bucket, n in enumerate([1, 9, 20, 300, 3, 14]):
        e = np.unique(np.sort(rng.integers(0, 2**40, (n, 2)), axis=1), axis=0)
        rows += [(bucket, min(n, 12), a, b) for a, b in [*e.tolist(), *[x for x in e[12:].tolist() for _ in "ab"]]]
    at, asked, u, v = np.array(rows).T
    draw = D.Draw(SketchSpec(rows=4, levels=9, sketches=14, seed=5))
    want = []
    for b in range(6):
        own = at == b
        x = int(asked[own][0])
        sums = np.zeros(((x + D.SPARE) * 4, 9, 3), dtype=np.int64)
        draw.add(sums, u[own], v[own])
        want += [(b, *e) for e in draw.edges(sums, x)]
    # the number of a bucket in a row of its own, behind its updates; one bucket more that nothing is asked of
    last = [[(b, 0, p, q) for (b, _, p, q) in rows if b == c] + [(c, x, 0, 0)] for c, x in sorted({(b, x) for b, x, *_ in rows})]
    told = np.array([r for c in last for r in c] + [(6, 0, 4, 5)]).T
    for room, step in ((2**18, 500), (50, 500), (50, 7)):
        draw.room = room
        for cols in ((at, asked, u, v), told):
            pieces = [pa.RecordBatch.from_arrays([pa.array(c[i : i + step]) for c in cols], ["bucket", "asked", "u", "v"]) for i in range(0, len(cols[0]), step)]
            got = [tuple(r.values()) for batch in draw.drawn(iter(pieces)) for r in batch.to_pylist()]
            assert sorted(got) == sorted(want)
    few = np.zeros(1, dtype=np.int64)
    with pytest.raises(SketchExhausted):
        draw.drawn_together(few, few + 2, few + 1, few + 2)


def test_buckets_in_arrays_are_those_of_the_columns(spark):
    from blocksketch.plans import densest as D

    u = spark.range(0, 500).selectExpr("id * 9007199254741 as u", "id * 9007199254741 + 77 as v", "1 as delta")
    got = D.in_buckets(u, 37, 9, 21).withColumn("own", D.bucket_of(F.col("u"), F.col("v"), 37, 9, 21))
    assert got.filter("bucket = own").count() == 500 and got.select("bucket").distinct().count() > 30


def test_peeling_in_order_goes_beyond_one_solver(spark):
    """Low vertices leave in Spark, and the stage is that of peel(); a graph that is even and too large is an error."""
    from blocksketch.plans import densest as D

    for seed in range(3):
        e = sorted(set(graph(30, 240, seed)) | {(i % 30, 30 + i) for i in range(150)})
        edges = spark.createDataFrame(e, "u long, v long").localCheckpoint()
        assert D.peeled_in_order(edges, 300) == solvers.peel(e) == D.peeled_in_order(edges)
    ring = spark.range(0, 40).selectExpr("id as u", "id + 1 as v").union(spark.sql("select 0L as u, 40L as v"))
    with pytest.raises(K.TooLarge):
        D.peeled_in_order(ring, 40)


def test_peeling_arrays_takes_far_numbers_and_loops_over_degrees():
    """Ends far apart; and degrees that grow, so that the heap's bound moves often."""
    for far in (1, 2**50):
        e = sorted({(a * far, b * far) for a in range(1, 70) for b in range(a + 1, a + 1 + a // 2 + (a % 7))})
        assert solvers.peel_arrays(*np.array(e).T) == solvers.peel(e)


def test_one_solver_takes_the_edges_of_sixty_copies():
    """densest_deletions_w14 has 23,637,900 edges over 60 copies of the tables at sf0.1."""
    assert K.ARRAYS >= 23_637_900


def test_strays_and_repeats_of_a_draw_are_counted(spark, monkeypatch):
    """A stray edge counts as often as it is drawn, an edge drawn twice from one bucket once; a draw of nothing has neither."""
    from blocksketch.plans import densest as D
    from blocksketch.queries import graph as G

    u = updates(spark, [(1, 2), (1, 3), (2, 3), (3, 4), (3, 4)], [1, 1, 1, 1, -1])
    x = D.densest_subgraph(u, 0.9)
    rows = [(5, 1, 2), (5, 1, 2), (6, 1, 2), (6, 1, 3), (7, 3, 4), (8, 3, 4), (8, 8, 9)]
    x["drawn"] = spark.createDataFrame(rows, "bucket long, u long, v long")
    monkeypatch.setattr(D, "densest_subgraph", lambda *a, **k: x)
    assert tuple(G._dense(spark, None, u, 0.9).first())[2:4] == (3, 1)
    monkeypatch.undo()
    none = updates(spark, [(1, 2), (1, 2)], [1, -1])
    assert tuple(G._dense(spark, None, none, 0.9).first()) == ("exact", True, 0, 0, 0)
