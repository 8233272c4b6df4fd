"""Many edge-disjoint forests, and what is read off them: edge connectivity, minimum cuts, sparsifiers, s-t cuts."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exact.solvers import adjacency, max_flow, stoer_wagner
from ..functions.hashing import uniform
from ..operators.cells import Buffers, deal, expand_rows
from ..session import cut, fresh
from ..spec import SketchSpec, size_spec
from .connectivity import touched
from .forest import LOCAL, Local, boruvka, contract_functional


def deletion_schedule(k: int) -> list[tuple[int, int, int, int, int]]:
    """(i, first deleted, last deleted, first sketch, last sketch) for i from 1 to k - 1: with 2**p the largest power of two in i, the last 2**p forests leave the next 2**p sketches."""
    out = []
    for i in range(1, k):
        p = i & -i
        out.append((i, i - p, i - 1, i, min(i + p - 1, k - 1)))
    return out


def deletion_touches(k: int, schedule: str) -> int:
    """Forest-from-sketch-group deletions: a pass over a sketch for each row of the schedule."""
    return sum(b - a + 1 for *_, a, b in deletion_schedule(k)) if schedule == "block" else k * (k - 1) // 2


class TooLarge(ValueError):
    """A certificate or vertex set beyond what one solver holds."""


class LevelsExhausted(ValueError):
    """No sampled graph has a cut below k: more levels or a larger k are needed."""


def super_width(vertices: int) -> int:
    """The forests of a super-forest: log2(V)**2."""
    return max(1, math.ceil(math.log2(max(2, vertices)) ** 2))


def chosen_schedule(k: int, vertices: int, memory_words: float = 2.0**27, width: int | None = None) -> str:
    """What "auto" means: "lazy" while k is no more than a super-forest's width; "naive" where k log2(V)**2 words exceed the memory, as the block schedule needs a vertex sketch in memory; "super" in between."""
    width = width or super_width(vertices)
    if k <= width:
        return "lazy"
    return "super" if k * super_width(vertices) < memory_words else "naive"


def deletions(k: int, schedule: str, width: int = 1) -> list[list[tuple[range, range]]]:
    """For each i from 0 to k - 1, what is done before sketch i is opened: (forests to delete, sketches to delete them from).

    "naive": the last forest from all later sketches. "lazy": all former forests from sketch i. "block": by
    deletion_schedule(). "super": deletion_schedule() over super-forests of width forests, and within a super-forest its
    own former forests when a sketch is opened.
    """
    out: list[list[tuple[range, range]]] = [[] for _ in range(k)]
    if schedule == "naive":
        for i in range(1, k):
            out[i].append((range(i - 1, i), range(i, k)))
    elif schedule == "lazy":
        for i in range(1, k):
            out[i].append((range(i), range(i, i + 1)))
    elif schedule in ("block", "super"):
        width = 1 if schedule == "block" else width
        for i, a, b, c, d in deletion_schedule(-(-k // width)):
            out[i * width].append((range(a * width, (b + 1) * width), range(c * width, min(k, (d + 1) * width))))
        for i in range(k):
            if i % width:
                out[i].append((range(i - i % width, i), range(i, i + 1)))
    else:
        raise ValueError(schedule)
    return out


class Without:
    """Sketches less deleted edges: over XOR the same as with them. Deleted edges are dealt once for each deletion, and serve all sketches that it covers."""

    def __init__(self, base, spec: SketchSpec):
        self.base, self.spec, self.gone = base, spec, {}

    def delete(self, edges: DataFrame, sketches: range) -> None:
        dealt = cut(deal(edges.select("u", "v", "g"), self.spec, ("g",), None))
        for i in sketches:
            self.gone.setdefault(i, []).append(dealt)

    def rows(self, sketch: int, a: int, b: int) -> DataFrame:
        out = self.base.rows(sketch, a, b)
        for dealt in self.gone.get(sketch, ()):
            out = out.unionByName(expand_rows(dealt, self.spec, (sketch, sketch + 1), (a, b), ("g",)), allowMissingColumns=True)
        return out


def certificates(updates: DataFrame, k: int, levels: int = 1, spec: SketchSpec | None = None, schedule: str = "auto", vertices: DataFrame | None = None, width: int | None = None) -> DataFrame:
    """(g, u, v, forest): k edge-disjoint forests of each sampled graph g, each maximal in what the former leave.

    updates: u, v, delta, and depth if there are levels; an edge is in graph g if its depth is g or more. All graphs
    grow from one stored copy of the updates, and are extracted together: k extractions, whatever the number of levels.
    Sketch i gives forest i after the former forests are deleted from it (deletions()); all schedules give the same.
    """
    spark = updates.sparkSession
    vertices = cut(touched(updates) if vertices is None else vertices)
    n = vertices.count()
    spec = spec or size_spec(n, updates.count(), sketches=k)
    width = width or super_width(n)
    spread = F.sequence(F.lit(0), F.col("depth")) if levels > 1 else None
    sketch = Without(Buffers(updates, spec, ("depth",) if levels > 1 else (), spread), spec)
    vs = vertices.select(F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("g"), "x")
    at = vs.toPandas() if n * levels <= LOCAL else None
    forests: list[DataFrame] = []
    steps = deletions(k, chosen_schedule(k, n, width=width) if schedule == "auto" else schedule, width)
    for i in range(k):
        for which, sketches in steps[i]:
            gone = None
            for j in which:
                gone = forests[j] if gone is None else gone.unionByName(forests[j])
            sketch.delete(gone, sketches)
        if at is not None:
            state = Local(at)
            state.extract(spark, sketch, spec, i)
            forest = state.forest(spark)
        else:
            forest = boruvka(sketch, spec, vs, sketch=i, mode="distributed")[1]
        forests.append(cut(forest.select("g", "u", "v", F.lit(i).alias("forest"))))
    out = forests[0]
    for f in forests[1:]:
        out = out.unionByName(f)
    return out


def k_certificate(updates: DataFrame, k: int, spec: SketchSpec | None = None, schedule: str = "auto", vertices: DataFrame | None = None, width: int | None = None) -> DataFrame:
    """(u, v, forest): k edge-disjoint forests of the graph, each maximal in what the former leave: every cut has the lesser of k and its own size in their union."""
    return certificates(updates.select("u", "v"), k, 1, spec, schedule, vertices, width).drop("g")


def collected(edges: DataFrame, limit: int | None = None) -> list[tuple]:
    """Edges of a certificate, whose number is bounded by k (V - 1); beyond the limit it is an error, not a silent sample."""
    limit = LOCAL if limit is None else limit
    rows = edges.limit(limit + 1).collect()
    if len(rows) > limit:
        raise TooLarge(f"more than {limit} edges; contraction_trials() bounds the minimum cut of such a DataFrame from above")
    return [tuple(r) for r in rows]


ARRAYS = 50_000_000  # edges that one solver takes as arrays, of up to 80 bytes an edge


def collected_arrays(edges: DataFrame, limit: int | None = None) -> tuple:
    """The ends of edges as two arrays; beyond the limit it is an error."""
    limit = ARRAYS if limit is None else limit
    edges = cut(edges.select("u", "v"))
    if edges.count() > limit:
        raise TooLarge(f"more than {limit} edges")
    return as_arrays(edges)


def as_arrays(edges: DataFrame) -> tuple:
    got = edges.toArrow()
    return got["u"].to_numpy(), got["v"].to_numpy()


def is_connected(edges: DataFrame, vertices: DataFrame) -> bool:
    """Whether the edges join all the vertices, counted in Spark."""
    from ..exact.external import components

    n = vertices.count()
    labels = components(edges.select("u", "v"))
    seen, parts = labels.agg(F.count(F.lit(1)), F.countDistinct("label")).first()
    return n <= 1 or seen == n and parts == 1


def edge_connectivity_upto(updates: DataFrame, k: int, exact_at_k: bool = True, spec: SketchSpec | None = None) -> tuple[int, bool]:
    """(lambda, False) if lambda <= k, else (k, True): at least k + 1, or k with exact_at_k=False.

    Connectedness is decided in Spark at any size; a connected certificate beyond one solver's size is an error (TooLarge).
    """
    t = k + 1 if exact_at_k else k
    vertices = cut(touched(updates))
    h = cut(k_certificate(updates, t, spec, vertices=vertices).select("u", "v"))
    if not is_connected(h, vertices):
        return 0, False
    edges = collected(h)
    value = min(stoer_wagner([(u, v, 1) for u, v in edges], sorted({x for e in edges for x in e}))[0], 10**9)
    return (k, True) if value >= t else (int(value), False)


def sampled_levels(updates: DataFrame, levels: int, seed: int) -> DataFrame:
    """updates with depth: an edge is in sampled graph i iff depth >= i; the same for its insertion and deletion."""
    h = uniform(seed, "depth", F.col("u"), F.col("v"))
    return updates.withColumn("depth", F.least(F.bit_count(h.bitwiseAND(-h) - 1), F.lit(levels - 1)).cast("int"))


def cut_k(eps: float, vertices: int, scale: float = 1.0) -> int:
    """k of the minimum cut's certificates: scale log2(V) / eps**2, 2 at least."""
    return max(2, math.ceil(scale * math.log2(max(2, vertices)) / eps**2))


def sparsifier_k(eps: float, vertices: int, scale: float = 1.0) -> int:
    """k of the sparsifier's certificates: scale log2(V)**2 / eps**2, 2 at least."""
    return max(2, math.ceil(scale * math.log2(max(2, vertices)) ** 2 / eps**2))


def enough_levels(length: int) -> int:
    """Sampled graphs for a stream of that length: the last one has about one edge."""
    return math.ceil(math.log2(max(2, length))) + 1


def _sampled_certificates(updates: DataFrame, k: int, levels: int, seed: int, spec: SketchSpec | None) -> tuple[list[list[tuple]], list[int]]:
    """The certificates of all sampled graphs, and the vertices, on the driver: k (V - 1) edges each at most, LOCAL together."""
    vertices = cut(touched(updates))
    n = vertices.count()
    if n > LOCAL:
        raise TooLarge(f"{n} vertices; a solver holds {LOCAL}")
    deep = sampled_levels(updates.select("u", "v"), levels, seed)
    spec = spec or size_spec(n, max(2, updates.count()), sketches=k, seed=seed + 101)
    out: list[list[tuple]] = [[] for _ in range(levels)]
    for g, u, v in collected(certificates(deep, k, levels, spec, vertices=vertices).select("g", "u", "v")):
        out[g].append((u, v))
    return out, [r.x for r in vertices.collect()]


def approx_min_cut(updates: DataFrame, k: int | None = None, levels: int | None = None, seed: int = 5, search: str = "binary", spec: SketchSpec | None = None, eps: float | None = None, scale: float = 1.0) -> tuple[float, list[int], int]:
    """(value, side, j): the least level j whose certificate has a minimum cut below k; value 2**j times that cut, within 1 + eps of the minimum cut with high probability.

    k comes from eps (cut_k()) if it is not given. levels: enough_levels() if not given; if no level has a cut below k,
    that is an error (LevelsExhausted). j = 0 is exact. search "binary" needs the connectivity to fall with the level,
    which holds with high probability; "linear" tries every level from 0.
    """
    if k is None:
        if eps is None:
            raise ValueError("give eps or k")
        k = cut_k(eps, touched(updates).count(), scale)
    levels = levels or enough_levels(updates.count())
    graphs, vs = _sampled_certificates(updates, k, levels, seed, spec)
    memo: dict[int, tuple[float, list[int]]] = {}

    def cut_of(i: int) -> tuple[float, list[int]]:
        if i not in memo:
            memo[i] = stoer_wagner([(u, v, 1) for u, v in graphs[i]], vs)
        return memo[i]

    if search == "linear":
        j = next((i for i in range(levels) if cut_of(i)[0] < k), levels - 1)
    else:
        lo, hi = 0, levels - 1
        while lo < hi:
            mid = (lo + hi) // 2
            lo, hi = (lo, mid) if cut_of(mid)[0] < k else (mid + 1, hi)
        j = lo
    value, side = cut_of(j)
    if value >= k and len(vs) > 1:
        raise LevelsExhausted(f"level {j}, the last of {levels}, has a cut of {value:g}, not below k = {k}")
    return 2.0**j * value, side, j


def cut_edges(edges: DataFrame, side: DataFrame) -> DataFrame:
    """(u, v, w) with one end in the side (x)."""
    s = side.select("x", F.lit(True).alias("inside")).distinct()
    a, b = s.select(F.col("x").alias("u"), F.col("inside").alias("iu")), s.select(F.col("x").alias("v"), F.col("inside").alias("iv"))
    return edges.join(a, "u", "left").join(b, "v", "left").filter("coalesce(iu, false) <> coalesce(iv, false)").select("u", "v", "w")


def cut_value(edges: DataFrame, side: DataFrame) -> DataFrame:
    return cut_edges(edges, side).agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("value"))


def local_connectivity(graph: list[tuple[int, int, float]], pairs: DataFrame, cap: float) -> DataFrame:
    """(s, t, flow) for pairs (s, t): flows stop at cap, below which they are exact. The graph, bounded by LOCAL edges, goes to every task."""
    if len(graph) > LOCAL:
        raise TooLarge(f"more than {LOCAL} edges")
    near = adjacency(graph)

    def run(frames):
        for f in frames:
            yield f.assign(flow=[max_flow(near, s, t, cap) if s in near and t in near else 0.0 for s, t in zip(f.s, f.t)])

    return pairs.select("s", "t").mapInPandas(run, "s long, t long, flow double")


def cut_sparsifier(updates: DataFrame, k: int | None = None, levels: int | None = None, seed: int = 5, eps: float | None = None, scale: float = 1.0) -> DataFrame:
    """(u, v, w, level): edge e has weight 2**j(e) if it is in the certificate of level j(e), the least level in which fewer than k paths join its ends.

    k comes from eps (sparsifier_k()) if it is not given. j(e) is searched in Spark, a task for a share of the edges;
    flows stop at k. An edge that k paths join in every level is an error (LevelsExhausted). The certificates of all
    levels together, LOCAL edges at most, go to every task.
    """
    spark = updates.sparkSession
    if k is None:
        if eps is None:
            raise ValueError("give eps or k")
        k = sparsifier_k(eps, touched(updates).count(), scale)
    levels = levels or enough_levels(updates.count())
    graphs, _ = _sampled_certificates(updates, k, levels, seed, None)
    near = [adjacency([(u, v, 1.0) for u, v in g]) for g in graphs]
    of = [set(g) for g in graphs]
    schema = "u long, v long, w double, level int"
    every = sorted(set().union(*of))
    if not every:
        return spark.createDataFrame([], schema)

    def run(frames):
        for f in frames:
            out = []
            for u, v in zip(f.u, f.v):
                flow = lambda i: max_flow(near[i], u, v, float(k)) if u in near[i] and v in near[i] else 0.0  # noqa: E731, B023
                j = next((i for i in range(levels) if flow(i) < k), None)
                if j is None:
                    raise LevelsExhausted(f"{k} paths join {u} and {v} in all {levels} levels")
                if (u, v) in of[j]:
                    out.append((u, v, 2.0**j, j))
            yield pd.DataFrame(out, columns=["u", "v", "w", "level"]).astype({"u": "int64", "v": "int64", "w": "float64", "level": "int32"})

    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return cut(spark.createDataFrame(every, "u long, v long").repartition(tasks, "u", "v").mapInPandas(run, schema))


def sampling_split(eps: float) -> float:
    """The accuracy given to each of two steps whose errors multiply to 1 + eps."""
    return math.sqrt(1 + eps) - 1


def cuts_on(sparse: DataFrame, pairs: DataFrame) -> DataFrame:
    """(s, t, flow): minimum s-t cuts of a weighted graph (u, v, w)."""
    return local_connectivity(collected(sparse.select("u", "v", "w")), pairs, float("inf"))


def st_min_cuts(updates: DataFrame, pairs: DataFrame, eps: float, scale: float = 1.0, seed: int = 5, k: int | None = None) -> DataFrame:
    """(s, t, flow): s-t minimum cuts within 1 + eps. The sparsifier is built from the stream at the split accuracy; flows on it are exact, so the second step's share is slack."""
    return cuts_on(cut_sparsifier(updates, k, None, seed, sampling_split(eps), scale), pairs)


def contraction_trials(edges: DataFrame, trials: int, seed: int = 3) -> DataFrame:
    """(trial, value): random contractions to two vertices, an upper bound on the minimum cut, for certificates beyond one solver.

    Edges get random ranks in each trial; contracting them in that order to two vertices is the minimum spanning forest
    of the ranks without its last edge. The forest is built in Spark, all trials together as groups g: in each round every
    label takes its edge of least rank, and contract_functional() unites them. No edge is collected. Edges are taken
    as undirected and parallel ones count each; a graph that is not connected has cut 0.
    """
    spark = edges.sparkSession
    graph = cut(edges.select("u", "v").filter("u <> v"))
    groups = spark.range(trials).withColumnRenamed("id", "g")
    # (rank, u, v) orders edges in full; parallel edges are one for the forest
    ranked = graph.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().crossJoin(groups).withColumn("key", F.struct(F.xxhash64("g", "u", "v", F.lit(seed)).alias("r"), "u", "v"))
    start = graph.select("u").union(graph.select("v")).distinct().withColumnRenamed("u", "x").crossJoin(groups).select("g", "x", F.col("x").alias("root"))
    labels, live, forest = cut(start), cut(ranked.select("g", "key", F.col("u").alias("a"), F.col("v").alias("b"))), None
    while live.limit(1).count():
        ends = live.select("g", F.col("a").alias("label"), F.col("b").alias("to"), "key").union(live.select("g", F.col("b").alias("label"), F.col("a").alias("to"), "key"))
        least = ends.groupBy("g", "label").agg(F.min_by("to", "key").alias("to"), F.min("key").alias("key"))
        least = cut(least)
        picked = least.select("g", "key").distinct()
        forest = picked if forest is None else forest.union(picked)
        united = contract_functional(least.select("g", "label", "to", F.col("key.u").alias("u"), F.col("key.v").alias("v")))[0]
        labels, live = relabelled(labels, united), relabelled_ends(live, united)
    if forest is None:
        return groups.select(F.col("g").alias("trial"), F.lit(0.0).alias("value"))
    # without the last edge of the forest
    forest = cut(forest)
    last = forest.groupBy("g").agg(F.max("key").alias("last"))
    kept = forest.join(last, "g").filter(F.col("key") < F.col("last")).select("g", "key.u", "key.v")
    split = forest_labels(start, kept)
    side = lambda c: split.select("g", F.col("x").alias(c), F.col("root").alias(f"root_{c}"))
    crossing = graph.crossJoin(groups).join(side("u"), ["g", "u"]).join(side("v"), ["g", "v"]).filter("root_u <> root_v").groupBy("g").agg(F.count(F.lit(1)).alias("n"))
    # two components or more have a cut of no edge as they are
    parts = labels.groupBy("g").agg(F.countDistinct("root").alias("parts"))
    return groups.join(crossing, "g", "left").join(parts, "g").select(F.col("g").alias("trial"), F.when(F.col("parts") > 1, 0.0).otherwise(F.coalesce(F.col("n").cast("double"), F.lit(0.0))).alias("value"))


def relabelled(labels: DataFrame, united: DataFrame) -> DataFrame:
    """(g, x, root) after labels have been united (g, label, root)."""
    new = united.select("g", F.col("label").alias("root"), F.col("root").alias("_new"))
    return fresh(cut(labels.join(new, ["g", "root"], "left").select("g", "x", F.coalesce("_new", "root").alias("root"))))


def relabelled_ends(live: DataFrame, united: DataFrame) -> DataFrame:
    """(g, key, a, b) between labels that are still apart."""
    new = lambda c: united.select("g", F.col("label").alias(c), F.col("root").alias(f"new_{c}"))
    moved = live.join(new("a"), ["g", "a"], "left").join(new("b"), ["g", "b"], "left")
    return fresh(cut(moved.select("g", "key", F.coalesce("new_a", "a").alias("a"), F.coalesce("new_b", "b").alias("b")).filter("a <> b")))


def forest_labels(start: DataFrame, kept: DataFrame) -> DataFrame:
    """(g, x, root) of the components of the edges (g, u, v), by the same rounds; start has every vertex as its own root."""
    labels = start
    live = cut(kept.select("g", F.struct("u", "v").alias("key"), F.col("u").alias("a"), F.col("v").alias("b")))
    while live.limit(1).count():
        ends = live.select("g", F.col("a").alias("label"), F.col("b").alias("to"), "key").union(live.select("g", F.col("b").alias("label"), F.col("a").alias("to"), "key"))
        least = cut(ends.groupBy("g", "label").agg(F.min_by("to", "key").alias("to"), F.min("key").alias("key")))
        united = contract_functional(least.select("g", "label", "to", F.col("key.u").alias("u"), F.col("key.v").alias("v")))[0]
        labels, live = relabelled(labels, united), relabelled_ends(live, united)
    return labels
