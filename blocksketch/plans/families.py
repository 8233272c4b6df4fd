"""Bipartiteness, spanning-tree weight, matrix-vector product: families over one or several connectivity sketches."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exact.external import bipartite_components, components, double_cover
from ..operators.cells import Buffers, expand_rows, recover_one
from ..session import cut, kept
from ..spec import SketchSpec, size_spec
from .connectivity import extract, touched
from .forest import LOCAL, Local, Union, _crossing_cells, _ends, _now, _places, _renamed, boruvka


def cover_stream(updates: DataFrame) -> DataFrame:
    """The double cover's stream: two updates for one."""
    d = double_cover(updates.select("u", "v"))
    return d.withColumn("delta", F.lit(1)).withColumn("seq", F.lit(0).cast("long")).withColumn("w", F.lit(1.0))


def bipartiteness(updates: DataFrame, spec: SketchSpec | None = None) -> DataFrame:
    """(label, bipartite) for every component. Updates must be valid; the cover's deletions cancel like the graph's.

    The double cover's extraction begins with what the graph's forest lifts to: both copies of a tree's edges are edges of
    the cover. Only the updates that join two of these sets, which a bipartite graph has none of, are sketched again.
    """
    updates = kept(updates.select("u", "v"))
    labels, forest, _ = extract(updates, spec)
    lifts = labels.select(F.explode(F.array(F.col("x") * 2, F.col("x") * 2 + 1)).alias("x"))
    lifted = components(double_cover(forest))
    start = cut(lifts.join(lifted, "x", "left").select("x", F.coalesce("label", "x").alias("label")))
    a = start.filter("x % 2 = 0").select(F.shiftright("x", 1).alias("u"), F.col("label").alias("lu"))
    b = start.filter("x % 2 <> 0").select(F.shiftright("x", 1).alias("v"), F.col("label").alias("lv"))
    # an edge's two copies join sets or do not, alike
    apart = cover_stream(updates.join(a, "u").join(b, "v").filter("lu <> lv").select("u", "v"))
    return bipartite_components(_joined(apart, start, spec))


def _joined(apart: DataFrame, start: DataFrame, spec: SketchSpec | None) -> DataFrame:
    """The labels (x, label) start, joined by updates between them."""
    apart = kept(apart.select("u", "v"))
    if not (length := apart.count()):
        return start
    own = [F.lit(0).alias("g"), "x"]
    spec = spec or size_spec(start.count(), length)
    return boruvka(Buffers(apart, spec), spec, start.select(*own), start=start.select(*own, "label"))[0].select("x", "label")


def is_bipartite(updates: DataFrame, spec: SketchSpec | None = None) -> DataFrame:
    """One row: the graph has half as many components as its double cover, or not."""
    return bipartiteness(updates, spec).agg(F.coalesce(F.min("bipartite"), F.lit(True)).alias("bipartite"))


def weight_levels(eps: float, top: float) -> list[float]:
    """(1 + eps)**i for i from 0 until it reaches top."""
    r = math.ceil(math.log(top) / math.log(1 + eps) - 1e-9) if top > 1 else 0
    return [(1 + eps) ** i for i in range(r + 1)]


def checked_weights(updates: DataFrame, top: float | None) -> float:
    """top, or the largest weight if none is given; weights that are no integers from 1 to top are an error, as the bound rests on them."""
    w = F.col("w")
    high, low, odd = updates.agg(F.max(w), F.min(w), F.count(F.when(w.isNull() | (w != F.floor(w)), 1))).first()
    if high is None:
        if odd:
            raise ValueError("edges without a weight")
        return top or 1.0
    if low < 1 or odd or top is not None and high > top:
        raise ValueError(f"weights must be integers from 1 to {top if top is not None else 'some top'}; found {low} to {high}, {odd} of them no integers")
    return float(top if top is not None else high)


def threshold_components(updates: DataFrame, eps: float, top: float | None = None, spec: SketchSpec | None = None) -> DataFrame:
    """(i, n_components): components of the graph of edges of weight (1 + eps)**i or less, isolated vertices counted.

    An edge is stored once, with its first threshold; threshold i has sketch i, of the edges up to it. The graphs are
    nested, so extraction of threshold i begins with the components of i - 1 and does only what the new edges add; the
    sketch it reads is fresh to what those depend on.
    """
    return _thresholds(updates, eps, top, spec)[0]


def _thresholds(updates: DataFrame, eps: float, top: float | None, spec: SketchSpec | None) -> tuple[DataFrame, float, int]:
    """threshold_components(), top, and the number of vertices. The edges are made and stored once; all else reads what is stored."""
    spark = updates.sparkSession
    updates = kept(updates.select("u", "v", "w"))
    top = checked_weights(updates, top)
    steps = weight_levels(eps, top)
    # the number of thresholds below a weight, which is an integer: looked up, not counted for each edge
    below = [sum(t < w - 1e-9 for t in steps) for w in range(int(top) + 1)] if top <= 10_000 else None
    first = F.element_at(F.array(*[F.lit(n) for n in below]), F.col("w").cast("int") + 1) if below else F.size(F.filter(F.array(*[F.lit(t) for t in steps]), lambda t: t < F.col("w") - 1e-9))
    updates = updates.select("u", "v", first.alias("first"))
    vertices = cut(touched(updates))
    count = vertices.count()
    spec = replace(spec or size_spec(count, updates.count()), sketches=len(steps))
    sketch = Thresholds(updates, spec)
    vs = vertices.select(F.lit(0).alias("g"), "x")
    if count <= LOCAL:
        state, out = Local(vs.toPandas()), []
        for i in range(len(steps)):
            if sketch.news[i]:
                state.extract(spark, sketch, spec, i)
            out.append((i, state.count(0)))
        return spark.createDataFrame(out, "i int, n_components long"), top, count
    labels, out, left, few = None, [], count, None
    for i in range(len(steps)):
        if few is None and left <= LOCAL and any(sketch.news[i:]):
            few = Few(updates.filter(F.col("first") >= i).select("u", "v", "first"), labels, spec)
        if few is not None:
            left -= few.extract(i) if sketch.news[i] else 0
        elif sketch.news[i] or labels is None:
            labels = cut(boruvka(sketch, spec, vs, sketch=i, start=labels)[0])
            left = labels.select("label").distinct().count()
        out.append((i, left))
    return spark.createDataFrame(out, "i int, n_components long"), top, count


class Few:
    """Thresholds from the one on at which LOCAL components or fewer are left: their labels are united on the driver.

    The edges that are still to come are labelled once; those inside a component add nothing to any sum and leave. A
    threshold's rows are made of its own edges between labels that are still apart.
    """

    def __init__(self, updates: DataFrame, labels: DataFrame, spec: SketchSpec):
        self.spec, self.union = spec, Union()
        self.edges = kept(_ends(updates, labels.select("x", "label")).filter("lu <> lv").repartition("first"))

    def extract(self, i: int) -> int:
        """The number of unions that threshold i brings."""
        spark, t, joined = self.edges.sparkSession, 0, 0
        own = self.edges.filter(F.col("first") == i).drop("first")
        while True:
            names = _now(spark, self.union)
            live = cut(own if names is None else _renamed(own, names))
            a, b = _places(self.spec, t)
            found = recover_one(_crossing_cells(live, self.spec, i, a, b).withColumn("g", F.lit(0)), self.spec, "g", "label", places=(i, a, b))
            # a label's edge joins it to the label at the other end
            ends = found.join(live.select("u", "v", "lu", "lv"), ["u", "v"], "left").select("label", "lu", "lv").distinct().collect()
            t += 1
            if not ends:
                return joined
            for _, lu, lv in sorted((r for r in ends if r.lu is not None), key=tuple):
                joined += self.union.join(lu, lv)


class Thresholds(Buffers):
    """Sketch i holds the edges whose first threshold is i or less; news: whether a threshold has edges of its own."""

    def __init__(self, updates: DataFrame, spec: SketchSpec):
        super().__init__(updates, spec, keep=("first",))
        have = {r[0] for r in self.given.select("first").distinct().collect()}  # a number for each threshold
        self.news = [i in have for i in range(spec.sketches)]

    def updates(self, sketch: int, started: bool) -> DataFrame:
        return self.given.filter(F.col("first") == sketch if started else F.col("first") <= sketch).select("u", "v")

    def rows(self, sketch: int, a: int, b: int) -> DataFrame:
        return expand_rows(self.dealt.filter(F.col("first") <= sketch), self.spec, (sketch, sketch + 1), (a, b)).withColumn("g", F.lit(0))


def mst_weight(updates: DataFrame, eps: float, top: float | None = None, form: str = "telescoped", spec: SketchSpec | None = None) -> DataFrame:
    """One row: the spanning-forest weight within a factor 1 + eps, integer weights from 1 to top (the largest weight if not given; a weight beyond it is an error).

    Weights are rounded up to powers of 1 + eps; with c_i components at threshold i the rounded forest weighs
    n - c_r (1+eps)^r + sum of c_i ((1+eps)^(i+1) - (1+eps)^i) over i < r. form="as_printed" shifts the differences by
    one and lies below the weight; it is kept for comparison.
    """
    c, top, n = _thresholds(updates, eps, top, spec)
    steps = weight_levels(eps, top)
    at = lambda xs: F.element_at(F.array(*[F.lit(x) for x in xs]), F.col("i") + 1)
    if form == "telescoped":
        gain = [steps[i + 1] - steps[i] for i in range(len(steps) - 1)] + [-steps[-1]]
        return c.agg((F.lit(float(n)) + F.sum(at(gain) * F.col("n_components"))).alias("weight"))
    gain = [steps[i] - (steps[i - 1] if i else 1 / (1 + eps)) for i in range(len(steps))]
    return c.agg((F.lit(float(n)) - steps[-1] + F.sum(at(gain) * F.col("n_components"))).alias("weight"))


def spmv(matrix: DataFrame, x: DataFrame, rows_per_vertex: int = 1) -> DataFrame:
    """(row, y) = matrix (row, col, val) times x (col, x), through the sketch-builder view: an entry is an edge whose vertex is row div rho and whose sketch row is row mod rho, and cells add up."""
    cells = matrix.join(x, "col").select((F.col("row") / rows_per_vertex).cast("long").alias("vertex"), (F.col("row") % rows_per_vertex).alias("r"), (F.col("val") * F.col("x")).alias("p"))
    return cells.groupBy("vertex", "r").agg(F.sum("p").alias("y")).select((F.col("vertex") * rows_per_vertex + F.col("r")).alias("row"), "y")
