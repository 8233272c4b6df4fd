"""Spanning forests out of cells: rounds of sampling, contracting and merging.

Each round sums that round's fresh rows by the current labels (every cell is read once in all), recovers one crossing
edge for each label, and contracts. A label without any cell left is closed; the loop ends when all are, so running out
of rows is an error that is seen. Independent sketches of many graphs run in one loop by the group column g.

Contraction has two forms. While the sampled edges number LOCAL or less, they are collected and united on the driver.
Beyond, labels form a functional graph (each open label has one out-edge); pointer doubling finds every label's cycle
and its least member, and the representative's own out-edge is left out, which breaks each cycle once.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import with_hashes
from ..operators.cells import Buffers, Given, apply_buffers, cut_cells, deal, expand_rows, fold, recover_one
from ..session import cut, fresh, kept
from ..spec import SketchExhausted, SketchSpec

LOCAL = 200_000


class Union:
    """Union by least member."""

    def __init__(self):
        self.up: dict = {}

    def root(self, x):
        up = self.up
        while (y := up.get(x, x)) != x:
            up[x] = up.get(y, y)
            x = y
        return x

    def join(self, a, b) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def contract_functional(edges: DataFrame, steps: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(labels: g, label, root; kept edges) from rows (g, label, to, u, v), one for each open label.

    steps: doublings at most; they end when no root moves. root is the least member of the stretch of 2**j steps behind
    a label's own; if the next stretch has the same least member, the walk came by it twice, so it went round the cycle.
    """
    n = edges.count()
    steps = steps or max(1, math.ceil(math.log2(max(2, n))) + 1)
    nodes = edges.select("g", "label").union(edges.select("g", "to")).distinct()
    f = nodes.join(edges.select("g", "label", "to"), ["g", "label"], "left").select("g", "label", F.coalesce("to", "label").alias("to"))
    f = f.withColumn("least", F.least("label", "to")).withColumn("root", F.lit(None).cast("long"))  # least: over the stretch from the label, 2**j steps long
    for _ in range(steps + 1):
        far = f.select("g", F.col("label").alias("to"), F.col("to").alias("to2"), F.col("least").alias("least2"))
        # cut each time: the plan reads f twice, and would double with every step
        f = fresh(cut(f.join(far, ["g", "to"]).select("g", "label", F.col("to2").alias("to"), F.least("least", "least2").alias("least"), F.col("least2").alias("root"), F.col("root").alias("before"))))
        if not f.filter("before is null or before <> root").limit(1).count():
            break
    labels = f.select("g", "label", "root")
    chosen = edges.join(labels, ["g", "label"]).filter("label <> root").select("g", "u", "v")
    return labels, chosen


def boruvka(source, spec: SketchSpec, vertices: DataFrame, sketch: int = 0, local: int = LOCAL, mode: str = "auto", start: DataFrame | None = None) -> tuple[DataFrame, DataFrame, int]:
    """(labels: g, x, label), (forest: g, u, v, round), number of rounds.

    source: what gives the cells of some rows (Buffers, Stored, Given), or cells in a DataFrame. vertices: g, x. start:
    labels (g, x, label) to begin from, of vertices known to be connected. Labels are least vertex numbers of components.
    """
    spark = vertices.sparkSession
    source = Given(source) if isinstance(source, DataFrame) else source
    if mode == "local" or mode == "auto" and vertices.count() <= local:
        state = Local(vertices.toPandas(), start.toPandas() if start is not None else None)
        rounds = state.extract(spark, source, spec, sketch)
        return state.labels(spark), state.forest(spark), rounds
    if isinstance(source, Buffers) and source.spread is None:
        return _contracted(source, spec, vertices, sketch, 0 if mode == "distributed" else local, start)
    labels, forest = cut(vertices.select("g", "x", F.col("x").alias("label")) if start is None else start.select("g", "x", "label")), None
    for t in range(spec.rows // spec.rows_per_round + 1):
        rows, places = _round_rows(source, spec, sketch, t)
        found = cut(recover_one(cut_cells(rows, labels, "g"), spec, "g", "label", places=places))
        if not found.limit(1).count():
            return _named(labels), forest if forest is not None else _no_forest(spark), t + 1
        ends = found.filter("u is not null")
        by = labels.select("g", F.col("x").alias("u"), F.col("label").alias("lu"))
        bv = labels.select("g", F.col("x").alias("v"), F.col("label").alias("lv"))
        e = ends.join(by, ["g", "u"]).join(bv, ["g", "v"]).filter("lu <> lv and (label = lu or label = lv)")
        e = cut(e.select("g", "label", F.when(F.col("label") == F.col("lu"), F.col("lv")).otherwise(F.col("lu")).alias("to"), "u", "v"))
        roots, chosen = contract_functional(e)
        labels = fresh(cut(labels.join(roots, ["g", "label"], "left").select("g", "x", F.coalesce("root", "label").alias("label"))))
        chosen = cut(chosen.withColumn("round", F.lit(t)))
        forest = chosen if forest is None else forest.unionByName(chosen)
    raise SketchExhausted(f"open components after {spec.rows} rows")


def _named(labels: DataFrame) -> DataFrame:
    """Labels as least vertex numbers; a label is some member of its component until here."""
    least = labels.groupBy("g", "label").agg(F.min("x").alias("least"))
    return labels.join(least, ["g", "label"]).select("g", "x", F.col("least").alias("label"))


def _ends(df: DataFrame, labels: DataFrame, how: str = "inner") -> DataFrame:
    """df with the labels (x, label) of its columns u and v, as lu and lv."""
    lu = labels.select(F.col("x").alias("u"), F.col("label").alias("lu"))
    lv = labels.select(F.col("x").alias("v"), F.col("label").alias("lv"))
    return df.join(lu, "u", how).join(lv, "v", how)


def _contracted(source: Buffers, spec: SketchSpec, vertices: DataFrame, sketch: int, local: int, start: DataFrame | None) -> tuple[DataFrame, DataFrame, int]:
    """boruvka() over update buffers that contract with the graph: (u, v, lu, lv), stored.

    An update inside a vertex set adds nothing to the set's sums, as both its ends are in them; so it leaves the buffers
    when the labels of its ends meet, and a round makes rows of the crossing updates only. While more than local labels
    are open, they are united and the buffers written again in Spark; from there on, the labels' unions are on the driver.
    """
    spark = vertices.sparkSession
    labels = cut(vertices.select("x", F.col("x").alias("label")) if start is None else start.select("x", "label"))
    updates, edges, forests, t = source.updates(sketch, start is not None), None, [], 0
    if start is not None:
        edges = kept(_ends(updates, labels).filter("lu <> lv"))
    while edges is None or not local or edges.select(F.explode(F.array("lu", "lv"))).distinct().count() > local:
        a, b = _places(spec, t)
        cells = apply_buffers(deal(updates, spec), spec, (sketch, sketch + 1), (a, b)).withColumnRenamed("x", "label") if edges is None else _crossing_cells(edges, spec, sketch, a, b)
        found = cut(recover_one(cells.withColumn("g", F.lit(0)), spec, "g", "label", places=(sketch, a, b)))
        t += 1
        if not found.limit(1).count():
            break
        e = _ends(found.filter("u is not null"), labels).filter("lu <> lv and (label = lu or label = lv)")
        e = cut(e.select("g", "label", F.when(F.col("label") == F.col("lu"), F.col("lv")).otherwise(F.col("lu")).alias("to"), "u", "v"))
        roots, chosen = contract_functional(e)
        forests.append(cut(chosen.withColumn("round", F.lit(t - 1))))
        roots = roots.select("label", "root")
        labels = fresh(cut(labels.join(roots, "label", "left").select("x", F.coalesce("root", "label").alias("label"))))
        edges = kept(_ends(updates if edges is None else edges.select("u", "v"), labels).filter("lu <> lv"))
    else:
        union, more = Union(), []
        while True:
            a, b = _places(spec, t)
            names = _now(spark, union)
            live = edges if names is None else _renamed(edges, names)
            found = recover_one(_crossing_cells(live, spec, sketch, a, b).withColumn("g", F.lit(0)), spec, "g", "label", places=(sketch, a, b))
            found = _ends(cut(found).select("u", "v"), labels, "left").toArrow()
            t += 1
            if not found.num_rows:
                break
            for u, v, lu, lv in sorted(zip(*(found[c].to_pylist() for c in ("u", "v", "lu", "lv"))), key=lambda r: (r[0] is None, r)):
                if u is not None and union.join(lu, lv):
                    more.append((0, u, v, t - 1))
        names = _now(spark, union)
        if names is not None:
            labels = labels.join(F.broadcast(names), "label", "left").select("x", F.coalesce("now", "label").alias("label"))
        if more:
            forests.append(spark.createDataFrame(pa.table([pa.array(c) for c in zip(*more)], ["g", "u", "v", "round"]), "g int, u long, v long, round int"))
    forest = reduce(DataFrame.unionByName, forests) if forests else _no_forest(spark)
    return _named(labels.select(F.lit(0).alias("g"), "x", "label")), forest, t


def _crossing_cells(edges: DataFrame, spec: SketchSpec, sketch: int, a: int, b: int) -> DataFrame:
    """(sk, label, row, lvl, sums) of the labels' vertex sets, from crossing updates (u, v, lu, lv); partly summed before the exchange."""
    records = with_hashes(edges.select(F.lit(0).alias("vg"), F.lit(0).cast("long").alias("x"), "u", "v", "lu", "lv"), spec, "u", "v", None, "chk")
    cells = expand_rows(records, spec, (sketch, sketch + 1), (a, b), ("lu", "lv"))
    return fold(cells.withColumn("label", F.explode(F.array("lu", "lv"))), "sk", "label", "row", "lvl")


def _now(spark, union: Union) -> DataFrame | None:
    """(label, now) of the labels that have been united with another."""
    if not union.up:
        return None
    old = list(union.up)
    return spark.createDataFrame(pa.table({"label": pa.array(old, pa.int64()), "now": pa.array([union.root(x) for x in old], pa.int64())}), "label long, now long")


def _renamed(edges: DataFrame, names: DataFrame) -> DataFrame:
    for c in ("lu", "lv"):
        edges = edges.join(F.broadcast(names.select(F.col("label").alias(c), F.col("now").alias(f"{c}_now"))), c, "left")
    return edges.select("u", "v", F.coalesce("lu_now", "lu").alias("lu"), F.coalesce("lv_now", "lv").alias("lv")).filter("lu <> lv")


def _places(spec: SketchSpec, t: int) -> tuple[int, int]:
    a, b = t * spec.rows_per_round, (t + 1) * spec.rows_per_round
    if b > spec.rows:
        raise SketchExhausted(f"open components after {spec.rows} rows")
    return a, b


def _round_rows(source, spec: SketchSpec, sketch: int, t: int) -> tuple[DataFrame, tuple[int, int, int]]:
    a, b = _places(spec, t)
    return source.rows(sketch, a, b), (sketch, a, b)


def _no_forest(spark) -> DataFrame:
    return spark.createDataFrame([], "g int, u long, v long, round int")


class Local:
    """Labels and sampled edges, LOCAL at most, on the driver; cells stay where they are.

    A vertex whose label showed no cell is done and takes no part in later rounds. Its label may open again only if more
    edges come in, for which extract() starts with all vertices.
    """

    def __init__(self, at: pd.DataFrame, start: pd.DataFrame | None = None):
        self.g, self.x = at.g.to_numpy(dtype=np.int32), at.x.to_numpy(dtype=np.int64)
        self.union, self.edges = Union(), []
        if start is not None:
            for g, x, label in start[["g", "x", "label"]].itertuples(index=False, name=None):
                self.union.join((g, x), (g, label))

    def _label(self) -> np.ndarray:
        root = self.union.root
        return np.array([root(k)[1] for k in zip(self.g.tolist(), self.x.tolist())], dtype=np.int64)

    def count(self, g: int) -> int:
        """Components of a group."""
        return len(set(self._label()[self.g == g].tolist()))

    def _frame(self, spark, label: np.ndarray, some: np.ndarray | slice = slice(None)) -> DataFrame:
        return spark.createDataFrame(pa.table({"g": self.g[some], "x": self.x[some], "label": label[some]}), "g int, x long, label long")

    def extract(self, spark, source, spec: SketchSpec, sketch: int = 0) -> int:
        """Contract until no label shows a cell; the number of rounds."""
        t, label, live = 0, self._label(), slice(None)
        while True:
            rows, places = _round_rows(source, spec, sketch, t)
            found = recover_one(cut_cells(rows, self._frame(spark, label, live), "g"), spec, "g", "label", places=places).collect()
            t += 1
            if not found:
                return t
            for g, _, u, v in sorted((r for r in found if r.u is not None), key=tuple):
                if self.union.join((g, u), (g, v)):
                    self.edges.append((g, u, v, t - 1))
            label = self._label()
            still = {self.union.root((r.g, r.label)) for r in found}
            live = np.array([k in still for k in zip(self.g.tolist(), label.tolist())], dtype=bool)

    def labels(self, spark) -> DataFrame:
        return self._frame(spark, self._label())

    def forest(self, spark) -> DataFrame:
        return spark.createDataFrame(self.edges, "g int, u long, v long, round int") if self.edges else _no_forest(spark)
