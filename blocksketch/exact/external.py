"""Exact baselines over the whole edge list, as joins and aggregates: components, bipartiteness, minimum spanning forest, adjacency size."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.forest import contract_functional
from ..session import cut, fresh, kept
from .solvers import Stars, least_labels

LOCAL_EDGES = 500_000  # arrays of 16 bytes an edge on the driver


def components(edges: DataFrame, limit: int = 60, local: int = LOCAL_EDGES) -> DataFrame:
    """(x, label), label the least vertex.

    Each partition's edges become stars of the components they form, before any exchange. Every label then moves to the
    least label around it, and on to where that one moved; edges contract with the labels, and are united on the driver
    once local or fewer are left. Of two labels that meet, one goes within two rounds, so the rounds are logarithmic.
    """
    live = kept(_stars(edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))))
    n = live.count()
    if n <= local:
        return _united(live, "x", "label")
    labels = cut(live.select(F.explode(F.array("u", "v")).alias("x")).distinct().select("x", F.col("x").alias("label")))
    for _ in range(limit):
        if n <= local:
            names = _united(live, "label", "now")
        else:
            both = live.select("u", "v").union(live.select("v", "u"))
            to = cut(both.groupBy(F.col("u").alias("label")).agg(F.min("v").alias("m")).select("label", F.least("label", "m").alias("to")))
            names = cut(to.join(to.select(F.col("label").alias("to"), F.col("to").alias("now")), "to").select("label", "now"))
        labels = fresh(cut(labels.join(names, "label", "left").select("x", F.coalesce("now", "label").alias("label"))))
        if n <= local:
            return labels
        for c in ("u", "v"):
            live = live.join(names.select(F.col("label").alias(c), F.col("now").alias(f"{c}_now")), c, "left")
            live = live.withColumn(c, F.coalesce(f"{c}_now", c)).drop(f"{c}_now")
        live = kept(_stars(live.filter("u <> v").select("u", "v")))
        n = live.count()
        if not n:
            return labels
    raise RuntimeError("labels did not settle")


def _stars(edges: DataFrame) -> DataFrame:
    return edges.mapInArrow(Stars(), "u long, v long")


def _united(edges: DataFrame, vertex: str, label: str) -> DataFrame:
    """The components of a few edges, found on the driver."""
    got = edges.toArrow()
    ids, least = least_labels(got["u"].to_numpy(), got["v"].to_numpy())
    return edges.sparkSession.createDataFrame(pa.table({vertex: pa.array(ids, pa.int64()), label: pa.array(least, pa.int64())}), f"{vertex} long, {label} long")


def double_cover(edges: DataFrame) -> DataFrame:
    """Two copies of every vertex, 2x and 2x + 1; an edge joins opposite copies."""
    two = F.array(*[F.struct((F.col(a) * 2).alias("a"), (F.col(b) * 2 + 1).alias("b")) for a, b in (("u", "v"), ("v", "u"))])
    return edges.select(F.explode(two).alias("e")).select(F.least("e.a", "e.b").alias("u"), F.greatest("e.a", "e.b").alias("v"))


def bipartite_components(cover: DataFrame) -> DataFrame:
    """(label, bipartite) from the labels of the double cover: a component is bipartite if its lifts stay apart, and its least vertex is that of the least lift."""
    two = cover.groupBy(F.shiftright("x", 1).alias("x")).agg(F.min("label").alias("least"), F.max("label").alias("most"))
    return two.groupBy(F.shiftright("least", 1).alias("label")).agg(F.min(F.col("least") != F.col("most")).alias("bipartite"))


def minimum_forest(edges: DataFrame) -> DataFrame:
    """(u, v, w) of a minimum spanning forest: every component's least edge, by (w, u, v), round after round."""
    live = cut(edges.select("u", "v", "w", F.col("u").alias("a"), F.col("v").alias("b")))
    out = None
    while live.limit(1).count():
        ends = live.select(F.col("a").alias("label"), F.struct("w", "u", "v", F.col("b").alias("to")).alias("e")).union(live.select(F.col("b"), F.struct("w", "u", "v", F.col("a").alias("to"))))
        best = cut(ends.groupBy("label").agg(F.min("e").alias("e")).select(F.lit(0).alias("g"), "label", "e.to", "e.u", "e.v", "e.w"))
        roots, kept = contract_functional(best)
        got = kept.join(best.select("u", "v", "w").distinct(), ["u", "v"]).select("u", "v", "w").distinct()
        out = got if out is None else out.unionByName(got)
        r = roots.select(F.col("label").alias("a"), F.col("root").alias("ra"))
        q = roots.select(F.col("label").alias("b"), F.col("root").alias("rb"))
        live = fresh(cut(live.join(r, "a").join(q, "b").filter("ra <> rb").select("u", "v", "w", F.col("ra").alias("a"), F.col("rb").alias("b"))))
    return out if out is not None else edges.select("u", "v", "w").limit(0)


def adjacency_size(updates: DataFrame, word_bytes: int = 8) -> DataFrame:
    """(edges, bytes) that a store of every live edge takes."""
    from ..operators.stream import edges_at

    return edges_at(updates).agg(F.count(F.lit(1)).alias("edges")).select("edges", (F.col("edges") * 2 * word_bytes).alias("bytes"))
