"""Connected components and spanning forests of a dynamic graph, and what follows from the labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.cells import Buffers, Stored, sketch_updates
from ..session import cut, kept
from ..spec import SketchSpec, size_spec
from .forest import boruvka


def touched(updates: DataFrame) -> DataFrame:
    """The vertices of the final graph and of every update: (x)."""
    return updates.select(F.col("u").alias("x")).union(updates.select(F.col("v").alias("x"))).distinct()


def live_vertices(updates: DataFrame) -> DataFrame:
    """Vertices with an edge left: those with a surviving update count."""
    from ..operators.stream import edges_at

    return touched(edges_at(updates))


def fit(updates: DataFrame, vertices: DataFrame, **more) -> SketchSpec:
    return size_spec(vertices.count(), updates.count(), **more)


def sketch_of(updates: DataFrame, spec: SketchSpec, vertices: int, length: int, mode: str = "block", store: str = "auto"):
    """The sketch of a stream, stored: as update buffers if the stream is shorter than the sketch's V phi words (store "buffers"), else as cells by row ("cells")."""
    if store == "auto":
        store = "buffers" if mode == "block" and length <= vertices * spec.words else "cells"
    return Buffers(updates, spec) if store == "buffers" else Stored(sketch_updates(updates, spec, mode=mode))


def extract(updates: DataFrame, spec: SketchSpec | None = None, vertices: DataFrame | None = None, mode: str = "block", extraction: str = "auto", store: str = "auto", **more) -> tuple[DataFrame, DataFrame, int]:
    """(labels: x, label), (forest: u, v, round), rounds."""
    updates = kept(updates.select("u", "v"))
    vertices = cut(touched(updates) if vertices is None else vertices)
    count, length = vertices.count(), updates.count()
    spec = spec or size_spec(count, length, **more)
    sketch = sketch_of(updates, spec, count, length, mode, store)
    labels, forest, rounds = boruvka(sketch, spec, vertices.select(F.lit(0).alias("g"), "x"), mode=extraction)
    return labels.drop("g"), forest.drop("g"), rounds


def connected_components(updates: DataFrame, spec: SketchSpec | None = None, vertices: DataFrame | None = None, **more) -> DataFrame:
    """(x, label): label is the least vertex number of x's component."""
    return extract(updates, spec, vertices, **more)[0]


def spanning_forest(updates: DataFrame, spec: SketchSpec | None = None, vertices: DataFrame | None = None, **more) -> DataFrame:
    """(u, v, round): an acyclic set of edges that connects what the graph connects."""
    return extract(updates, spec, vertices, **more)[1]


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("label").agg(F.count(F.lit(1)).alias("size"))


def same_component(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs (s, t) with same BOOLEAN; a vertex without label is connected to itself only."""
    a = labels.select(F.col("x").alias("s"), F.col("label").alias("ls"))
    b = labels.select(F.col("x").alias("t"), F.col("label").alias("lt"))
    out = pairs.join(a, "s", "left").join(b, "t", "left")
    return out.select("s", "t", (F.coalesce("ls", "s") == F.coalesce("lt", "t")).alias("same"))
