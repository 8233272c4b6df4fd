"""Linear sketch cells: ingestion, merging, sums over vertex sets, and recovery of one crossing edge.

CELL rows: sk, vg, x (the vertex), row, lvl, xu, xv, chk. An edge stands at its own level only, once in each row; the
sum over levels at or above l (a suffix XOR) is the sample of rate 2**-l. A deletion is the same XOR as an insertion.
"""

from __future__ import annotations

import math
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import level_text, row_constants, with_hashes
from ..session import cut, shared_folder
from ..spec import SketchSpec
from .stream import edge_records

KEYS = ("sk", "vg", "x", "row", "lvl")
SUMS = ("xu", "xv", "chk")


def vertex_group(x: Column, groups: int) -> Column:
    return F.pmod(F.xxhash64(x), F.lit(groups)).cast("int")


def _groups(df: DataFrame) -> int:
    return 8 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def fold(cells: DataFrame, *keys: str) -> DataFrame:
    """XOR of cells with equal keys; cells that cancel go."""
    out = cells.groupBy(*keys).agg(*[F.expr(f"bit_xor({c}) as {c}") for c in SUMS])
    return out.filter("xu <> 0 or xv <> 0 or chk <> 0")


def expand_rows(records: DataFrame, spec: SketchSpec, sketches: tuple[int, int] | None = None, rows: tuple[int, int] | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Every record in each row of each sketch of the ranges, at its level; keep: further columns that stay. records: vg, x, u, v, chk."""
    a, b = sketches or (0, spec.sketches)
    r0, r1 = rows or (0, spec.rows)
    places = [(sk, row) for sk in range(a, b) for row in range(r0, r1)]
    out = records.select("vg", "x", "u", "v", "chk", *keep, F.explode(row_constants(spec, places)).alias("at"))
    out = with_hashes(out, spec, "u", "v")
    return out.selectExpr("at.sk as sk", "vg", "x", "at.row as row", f"{level_text('_h', spec.levels)} as lvl", "u as xu", "v as xv", "chk", *keep)


def _records(updates: DataFrame, spec: SketchSpec, keep: tuple[str, ...] = ()) -> DataFrame:
    """(vg, x, u, v, keep): each update at both its ends."""
    return edge_records(updates.select("u", "v", *keep)).select(vertex_group(F.col("x"), _groups(updates)).alias("vg"), "x", "u", "v", *keep)


def hubs_of(records: DataFrame, tasks: int) -> tuple[DataFrame, int] | None:
    """(hub vertices x, salts), or None if the vertex groups are even: the early flush of a buffer that fills before the others.

    Groups are counted, a number for each of the 8 x partitions groups; only where one holds more than half a task's fair
    share are its vertices counted. A hub has more than a quarter of that share, so there are fewer than 4 x tasks hubs,
    which bounds what is broadcast, whatever the input.
    """
    sizes = {r.vg: r.n for r in records.groupBy("vg").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = sum(sizes.values()) / max(1, tasks)
    heavy = [g for g, n in sizes.items() if n > share / 2]
    if not heavy or share < HUB_RECORDS:
        return None
    degrees = cut(records.filter(F.col("vg").isin(heavy)).groupBy("x").agg(F.count(F.lit(1)).alias("deg")).filter(F.col("deg") > share / 4))
    top = degrees.agg(F.max("deg")).first()[0]
    return (degrees.select("x"), min(16 * tasks, math.ceil(16 * top / share))) if top else None


HUB_RECORDS = 10_000  # a task's fair share from which hubs are worth a pass; fewer records are no burden to one task


def deal(updates: DataFrame, spec: SketchSpec, keep: tuple[str, ...] = (), hubs: DataFrame | str | None = "auto", salts: int = 16) -> DataFrame:
    """The update buffers: (vg, x, u, v, chk, keep, and salt if there are hubs), dealt to vertex groups by one exchange of narrow rows.

    hubs: "auto" finds them by hubs_of(); a table of vertices (x) gives them, of any size (a large one is joined by a
    shuffle, as Spark decides); None leaves them. A hub's updates are spread over salts.
    """
    records = _records(updates, spec, keep)
    n = int(updates.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if isinstance(hubs, str):
        found = hubs_of(records, n)
        if found:
            salts = found[1]
        hubs = F.broadcast(found[0]) if found else None
    checked = lambda dealt: with_hashes(dealt, spec, "u", "v", None, "chk")
    if hubs is None:
        return checked(records.repartition(n, "vg"))
    spread = records.join(hubs.select("x", F.lit(True).alias("hub")), "x", "left")
    salt = F.when(F.col("hub"), F.pmod(F.xxhash64("u", "v"), F.lit(salts))).otherwise(0).cast("int")
    return checked(spread.select("vg", "x", "u", "v", *keep, salt.alias("salt")).repartition(n, "vg", "salt"))


def deal_by(updates: DataFrame, spec: SketchSpec, key: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """(vg, x, u, v, chk, key, keep), dealt by a key column of the updates instead of by vertex groups: cells are then summed by that key, too."""
    n = 4 * int(updates.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # keys may be few, and should seldom meet in a task
    narrow = updates.select("u", "v", key, *keep).repartition(n, key)
    return with_hashes(_records(narrow, spec, (key, *keep)), spec, "u", "v", None, "chk")


def apply_buffers(dealt: DataFrame, spec: SketchSpec, sketches: tuple[int, int] | None = None, rows: tuple[int, int] | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """The cells of dealt updates. Rows are made behind the exchange, so the aggregate needs no other; salted parts are summed again."""
    if "salt" not in dealt.columns:
        return fold(expand_rows(dealt, spec, sketches, rows, keep), *KEYS, *keep)
    return fold(fold(expand_rows(dealt, spec, sketches, rows, ("salt", *keep)), "salt", *KEYS, *keep), *KEYS, *keep)


def sketch_updates(updates: DataFrame, spec: SketchSpec, sketches: tuple[int, int] | None = None, rows: tuple[int, int] | None = None, mode: str = "block", hubs: DataFrame | str | None = "auto", salts: int = 16) -> DataFrame:
    """The cells of a stream.

    mode "block": the narrow updates are dealt to vertex groups by one exchange, and rows are made behind it (deal(),
    apply_buffers()). "combine_first": rows are made and partly summed before the exchange, for few vertices and
    many updates each. "per_update": every row of every update travels (the naive order). "global_sort": the stream is
    sorted by vertex first.
    """
    if mode == "block":
        return apply_buffers(deal(updates, spec, (), hubs, salts), spec, sketches, rows)
    n = int(updates.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    records = _records(updates, spec)
    checked = lambda r: with_hashes(r, spec, "u", "v", None, "chk")
    if mode == "combine_first":
        return fold(expand_rows(checked(records), spec, sketches, rows), *KEYS)
    if mode == "per_update":
        return fold(expand_rows(checked(records), spec, sketches, rows).repartition(n, "vg"), *KEYS)
    if mode == "global_sort":
        return fold(expand_rows(checked(records.repartitionByRange(n, "x").sortWithinPartitions("x")), spec, sketches, rows), *KEYS)
    raise ValueError(mode)


def sketch_in_chunks(updates: DataFrame, spec: SketchSpec, chunks: int) -> DataFrame:
    """For vertex sketches larger than memory: the updates are dealt and written once, and applied to one chunk of the rows at a time."""
    step = -(-spec.rows // chunks)
    dealt = cut(deal(updates, spec))
    out = None
    for a in range(0, spec.rows, step):
        part = apply_buffers(dealt, spec, rows=(a, min(a + step, spec.rows)))
        out = part if out is None else out.unionByName(part)
    return out


class Buffers:
    """A sketch as its stored update buffers: the rows that extraction asks for are made when it does, a chunk at a time, and rows that are never asked for never.

    This is the cheaper store while the stream is shorter than the sketch. spread: an array column of groups g, made
    from the keep columns, in each of which a cell stands (threshold or sampled graphs that grow from one stored copy).
    """

    def __init__(self, updates: DataFrame, spec: SketchSpec, keep: tuple[str, ...] = (), spread: Column | None = None, hubs: DataFrame | str | None = "auto"):
        self.spec, self.keep, self.spread, self.hubs = spec, keep, spread, hubs
        self.given = updates.select("u", "v", *keep)

    @cached_property
    def dealt(self) -> DataFrame:
        return cut(deal(self.given, self.spec, self.keep, self.hubs))

    def updates(self, sketch: int, started: bool) -> DataFrame:
        """(u, v) of the sketch's updates, once each. started: without those that lie inside the components of the sketches before."""
        return self.given.select("u", "v")

    def rows(self, sketch: int, a: int, b: int) -> DataFrame:
        # parts of cells: extraction sums them by vertex set at once, so vertices need no sum of their own
        cells = expand_rows(self.dealt, self.spec, (sketch, sketch + 1), (a, b), self.keep)
        return cells.withColumn("g", F.explode(self.spread) if self.spread is not None else F.lit(0)).drop(*self.keep)


class Stored:
    """A sketch as cells in Parquet by sketch and row: a round of extraction reads the folders of its rows and no other."""

    def __init__(self, cells: DataFrame, path: str | None = None):
        self.path = path or shared_folder(cells.sparkSession, "cells")
        write_cells(cells, self.path)
        self.cells = cells.sparkSession.read.parquet(self.path)

    def rows(self, sketch: int, a: int, b: int) -> DataFrame:
        own = self.cells.filter((F.col("sk") == sketch) & (F.col("row") >= a) & (F.col("row") < b))
        return own if "g" in own.columns else own.withColumn("g", F.lit(0))


class Given:
    """Cells in a DataFrame, as they are (snapshots, sums of sketches)."""

    def __init__(self, cells: DataFrame):
        self.cells = cells if "g" in cells.columns else cells.withColumn("g", F.lit(0))

    def rows(self, sketch: int, a: int, b: int) -> DataFrame:
        return self.cells.filter((F.col("sk") == sketch) & (F.col("row") >= a) & (F.col("row") < b))


def write_cells(cells: DataFrame, path: str, band: int | None = None, bucketed: str | None = None, buckets: int = 32) -> None:
    """The sketch store: Parquet by sketch, row (and band of levels, the column split), sorted by vertex; or, with bucketed, a table of that name in buckets of vertices."""
    by = ["sk", "row"]
    if band:
        cells, by = cells.withColumn("band", level_band(F.col("lvl"), band)), ["sk", "row", "band"]
    if bucketed:
        cells.write.mode("overwrite").bucketBy(buckets, "x").sortBy("x").option("path", path).saveAsTable(bucketed)
    else:
        cells.sortWithinPartitions(*by, "x").write.mode("overwrite").partitionBy(*by).parquet(path)


def read_bands(spark, path: str, least: int) -> DataFrame:
    """Cells of bands from one on: the folders of lower levels, which hold most cells, are not read."""
    return spark.read.parquet(path).filter(F.col("band") >= least)


def level_band(lvl: Column, width: int) -> Column:
    """The column split: bands of width levels, stored apart; high bands hold few cells."""
    return (lvl / width).cast("int")


def merge_cells(*cells: DataFrame) -> DataFrame:
    out = cells[0]
    for c in cells[1:]:
        out = out.unionByName(c)
    return fold(out, *KEYS)


def subtract_cells(a: DataFrame, b: DataFrame) -> DataFrame:
    """a without b; over XOR the same as their sum."""
    return merge_cells(a, b)


def cut_cells(cells: DataFrame, labels: DataFrame, *more: str) -> DataFrame:
    """Cells of each label's vertex set: its inner edges cancel, its crossing edges stay. labels: x, label (and more key columns)."""
    return fold(cells.join(labels, ["x", *more]), *more, "sk", "label", "row", "lvl")


def suffix_sums(cells: DataFrame, *keys: str) -> DataFrame:
    """XOR over this level and all above it."""
    over = f"over (partition by {', '.join(keys)}{', ' if keys else ''}sk, row order by lvl desc rows between unbounded preceding and current row)"
    return cells.selectExpr(*keys, "sk", "row", "lvl", *[f"bit_xor({c}) {over} as {c}" for c in SUMS])


def _tested(cells: DataFrame, spec: SketchSpec, *keys: str, places: tuple[int, int, int] | None = None) -> DataFrame:
    """suffix_sums() with ok, whether a sum is one edge: u < v, its checksum fits, and the edge's own level in this row is not below."""
    sk, r0, r1 = places or (None, 0, spec.rows)
    order = [(k, row) for k in (range(spec.sketches) if sk is None else [sk]) for row in range(r0, r1)]
    index = F.col("row") - r0 + (F.col("sk") * spec.rows if sk is None else 0) + 1
    s = suffix_sums(cells, *keys).withColumn("at", F.element_at(row_constants(spec, order), index.cast("int")))
    s = with_hashes(s, spec, "xu", "xv", "at", "own_chk")
    ok = f"xu < xv and chk = own_chk and {level_text('_h', spec.levels)} >= lvl as ok"
    return s.selectExpr(*keys, "sk", "row", "lvl", *SUMS, ok)


def recover(cells: DataFrame, spec: SketchSpec, *keys: str) -> DataFrame:
    """(keys, sk, row, u, v, lvl): from each row that shows a single edge, that edge, at the highest level that does."""
    best = F.max_by(F.struct("xu", "xv"), "lvl").alias("e")
    return _tested(cells, spec, *keys).filter("ok").groupBy(*keys, "sk", "row").agg(best, F.max("lvl").alias("lvl")).select(*keys, "sk", "row", F.col("e.xu").alias("u"), F.col("e.xv").alias("v"), "lvl")


def recover_one(cells: DataFrame, spec: SketchSpec, *keys: str, places: tuple[int, int, int] | None = None) -> DataFrame:
    """(keys, u, v): one crossing edge for each vertex set that has a cell: of its first row that shows one, at the highest level; u and v null where no row does. places: (sketch, first row, end) if all cells are of these."""
    first = F.expr("min(if(ok, struct(row, -lvl as deep, xu, xv), null)) as e")
    return _tested(cells, spec, *keys, places=places).groupBy(*keys).agg(first).select(*keys, F.col("e.xu").alias("u"), F.col("e.xv").alias("v"))


def cut_is_empty(cells: DataFrame, labels: DataFrame) -> DataFrame:
    """(label, is_empty): whether all the set's sums are zero, which certifies that no edge leaves it."""
    live = cells.select("label").distinct().withColumn("live", F.lit(True))
    return labels.select("label").distinct().join(live, "label", "left").select("label", F.col("live").isNull().alias("is_empty"))


def finalize(cells: DataFrame, spec: SketchSpec, dense: bool = False) -> DataFrame:
    """The list of vertex sketches by vertex: sparse rows, or an array of levels for each row."""
    if not dense:
        return cells.orderBy("sk", "x", "row", "lvl")
    by = cells.groupBy("sk", "x", "row").agg(F.map_from_entries(F.collect_list(F.struct("lvl", F.struct(*SUMS)))).alias("m"))
    zero = F.struct(*[F.lit(0).cast("long").alias(c) for c in SUMS])
    arr = F.transform(F.sequence(F.lit(0), F.lit(spec.levels - 1)), lambda i: F.coalesce(F.col("m")[i], zero))
    return by.select("sk", "x", "row", arr.alias("cells")).orderBy("sk", "x", "row")
