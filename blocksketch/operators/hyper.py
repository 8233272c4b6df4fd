"""Hyperedge sketches: signed sums modulo P, since copies of a hyperedge do not cancel by pairs.

The least member carries the coefficient |e| - 1 and every other member -1, so a vertex set's sum over e is zero iff e
lies wholly inside or outside. Cells hold the sums of coefficients, of coefficient times each member (members padded
with -1 + 1 = 0 to r places, each in two limbs of 30 bits), and of coefficient times a fingerprint.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import P, coefficients, level, poly_hash
from ..session import cut, fresh, kept
from ..spec import SketchExhausted, SketchSpec, size_spec
from ..plans.forest import LOCAL, Union, _places
from .cells import _groups, vertex_group

LIMB = 2**30


def _mod(x: Column) -> Column:
    return F.pmod(x, F.lit(P).cast("long"))


def canonical_hyperedges(df: DataFrame, members: str) -> DataFrame:
    """(members, and delta if df has it): sorted distinct members; a set of fewer than two crosses no cut and goes."""
    m = F.array_sort(F.array_distinct(F.col(members).cast("array<long>")))
    delta = [F.col("delta").cast("int").alias("delta")] if "delta" in df.columns else []
    return df.select(m.alias("members"), *delta).filter(F.size("members") > 1)


def digits(members: Column, r: int) -> Column:
    """2r numbers below 2**30: the low and high limbs of member + 1, and zeros for missing members."""
    padded = F.slice(F.concat(F.transform(members, lambda m: m + 1), F.array_repeat(F.lit(0).cast("long"), r)), 1, r)
    return F.flatten(F.transform(padded, lambda m: F.array(m % LIMB, (m / LIMB).cast("long"))))


def fingerprint(spec: SketchSpec, digits_: Column) -> Column:
    """The fifth power, a bijection modulo P, of a polynomial of the digits. The polynomial alone is linear in them, so the sum of several hyperedges would pass for one."""
    c = [x[0] for x in coefficients(spec.seed, 1, "hyper")][0]
    return F.aggregate(digits_, F.lit(1).cast("long"), lambda a, d: _mod(_mod(a * c) + d), lambda a: _mod(_mod(_mod(a * a) * _mod(a * a)) * a))


def with_fingerprint(hyper: DataFrame, spec: SketchSpec, r: int) -> DataFrame:
    """hyper with fp, once for each hyperedge. Up to WIDE members it is plain arithmetic, which is compiled; an aggregate over an array is interpreted."""
    if r > WIDE:
        return hyper.withColumn("fp", fingerprint(spec, digits(F.col("members"), r)))
    c, a = coefficients(spec.seed, 1, "hyper")[0][0], "1L"
    for i in range(2 * r):
        a = f"pmod(pmod({a} * {c}L, {P}L) + {_digit(i)}, {P}L)"
    own = [f"`{x}`" for x in hyper.columns]
    out = hyper.selectExpr(*own, f"{a} as _a").selectExpr(*own, "_a", f"pmod(_a * _a, {P}L) as _b")
    return out.selectExpr(*own, "_a", f"pmod(_b * _b, {P}L) as _b").selectExpr(*own, f"pmod(_b * _a, {P}L) as fp")


WIDE = 32


def _digit(i: int) -> str:
    """The i-th of digits() as text."""
    return f"coalesce(get(members, {i // 2}) + 1L, 0L) {'div' if i % 2 else '%'} {LIMB}L"


def hyper_hash(spec: SketchSpec, sk: Column, row: Column, fp: Column) -> Column:
    table = coefficients(spec.seed, spec.sketches * spec.rows, "hyper-row")
    at = (sk * spec.rows + row + 1).cast("int")
    a, b, c = (F.element_at(F.array(*[F.lit(t[i]).cast("long") for t in table]), at) for i in range(3))
    return _mod(_mod(_mod(fp * fp) * a) + _mod(fp * b) + c)


def hyperedge_records(hyper: DataFrame) -> DataFrame:
    """(members, x, coef), one for each member."""
    least = F.element_at("members", 1)
    return hyper.select("members", F.explode("members").alias("x"), least.alias("_l")).select("members", "x", F.when(F.col("x") == F.col("_l"), F.size("members") - 1).otherwise(-1).cast("long").alias("coef"))


def _updates(hyper: DataFrame) -> DataFrame:
    """(members, x, coef, fp), one for each member of each update. hyper: members, fp, and delta if deletions occur."""
    delta = F.col("delta").cast("long") if "delta" in hyper.columns else F.lit(1).cast("long")
    rec = hyper.select("members", "fp", delta.alias("delta")).select("members", "fp", "delta", F.explode("members").alias("x"))
    coef = F.when(F.col("x") == F.element_at("members", 1), F.size("members") - 1).otherwise(-1).cast("long") * F.col("delta")
    return rec.select("members", "x", coef.alias("coef"), "fp")


def hyper_buffers(hyper: DataFrame, spec: SketchSpec, r: int) -> DataFrame:
    """(vg, x, coef, members, fp): each update at each of its members, dealt to vertex groups. hyper: members, and delta if deletions occur."""
    n = int(hyper.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rec = _updates(hyper if "fp" in hyper.columns else with_fingerprint(hyper, spec, r))
    return rec.select(vertex_group(F.col("x"), _groups(hyper)).alias("vg"), "x", "coef", "members", "fp").repartition(n, "vg")


def expand_hyper(updates: DataFrame, spec: SketchSpec, r: int, a: int, b: int, *keys: str) -> DataFrame:
    """Parts of HCELL rows in rows a to b - 1: the keys (vg and x if not given), row, lvl, s0, chk, c0 .. c(2r - 1). updates: the keys, coef, members, fp."""
    keys = keys or ("vg", "x")
    rec = updates.select("*", F.explode(F.sequence(F.lit(a), F.lit(b - 1))).alias("row"))
    lvl = level(hyper_hash(spec, F.lit(0), F.col("row"), F.col("fp")), spec.levels)
    times = lambda c: f"pmod(pmod(coef, {P}L) * ({c}), {P}L)"
    sums = [f"pmod(coef, {P}L) as s0", f"{times('fp')} as chk", *[f"{times(_digit(i))} as c{i}" for i in range(2 * r)]]
    return rec.withColumn("lvl", lvl).selectExpr(*keys, "row", "lvl", *sums)


def sketch_hyper(hyper: DataFrame, spec: SketchSpec, r: int) -> DataFrame:
    """HCELL rows: vg, x, row, lvl, s0, chk, coord residues, of all rows of the sketch. hyper: members, and delta if deletions occur."""
    return fold_hyper(expand_hyper(hyper_buffers(hyper, spec, r), spec, r, 0, spec.rows), r, "vg", "x", "row", "lvl")


def fold_hyper(cells: DataFrame, r: int, *keys: str) -> DataFrame:
    names = ["s0", "chk", *[f"c{i}" for i in range(2 * r)]]
    out = cells.groupBy(*keys).agg(*[F.expr(f"pmod(sum({c}), {P}L) as {c}") for c in names])
    return out.filter("s0 <> 0 or chk <> 0 or c0 <> 0")


class Sums:
    """Cells of a hyperedge sketch as arrays: folding updates into them, and what they show. Spark's generated code for 2r + 2 sums is too large to be compiled, from r = 17 on at least."""

    def __init__(self, spec: SketchSpec, r: int):
        self.spec, self.r, self.names = spec, r, ["s0", "chk", *[f"c{i}" for i in range(2 * r)]]
        self.rows = np.array([c[:3] for c in coefficients(spec.seed, spec.sketches * spec.rows, "hyper-row")], dtype=np.int64)
        self.base = coefficients(spec.seed, 1, "hyper")[0][0]
        self.chunk = max(1024, 2**21 // r)

    def levels(self, row: np.ndarray, fp: np.ndarray) -> np.ndarray:
        x, y, z = self.rows[row].T
        h = ((fp * fp % P) * x % P + fp * y % P + z) % P
        return np.minimum(np.where(h == 0, 64, np.bitwise_count((h & -h) - 1)), self.spec.levels - 1).astype(np.int64)

    @staticmethod
    def fold(key: tuple[np.ndarray, ...], sums: np.ndarray) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
        """Sums of equal (label, row, lvl) in their order, levels falling; zeros go."""
        order = np.lexsort((-key[2], key[1], key[0]))
        key, sums = tuple(k[order] for k in key), sums[order]
        start = np.flatnonzero(np.append(True, np.any([k[1:] != k[:-1] for k in key], axis=0))) if len(order) else order
        sums = np.add.reduceat(sums, start, axis=0) % P if len(start) else sums
        some = (sums != 0).any(1)
        return tuple(k[start][some] for k in key), sums[some]

    def of(self, batch: pa.RecordBatch, label: str, a: int, b: int) -> tuple[tuple[np.ndarray, ...], np.ndarray]:
        """The cells of updates in rows a to b - 1. Products stay below 2**62 in a chunk's sums, so the modulus is taken once."""
        x, coef, fp = (batch[c].to_numpy() for c in (label, "coef", "fp"))
        lists = batch["members"]
        size = lists.value_lengths().to_numpy()
        at = np.repeat(np.arange(len(size)), size), np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        m = np.zeros((len(size), self.r), dtype=np.int64)
        m[at] = lists.flatten().to_numpy() + 1
        sums = np.empty((len(size), 2 * self.r + 2), dtype=np.int64)
        sums[:, 0], sums[:, 1], sums[:, 2::2], sums[:, 3::2] = 1, fp, m % LIMB, m // LIMB
        sums *= coef[:, None]
        parts = [self.fold((x, np.full(len(x), row), self.levels(np.full(len(x), row), fp)), sums) for row in range(a, b)]
        return tuple(np.concatenate(k) for k in zip(*(k for k, _ in parts))), np.concatenate([s for _, s in parts])

    def show(self, row: np.ndarray, lvl: np.ndarray, sums: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(whether a sum over a level and all above it is one hyperedge, its members + 1 in a row, zeros behind)."""
        inv = np.ones(len(row), dtype=np.int64)
        for bit in bin(P - 2)[2:]:  # s0**(P - 2) is its inverse
            inv = inv * inv % P
            if bit == "1":
                inv = inv * sums[:, 0] % P
        d = sums[:, 2:] * inv[:, None] % P
        fp = np.ones(len(row), dtype=np.int64)
        for i in range(2 * self.r):
            fp = (fp * self.base % P + d[:, i]) % P
        fp = (fp * fp % P) * (fp * fp % P) % P * fp % P
        members = d[:, 0::2] + d[:, 1::2] * LIMB
        good = (sums[:, 0] != 0) & (sums[:, 1] * inv % P == fp) & (self.levels(row, fp) >= lvl) & (d < LIMB).all(1) & ((members > 0).sum(1) > 1)
        return good, members

    @staticmethod
    def lists(good: np.ndarray, members: np.ndarray) -> pa.Array:
        mask = (members > 0) & good[:, None]
        at = np.concatenate([[0], np.cumsum(mask.sum(1))])
        return pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(members[mask] - 1, pa.int64()), mask=pa.array(~good))

    def tested(self, keys: tuple[str, ...]):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                col = lambda c: batch[c].to_numpy().astype(np.int64)
                good, members = self.show(col("row"), col("lvl"), np.stack([col(c) for c in self.names], axis=1))
                yield pa.RecordBatch.from_arrays([*(batch[k] for k in keys), batch["row"], self.lists(good, members)], [*keys, "row", "members"])

        return run

    def chunks(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, self.chunk):
                yield batch.slice(i, self.chunk)

    def folded(self, a: int, b: int):
        """Updates (label, coef, members, fp) in any order to parts of cells."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            key, sums = (np.empty(0, dtype=np.int64),) * 3, np.empty((0, 2 * self.r + 2), dtype=np.int64)
            for batch in self.chunks(batches):
                more, own = self.of(batch, "label", a, b)
                key, sums = self.fold(tuple(np.concatenate(k) for k in zip(key, more)), np.concatenate([sums, own]))
                if len(sums) > self.chunk:
                    yield self.batch(key, sums)
                    key, sums = tuple(k[:0] for k in key), sums[:0]
            if len(sums):
                yield self.batch(key, sums)

        return run

    def batch(self, key, sums) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(key[0]), pa.array(key[1], pa.int32()), pa.array(key[2], pa.int32()), *(pa.array(c) for c in sums.T.copy())], ["label", "row", "lvl", *self.names])

    def found(self, a: int, b: int):
        """Updates (label, coef, members, fp), a label's all behind one another, to (label, members): what every label with a cell shows."""

        def shown(key, sums) -> pa.RecordBatch:
            label, row, lvl = key
            start = np.append(True, (label[1:] != label[:-1]) | (row[1:] != row[:-1]))
            first = np.flatnonzero(start)[np.cumsum(start) - 1]
            run = np.cumsum(sums, axis=0)
            good, members = self.show(row, lvl, (run - run[first] + sums[first]) % P)
            one = np.flatnonzero(np.append(True, label[1:] != label[:-1]))
            best = np.minimum.reduceat(np.where(good, np.arange(len(label)), len(label)), one)  # the first row that shows one, at the highest level
            ok = best < len(label)
            return pa.RecordBatch.from_arrays([pa.array(label[one]), self.lists(ok, members[np.where(ok, best, 0)])], ["label", "members"])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            key, sums = (np.empty(0, dtype=np.int64),) * 3, np.empty((0, 2 * self.r + 2), dtype=np.int64)
            for batch in self.chunks(batches):
                more, own = self.of(batch, "label", a, b)
                key, sums = self.fold(tuple(np.concatenate(k) for k in zip(key, more)), np.concatenate([sums, own]))
                last = key[0] == batch["label"][-1].as_py()  # more of it may follow
                if not last.all():
                    yield shown(tuple(k[~last] for k in key), sums[~last])
                    key, sums = tuple(k[last] for k in key), sums[last]
            if len(sums):
                yield shown(key, sums)

        return run


def recover_hyper(cells: DataFrame, spec: SketchSpec, r: int, *keys: str) -> DataFrame:
    """(keys, members): a crossing hyperedge for each vertex set that shows one; null where no row does."""
    names = ["s0", "chk", *[f"c{i}" for i in range(2 * r)]]
    over = f"over (partition by {', '.join(keys)}, row order by lvl desc rows between unbounded preceding and current row)"
    s = cells.selectExpr(*keys, "row", "lvl", *[f"pmod(sum({c}) {over}, {P}L) as {c}" for c in names])
    kinds = ", ".join(f"{k} {kind}" for k, kind in s.dtypes if k in keys)
    s = s.mapInArrow(Sums(spec, r).tested(keys), f"{kinds}, row int, members array<long>")
    return s.groupBy(*keys).agg(F.expr("min(if(members is not null, struct(row, members), null)).members as members"))


def rank(hyper: DataFrame) -> int:
    """The most members of a hyperedge, 2 at least."""
    return max(2, hyper.agg(F.max(F.size("members"))).first()[0] or 0)


def hyper_components(hyper: DataFrame, r: int | None = None, spec: SketchSpec | None = None, extraction: str = "auto") -> tuple[DataFrame, DataFrame]:
    """(labels: x, label; spanning hypergraph: members). r: the most members of a hyperedge, counted if not given; a larger hyperedge is an error.

    Up to LOCAL vertices (or extraction="local"), sampled hyperedges are united on the driver, each chosen one joining
    something new. Beyond (or "distributed"), every round's hyperedges become stars over the labels they touch, whose
    components are the next labels; all sampled hyperedges are returned then, which may close cycles.
    """
    hyper = kept(hyper)  # made once; all else reads what is stored
    most = rank(hyper)
    if r is not None and most > r:
        raise ValueError(f"a hyperedge of {most} members; r is {r}")
    r = r or most
    vertices = cut(hyper.select(F.explode("members").alias("x")).distinct())
    count = vertices.count()
    spec = spec or size_spec(count, max(2, hyper.count()))
    if "delta" in hyper.columns:
        hyper = kept(net(hyper))
    if extraction == "local" or extraction == "auto" and count <= LOCAL:
        return _local(HyperBuffers(hyper, spec, r), vertices, spec, r)  # the rows of a round are made when it reads them
    return _distributed(hyper, vertices, spec, r)


def net(hyper: DataFrame) -> DataFrame:
    """Update buffers without what cancels in them: a hyperedge's updates as one, of its sign; how often it is there does not matter to what it connects."""
    n = F.sum("delta")
    return hyper.groupBy("members").agg(F.signum(n).cast("int").alias("delta")).filter("delta <> 0")


class HyperBuffers:
    """A hyperedge sketch as its stored update buffers."""

    def __init__(self, hyper: DataFrame, spec: SketchSpec, r: int):
        self.spec, self.r, self.sparkSession = spec, r, hyper.sparkSession
        self.buffers = kept(hyper_buffers(hyper, spec, r))

    def sums(self, labels: DataFrame, t: int) -> DataFrame:
        """The cells of round t by label."""
        return _by_label(self.buffers, labels, self.spec, self.r, t)


def _by_label(updates: DataFrame, labels: DataFrame, spec: SketchSpec, r: int, t: int) -> DataFrame:
    """The cells of round t by label, partly summed before the exchange."""
    names = ", ".join(f"{c} long" for c in ("s0", "chk", *[f"c{i}" for i in range(2 * r)]))
    own = updates.join(labels, "x").select("label", "coef", "members", "fp")
    return fold_hyper(own.mapInArrow(Sums(spec, r).folded(*_places(spec, t)), f"label long, row int, lvl int, {names}"), r, "label", "row", "lvl")


def _first_round(hyper: DataFrame, spec: SketchSpec, r: int) -> DataFrame:
    """(label, members): what each vertex alone shows, from its updates behind one exchange."""
    dealt = hyper_buffers(hyper, spec, r).select("vg", F.col("x").alias("label"), "coef", "members", "fp").sortWithinPartitions("vg", "label")
    return dealt.select("label", "coef", "members", "fp").mapInArrow(Sums(spec, r).found(*_places(spec, 0)), "label long, members array<long>")


def _local(cells: HyperBuffers, vertices: DataFrame, spec: SketchSpec, r: int) -> tuple[DataFrame, DataFrame]:
    spark, at = cells.sparkSession, vertices.toPandas()
    union, chosen, t = Union(), [], 0
    while True:
        labels = spark.createDataFrame(pd.DataFrame({"x": at.x, "label": [union.root(x) for x in at.x.tolist()]}), "x long, label long")
        found = recover_hyper(cells.sums(labels, t), spec, r, "label").collect()
        if not found:
            return labels, spark.createDataFrame([(m,) for m in chosen], "members array<long>")
        for row in sorted((x for x in found if x.members), key=lambda x: x.label):
            if any([union.join(row.members[0], m) for m in row.members[1:]]):
                chosen.append(list(row.members))
        t += 1


def _distributed(hyper: DataFrame, vertices: DataFrame, spec: SketchSpec, r: int) -> tuple[DataFrame, DataFrame]:
    """The first round folds whole vertices, behind the one exchange of their updates. From there on the hyperedges contract
    with the graph: one whose members have all met adds nothing to the sum of a label's vertices, and is read no more."""
    from ..exact.external import components

    live = kept(with_fingerprint(hyper, spec, r).withColumn("e", F.monotonically_increasing_id()))
    labels, chosen, t = vertices.select("x", F.col("x").alias("label")), None, 0
    while True:
        found = recover_hyper(_by_label(_updates(live), labels, spec, r, t), spec, r, "label") if t else _first_round(live, spec, r)
        found = cut(found)
        if not found.limit(1).count():
            return labels, chosen if chosen is not None else hyper.sparkSession.createDataFrame([], "members array<long>")
        got = found.filter("members is not null").select("members").distinct()
        touched = got.select(F.col("members")[0].alias("first"), F.explode("members").alias("x")).join(labels, "x")
        star = touched.groupBy("first", "label").agg(F.lit(1)).join(labels.select(F.col("x").alias("first"), F.col("label").alias("u")), "first").filter("u <> label")
        roots = components(star.select("u", F.col("label").alias("v"))).select(F.col("x").alias("label"), F.col("label").alias("root"))
        labels = fresh(cut(labels.join(roots, "label", "left").select("x", F.coalesce("root", "label").alias("label"))))
        chosen = got if chosen is None else chosen.union(got).distinct()
        live = kept(crossing(live, labels))
        t += 1


def crossing(hyper: DataFrame, labels: DataFrame) -> DataFrame:
    """The hyperedges (members, e and more) whose members have more than one label."""
    met = hyper.select("e", F.explode("members").alias("x")).join(labels, "x").groupBy("e").agg(F.min("label").alias("lo"), F.max("label").alias("hi"))
    return hyper.join(met.filter("lo <> hi").select("e"), "e", "left_semi")
