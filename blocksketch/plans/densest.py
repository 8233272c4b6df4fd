"""Densest subgraph by one partition of the edges into buckets, drawing from the buckets' sketches, and peeling the sample."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exact.solvers import peel_arrays, peel_batch_arrays
from ..functions.hashing import P, coefficients, poly_hash, with_hashes
from ..operators.cells import SUMS, expand_rows
from ..session import cut, fresh
from ..spec import SketchExhausted, SketchSpec
from . import kconn

ROWS = 12  # of a bucket's sketch: a row shows no single edge in about 3 of 10 cases, all of them in 1 of 2 million
SPARE = 2  # sketches of a bucket beyond its draws: a million draws would meet one without an edge in half of all runs


def bucket_of(u, v, buckets: int, seed: int, t: int = 16):
    """A t-wise independent bucket for an edge."""
    c = coefficients(seed, t, "bucket")
    mixed = F.pmod(F.pmod(u, F.lit(P).cast("long")) * c[0][0], F.lit(P).cast("long")) + F.pmod(F.pmod(v, F.lit(P).cast("long")) * c[0][1], F.lit(P).cast("long"))
    return F.pmod(poly_hash(mixed, [x[2] for x in c]), F.lit(buckets)).cast("int")


def bucket_arrays(u: np.ndarray, v: np.ndarray, c: list[tuple[int, ...]], buckets: int) -> np.ndarray:
    """bucket_of() over arrays; c: its coefficients."""
    x, h = _near(_near(u % P * c[0][0]) + _near(v % P * c[0][1])), np.zeros(len(u), dtype=np.int64)
    for row in c:
        h = _near(h * x + row[2])
    return np.where(h >= P, h - P, h) % buckets


def in_buckets(updates: DataFrame, buckets: int, seed: int, t: int) -> DataFrame:
    """(u, v, delta, bucket): bucket_of() every update, in arrays, as Spark would interpret the polynomial term by term."""
    c = coefficients(seed, t, "bucket")

    def run(batches):
        for b in batches:
            at = bucket_arrays(b["u"].to_numpy(), b["v"].to_numpy(), c, buckets)
            yield pa.RecordBatch.from_arrays([b["u"], b["v"], b["delta"], pa.array(at.astype(np.int32))], ["u", "v", "delta", "bucket"])

    return updates.selectExpr("u", "v", "cast(delta as int) as delta").mapInArrow(run, "u long, v long, delta int, bucket int")


def bucket_stats(updates: DataFrame, buckets: int, seed: int = 9) -> DataFrame:
    """(bucket, n): surviving edges, from signed counters; deletions count down."""
    return counters(updates.withColumn("bucket", bucket_of(F.col("u"), F.col("v"), buckets, seed)))


def counters(bucketed: DataFrame) -> DataFrame:
    return bucketed.groupBy("bucket").agg(F.sum("delta").cast("long").alias("n")).filter("n > 0")


def drawn_numbers(counts: DataFrame, p: float, seed: int) -> DataFrame:
    """(bucket, n, x): x ~ Bin(n, p), from a generator seeded by (seed, bucket), so that reruns agree."""

    def run(frames):
        for f in frames:
            yield f.assign(x=[int(np.random.default_rng([seed, int(b)]).binomial(n, p)) if p < 1 else n for b, n in zip(f.bucket, f.n)])

    return counts.select(F.col("bucket").cast("long").alias("bucket"), "n").mapInPandas(run, "bucket long, n long, x long")


def asked_for(numbers: DataFrame, spec: SketchSpec) -> tuple[DataFrame, int]:
    """(bucket, asked) of the buckets that are drawn from, and the most that any is asked for; more than there are sketches is an error."""
    asked = numbers.filter("x > 0").select("bucket", F.col("x").alias("asked"))
    most = asked.agg(F.max("asked")).first()[0] or 0
    if most > spec.sketches:
        raise SketchExhausted(f"{most} edges are drawn from a bucket of {spec.sketches} sketches")
    return asked, most


def bucket_sketches(bucketed: DataFrame, numbers: DataFrame, spec: SketchSpec) -> DataFrame:
    """(bucket, x, sk, row, lvl, sums): the cells of the first x sketches of every bucket, which is the vertex and vertex group here; sketches that no draw asks for are not made."""
    asked, most = asked_for(numbers, spec)
    rec = bucketed.select(F.col("bucket").cast("long").alias("bucket"), "u", "v").join(asked, "bucket")
    rec = with_hashes(rec.select(F.lit(0).alias("vg"), F.col("bucket").alias("x"), "u", "v", "asked"), spec, "u", "v", None, "chk")
    cells = expand_rows(rec, spec, (0, max(1, most)), None, ("asked",)).filter("sk < asked")
    out = cells.groupBy("x", "asked", "sk", "row", "lvl").agg(*[F.expr(f"bit_xor({c}) as {c}") for c in SUMS]).filter("xu <> 0 or xv <> 0 or chk <> 0")
    return out.select(F.col("x").alias("bucket"), "asked", "sk", "row", "lvl", *SUMS)


def _near(x: np.ndarray) -> np.ndarray:
    """x modulo P, from 0 to P + 7, for 0 <= x < 2**63: twice the sum of its two parts of 31 bits."""
    x = (x & P) + (x >> 31)
    return (x & P) + (x >> 31)


def _mod(x: np.ndarray) -> np.ndarray:
    """x modulo P; x itself if that is what it is, as a division takes longer than a hash's other steps."""
    return x if len(x) and x.min() >= 0 and x.max() < P else x % P


def _hashes(u: np.ndarray, v: np.ndarray, c: np.ndarray) -> np.ndarray:
    """edge_hash() of every edge, its ends modulo P, under every row of six coefficients: rows x edges."""
    c = c.T[:, :, None]
    x = _near(u * c[0] + v * c[1] + c[2])  # below 2**63, as all factors are below P
    h = _near(x * x) * c[3]
    h = _near((h & P) + (h >> 31) + x * c[4] + c[5])
    return np.where(h >= P, h - P, h)


class Draw:
    """Edges of one bucket, from its sketches one after the other; a found edge leaves the later sketches before they are asked."""

    def __init__(self, spec: SketchSpec):
        self.spec, self.row = spec, np.array(coefficients(spec.seed, spec.sketches * spec.rows, "row"), dtype=np.int64)
        self.chk = np.array(coefficients(spec.seed, 2, "chk"), dtype=np.int64)
        self.plain = self.row.tolist(), self.chk.tolist()
        self.chunk = 2**19  # hashes at a time
        self.wide = max(1, 2**16 // spec.levels)  # rows at a time: places of 16 bits are sorted by their digits
        self.room = 2**19  # updates whose buckets are drawn from together

    @staticmethod
    def _hash(u: int, v: int, c: list[int]) -> int:
        x = (u * c[0] + v * c[1] + c[2]) % P
        return (x * x * c[3] + x * c[4] + c[5]) % P

    def _levels(self, h: np.ndarray) -> np.ndarray:
        low = np.bitwise_count((h & -h) - 1)
        return np.minimum(np.where(h == 0, 64, low), self.spec.levels - 1)

    def add(self, sums: np.ndarray, u: np.ndarray, v: np.ndarray) -> None:
        """Updates into the cells of the first sketches: rows x levels x 3, rows of all sketches behind one another."""
        mu, mv = u % P, v % P
        one = _hashes(mu, mv, self.chk)
        values = np.stack([u, v, one[0] * 2**31 + one[1]], axis=1)
        flat = sums.reshape(-1, 3)
        for r in range(0, len(sums), self.wide):
            c = self.row[r : min(r + self.wide, len(sums))]
            step = max(1, self.chunk // len(c))
            for i in range(0, len(u), step):
                lvl = self._levels(_hashes(mu[i : i + step], mv[i : i + step], c))
                place = (np.arange(len(c))[:, None] * self.spec.levels + lvl).astype(np.uint16).ravel()
                order = np.argsort(place, kind="stable")
                place = place[order]
                start = np.flatnonzero(np.append(True, place[1:] != place[:-1]))
                flat[place[start].astype(np.int64) + r * self.spec.levels] ^= np.bitwise_xor.reduceat(values[i : i + step][order % lvl.shape[1]], start, axis=0)

    def one(self, sums: np.ndarray, sk: int) -> tuple[int, int, int] | None:
        """An edge (u, v, checksum) of the sketch: of the first row that shows one, at the highest level; sums: rows x levels x 3."""
        rows, (a, b) = self.plain[0], self.plain[1]
        for row in range(self.spec.rows):
            tail = np.bitwise_xor.accumulate(sums[row, ::-1]).tolist()
            for deep, (u, v, chk) in enumerate(tail):
                if u < v and (u or v) and chk == self._hash(u, v, a) * 2**31 + self._hash(u, v, b):
                    h, lvl = self._hash(u, v, rows[sk * self.spec.rows + row]), self.spec.levels - 1 - deep
                    if not h or h & -h >= 1 << lvl:
                        return u, v, chk
        return None

    def edges(self, sums: np.ndarray, x: int) -> list[tuple[int, int]]:
        """x edges from the cells of x sketches and of the spare ones, which it uses up. A sketch that shows no edge is passed over."""
        found, n, sk = [], self.spec.rows, 0
        while len(found) < x:
            if sk * n == len(sums):
                raise SketchExhausted(f"{len(found)} of {x} edges of a bucket are shown by its {sk} sketches")
            e = self.one(sums[sk * n : (sk + 1) * n], sk)
            sk += 1
            if e is None:
                continue
            found.append(e[:2])
            if len(found) < x:
                lvl = self._levels(_hashes(np.array([e[0] % P]), np.array([e[1] % P]), self.row[sk * n : len(sums)]))[:, 0]
                sums[np.arange(sk * n, len(sums)), lvl] ^= np.array(e)
        return found

    def shown(self, at: np.ndarray, u: np.ndarray, v: np.ndarray, chk: np.ndarray, c: np.ndarray, fu: np.ndarray, fv: np.ndarray, waits: np.ndarray) -> None:
        """Puts the edges that a row, of coefficients c, shows of each bucket into fu and fv: of the highest level that does. Such buckets wait no more. at: the updates' buckets, in order."""
        lvl = self._levels(_hashes(_mod(u), _mod(v), c[None])[0])
        for deep in range(self.spec.levels):
            if deep:
                keep = np.flatnonzero(lvl >= deep)
                at, u, v, chk, lvl = at[keep], u[keep], v[keep], chk[keep], lvl[keep]
            if not len(at):
                break
            start = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
            own, xu, xv, sums = at[start], *(np.bitwise_xor.reduceat(x, start) for x in (u, v, chk))
            some = xu < xv
            own, xu, xv, sums = own[some], xu[some], xv[some], sums[some]
            mu, mv = _mod(xu), _mod(xv)
            one = _hashes(mu, mv, self.chk)
            good = (one[0] * 2**31 + one[1] == sums) & (self._levels(_hashes(mu, mv, c[None])[0]) >= deep)
            own = own[good]
            fu[own], fv[own], waits[own] = xu[good], xv[good], False

    def drawn_together(self, bucket: np.ndarray, asked: np.ndarray, u: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
        """The edges (bucket, u, v) drawn from many small buckets, given in order and with all their updates; a bucket is asked for the most that its rows say.

        Updates of a bucket are fewer than its cells, so they are what is stored: a row's cells are made when it is asked, of
        all buckets whose rows before show nothing, and a found edge leaves the updates, and thereby all later sketches. The
        edges are those of edges().
        """
        first = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
        names, x, at = bucket[first], np.maximum.reduceat(asked, first), np.repeat(np.arange(len(first)), np.diff(np.append(first, len(bucket))))
        real = (u != v) & (x > 0)[at]
        at, u, v = at[real], u[real], v[real]
        one = _hashes(_mod(u), _mod(v), self.chk)
        chk = one[0] * 2**31 + one[1]
        order = np.lexsort((chk, at))
        at, u, v, chk = at[order], u[order], v[order], chk[order]
        # an even number of equal updates adds nothing to any cell, an odd one what one of them adds
        run = np.flatnonzero(np.append(True, (at[1:] != at[:-1]) | (u[1:] != u[:-1]) | (v[1:] != v[:-1])))
        run = run[np.diff(np.append(run, len(at))) % 2 == 1]
        at, u, v, chk = at[run], u[run], v[run], chk[run]
        got, out, sk = np.zeros(len(names), dtype=np.int64), [], 0
        while len(open_ := np.flatnonzero(got < x)):
            short = open_[x[open_] + SPARE <= sk]
            if len(short):
                raise SketchExhausted(f"{got[short[0]]} of {x[short[0]]} edges of a bucket are shown by its {sk} sketches")
            keep = (got < x)[at]
            at, u, v, chk = at[keep], u[keep], v[keep], chk[keep]
            fu, fv, waits = np.zeros(len(names), dtype=np.int64), np.zeros(len(names), dtype=np.int64), got < x
            for row in range(self.spec.rows):
                asks = waits[at]
                if not asks.any():
                    break
                asking = (at, u, v, chk) if asks.all() else (at[asks], u[asks], v[asks], chk[asks])
                self.shown(*asking, self.row[sk * self.spec.rows + row], fu, fv, waits)
            own = np.flatnonzero((got < x) & ~waits)
            got[own] += 1
            out.append((names[own], fu[own], fv[own]))
            keep = (u != fu[at]) | (v != fv[at])
            at, u, v, chk = at[keep], u[keep], v[keep], chk[keep]
            sk += 1
        return self.batch(*(np.concatenate(c) for c in zip(*out))) if out else self.batch(*[np.zeros(0, dtype=np.int64)] * 3)

    def drawn(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Updates (bucket, asked, u, v) in order of buckets to the edges (bucket, u, v) drawn. Rows with u = v are no updates.

        Of a bucket that alone has more updates than room, only its cells are held: of all sketches, as its number may come last.
        """
        now, x, sums, held, n = None, 0, None, [], 0

        def add(asked, u, v):
            real = u != v
            self.add(sums, u[real], v[real])
            return max(x, int(asked.max(initial=0)))

        def done():
            return self.batch(*np.array([(now, u, v) for u, v in self.edges(sums[: (x + SPARE) * self.spec.rows], x)], dtype=np.int64).reshape(-1, 3).T)

        for batch in batches:
            cols = [batch[c].to_numpy() for c in ("bucket", "asked", "u", "v")]
            if sums is not None:
                end = int(np.searchsorted(cols[0], now, side="right"))
                x = add(*[c[:end] for c in cols[1:]])
                if end == len(cols[0]):
                    continue
                yield done()
                sums, cols = None, [c[end:] for c in cols]
            held.append(cols)
            n += len(cols[0])
            if n < self.room:
                continue
            cols = [np.concatenate(c) for c in zip(*held)]
            last = int(np.searchsorted(cols[0], cols[0][-1]))
            if last:
                yield self.drawn_together(*[c[:last] for c in cols])
            held, n = [[c[last:] for c in cols]], n - last
            if n >= self.room:
                now, x = int(cols[0][-1]), 0
                sums = np.zeros((self.spec.sketches * self.spec.rows, self.spec.levels, 3), dtype=np.int64)
                x = add(*[c[last:] for c in cols[1:]])
                held, n = [], 0
        if sums is not None:
            yield done()
        if n:
            yield self.drawn_together(*[np.concatenate(c) for c in zip(*held)])

    @staticmethod
    def batch(*columns: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["bucket", "u", "v"])


def bucket_sample(bucketed: DataFrame, numbers: DataFrame, spec: SketchSpec) -> DataFrame:
    """(bucket, u, v): x edges of each bucket without replacement, recovered from its sketches.

    The narrow updates and each bucket's number travel once, to their buckets; cells are made there, in arrays, of many buckets together.
    """
    asked, most = asked_for(numbers, spec)
    rec = bucketed.select(F.col("bucket").cast("long").alias("bucket"), F.lit(0).cast("long").alias("asked"), "u", "v")
    rec = rec.unionAll(asked.select("bucket", F.col("asked").cast("long"), F.lit(0).cast("long").alias("u"), F.lit(0).cast("long").alias("v")))
    n = int(bucketed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rec.repartition(n, F.xxhash64("bucket")).sortWithinPartitions("bucket").mapInArrow(Draw(replace(spec, sketches=most + SPARE)).drawn, "bucket long, u long, v long")


def live_vertices(updates: DataFrame) -> DataFrame:
    """(x): vertices with an edge left, from a signed degree counter for each."""
    ends = updates.select(F.explode(F.array("u", "v")).alias("x"), "delta")
    return ends.groupBy("x").agg(F.sum("delta").alias("deg")).filter("deg > 0").select("x")


def densest_subgraph(updates: DataFrame, eps: float, seed: int = 9, peeling: str = "sequential", partitions: str = "single", rows: int = ROWS) -> dict:
    """{density, vertices, p, edges, sample, regime, large, drawn (DataFrame bucket, u, v), numbers (DataFrame bucket, n, x)}; density within a factor 2 (1 + eps) with high probability.

    Every surviving edge is sampled with p = V log V / (eps^2 E), at most 1 (regime "exact"). partitions "single": one
    log V-wise independent partition into V / eps^2 buckets with log2(V)**2 sketches each; the buckets are small with
    high probability, and large tells how many are not. "parallel", the earlier form: log V pairwise independent
    partitions, of whose buckets only the small ones (4 eps^2 E / V edges) are drawn from; an edge counts in its first
    small bucket. peeling "batch" peels in Spark once the sample is beyond one solver's size.
    """
    e = updates.agg(F.sum("delta")).first()[0] or 0
    v = live_vertices(updates).count()
    if not e:  # every edge was deleted again, or there was none
        none = lambda schema: updates.sparkSession.createDataFrame([], schema)
        return {"density": 0.0, "vertices": [], "p": 1.0, "edges": 0, "sample": 0, "regime": "exact", "large": 0, "drawn": none("bucket long, u long, v long"), "numbers": none("bucket long, n long, x long")}
    log = math.ceil(math.log2(max(2, v)))
    p = min(1.0, v * math.log2(max(2, v)) / (eps * eps * e))
    buckets, small = max(1, math.ceil(v / (eps * eps))), 4 * eps * eps * e / v
    levels = math.ceil(math.log2(max(2.0, small))) + 8
    narrow = updates.select("u", "v", "delta")
    if partitions == "single":
        bucketed = cut(in_buckets(narrow, buckets, seed, max(16, log)))
        numbers = cut(drawn_numbers(counters(bucketed), p, seed))
        spec = SketchSpec(rows=rows, levels=levels, sketches=max(8, log * log), seed=seed)
        drawn = cut(bucket_sample(bucketed, numbers, spec))
        sample = drawn.select("u", "v")
    else:
        place = [bucket_of(F.col("u"), F.col("v"), buckets, seed + j, 2).cast("long") * log + j for j in range(log)]
        bucketed = cut(narrow.select("u", "v", "delta", F.explode(F.array(*place)).alias("bucket")))
        numbers = cut(drawn_numbers(counters(bucketed).filter(F.col("n") <= small), p, seed))
        spec = SketchSpec(rows=rows, levels=levels, sketches=max(8, math.ceil(small)), seed=seed)
        drawn = cut(bucket_sample(bucketed, numbers, spec))
        earlier = drawn.select("bucket", "u", "v", F.explode(F.array(*place)).alias("other")).filter(F.col("other") % log < F.col("bucket") % log)
        counted = earlier.join(numbers.select(F.col("bucket").alias("other")), "other", "left_semi").select("bucket", "u", "v").distinct()
        sample = cut(drawn.join(counted, ["bucket", "u", "v"], "left_anti").select("u", "v"))
    size = sample.count()
    if peeling == "batch":
        density, vertices = peeled(sample)
    else:
        density, vertices = peeled_in_order(sample)
    large = numbers.filter(F.col("n") > small).count()
    return {"density": density / p, "vertices": vertices, "p": p, "edges": e, "sample": size, "regime": "exact" if p == 1 else "sampled", "large": large, "drawn": drawn, "numbers": numbers}


def peeled_in_order(edges: DataFrame, limit: int | None = None) -> tuple[float, list[int]]:
    """peel() of the distinct edges, beyond one solver's size too.

    Whoever removes a vertex of degree below the density raises the density. Peeling does nothing else until all degrees
    have reached it, so the densest stage comes no sooner, and up to there vertices may leave in any order: all at once, in
    Spark, until what is left fits the solver. What is larger still, with every degree at the density or above, is an error.
    """
    limit, live = kconn.ARRAYS if limit is None else limit, edges.select("u", "v")
    while (m := live.count()) > limit:
        deg = cut(live.select(F.explode(F.array("u", "v")).alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("deg")))
        n = deg.count()
        high = deg.filter(F.col("deg") * n >= m).select("x")
        if high.count() == n:
            raise kconn.TooLarge(f"more than {limit} edges, and every vertex has the density or more")
        live = fresh(cut(live.join(high.withColumnRenamed("x", "u"), "u", "left_semi").join(high.withColumnRenamed("x", "v"), "v", "left_semi").select("u", "v")))
    return peel_arrays(*kconn.as_arrays(live))


def peeled(edges: DataFrame, delta: float = 0.1, local: int = 200_000) -> tuple[float, list[int]]:
    """(density, vertices): all vertices of degree (1 + delta) times twice the density or less go, round after round; in Spark until what is left fits one solver, within a factor 2 (1 + delta)."""
    live, best, kept = edges.select("u", "v"), 0.0, None
    while (m := live.count()) > local:
        deg = cut(live.select(F.explode(F.array("u", "v")).alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("deg")))
        density = m / deg.count()
        if density > best:
            best, kept = density, deg.select("x")
        high = deg.filter(F.col("deg") > 2 * (1 + delta) * density).select("x")
        live = fresh(cut(live.join(high.withColumnRenamed("x", "u"), "u", "left_semi").join(high.withColumnRenamed("x", "v"), "v", "left_semi").select("u", "v")))
    rest = live.toArrow()
    density, vertices = peel_batch_arrays(rest["u"].to_numpy(), rest["v"].to_numpy(), delta)
    if density >= best or kept is None:
        return density, vertices
    return best, np.sort(kept.toArrow()["x"].to_numpy()).tolist()
