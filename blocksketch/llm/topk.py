"""Exact top-k search by integer inner product: MaxScore inside each shard, and a merge of shards.

A vector's dimensions are its terms. A shard keeps postings by term: the column of that dimension over the shard's rows,
in chunks of CHUNK rows with the chunk's least and largest value of each term; rows come by falling length, so that
good scores come early. For a query, a term adds at most |q_d| * (high - low) to the least a row of the chunk can
have. For every query and chunk, the terms are split by these bounds against the query's running k-th best score: the
smallest ones, which together cannot bring a row up to it, are non-essential. The postings of the essential terms are
traversed for all rows of the chunk (with none essential, the chunk is passed over); the others are probed, the largest
bounds first, only in rows whose partial score plus the bounds of what is left still reaches the running score. Rows
that tie with it stay in. Exact scores then raise the running score for the next chunk.

Vectors are dealt to shards and packed, a block of rows each; queries are packed into blocks, and each block of queries
meets each shard once: both go to the shard's task by one exchange, the shard's rows first. That is no join, whose query
side Spark takes for small and broadcasts, with all its copies, through the driver. Packed numbers are as narrow as they
can be, and shards grow with the vectors (to LARGE rows), as queries travel once for every shard. Every shard returns k
rows a query, and a window over a query's rows merges the shards.

Defined results: vectors that are null, empty, or hold a null or non-finite component take no part. Vectors of different
lengths score as if the shorter ended in zeros. A row with the query's own id is never its result, and repeated query
ids ask once (the least vector by components). A null id is never a query and sorts last among ties. Fewer than k
candidates give fewer rows. Components are floored to integers in double precision; sums are exact to 2**53, and a
shard whose bounds go beyond that is scored in Python integers; a score that no long can hold is an error.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import columns

SHARD, LARGE, SHARDS, BLOCK, CHUNK, PROBE, EXACT = 8192, 65536, 64, 256, 2048, 8, 2.0**52
NO_ID = 2**63 - 1
_PACK = "blk long, ids array<long>, dims int, kind string, data binary"


def quantised(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256) -> DataFrame:
    """(vec_id long, v array<double> of integers)."""
    v = columns(vectors, vec_id=id_col, v=vector_col).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("v").cast("array<double>").alias("v"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return v.filter(F.col("v").isNotNull() & (F.size("v") > 0) & finite).select("vec_id", F.transform("v", lambda x: F.floor(x * float(scale)).cast("double")).alias("v"))


def _narrowest(m: np.ndarray) -> str:
    """The narrowest type that holds a matrix of whole doubles."""
    most = np.abs(m).max(initial=0)
    return next((t for t in ("i1", "i2", "i4") if most <= np.iinfo(t).max), "f8")


def _matrix(data: bytes, kind: str, dims: int) -> np.ndarray:
    return np.frombuffer(data, dtype=kind).reshape(-1, dims).astype(float)


def _packer(size: int):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids: list = []
        rows: list[np.ndarray] = []
        blk = None

        def flush() -> pa.RecordBatch:
            dims = max(map(len, rows))
            m = np.zeros((len(rows), dims))
            for i, r in enumerate(rows):
                m[i, : len(r)] = r
            kind = _narrowest(m)
            return pa.RecordBatch.from_arrays([pa.array([blk], pa.int64()), pa.array([ids], pa.list_(pa.int64())), pa.array([dims], pa.int32()), pa.array([kind]), pa.array([m.astype(kind).tobytes()], pa.binary())], ["blk", "ids", "dims", "kind", "data"])

        for b in batches:
            for k, i, v in zip(b["blk"].to_pylist(), b["vec_id"].to_pylist(), b["v"]):
                if rows and (k != blk or len(rows) >= size):
                    yield flush()
                    ids, rows = [], []
                blk = k
                ids.append(i)
                rows.append(np.asarray(v.values))
        if rows:
            yield flush()

    return pack


def _packed(vectors: DataFrame, size: int, n: int) -> DataFrame:
    blocks = max(1, -(-n // size))
    dealt = vectors.withColumn("blk", F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks))).repartition(blocks, "blk").sortWithinPartitions("blk", "vec_id", "v")
    return dealt.select("blk", "vec_id", "v").mapInArrow(_packer(size), _PACK)


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best by score, then by id; all places that tie with the k-th are looked at."""
    if len(scores) > k:
        cut = np.partition(scores, len(scores) - k)[len(scores) - k]
        at = np.flatnonzero(scores >= cut)
    else:
        at = np.arange(len(scores))
    return at[np.lexsort((ids[at], -scores[at]))[:k]]


class Shard:
    """Postings by term, in chunks of rows. probed counts the terms of rows that were read, of all that there are."""

    def __init__(self, rows: np.ndarray, ids: list, chunk: int = CHUNK):
        order = np.argsort(-np.einsum("ij,ij->i", rows, rows), kind="stable")
        x = rows[order]
        self.ids = [ids[i] for i in order.tolist()]
        self.rank = np.array([NO_ID if i is None else i for i in self.ids], dtype=np.int64)
        self.place: dict = {}
        for n, i in enumerate(self.ids):
            self.place.setdefault(i, []).append(n)
        self.rows, self.chunk = x, chunk
        self.largest = np.abs(x).max(0)
        self.chunks = [(a, np.ascontiguousarray(x[a : a + chunk].T), x[a : a + chunk].max(0), x[a : a + chunk].min(0)) for a in range(0, len(x), chunk)]
        self.probed = self.every = 0

    def best(self, q: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, scores) of the query's k best rows other than its own."""
        mine = self.place.get(own, ())
        top, score = np.empty(0, dtype=np.int64), np.empty(0)
        size = np.abs(q)
        for a, post, high, low in self.chunks:
            dims, n = post.shape
            bound = size * (high - low)
            order = np.argsort(-bound)
            left = np.append(np.cumsum(bound[order][::-1])[::-1], 0.0)  # what the terms from a place on can add
            least = np.minimum(q * high, q * low)[order]
            base = least.sum()
            need = score[-1] - base if len(score) == k else -1.0  # beyond the least a row can have
            split = int(np.searchsorted(-left, -need, "right")) if need > 0 else dims  # terms from there on are non-essential
            self.every += dims * n
            if not split:
                continue
            e = order[:split]
            got = q[e] @ post[e] - least[:split].sum()
            self.probed += split * n
            at = np.flatnonzero(got + left[split] >= need)
            if mine:
                at = at[~np.isin(at + a, mine)]
            got, step = got[at], PROBE
            while split < dims and len(at):
                t = order[split : split + step]
                got = got + self.rows[a + at[:, None], t] @ q[t] - least[split : split + step].sum()
                self.probed += len(t) * len(at)
                split, step = split + len(t), 2 * step
                go = got + left[split] >= need
                at, got = at[go], got[go]
            if len(at):
                places, scores = np.append(top, at + a), np.append(score, got + base)
                keep = _best(scores, self.rank[places], k)
                top, score = places[keep], scores[keep]
        return top, score


class Rows:
    """One shard's rows, with postings made once for each number of dimensions that is asked for."""

    def __init__(self, rows: np.ndarray, ids: list):
        self.rows, self.ids, self.largest, self.shards = rows, ids, np.abs(rows).max(0), {}

    def search(self, queries: np.ndarray, q_ids: list, k: int) -> Iterator[tuple[int, int | None, int]]:
        """(query id, row id, score): each query's k best rows of the shard."""
        dims = max(queries.shape[1], self.rows.shape[1])
        wide = lambda m: np.pad(m, ((0, 0), (0, dims - m.shape[1]))) if m.shape[1] < dims else m
        q = wide(queries)
        if (np.abs(q) @ wide(self.largest[None])[0]).max() >= EXACT:
            x = wide(self.rows)
            for n, qi in enumerate(q_ids):
                own = [int(a) for a in q[n]]
                got = sorted((-sum(a * int(b) for a, b in zip(own, r)), i is None, i or 0, i) for i, r in zip(self.ids, x) if i != qi)[:k]
                yield from ((qi, i, -s) for s, _, _, i in got)
            return
        shard = self.shards.get(dims)
        if shard is None:
            shard = self.shards[dims] = Shard(wide(self.rows), self.ids)
        for n, qi in enumerate(q_ids):
            for p, s in zip(*shard.best(q[n], qi, k)):
                yield qi, shard.ids[p], int(s)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """(query_id, rank, vec_id, score); both inputs as from quantised()."""
    asked = queries.filter("vec_id is not null").groupBy("vec_id").agg(F.min("v").alias("v"))
    n, m = vectors.count(), asked.count()
    size = min(LARGE, max(SHARD, -(-n // SHARDS)))
    n_shards = max(1, -(-n // size))
    packed = ("ids", "dims", "kind", "data")
    shards = _packed(vectors, size, n).select(F.col("blk").alias("shard"), F.lit(0).alias("part"), *packed)
    everywhere = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_shards - 1).cast("long"))).alias("shard")
    blocks = _packed(asked, BLOCK, m).select(everywhere, F.lit(1).alias("part"), *packed)
    met = shards.union(blocks).repartition(n_shards, "shard").sortWithinPartitions("shard", "part")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, rows = None, []
        for b in batches:
            for shard, part, ids, dims, kind, data in zip(*(b[c] for c in ("shard", "part", *packed))):
                if shard.as_py() != at:
                    at, rows = shard.as_py(), []
                x, ids = _matrix(data.as_py(), kind.as_py(), dims.as_py()), ids.as_py()
                if part.as_py() == 0:
                    rows.append(Rows(x, ids))
                    continue
                got = [g for r in rows for g in r.search(x, ids, k)]
                yield pa.RecordBatch.from_arrays([pa.array([g[c] for g in got], pa.int64()) for c in range(3)], ["query_id", "vec_id", "score"])

    found = met.mapInArrow(search, "query_id long, vec_id long, score long")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), F.asc_nulls_last("vec_id")))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    v = quantised(table(spark, sf_dir, "embeddings"))
    return top_k(v, v.filter("vec_id % 50 = 0"), 5)


SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
