"""N-gram Jaccard join: near duplicates on word shingles, with Bayesian pruning and exact verification.

1. Every document's distinct shingles (WIDTH words; a document of fewer words has its whole word sequence as its one
   shingle) give a 128-bit key, the same for documents of equal shingle sets: those form a class and are compared once.
2. BANDS bands of ROWS MinHash values: a pair of similarity 0.8 shares no band with probability (1 - 0.8^6)^45, about one in
   a million; a pair sharing one passage shares a band hardly ever. Each bucket links its classes to its least class, so
   a bucket of any size gives one edge a member, and the components of these edges are the candidate clusters; most
   of a large group meets in the first few bands, and the others then see it as one.
3. Clusters are dealt to blocks by a hash of the member, a block pair a group: no group grows with the cluster. In a
   group, MinHash values are compared STEP at a time; a pair whose posterior probability of similarity >= threshold
   (uniform prior) falls below TOLERANCE is dropped, and every other pair is verified on its shingle sets. A group
   returns each class's number of links and a spanning forest of the links, not the pairs.
4. Components of the forests are the near-duplicate groups.

Defined results: a document without words (null and empty texts too) links to none and is its own group. Rows of equal
doc_id are rows like others. A group's id is its least doc_id, null last. Empty tables give empty tables. Other columns
are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from .common import boxed, columns, components, cut, hash_words, mix64, trim_memory, windows

WIDTH, THRESHOLD, BANDS, ROWS, STEP, TOLERANCE = 5, 0.8, 45, 6, 32, 1e-7
BLOCK_ROWS, BLOCK_SHINGLES, FEW = 512, 400_000, 5
_CHUNK = 2048
_MULTIPLIERS = np.random.default_rng(17).integers(0, 2**31, BANDS * ROWS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)


def shingle_sets(texts: pa.Array, width: int = WIDTH) -> list[np.ndarray]:
    """Each text's sorted distinct 64-bit shingle hashes."""
    h, ends = hash_words(texts)
    own = (h[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist()))
    return [np.unique(windows(x, min(width, len(x)))) if len(x) else x for x in own]


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """MinHash values, a row for each set; all sets have a shingle."""
    out = np.full((len(sets), BANDS * ROWS), 2**32 - 1, dtype=np.uint32)
    x = np.concatenate([(s >> np.uint64(32)).astype(np.uint32) for s in sets])
    own = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    for a in range(0, len(x), _CHUNK):
        part = own[a : a + _CHUNK]
        starts = np.flatnonzero(np.diff(part, prepend=-1))
        least = np.minimum.reduceat(x[a : a + _CHUNK, None] * _MULTIPLIERS, starts, axis=0)
        at = part[starts]
        out[at] = np.minimum(out[at], least)
    return out


def band_hashes(sig: np.ndarray) -> np.ndarray:
    s = sig.reshape(len(sig), BANDS, ROWS).astype(np.uint64)
    with np.errstate(over="ignore"):
        h = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), s.shape[:2]).copy()
        for r in range(ROWS):
            h = mix64(h * np.uint64(0x9E3779B97F4A7C15) + s[:, :, r])
    return h.view(np.int64)


def keep_from(n: int, threshold: float, tolerance: float) -> int:
    """The fewest matches among n values with which P(similarity >= threshold | matches) reaches tolerance.

    With a uniform prior the posterior is a Beta law, and its tail is P(Binomial(n + 1, threshold) <= matches).
    """
    total = 0.0
    for m in range(n + 2):
        total += comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        if total >= tolerance:
            return m
    return n


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for a in range(0, whole.num_rows, 1000):
            b = whole.slice(a, 1000)
            sets = shingle_sets(b["text"])
            some = [i for i, s in enumerate(sets) if len(s)]
            keys = [xxhash.xxh3_128_intdigest(s.tobytes()) if len(s) else None for s in sets]
            bands: list = [None] * len(sets)
            if some:
                for i, row in zip(some, band_hashes(signatures([sets[i] for i in some]))):
                    bands[i] = row
            half = lambda shift: pa.array([None if k is None else ((k >> shift) & (2**64 - 1)) - 2**63 for k in keys], pa.int64())
            yield pa.RecordBatch.from_arrays([b["doc_id"], b["d1"], b["d2"], half(0), half(64), pa.array(list(map(len, sets)), pa.int32()), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "d1", "d2", "k1", "k2", "n", "bands"])
    trim_memory()


def _payload(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for a in range(0, whole.num_rows, 1000):
            b = whole.slice(a, 1000)
            sets = shingle_sets(b["text"])
            sig = signatures(sets)
            yield pa.RecordBatch.from_arrays([*[b[c] for c in ("root", "blocks", "k1", "k2", "m")], pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([s[: 4 * STEP].tobytes() for s in sig], pa.binary())], ["root", "blocks", "k1", "k2", "m", "set", "sig"])
    trim_memory()


def links_in(sig: np.ndarray, sets: list[np.ndarray], left: np.ndarray, right: np.ndarray | None, threshold: float = THRESHOLD, tolerance: float = TOLERANCE) -> tuple[np.ndarray, np.ndarray]:
    """Linked pairs (i, j) of places left x right, or of all pairs i < j of left if right is None."""
    cols = left if right is None else right
    match = np.zeros((len(left), len(cols)), dtype=np.int16)
    for h in range(STEP):
        match += sig[left, h][:, None] == sig[cols, h][None, :]
    ok = match >= keep_from(STEP, threshold, tolerance)
    if right is None:
        ok = np.triu(ok, 1)
    p, q = np.nonzero(ok)
    seen, i, j = match[p, q].astype(np.int32), left[p], cols[q]
    for done in range(STEP, sig.shape[1], STEP):
        seen = seen + (sig[i, done : done + STEP] == sig[j, done : done + STEP]).sum(1, dtype=np.int32) if len(i) < 200_000 else seen + np.concatenate([(sig[i[a : a + 100_000], done : done + STEP] == sig[j[a : a + 100_000], done : done + STEP]).sum(1, dtype=np.int32) for a in range(0, len(i), 100_000)])
        go = seen >= keep_from(done + STEP, threshold, tolerance)
        i, j, seen = i[go], j[go], seen[go]
    size = np.array([len(s) for s in sets])
    if len(i) > 2000:  # many pairs: incidence matrices over the group's shingles, a slice of shingles at a time
        flat, at = np.unique(np.concatenate(sets), return_inverse=True)
        own = np.repeat(np.arange(len(sets)), size)
        order = np.argsort(at, kind="stable")
        at, own = at[order], own[order]
        both = np.zeros((len(sets), len(sets)), dtype=np.float32)
        for a in range(0, len(flat), 4096):
            lo, hi = np.searchsorted(at, [a, a + 4096])
            m = np.zeros((len(sets), min(4096, len(flat) - a)), dtype=np.float32)
            m[own[lo:hi], at[lo:hi] - a] = 1
            both += m @ m.T
        common = both[i, j].astype(np.int64)
    else:
        common = np.array([len(np.intersect1d(sets[x], sets[y], assume_unique=True)) for x, y in zip(i, j)], dtype=np.int64)
    go = common >= threshold * (size[i] + size[j] - common) - 1e-9
    return i[go], j[go]


def _group(rows: list[tuple], cross: bool) -> tuple[list, list]:
    """(k1, k2, links, documents linked) of classes with a link, and forest edges (k1, k2, k1, k2). rows: block, k1, k2, m, set, sig."""
    rows = [r for i, r in enumerate(rows) if not i or r[:3] != rows[i - 1][:3]]  # a class may have come from several equal rows
    sig = np.array([np.frombuffer(r[5], dtype=np.uint32) for r in rows])
    sets = [np.frombuffer(r[4], dtype=np.uint64) for r in rows]
    blk = np.array([r[0] for r in rows])
    if cross:
        i, j = links_in(sig, sets, np.flatnonzero(blk == blk.min()), np.flatnonzero(blk == blk.max())) if blk.min() != blk.max() else (np.empty(0, int), np.empty(0, int))
    else:
        i, j = links_in(sig, sets, np.arange(len(rows)), None)
    if not len(i):
        return [], []
    m = np.array([r[3] for r in rows], dtype=np.int64)
    links, docs = np.zeros(len(rows), dtype=np.int64), np.zeros(len(rows), dtype=np.int64)
    for a, b in ((i, j), (j, i)):
        np.add.at(links, a, 1)
        np.add.at(docs, a, m[b])
    up = list(range(len(rows)))

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    forest = []
    for a, b in zip(i.tolist(), j.tolist()):
        x, y = root(a), root(b)
        if x != y:
            up[x] = y
            forest.append((*rows[a][1:3], *rows[b][1:3]))
    return [(*rows[x][1:3], int(links[x]), int(docs[x])) for x in np.flatnonzero(links)], forest


_OUT = "k1 long, k2 long, links long, docs long, o1 long, o2 long"


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    key, rows = None, []

    def flush() -> pa.RecordBatch:
        nodes, forest = _group(rows, key[1] != key[2])
        out = [(a, b, n, d, None, None) for a, b, n, d in nodes] + [(a, b, None, None, c, d) for a, b, c, d in forest]
        return pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], pa.int64()) for c in range(6)], ["k1", "k2", "links", "docs", "o1", "o2"])

    for b in batches:
        for r in zip(*(b[c].to_pylist() for c in ("root", "bi", "bj", "blk", "k1", "k2", "m", "set", "sig"))):
            if r[:3] != key:
                if len(rows) > 1:
                    yield flush()
                key, rows = r[:3], []
            rows.append(r[3:])
    if len(rows) > 1:
        yield flush()
    rows = []
    trim_memory()


def _identified(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, text and a 128-bit hash (d1, d2) of both, by which rows meet again."""
    d = columns(docs, doc_id=id_col, text=text_col)
    parts = [F.col("doc_id"), F.col("doc_id").isNull(), F.col("text")]
    return d.withColumn("d1", F.xxhash64(*parts)).withColumn("d2", F.xxhash64(F.lit("second"), *parts))


def _clusters(sketched: DataFrame) -> DataFrame:
    """(node, root): the candidate cluster of every class that shares a bucket with another.

    The first FEW bands come first and most members of a group meet there; the other bands then deal with the clusters
    found so far, of which a bucket holds few, instead of with each member again.
    """
    found = None
    for a, b in ((0, FEW), (FEW, BANDS)):
        rows = sketched.select("k1", F.slice("bands", a + 1, b - a).alias("bands"))
        if found is not None:
            rows = rows.join(found.select(F.col("node").alias("k1"), "root"), "k1", "left").select(F.coalesce("root", "k1").alias("k1"), "bands")
        in_band = rows.select("k1", F.explode("bands").alias("bh"))
        shared = in_band.groupBy("bh").agg(F.min("k1").alias("lo"), F.max("k1").alias("hi")).filter("lo <> hi").select("bh", "lo")
        joined = components(in_band.join(shared, "bh").filter("k1 <> lo").select("k1", "lo").distinct(), "k1", "lo")
        if found is None:
            found = joined
        else:
            j = joined.select(F.col("node").alias("root"), F.col("root").alias("higher"))
            old = found.join(j, "root", "left").select("node", F.coalesce("higher", "root").alias("root"))
            found = old.unionByName(joined.join(found, "node", "left_anti"))
    return found


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, d1, d2, class_id, first struct, n_links, n_text_links, n_copies, n_shingles): a row for each row of docs.

    class_id: the least doc_id of the group of documents connected by links; first: (no id, doc_id, d1, d2) of the
    group's first row; n_links: other documents of similarity >= 0.8, copies included; n_text_links: linked classes of
    equal shingle sets; n_copies: documents of the own class.
    """
    d = _identified(docs, id_col, text_col)
    kind = dict(d.dtypes)["doc_id"]
    t = cut(d.select("doc_id", "d1", "d2", "text").mapInArrow(_sketch, f"doc_id {kind}, d1 long, d2 long, k1 long, k2 long, n int, bands array<long>"))
    place = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "d1", "d2")
    some = t.filter("n > 0")
    classes = cut(some.groupBy("k1", "k2").agg(F.min(place).alias("rep"), F.count(F.lit(1)).alias("m"), F.max("n").alias("n")))
    cluster = _clusters(some)
    members = classes.join(cluster.select(F.col("node").alias("k1"), "root"), "k1")
    sizes = members.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_ROWS), F.ceil(F.sum("n") / BLOCK_SHINGLES)).alias("blocks"))
    members = members.join(sizes, "root").select(F.col("rep.d1").alias("d1"), F.col("rep.d2").alias("d2"), "root", "blocks", "k1", "k2", "m")
    with_text = d.select("d1", "d2", "text").join(members, ["d1", "d2"]).select("root", "blocks", "k1", "k2", "m", "text")
    payload = with_text.mapInArrow(_payload, "root long, blocks long, k1 long, k2 long, m long, set binary, sig binary")
    payload = payload.withColumn("blk", F.pmod(F.xxhash64("k2", "k1"), "blocks")).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = payload.select("root", F.least("blk", "other").alias("bi"), F.greatest("blk", "other").alias("bj"), "blk", "k1", "k2", "m", "set", "sig")
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = cut(dealt.repartition(n, "root", "bi", "bj").sortWithinPartitions("root", "bi", "bj", "blk", "k1", "k2").mapInArrow(_verify, _OUT))
    counts = found.filter("o1 is null").groupBy("k1", "k2").agg(F.sum("links").alias("links"), F.sum("docs").alias("docs"))
    groups = components(found.filter("o1 is not null").select(F.struct("k1", "k2").alias("a"), F.struct(F.col("o1").alias("k1"), F.col("o2").alias("k2")).alias("b")))
    groups = groups.select(F.col("node.k1").alias("k1"), F.col("node.k2").alias("k2"), "root")
    full = classes.join(groups, ["k1", "k2"], "left").join(counts, ["k1", "k2"], "left")
    full = full.select("k1", "k2", "rep", "m", F.coalesce("root", F.struct("k1", "k2")).alias("root"), F.coalesce("links", F.lit(0)).cast("long").alias("links"), F.coalesce("docs", F.lit(0)).cast("long").alias("docs"))
    first = full.groupBy("root").agg(F.min("rep").alias("first"))
    full = full.join(first, "root").select("k1", "k2", "first", "m", "links", "docs")
    out = some.select("doc_id", "d1", "d2", "k1", "k2", "n").join(full, ["k1", "k2"])
    cols = [F.col("first.doc_id").alias("class_id"), "first", (F.col("docs") + F.col("m") - 1).alias("n_links"), F.col("links").alias("n_text_links"), F.col("m").alias("n_copies"), F.col("n").alias("n_shingles")]
    alone = t.filter("n = 0").select("doc_id", "d1", "d2", F.col("doc_id").alias("class_id"), place.alias("first"), F.lit(0).cast("long").alias("n_links"), F.lit(0).cast("long").alias("n_text_links"), F.lit(1).cast("long").alias("n_copies"), F.lit(0).alias("n_shingles"))
    return out.select("doc_id", "d1", "d2", *cols).unionByName(alone)


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay, one of each group (its first by doc_id), with docs' columns; documents without words all stay."""
    found = near_duplicates(docs, id_col, text_col)
    stay = found.filter("first.d1 = d1 and first.d2 = d2").groupBy("d1", "d2").agg(F.max("n_shingles").alias("shingles"))
    parts = [F.col(f"`{id_col}`"), F.col(f"`{id_col}`").isNull(), F.col(f"`{text_col}`")]
    # rows of equal id and text may differ in other columns: the choice among them is by a hash, so that reruns agree
    others = [F.col(f"`{c}`") for c, kind in docs.dtypes if c not in (id_col, text_col) and "map<" not in kind and "variant" not in kind]
    keyed = boxed(docs, d1=F.xxhash64(*parts), d2=F.xxhash64(F.lit("second"), *parts), other=F.xxhash64(F.lit(0), *others))
    once = F.row_number().over(W.partitionBy("d1", "d2").orderBy("other"))
    return keyed.join(stay, ["d1", "d2"]).withColumn("once", once).filter("once = 1 or shingles = 0").select("_row.*")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "n_links", "n_text_links", "n_copies")
