"""Substring deduplication by level-wise doubling over hashed word windows.

A window of LENGTH words is removed if its word sequence also starts in a document of smaller doc_id. Levels run from
START words, doubling up to LENGTH. At each level below the last, a window of LENGTH words is stood for by its anchor,
the least hash among the level's shorter windows in it: equal windows have equal anchors, so a window whose anchor
stands in one document alone repeats nowhere and is dropped, and neighbouring windows mostly share an anchor. Only
windows whose anchor repeats go on to twice the length; the last level compares the windows themselves.

Texts are dealt to batches of about BATCH bytes, once; every level reads that one exchange. A batch sends each
partition of the hash space its sorted distinct hashes as one packed row (with the batch's least doc_id for each at
the last level), and gets back those that repeat. A hash is sent once a batch, so a passage in every document makes a
row's worth of entries, not pairs. Levels below the last only choose candidates and use 64 bits; the last one, which
decides, compares windows by 128 bits. remove_repeats() knows its longest window, so its levels are one plan over one
exchange of texts, and a batch without candidates sends nothing to the next; longest_repeats() has no longest window
and doubles, a job a level, until no candidate survives.

Defined results: null and empty texts have no words. Rows of equal doc_id are one document for comparing; each row is
returned. A null doc_id is larger than any other. Empty tables give empty tables. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORDS, columns, cut, hash_words, narrow, pack, unpack, windows

LENGTH, START, BATCH, ENTRIES, TASK, NO_ID = 13, 7, 8_000_000, 1_000_000, 64_000_000, 2**63 - 1


def levels(length: int = LENGTH, start: int = START) -> list[int]:
    out = [min(start, length)]
    while out[-1] < length:
        out.append(min(2 * out[-1], length))
    return out


def sliding_min(x: np.ndarray, n: int) -> np.ndarray:
    """The least of every n consecutive values, by doubling."""
    have = 1
    while have < n:
        step = min(have, n - have)
        x = np.minimum(x[:-step], x[step:])
        have += step
    return x


class Batch:
    """The windows of a batch of documents: anchors of any level, and where each window and document lies."""

    def __init__(self, table: pa.Table, length: int):
        self.ids = np.array([NO_ID if i is None else i for i in table["doc_id"].to_pylist()], dtype=np.int64)
        self.hashes, self.others, ends = hash_words(table["text"].combine_chunks(), lanes=2)
        self.sizes = np.diff(ends, prepend=0)
        self.own = np.repeat(np.arange(len(self.ids)), self.sizes)
        self.start = self.starts(length)
        self.owner = self.ids[self.own[self.start]]
        self.length = length

    def starts(self, length: int) -> np.ndarray:
        """Where the windows inside one document start."""
        m = max(0, len(self.hashes) - length + 1)
        return np.flatnonzero(self.own[:m] == self.own[length - 1 :]) if m else np.empty(0, dtype=np.int64)

    def anchors(self, level: int) -> np.ndarray:
        """One for each window of self.start."""
        if not len(self.start):
            return np.empty(0, dtype=np.uint64)
        return sliding_min(windows(self.hashes, level), self.length - level + 1)[self.start]

    def second(self, at: np.ndarray | slice = slice(None)) -> np.ndarray:
        """The other 64 bits of windows of self.start."""
        return windows(self.others, self.length)[self.start[at]] if len(self.start) else np.empty(0, dtype=np.uint64)


def _least_ids(h: np.ndarray, g: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, ...]:
    """(distinct pairs (h, g) in order, least id of each, greatest id of each)."""
    if not len(h):
        return h, g, ids, ids
    order = np.lexsort((g, h))
    h, g, i = h[order], g[order], ids[order]
    at = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (g[1:] != g[:-1])]))
    return h[at], g[at], np.minimum.reduceat(i, at), np.maximum.reduceat(i, at)


def _place(h: np.ndarray, g: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The place of each pair (x, y) among the ordered distinct pairs (h, g), or -1."""
    if not len(h) or not len(x):
        return np.full(len(x), -1)
    at = np.searchsorted(h, x)
    out = np.full(len(x), -1)
    live = np.flatnonzero(at < len(h))
    while len(live):  # pairs of equal h lie next to each other, hardly ever more than one
        live = live[h[at[live]] == x[live]]
        hit = g[at[live]] == y[live]
        out[live[hit]] = at[live[hit]]
        live = live[~hit]
        at[live] += 1
        live = live[at[live] < len(h)]
    return out


def _parts(h: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """The order that puts hashes by partition, and the partitions' bounds."""
    p = (h % np.uint64(parts)).astype(np.int64)
    order = np.argsort(p, kind="stable")
    return order, np.searchsorted(p[order], np.arange(parts + 1))


_SENT = "p long, batch long, data binary"
_BACK = "batch long, data binary"


def _rows(names: list[str], rows: list[tuple]) -> pa.Table:
    kinds = [pa.binary() if n == "data" else pa.int64() for n in names]
    return pa.table({n: pa.array([r[c] for r in rows], k) for c, (n, k) in enumerate(zip(names, kinds))})


def _send(batch: int, b: Batch, level: int, alive: np.ndarray | None, parts: int) -> pa.Table:
    a, ids = b.anchors(level), b.owner
    last = level == b.length
    other = b.second() if last else np.zeros(len(a), dtype=np.uint64)
    if alive is not None:
        a, ids, other = a[alive], ids[alive], other[alive]
    h, g, least, most = _least_ids(a, other, ids)
    order, bound = _parts(h, parts)
    out = []
    for p in range(parts):
        o = order[bound[p] : bound[p + 1]]
        if len(o):
            low = least[o].min()
            out.append((p, batch, pack(h[o], g[o], np.array([low]), narrow(least[o] - low)) if last else pack(h[o], np.packbits(least[o] != most[o]))))
    return _rows(["p", "batch", "data"], out)


def _repeated(key, table):
    """To each batch: its hashes that stand in two documents or more."""
    batches, blobs = table["batch"].to_pylist(), [unpack(x) for x in table["data"].to_pylist()]
    h = np.concatenate([b[0] for b in blobs])
    twice = np.concatenate([np.unpackbits(b[1], count=len(b[0])).astype(bool) for b in blobs])
    u, n = np.unique(h, return_counts=True)
    good = np.union1d(u[n > 1], h[twice])
    got = ((b, x[np.isin(x, good, assume_unique=True)]) for b, (x, _) in zip(batches, blobs))
    return _rows(["batch", "data"], [(b, pack(x)) for b, x in got if len(x)])


def _earlier(key, table):
    """To each batch: its windows, by both hashes, that stand in a document smaller than all of the batch's own that have them."""
    batches = table["batch"].to_pylist()
    blobs = [(h, g, low[0] + ids.astype(np.int64)) for h, g, low, ids in map(unpack, table["data"].to_pylist())]
    h, g, least, _ = _least_ids(*(np.concatenate([b[i] for b in blobs]) for i in range(3)))
    out = []
    for batch, (x, y, ids) in zip(batches, blobs):
        go = least[_place(h, g, x, y)] < ids
        if go.any():
            out.append((batch, pack(x[go], y[go])))
    return _rows(["batch", "data"], out)


def _union(table: pa.Table) -> np.ndarray:
    got = [unpack(x)[0] for x in table["data"].to_pylist()]
    return np.unique(np.concatenate(got)) if got else np.empty(0, dtype=np.uint64)


def _gone(b: Batch, found: pa.Table) -> np.ndarray:
    """Which windows a smaller document has, of another batch or of this one."""
    w = b.anchors(b.length)
    if not len(w):
        return np.zeros(0, dtype=bool)
    got = [unpack(x) for x in found["data"].to_pylist()]
    h, g = (np.concatenate([x[i] for x in got]) if got else np.empty(0, dtype=np.uint64) for i in range(2))
    order = np.argsort(w, kind="stable")
    new = np.concatenate([[True], w[order][1:] != w[order][:-1], [True]])
    some = np.isin(w, h)
    some[order[~(new[1:] & new[:-1])]] = True  # equal in 64 bits to another of the batch, or to one from elsewhere
    some = np.flatnonzero(some)
    x, y, ids = w[some], b.second(some), b.owner[some]
    u, v, least, _ = _least_ids(x, y, ids)
    h, g, _, _ = _least_ids(h, g, np.zeros(len(h), dtype=np.int64))
    out = np.zeros(len(w), dtype=bool)
    out[some] = (_place(h, g, x, y) >= 0) | (ids > least[_place(u, v, x, y)])
    return out


def _first(level: int, length: int, parts: int):
    return lambda key, table: _send(key[0].as_py(), Batch(table, length), level, None, parts)


def _next(before: int, level: int, length: int, parts: int):
    def run(key, table, found):
        if not table.num_rows or not found.num_rows:
            return _rows(["p", "batch", "data"], [])
        b = Batch(table, length)
        return _send(table["batch"][0].as_py(), b, level, np.isin(b.anchors(before), _union(found)), parts)

    return run


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, start: int = START) -> DataFrame:
    """(doc_id, n_words, n_removed, removed array<struct<start, end>>, kept): spans of words, end exclusive; kept joins the others by a space."""
    spark = docs.sparkSession
    d = columns(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    size = d.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    batches, parts = max(8, -(-size // BATCH)), max(32, -(-size // (12 * ENTRIES)))
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // TASK))
    texts = d.withColumn("batch", F.pmod(F.xxhash64("doc_id", "text"), F.lit(batches))).repartition(n, "batch")
    steps = levels(length, start)
    back = None
    for before, level in zip([None, *steps], steps):
        sent = texts.groupBy("batch").applyInArrow(_first(level, length, parts), _SENT) if back is None else texts.groupBy("batch").cogroup(back.groupBy("batch")).applyInArrow(_next(before, level, length, parts), _SENT)
        back = sent.repartition(n, "p").groupBy("p").applyInArrow(_repeated if level < length else _earlier, _BACK)
    kept_type = "doc_id long, n_words long, n_removed long, removed array<struct<start: long, end: long>>, kept string"

    def finish(key, table: pa.Table, found: pa.Table) -> Iterator[pa.Table]:
        if not table.num_rows:
            return
        b = Batch(table, length)
        gone = _gone(b, found)
        edge = np.zeros(len(b.hashes) + 1, dtype=np.int64)
        np.add.at(edge, b.start[gone], 1)
        np.add.at(edge, b.start[gone] + length, -1)
        covered = np.cumsum(edge[:-1]) > 0
        at, out = 0, []
        for i, text, size in zip(table["doc_id"].to_pylist(), table["text"].to_pylist(), b.sizes.tolist()):
            c = covered[at : at + size]
            at += size
            words = WORDS.findall(text or "")
            spans = np.flatnonzero(np.diff(np.concatenate([[False], c, [False]]).astype(np.int8))).reshape(-1, 2).tolist()
            kept, end = [], 0
            for x, y in spans:
                kept += words[end:x]
                end = y
            out.append((i, size, int(c.sum()), [{"start": x, "end": y} for x, y in spans], " ".join(kept + words[end:] if spans else words)))
            if len(out) >= 1000:
                yield _kept(out)
                out = []
        yield _kept(out)

    return texts.groupBy("batch").cogroup(back.groupBy("batch")).applyInArrow(lambda key, a, b: pa.concat_tables(finish(key, a, b)) if a.num_rows else _kept([]), kept_type)


def _kept(rows: list[tuple]) -> pa.Table:
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.string()]
    return pa.table({n: pa.array([r[c] for r in rows], k) for c, (n, k) in enumerate(zip(["doc_id", "n_words", "n_removed", "removed", "kept"], kinds))})


def longest_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", start: int = START) -> DataFrame:
    """(doc_id, longest): for each document with a window of start words that another document has too, the greatest level of start, 2 start, 4 start, ... at which it still has one.

    A window goes on to twice its length only if both halves repeat; levels end when none does. Windows are compared by 64 bits.
    """
    spark = docs.sparkSession
    d = columns(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    size = d.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    batches, parts = max(8, -(-size // BATCH)), max(32, -(-size // (12 * ENTRIES)))
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // TASK))
    texts = cut(d.withColumn("batch", F.pmod(F.xxhash64("doc_id", "text"), F.lit(batches))).repartition(n, "batch"))

    def whole(b: Batch, level: int, found: pa.Table | None) -> tuple[np.ndarray, np.ndarray]:
        """(starts, hashes) of the windows of a level whose halves repeat."""
        at = b.starts(level)
        if found is not None:
            half = np.isin(windows(b.hashes, level // 2), _union(found))
            at = at[half[at] & half[at + level // 2]]
        return at, windows(b.hashes, level)[at]

    def send(level: int):
        def run(key, table, found):
            if not table.num_rows:
                return _rows(["p", "batch", "data"], [])
            b = Batch(table, level)
            at, h = whole(b, level, found)
            h, _, least, most = _least_ids(h, np.zeros(len(h), dtype=np.uint64), b.ids[b.own[at]])
            order, bound = _parts(h, parts)
            rows = [(p, table["batch"][0].as_py(), pack(h[o], np.packbits(least[o] != most[o]))) for p in range(parts) if len(o := order[bound[p] : bound[p + 1]])]
            return _rows(["p", "batch", "data"], rows)

        return run

    def first(key, table):
        return send(start)(key, table, None)

    def holders(level: int):
        def run(key, table, found):
            b = Batch(table, level)  # no row, no word, no window
            at = b.starts(level)
            at = at[np.isin(windows(b.hashes, level)[at], _union(found))] if len(at) else at
            ids = np.unique(b.ids[b.own[at]])
            return pa.table({"doc_id": pa.array(ids, mask=ids == NO_ID), "longest": pa.array(np.full(len(ids), level))})

        return run

    level, back, out = start, None, None
    while True:
        grouped = texts.groupBy("batch")
        sent = grouped.applyInArrow(first, _SENT) if back is None else grouped.cogroup(back.groupBy("batch")).applyInArrow(send(level), _SENT)
        back = cut(sent.repartition(n, "p").groupBy("p").applyInArrow(_repeated, _BACK))
        if not back.limit(1).count():
            break
        held = texts.groupBy("batch").cogroup(back.groupBy("batch")).applyInArrow(holders(level), "doc_id long, longest long")
        out = held if out is None else out.unionByName(held)
        level *= 2
    if out is None:
        return spark.createDataFrame([], "doc_id long, longest long")
    return out.groupBy("doc_id").agg(F.max("longest").alias("longest"))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return remove_repeats(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


SQL = r"""
WITH w AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
p AS (SELECT doc_id, unnest(range(1, len(ws) - 11)) AS i, ws FROM w),
g AS (SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS win FROM p),
m AS (SELECT win, min(doc_id) AS least FROM g GROUP BY win),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS j FROM g JOIN m USING (win) WHERE least < doc_id),
gone AS (SELECT doc_id, list(j) AS js, count(*) AS n FROM c GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n, 0) AS n_removed,
       sha256(coalesce(array_to_string(CASE WHEN js IS NULL THEN ws ELSE list_filter(ws, lambda x, k: NOT list_contains(js, k)) END, ' '), '')) AS kept_sha256
FROM w LEFT JOIN gone USING (doc_id)
"""
