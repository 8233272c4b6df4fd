"""Katz backoff language model: training counts over the whole corpus and the score of every text, in one exchange of bigrams.

Words are ASCII-lower-cased, and each text ends in one end token. P(w | h) is d(c(hw)) c(hw) / c(h) for a bigram seen in
training, else alpha(h) P(w); P(w) is discounted in the same way and leaves its rest to one unknown word. d is the
Good-Turing discount for small counts (see discounts()); a larger count gives up DELTA, so that every context keeps mass for unseen words. alpha(h)
is what the seen bigrams leave, over the P(w) of all words not seen after h: exactly normalised.

The n-gram tables are partitioned by the hash of the predicted word (a word of more than a K-th of all tokens is spread
by its contexts, with its exact count handed to all; their number is bounded by SPREAD). Everything about tokens w is
then in one partition: c(w), all c(hw), P(w). A partition evaluates its tokens of every text there and then: what
depends on global discounts is returned as counts (bigrams seen r times), what depends on the context as one row for
each unseen token, which backs off at the partition of h, where alpha(h) is put together from partial sums. So texts are
read, sent and scored once, and no table is broadcast or collected; the driver sees eight counts of counts and the
spread words.

Texts travel as packed rows, one for each BATCH_BYTES of texts and partition.

Defined results: null and empty texts hold one end token. A null id is trained on, not held out. Repeated rows count
and are scored each. Without training texts every score is 0 tokens' knowledge: P of the unknown word is 1. Empty tables
give empty tables. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import columns, hash_words, mix64, narrow, pack, slices, sum_by, unpack

END, START, K, DELTA, BASE_ADD = np.uint64(0x5EED0000000000E1), np.uint64(0x5EED0000000000A7), 5, 0.1, 0.1
SPREAD, SALTS, BATCH_BYTES, PART_BYTES, LEAST_PARTS, TASK_PARTS = 20_000, 8, 6_000_000, 9_000_000, 48, 4
_SENT = "p long, kind int, uid long, data binary"
_ROUTED = "route long, kind int, uid long, n long, data binary"
_BY_UID = "uid long, kind int, data binary"
BLOB, META, CONTEXT, UNSEEN, DOCS, STATS = range(6)


def discounts(n: list[float]) -> np.ndarray:
    """d[r] for r from 0 to K (d[0] unused); n[r - 1] n-grams have r occurrences, r to K + 1.

    Good-Turing discounts up to the largest k <= K for which all lie between 0 and 1; counts from k + 1 to K give up
    DELTA like larger ones. If no k serves, half an occurrence comes off each.
    """
    r = np.arange(1, K + 1)
    d = np.full(K + 1, np.nan)
    for k in range(K, 0, -1):
        if min(n[: k + 1]) <= 0 or n[0] == (k + 1) * n[k]:
            continue
        common = (k + 1) * n[k] / n[0]
        own = np.array([((i + 1) * n[i] / (i * n[i - 1]) - common) / (1 - common) for i in range(1, k + 1)])
        if np.all((own > 0) & (own < 1)):
            d[1 : k + 1], d[k + 1 :] = own, 1 - DELTA / r[k:]
            return d
    d[1:] = (r - 0.5) / r
    return d


def kept_mass(counts: np.ndarray, d: np.ndarray) -> np.ndarray:
    """d(c) c."""
    small = np.minimum(counts, K).astype(int)
    return np.where(counts > K, counts - DELTA, np.where(counts > 0, np.nan_to_num(d)[small] * counts, 0.0))


def _pair(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix64(h * np.uint64(0x9E3779B97F4A7C15) + w)


def _part(x: np.ndarray, parts: int) -> np.ndarray:
    return ((x >> np.uint64(20)) % np.uint64(parts)).astype(np.int64)


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(word, context, text) of every token, and the texts' numbers of tokens."""
    words, ends = hash_words(texts, lower=True)
    sizes = np.diff(ends, prepend=0) + 1
    stop = np.cumsum(sizes) - 1
    w = np.empty(len(words) + len(sizes), dtype=np.uint64)
    inner = np.ones(len(w), dtype=bool)
    inner[stop] = False
    w[inner], w[stop] = words, END
    h = np.concatenate([[START], w[:-1]])
    h[stop[:-1] + 1] = START
    return w, h, np.repeat(np.arange(len(sizes)), sizes), sizes


def _runs(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each run, one run behind the other."""
    total = int(sizes.sum())
    ahead = np.cumsum(sizes) - sizes
    return np.arange(total) - np.repeat(ahead, sizes) + np.repeat(starts, sizes)


def _changes(*xs: np.ndarray) -> np.ndarray:
    """Where a run of equal values starts."""
    new = np.zeros(len(xs[0]), dtype=bool)
    if len(new):
        new[0] = True
    for x in xs:
        new[1:] |= x[1:] != x[:-1]
    return np.flatnonzero(new)


def _table(names: list[str], rows: list[tuple], ints: tuple[str, ...] = ("kind",)) -> pa.RecordBatch:
    kind = lambda n: pa.binary() if n == "data" else pa.int32() if n in ints else pa.int64()
    return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], kind(n)) for c, n in enumerate(names)], names)


def _vocabulary_sent(parts: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x for whole in batches for x in slices(whole, "text", BATCH_BYTES)):
            w, _, own, _ = tokens(b["text"])
            train = ~np.array(b["held"].to_pylist(), dtype=bool)
            u, c = np.unique(w[train[own]], return_counts=True)
            p = _part(u, parts)
            order = np.argsort(p, kind="stable")
            at = np.searchsorted(p[order], np.arange(parts + 1))
            yield _table(["p", "data"], [(k, pack(u[o], narrow(c[o]))) for k in range(parts) if len(o := order[at[k] : at[k + 1]])])

    return run


def _vocabulary(least: float):
    """(key, word, n): the number of words of 1 to K + 1 occurrences, of all words (0), of all tokens (-1), of words above K (-2), of their tokens (-3); -4: a frequent word."""

    def run(key, table):
        got = [unpack(x) for x in table["data"].to_pylist()]
        u, at = np.unique(np.concatenate([g[0] for g in got]), return_inverse=True)
        c = sum_by(at, np.concatenate([g[1].astype(float) for g in got]), len(u)).astype(np.int64)
        rows = [(r, 0, int((c == r).sum())) for r in range(1, K + 2)] + [(0, 0, len(u)), (-1, 0, int(c.sum())), (-2, 0, int((c > K).sum())), (-3, 0, int(c[c > K].sum()))]
        rows += [(-4, x, n) for x, n in zip(u.view(np.int64)[c >= least].tolist(), c[c >= least].tolist())]
        return pa.table({n: pa.array([r[i] for r in rows], pa.int64()) for i, n in enumerate(("key", "word", "n"))})

    return run


class Words:
    """What every partition is told of the unigrams: totals, discounts, and the frequent words with their counts."""

    def __init__(self, rows: list[tuple[int, int, int]], parts: int):
        n = {}
        for key, _, c in rows:
            if key > -4:
                n[key] = n.get(key, 0) + c
        self.parts, self.total, self.distinct = parts, n.get(-1, 0), n.get(0, 0)
        self.d = discounts([n.get(r, 0) for r in range(1, K + 2)])
        kept = sum(self.d[r] * r * n.get(r, 0) for r in range(1, K + 1)) + n.get(-3, 0) - DELTA * n.get(-2, 0)
        self.unknown = 1 - kept / self.total if self.total else 1.0
        often = sorted((w, c) for key, w, c in rows if key == -4 and c >= self.total / min(10 * parts, SPREAD))
        often = sorted((np.int64(w).view(np.uint64), c) for w, c in often)
        self.often, self.often_count = np.array([w for w, _ in often], dtype=np.uint64), np.array([c for _, c in often], dtype=np.int64)
        self.texts = 0  # training texts: occurrences of the end token

    def find(self, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(frequent, count if so)."""
        if not len(self.often):
            return np.zeros(len(w), dtype=bool), np.zeros(len(w), dtype=np.int64)
        at = np.minimum(np.searchsorted(self.often, w), len(self.often) - 1)
        hit = self.often[at] == w
        return hit, np.where(hit, self.often_count[at], 0)

    def probability(self, c: np.ndarray) -> np.ndarray:
        return np.where(c > 0, kept_mass(c, self.d) / max(self.total, 1), self.unknown)


def _bigrams_sent(words: Words):
    parts = words.parts

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task = TaskContext.get().partitionId()
        for number, b in enumerate(x for whole in batches for x in slices(whole, "text", BATCH_BYTES)):
            uid = task * (1 << 24) + number
            w, h, own, sizes = tokens(b["text"])
            held = np.array(b["held"].to_pylist(), dtype=bool)
            ids = b["doc_id"]
            known = np.array(ids.is_valid().to_pylist(), dtype=bool)
            g = _pair(h, w)
            order = np.argsort(g, kind="stable")  # texts stay in order within a bigram
            g, own = g[order], own[order]
            at = _changes(g, own)  # one entry for each bigram of a text
            total = len(g)
            text, count, g = own[at], np.diff(np.append(at, total)), g[at]
            pair_at = _changes(g)
            size = np.diff(np.append(pair_at, len(at)))
            first = order[at[pair_at]]
            pw, ph = w[first], h[first]
            del w, h, own, order, first, at
            p = np.where(words.find(pw)[0], _part(g[pair_at], parts), _part(pw, parts))
            o = np.argsort(pw, kind="stable")
            o = o[np.argsort(p[o].astype(np.int32), kind="stable")]
            bound = np.searchsorted(p[o], np.arange(parts + 1))
            bits = np.packbits(held)
            rows = [(uid % parts, META, uid, pack(np.array(ids.fill_null(0).to_pylist(), dtype=np.int64), known, sizes.astype(np.int64), held))]
            for k in range(parts):
                own_pairs = o[bound[k] : bound[k + 1]]
                if len(own_pairs):
                    e = _runs(pair_at[own_pairs], size[own_pairs])
                    run_at = _changes(pw[own_pairs])
                    rows.append((k, BLOB, uid, pack(pw[own_pairs][run_at], narrow(np.diff(np.append(run_at, len(own_pairs)))), ph[own_pairs], narrow(size[own_pairs]), narrow(text[e]), narrow(count[e]), bits, np.array([len(held)]))))
            yield _table(["p", "kind", "uid", "data"], rows)

    return run


class Partition:
    """The bigram table of one partition, put together from its packed rows."""

    def __init__(self, table: pa.Table):
        self.uids, blobs = [], []
        for kind, uid, data in zip(*(table[c].to_pylist() for c in ("kind", "uid", "data"))):
            if kind == BLOB:
                self.uids.append(uid)
                blobs.append(unpack(data))
        self.w = np.concatenate([np.repeat(b[0], b[1].astype(np.int64)) for b in blobs]) if blobs else np.empty(0, np.uint64)
        self.h = np.concatenate([b[2] for b in blobs]) if blobs else np.empty(0, np.uint64)
        self.texts, self.counts, self.held, self.n_docs, trained = [], [], [], [], []
        self.sizes = [b[3].astype(np.int64) for b in blobs]
        for b, size in zip(blobs, self.sizes):
            n = int(b[7][0])
            held = np.unpackbits(b[6], count=n).astype(bool)
            text, count = b[4].astype(np.int64), b[5].astype(np.int64)
            self.texts.append(text)
            self.counts.append(count)
            self.n_docs.append(n)
            trained.append(np.add.reduceat(count * ~held[text], np.cumsum(size) - size))
        u, self.at = np.unique(_pair(self.h, self.w), return_inverse=True)
        self.first = np.empty(len(u), dtype=np.int64)
        self.first[self.at[::-1]] = np.arange(len(self.at))[::-1]
        self.seen = sum_by(self.at, np.concatenate(trained).astype(float), len(u)).astype(np.int64) if blobs else np.empty(0, np.int64)


def _bigram_counts(key, table):
    c = Partition(table).seen
    return pa.table({"r": pa.array(range(1, K + 2), pa.int64()), "n": pa.array([int((c == r).sum()) for r in range(1, K + 2)], pa.int64())})


def _routes(h: np.ndarray, words: Words, salt: np.ndarray | int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.where(words.find(h)[0] | (h == START), _part(mix64(h + np.uint64(1) + np.asarray(salt, dtype=np.uint64)), words.parts), _part(h, words.parts))


def _evaluate(words: Words):
    parts = words.parts

    def run(key, table):
        rows = [(uid % parts, META, uid, None, data) for kind, uid, data in zip(*(table[c].to_pylist() for c in ("kind", "uid", "data"))) if kind == META]
        t = Partition(table)
        if not t.uids:
            return pa.Table.from_batches([_table(["route", "kind", "uid", "n", "data"], rows)])
        w, h = t.w[t.first], t.h[t.first]  # distinct bigrams
        uw, at = np.unique(w, return_inverse=True)
        hit, count = words.find(uw)
        c = np.where(hit, count, sum_by(at, t.seen.astype(float), len(uw)).astype(np.int64))
        p = words.probability(c)[at]
        c = c[at]
        # contexts: partial sums over the words seen after them
        s = np.flatnonzero(t.seen > 0)
        s = s[np.argsort(h[s], kind="stable")]
        run_at = _changes(h[s])
        if len(s):
            add = lambda x: np.add.reduceat(x, run_at)
            seen, ctx = t.seen[s], h[s][run_at]
            sums = [narrow(add((seen == r).astype(np.int64))) for r in range(1, K + 1)] + [narrow(add((seen > K).astype(np.int64))), narrow(add(np.where(seen > K, seen, 0))), add(p[s])]
            spread = words.find(ctx)[0] | (ctx == START)
            for salt in range(SALTS):
                take = np.arange(len(ctx)) if not salt else np.flatnonzero(spread)  # a frequent context goes to every salt's partition
                route = _routes(ctx[take], words, salt)
                order = np.argsort(route, kind="stable")
                bound = np.searchsorted(route[order], np.arange(parts + 1))
                for k in range(parts):
                    if len(o := take[order[bound[k] : bound[k + 1]]]):
                        rows.append((k, CONTEXT, salt, None, pack(ctx[o], *[x[o] for x in sums])))
        # texts
        per_pair = {"base": np.log10(c + BASE_ADD), "rest": np.where(t.seen > K, np.log10(np.maximum(t.seen - DELTA, 0.5)), 0.0) - np.where(w == END, 0.0, np.log10(np.maximum(c, 1)))}
        lost: list[list[np.ndarray]] = []
        start = 0
        for uid, size, text, n_of, docs in zip(t.uids, t.sizes, t.texts, t.counts, t.n_docs):
            g = np.repeat(t.at[start : start + len(size)], size)
            start += len(size)
            r, x = t.seen[g], n_of.astype(float)
            arrays = [narrow(sum_by(text, x * (r == k), docs).astype(np.int64)) for k in range(1, K + 1)] + [narrow(sum_by(text, x * (c[g] > 0), docs).astype(np.int64)), sum_by(text, x * per_pair["base"][g], docs), sum_by(text, x * per_pair["rest"][g], docs)]
            rows.append((uid % parts, DOCS, uid, None, pack(*arrays)))
            gone = np.flatnonzero(r == 0)
            lost.append([h[g[gone]], np.log10(p[g[gone]]) if len(gone) else np.empty(0), np.full(len(gone), uid, dtype=np.int64), text[gone], n_of[gone]])
        hs, ps, us, ts, ns = (np.concatenate([x[i] for x in lost]) for i in range(5))
        route = _routes(hs, words, us % SALTS)
        order = np.argsort(route, kind="stable")
        bound = np.searchsorted(route[order], np.arange(parts + 1))
        for k in range(parts):
            if len(o := order[bound[k] : bound[k + 1]]):
                rows.append((k, UNSEEN, 0, None, pack(hs[o], ps[o], us[o], narrow(ts[o]), narrow(ns[o]))))
        return pa.Table.from_batches([_table(["route", "kind", "uid", "n", "data"], rows)])

    return run


def _back_off(words: Words):
    """At the partition of the context: alpha, and with it the unseen tokens; and the sums of each batch's texts."""

    def run(key, table):
        by: dict[int, list] = {k: [] for k in range(6)}
        for kind, uid, n, data in zip(*(table[c].to_pylist() for c in ("kind", "uid", "n", "data"))):
            by[kind].append((uid, n, data))
        n_r = {r: n for r, n, _ in by[STATS]}
        d = discounts([n_r.get(r, 0) for r in range(1, K + 2)])
        out = [(uid, META, data) for uid, _, data in by[META]]
        texts: dict[int, list] = {}
        for uid, _, data in by[DOCS]:
            a = [x.astype(float) for x in unpack(data)]
            texts[uid] = [x + y for x, y in zip(texts[uid], a)] if uid in texts else a
        for uid, a in texts.items():
            score = a[K + 2] + sum(a[r - 1] * np.log10(d[r] * r) for r in range(1, K + 1))
            out.append((uid, DOCS, pack(a[K].astype(np.int64), a[K + 1], score)))
        if by[UNSEEN]:
            h, lp, uid, text, n = (np.concatenate([x[i] for x in map(unpack, (data for *_, data in by[UNSEEN]))]) for i in range(5))
            weight = np.zeros(len(h))
            if by[CONTEXT]:
                got = [unpack(data) for *_, data in by[CONTEXT]]
                ctx, at = np.unique(np.concatenate([g[0] for g in got]), return_inverse=True)
                # a context may have come for several salts that share this partition: each is whole by itself
                salt = np.concatenate([np.full(len(g[0]), s) for (s, *_), g in zip(by[CONTEXT], got)])
                lowest = np.full(len(ctx), SALTS)
                np.minimum.at(lowest, at, salt)
                live = (salt == lowest[at]).astype(float)
                sums = [sum_by(at, live * np.concatenate([g[i + 1] for g in got]).astype(float), len(ctx)) for i in range(K + 3)]
                count = sum(r * sums[r - 1] for r in range(1, K + 1)) + sums[K + 1]
                kept = sum(d[r] * r * sums[r - 1] for r in range(1, K + 1)) + sums[K + 1] - DELTA * sums[K]
                # count * alpha: the count cancels the context's count, which every token's sum has taken off
                left = np.log10((count - kept) / (1 - sums[K + 2]))
                where = np.minimum(np.searchsorted(ctx, h), len(ctx) - 1)
                weight = np.where(ctx[where] == h, left[where], 0.0)
            value = n * (lp + weight)
            order = np.argsort(uid, kind="stable")
            at = _changes(uid[order])
            for x, y in zip(at, [*at[1:], len(order)]):
                o = order[x:y]
                u, inverse = np.unique(text[o], return_inverse=True)
                out.append((int(uid[o[0]]), UNSEEN, pack(u.astype(np.int64), sum_by(inverse, value[o], len(u)))))
        return pa.Table.from_batches([_table(["uid", "kind", "data"], out)])

    return run


_SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _finish(words: Words, start_log: float):
    def run(key, table):
        ids = known = sizes = held = counts = base = score = None
        more = []
        for kind, data in zip(table["kind"].to_pylist(), table["data"].to_pylist()):
            if kind == META:
                ids, known, sizes, held = unpack(data)
            elif kind == DOCS:
                counts, base, score = unpack(data)
            else:
                more.append(unpack(data))
        score = score - start_log
        for text, value in more:
            np.add.at(score, text, value)
        base = base - sizes * np.log10(words.total + BASE_ADD * (words.distinct + 1))
        return pa.table({"doc_id": pa.array(ids, mask=~known), "held_out": pa.array(held), "n_tokens": pa.array(sizes), "n_known": pa.array(counts), "train_tokens": pa.array(np.full(len(ids), words.total)), "base_score": pa.array(base), "score": pa.array(score)})

    return run


def score_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 10) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score): learns from texts with crc32(id) mod folds not 0."""
    spark = docs.sparkSession
    d = columns(docs, doc_id=id_col, text=text_col).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    d = d.withColumn("held", F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds == 0, F.lit(False)))
    size, texts = d.agg(F.sum(F.octet_length("text")), F.count(F.when(~F.col("held"), 1))).first()
    size = size or 0
    parts = max(LEAST_PARTS, -(-size // PART_BYTES))
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-parts // TASK_PARTS))
    often = max(2.0, size / (32 * min(10 * parts, SPREAD)))  # a K-th of the tokens or less, for words up to 32 bytes on average
    vocabulary = d.select("text", "held").mapInArrow(_vocabulary_sent(parts), "p long, data binary").repartition(n, "p").groupBy("p").applyInArrow(_vocabulary(often), "key long, word long, n long")
    words = Words([tuple(r) for r in vocabulary.groupBy("key", "word").agg(F.sum("n").alias("n")).collect()], parts)
    sent = d.mapInArrow(_bigrams_sent(words), _SENT).repartition(n, "p")
    stats = sent.groupBy("p").applyInArrow(_bigram_counts, "r long, n long").groupBy("r").agg(F.sum("n").alias("n"))
    routes = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))).alias("route")
    stats = stats.select(routes, F.lit(STATS).alias("kind"), F.col("r").alias("uid"), "n", F.lit(None).cast("binary").alias("data"))
    routed = sent.groupBy("p").applyInArrow(_evaluate(words), _ROUTED).unionByName(stats).repartition(n, "route")
    by_uid = routed.groupBy("route").applyInArrow(_back_off(words), _BY_UID).repartition(n, "uid")
    return by_uid.groupBy("uid").applyInArrow(_finish(words, float(np.log10(max(texts or 0, 1)))), _SCORES)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return score_texts(table(spark, sf_dir, "documents"))
