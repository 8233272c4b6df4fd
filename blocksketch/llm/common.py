"""Helpers shared by the corpus operators: table loading, fixed hashes, word splitting, components."""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters, U+0009 to U+000D and U+0020.
WHITE = "\t\n\x0b\x0c\r "
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def columns(docs: DataFrame, **wanted: str) -> DataFrame:
    """Only the named columns, as output=input; any other column, whatever its name, is left out."""
    return docs.select(*[docs[old].alias(new) for new, old in wanted.items()])


def sized_partitions(spark: SparkSession, least: int = 0) -> int:
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), least)


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The cluster's spark.checkpoint.dir if there is one; a folder under the warehouse where none is set, as in tests: an error on a cluster whose warehouse is a local folder."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared, warehouse = spark.conf.get("spark.checkpoint.dir", None), spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
        if not shared and not sc.master.startswith("local[") and sc.master != "local" and warehouse.startswith(("/", "file:")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(shared or warehouse + "/_checkpoints")


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder's path beside the checkpoints."""
    import uuid

    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4()}"


def remove_folder(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def boxed(df: DataFrame, **more: Column) -> DataFrame:
    """The whole row as the struct _row, beside working columns: no name of df's clashes with a working name."""
    return df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("_row"), *[c.alias(n) for n, c in more.items()])


def trim_memory() -> None:
    """Give a Python worker's free memory back to the system; idle workers otherwise keep the most they ever had."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # a system without it
        pass


def cut(df: DataFrame) -> DataFrame:
    """The rows written to the shared checkpoint folder, with a fresh lineage."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


ARROW_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Arrow batches of so many rows at most in this session, as texts may be long: a worker and its executor hold whole batches."""
    if not 0 < int(spark.conf.get(ARROW_ROWS)) <= rows:
        spark.conf.set(ARROW_ROWS, str(rows))


def fresh(df: DataFrame) -> DataFrame:
    """The same rows as a plan without estimates. Estimates of joins multiply from round to round of a loop, without bound."""
    spark = df.sparkSession
    return DataFrame(spark._jsparkSession.createDataFrame(df._jdf.javaRDD(), df._jdf.schema()), spark)


def release(spark: SparkSession) -> None:
    """Let go of finished plans now: a loop of many small jobs otherwise fills a small driver before its JVM collects."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


_SOLID = np.array([c not in (32, *range(9, 14)) for c in range(256)])
_LOWER = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], dtype=np.uint8)
_TAIL = np.array([(1 << 8 * n) - 1 for n in range(9)], dtype=np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_LANES = (np.uint64(0x2545F4914F6CDD1D), np.uint64(0xD6E8FEB86659FD93))
_PART = 1 << 20


def _hash_spans(data: np.ndarray, s: np.ndarray, e: np.ndarray, lanes: int) -> list[np.ndarray]:
    """A hash of data[s:e] for each span, none empty, in each lane.

    Every eight bytes are mixed on their own, mixed again with their place, and added up; the sum is mixed with the
    length. The mixing is not linear, so no pattern of letters makes two words meet by rule, as a polynomial modulo
    2**64 lets them; different words meet with odds of 2**-64 in one lane and 2**-128 in both.
    """
    padded = np.zeros(len(data) + 8, dtype=np.uint8)
    padded[: len(data)] = data
    eights = np.ndarray(len(data) + 1, dtype="<u8", buffer=padded, strides=(1,))
    size = e - s
    n = (size + 7) >> 3
    first = np.cumsum(n) - n
    place = np.arange(int(n.sum())) - np.repeat(first, n)
    x = eights[np.repeat(s, n) + 8 * place]
    x[first + n - 1] &= _TAIL[size - 8 * (n - 1)]
    with np.errstate(over="ignore"):
        step = place.astype(np.uint64) * _ODD
        return [mix64(np.add.reduceat(mix64(mix64(x ^ lane) ^ step), first) + size.astype(np.uint64) * lane) for lane in _LANES[:lanes]]


def hash_words(texts, lower: bool = False, lanes: int = 1) -> tuple[np.ndarray, ...]:
    """(hashes, ends): the 64-bit hash of every word of an Arrow string array, and where each text's words end; with two lanes (hashes, other hashes, ends).

    Words are hashed over the array's own buffer of UTF-8 bytes, so no Python object is made for a word. With lower, A-Z
    count as a-z. Null texts have no words.
    """
    import pyarrow as pa
    import pyarrow.compute as pc

    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    n = len(texts)
    if not n:
        return *[np.empty(0, dtype=np.uint64)] * lanes, np.empty(0, dtype=np.int64)
    off = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + n + 1]
    raw = np.frombuffer(texts.buffers()[2], dtype=np.uint8) if texts.buffers()[2] is not None else np.empty(0, np.uint8)
    out, count, a = [[] for _ in range(lanes)], np.zeros(n, dtype=np.int64), 0
    while a < n:  # texts of about _PART bytes together, one text at least
        b = max(a + 1, int(np.searchsorted(off, off[a] + _PART, "right")) - 1)
        b = min(b, n)
        data, cuts = raw[off[a] : off[b]], off[a : b + 1] - off[a]
        if len(data):
            solid = _SOLID[data]
            first, last = solid.copy(), solid.copy()
            first[1:] &= ~solid[:-1]
            last[:-1] &= ~solid[1:]
            inner = cuts[(cuts > 0) & (cuts < len(data))]  # a text's end also ends a word
            first[inner] = solid[inner]
            last[inner - 1] = solid[inner - 1]
            s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
            if len(s):
                for lane, h in zip(out, _hash_spans(_LOWER[data] if lower else data, s, e, lanes)):
                    lane.append(h)
            count[a:b] = np.diff(np.searchsorted(s, cuts))
        a = b
    return *[np.concatenate(x) if x else np.empty(0, dtype=np.uint64) for x in out], np.cumsum(count)


def slices(batch, column: str, size: int):
    """A record batch in parts of about size bytes of the text column, one row at least."""
    import pyarrow as pa
    import pyarrow.compute as pc

    ends = np.cumsum(pc.fill_null(pc.binary_length(batch[column].cast(pa.large_string())), 0).to_numpy(zero_copy_only=False))
    a = 0
    while a < batch.num_rows:
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + size, "right")))
        yield batch.slice(a, b - a)
        a = b


def pack(*arrays: np.ndarray) -> bytes:
    import pickle

    import pyarrow as pa

    raw = pickle.dumps([(a.dtype.str, a.tobytes()) for a in arrays])
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unpack(data: bytes) -> list[np.ndarray]:
    import pickle

    import pyarrow as pa

    raw = pa.decompress(data[8:], int.from_bytes(data[:8], "little"), codec="zstd", asbytes=True)
    return [np.frombuffer(b, dtype=d) for d, b in pickle.loads(raw)]


def narrow(x: np.ndarray) -> np.ndarray:
    """The same numbers, none below 0, in the smallest unsigned type."""
    return x.astype(np.min_scalar_type(int(x.max()) if len(x) else 0))


def sum_by(at: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(at, weights=x, minlength=n)


def windows(hashes: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit hash of every run of n consecutive words."""
    m = len(hashes) - n + 1
    if m <= 0:
        return np.empty(0, dtype=np.uint64)
    with np.errstate(over="ignore"):
        out = hashes[:m].copy()
        for i in range(1, n):
            out = out * np.uint64(0x9E3779B97F4A7C15) + hashes[i : i + m]
        return mix64(out)


def running(df: DataFrame, order: list[Column], sums: dict[str, Column]) -> DataFrame:
    """df with the sum of each column over all rows before, in an order without ties: ranges are dealt to partitions and summed there, and the totals of the partitions before are joined on."""
    from pyspark.sql import Window as W

    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.select(*[F.col(f"`{c}`") for c in df.columns], *[c.alias(f"_of_{n}") for n, c in sums.items()]).repartitionByRange(parts, *order)
    dealt = cut(dealt.withColumn("_part", F.spark_partition_id()))
    inside = W.partitionBy("_part").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    # one row a partition
    before = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    totals = dealt.groupBy("_part").agg(*[F.sum(f"_of_{n}").alias(f"_of_{n}") for n in sums])
    zero = lambda c: F.coalesce(c, F.lit(0))
    totals = totals.select("_part", *[zero(F.sum(f"_of_{n}").over(before)).alias(f"_to_{n}") for n in sums])
    out = dealt.select("*", *[zero(F.sum(f"_of_{n}").over(inside)).alias(f"_in_{n}") for n in sums]).join(F.broadcast(totals), "_part")
    return out.select(*[F.col(f"`{c}`") for c in df.columns], *[(F.col(f"_in_{n}") + F.col(f"_to_{n}")).alias(n) for n in sums])


def same(a: Column, b: Column) -> Column:
    return a.eqNullSafe(b)


def components(edges: DataFrame, a: str = "a", b: str = "b", limit: int = 60) -> DataFrame:
    """(node, root): the least node of each component of the graph of edges; only nodes with an edge.

    Every round replaces each node's label by the least label around it and then by that label's own label, so the
    rounds are about the logarithm of the longest chain. Labels are cut to the checkpoint folder after each round. The
    per-node minimum is partly aggregated before the shuffle, and Spark splits the joins of a hot label.
    """
    spark = edges.sparkSession
    ends = edges.select(F.col(a).alias("x"), F.col(b).alias("y")).filter("x <> y")
    both = ends.union(ends.select("y", "x"))
    both = cut(both.union(both.select("x", F.col("x").alias("y"))).distinct())  # with a loop at each node, so that a round's minimum holds its own label
    labels = cut(both.groupBy(F.col("x").alias("node")).agg(F.min("y").alias("root")))
    for _ in range(limit):
        own = F.max(F.when(F.col("x") == F.col("y"), F.col("root"))).alias("old")
        step = both.join(labels.withColumnRenamed("node", "y"), "y").groupBy(F.col("x").alias("node")).agg(F.min("root").alias("root"), own)
        jump = labels.select(F.col("node").alias("root"), F.col("root").alias("next"))
        now = fresh(cut(step.join(jump, "root").select("node", "old", F.least("root", "next").alias("root"))))
        labels = now.select("node", "root")
        release(spark)
        if not now.filter("root <> old").limit(1).count():
            return labels
    raise RuntimeError(f"components of a graph did not settle in {limit} rounds")
