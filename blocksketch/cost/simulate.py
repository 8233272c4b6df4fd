"""Block I/Os that a real stream costs, counted; and what Spark moved for a query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.stream import edge_records


def simulate_io(updates: DataFrame, phi: int, vertices: int, block: int, mode: str = "block") -> DataFrame:
    """One row (ios): updates need seq numbers from 0 or 1 upwards; a group is max(1, block // phi) consecutive vertices.

    "block": batches of V phi updates by seq; two permuted records an update, and each batch's touched groups read and
    written once. "per_update": every update reads and writes both vertex sketches. "global_sort": two records an update
    sorted in blocks, then each touched group once.
    """
    per = max(1, block // phi)
    blocks = -(-per * phi // block)
    rec = edge_records(updates).select((F.col("seq") / (vertices * phi)).cast("long").alias("batch"), (F.col("x") / per).cast("long").alias("grp"))
    if mode == "per_update":
        return updates.agg((F.count(F.lit(1)) * 4 * max(1, -(-phi // block))).cast("long").alias("ios"))
    if mode == "global_sort":
        return rec.agg((F.count(F.lit(1)) + 2 * blocks * F.countDistinct("grp")).cast("long").alias("ios"))
    return rec.agg((F.ceil(F.count(F.lit(1)) * 2 / block) + 2 * blocks * F.countDistinct("batch", "grp")).cast("long").alias("ios"))


def simulate_sql(updates_sql: str, phi: int, vertices: int, block: int, mode: str = "block") -> str:
    per = max(1, block // phi)
    blocks = -(-per * phi // block)
    rec = f"WITH s AS ({updates_sql}), r AS (SELECT seq // {vertices * phi} AS batch, u // {per} AS grp FROM s UNION ALL SELECT seq // {vertices * phi}, v // {per} FROM s) "
    if mode == "per_update":
        return rec + f"SELECT CAST(count(*) * {4 * max(1, -(-phi // block))} AS BIGINT) AS ios FROM s"
    if mode == "global_sort":
        return rec + f"SELECT CAST(count(*) + {2 * blocks} * count(DISTINCT grp) AS BIGINT) AS ios FROM r"
    return rec + f"SELECT CAST(ceil(count(*) * 2 / {float(block)}) + {2 * blocks} * count(DISTINCT (batch, grp)) AS BIGINT) AS ios FROM r"


def lru_ios(updates: list[tuple[int, int]], phi: int, block: int, memory: int) -> int:
    """Reads and writes with an LRU cache of memory // block blocks, a vertex sketch in blocks of its own; for small streams."""
    from collections import OrderedDict

    size, cache, ios = max(1, -(-phi // block)), OrderedDict(), 0
    room = max(1, memory // (block * size))
    for pair in updates:
        for x in pair:
            if x in cache:
                cache.move_to_end(x)
            else:
                ios += size
                cache[x] = True
                if len(cache) > room:
                    cache.popitem(last=False)
                    ios += size
    return ios + size * len(cache)


def measured(spark: SparkSession, run) -> dict:
    """Shuffle and input figures of the stages that run() starts, from Spark's status store."""
    store = spark.sparkContext._jsc.sc().statusStore()
    before = {s.stageId() for s in _stages(store)}
    run()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    new = [s for s in _stages(store) if s.stageId() not in before]
    return {"shuffle_bytes": sum(s.shuffleWriteBytes() for s in new), "shuffle_records": sum(s.shuffleWriteRecords() for s in new), "input_bytes": sum(s.inputBytes() for s in new), "spilled_bytes": sum(s.diskBytesSpilled() for s in new)}


def _stages(store):
    seq = store.stageList(None, False, False, getattr(store, "stageList$default$4")(), getattr(store, "stageList$default$5")())
    return [seq.apply(i) for i in range(seq.length())]
