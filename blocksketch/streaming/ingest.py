"""Streaming ingestion: each micro-batch of updates is sketched and stored under its batch id; snapshots XOR the stored batches.

A batch's folder is overwritten when the batch is replayed, as XOR of the same cells twice would cancel them.

Panes store a batch's cells by ranges of the sequence number, so a sliding window is the XOR of its panes. Cells may also
be kept as state of the query: one state row a cell (an aggregate in the JVM), or one a vertex group (a Python function).
The state store is the session's; for large states set the RocksDB provider before the query starts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.cells import KEYS, SUMS, deal, deal_by, expand_rows, fold, sketch_updates
from ..spec import SketchSpec


def write_batch(batch: DataFrame, batch_id: int, path: str, spec: SketchSpec) -> None:
    sketch_updates(batch, spec).write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")


def start_ingest(updates: DataFrame, path: str, checkpoint: str, spec: SketchSpec):
    """A running query that stores cells for each micro-batch of a stream of UPDATE rows."""
    return updates.writeStream.foreachBatch(lambda df, i: write_batch(df, i, path, spec)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def snapshot(spark: SparkSession, path: str, upto: int | None = None, compacted: str | None = None) -> DataFrame:
    """The cells of the batches so far; partition pruning leaves out later ones, and those that a folder of compact() stands for."""
    cells = spark.read.option("basePath", path).parquet(path)
    if upto is not None:
        cells = cells.filter(F.col("batch_id") <= upto)
    if compacted:
        base = spark.read.option("basePath", compacted).parquet(compacted)
        last = base.agg(F.max("batch_id")).first()[0]
        if upto is not None and upto < last:
            raise ValueError(f"batches up to {last} are compacted; a snapshot up to {upto} needs the batches themselves")
        base = base.filter(F.col("batch_id") == last)
        cells = base.unionByName(cells.filter(F.col("batch_id") > last))
    return fold(cells, *KEYS)


def compact(spark: SparkSession, path: str, target: str, upto: int) -> None:
    """One folder of summed cells for the batches up to one; snapshot(compacted=target) reads the latest of them and the batches behind it."""
    snapshot(spark, path, upto).write.mode("overwrite").parquet(f"{target}/batch_id={upto}")


RUN = 64  # panes in a folder: a folder and a file for every pane and batch grow with the stream, and creating and listing them took most of the time


def pane_cells(batch: DataFrame, spec: SketchSpec, width: int) -> DataFrame:
    """The batch's cells by pane and run of panes.

    A run is written by one task: files as many as folders, whatever the partitions. The narrow updates are dealt to runs,
    and cells are made behind that exchange; a run's numbers bound what its task gets, so hubs need no salt.
    """
    batch = batch.withColumn("pane", F.floor(F.col("seq") / width))
    dealt = deal_by(batch.withColumn("run", F.floor(F.col("pane") / RUN)), spec, "run", ("pane",))
    return fold(expand_rows(dealt, spec, keep=("run", "pane")), "run", "pane", *KEYS)


def write_panes(batch: DataFrame, batch_id: int, path: str, spec: SketchSpec, width: int, delay: int | None = None) -> None:
    """The batch's cells by panes of width sequence numbers, and with delay a row of counts.

    A row is late if it lies more than delay below the highest number of the batches before; late rows are sketched into
    their own pane like others, and only counted, as sums take updates in any order.
    """
    cells = pane_cells(batch, spec, width).sortWithinPartitions("run", "pane")
    cells.write.mode("overwrite").partitionBy("run").parquet(f"{path}/cells/batch_id={batch_id}")
    if delay is None:
        return
    spark = batch.sparkSession
    horizon = None
    if batch_id:
        stats = spark.read.schema("n long, late long, top long, batch_id int").option("basePath", f"{path}/stats").parquet(f"{path}/stats")
        horizon = stats.filter(F.col("batch_id") < batch_id).agg(F.max("top")).first()[0]
    late = F.coalesce(F.count_if(F.col("seq") < F.lit(horizon).cast("long") - delay), F.lit(0))
    row = batch.agg(F.count(F.lit(1)).alias("n"), late.alias("late"), F.max("seq").alias("top"))
    row.write.mode("overwrite").parquet(f"{path}/stats/batch_id={batch_id}")


def start_panes(updates: DataFrame, path: str, checkpoint: str, spec: SketchSpec, width: int, delay: int | None = None):
    return updates.writeStream.foreachBatch(lambda df, i: write_panes(df, i, path, spec, width, delay)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def window_cells(spark: SparkSession, path: str, first: int, last: int) -> DataFrame:
    """The cells of the updates in panes first to last; the folders of other runs are not read, and of a folder's files, which are sorted by pane, only the row groups with these panes."""
    cells = spark.read.option("basePath", f"{path}/cells").parquet(f"{path}/cells")
    return fold(cells.filter(F.col("run").between(first // RUN, last // RUN) & F.col("pane").between(first, last)), *KEYS)


def late_counts(spark: SparkSession, path: str) -> DataFrame:
    """(n, late): rows sketched so far, and how many of them came late."""
    return spark.read.parquet(f"{path}/stats").agg(F.sum("n").alias("n"), F.sum("late").alias("late"))


def changed_cells(updates: DataFrame, spec: SketchSpec) -> DataFrame:
    """A stream of cells with their running sums as the state, for update mode: each batch gives the cells that it changed, zeros too."""
    records = deal(updates, spec, hubs=None)
    return expand_rows(records, spec).groupBy(*KEYS).agg(*[F.expr(f"bit_xor({c}) as {c}") for c in SUMS])


def changed_by_group(updates: DataFrame, spec: SketchSpec) -> DataFrame:
    """The same stream with one state for each vertex group, which holds the group's sketch as packed arrays.

    A group's rows come in Arrow batches and are summed batch by batch, so a hub costs its cells, not its updates.
    """
    names = [k for k in KEYS if k != "vg"]
    schema = "sk int, vg int, x long, row int, lvl int, xu long, xv long, chk long"

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        have = pd.DataFrame(np.frombuffer(state.get[0], dtype="<i8").reshape(-1, 7), columns=[*names, *SUMS]) if state.exists else None
        new = None
        for b in batches:
            new = _xor_rows(pd.concat([new, b[[*names, *SUMS]].astype("int64")]), names)
        whole = _xor_rows(pd.concat([have, new]), names)
        state.update((np.ascontiguousarray(whole.to_numpy(dtype="<i8")).tobytes(),))
        out = new[names].merge(whole, on=names)
        out.insert(1, "vg", key[0])
        yield out.astype({"sk": "int32", "vg": "int32", "row": "int32", "lvl": "int32"})

    cells = expand_rows(deal(updates, spec, hubs=None), spec)
    return cells.groupBy("vg").applyInPandasWithState(step, schema, "cells binary", "update", GroupStateTimeout.NoTimeout)


def _xor_rows(rows: pd.DataFrame, names: list[str]) -> pd.DataFrame:
    """One row for each key, with the XOR of its sums; cells that cancel stay, as a change to zero is a change."""
    rows = rows.sort_values(names, ignore_index=True)
    if rows.empty:
        return rows
    first = np.flatnonzero(np.r_[True, (rows[names].to_numpy()[1:] != rows[names].to_numpy()[:-1]).any(axis=1)])
    out = rows.loc[first, names].reset_index(drop=True)
    for c in SUMS:
        out[c] = np.bitwise_xor.reduceat(rows[c].to_numpy(dtype=np.int64), first)
    return out


def start_changes(changed: DataFrame, path: str, checkpoint: str):
    """A running query that stores each batch's changed cells under its batch id; a replayed batch overwrites its own."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")

    return changed.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def latest_cells(spark: SparkSession, path: str) -> DataFrame:
    """Every cell as its last batch left it."""
    cells = spark.read.option("basePath", path).parquet(path)
    last = F.max_by(F.struct(*SUMS), "batch_id").alias("at")
    return cells.groupBy(*KEYS).agg(last).select(*KEYS, "at.*").filter("xu <> 0 or xv <> 0 or chk <> 0")


def stored(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """The rows a stream leaves after all its input, in a Parquet sink, of any size."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """The table a stream leaves after all its input, on the driver: for small aggregates; stored() takes rows."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
