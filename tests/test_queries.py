"""A few registered queries against their SQL; the driver compares all of them."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", ["edges_canonical", "cells_w1", "cells_delete_cancels", "cc_w3", "cc_w4", "forest_w16", "verdict_grid", "io_sim_block", "op_join_asof", "op_window_frame", "stream_cells_equals_batch", "stream_compacted", "stream_pane_window", "stream_cell_state", "stream_group_state", "stream_late_counted", "measured_shuffle_w3", "deletion_schedule_k8"])
def test_matches_sql(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    rel = duck.sql(entry.oracle_sql()[name])
    assert sorted(rel.columns) == cols
    want = sorted(repr(tuple(r[rel.columns.index(c)] for c in cols)) for r in rel.fetchall())
    assert sorted(repr(tuple(r[c] for c in cols)) for r in df.collect()) == want


def test_compacted_snapshot_refuses_an_earlier_time(spark):
    from blocksketch.queries import streams
    from blocksketch.session import shared_folder
    from blocksketch.streaming import ingest

    path, target = streams._ingested(spark, SF), shared_folder(spark, "compacted")
    ingest.compact(spark, path, target, 2)
    with pytest.raises(ValueError, match="compacted"):
        ingest.snapshot(spark, path, 1, target)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_panes_share_folders(spark):
    """Files do not grow with panes and partitions: one for each run of panes and batch."""
    from blocksketch.operators import cells as C
    from blocksketch.queries.graph import SPEC
    from blocksketch.session import shared_folder
    from blocksketch.streaming import ingest

    path = shared_folder(spark, "panes")
    rows = spark.range(0, 40_000).selectExpr("id as seq", "id as u", "id + 50000 as v")
    ingest.write_panes(rows, 0, path, SPEC, 100)
    files = spark.read.parquet(f"{path}/cells").inputFiles()
    assert len(files) <= -(-400 // ingest.RUN)
    got = ingest.window_cells(spark, path, 60, 70)
    want = C.sketch_updates(rows.filter("seq >= 6000 and seq < 7100"), SPEC)
    assert sorted(map(tuple, got.select(want.columns).collect())) == sorted(map(tuple, want.collect()))


READ = ["bounds_own", "bounds_prior", "casestudy_break_even", "casestudy_sizes", "crossovers", "deletion_cost", "deletion_cost_formula", "deletion_schedule_k8", "io_formulas", "ksketch_grid", "lower_bound_gap", "model_fit"]  # queries that read a given table


@pytest.mark.parametrize("name", READ)
def test_reads_a_given_table(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    assert df.inputFiles() and df.count()
    if name in entry.oracle_sql():
        test_matches_sql(spark, duck, name)


def test_panes_are_made_behind_one_exchange_of_updates(spark):
    """Cells, which are many for each update, do not travel."""
    from blocksketch.queries.graph import SPEC
    from blocksketch.streaming import ingest

    cells = ingest.pane_cells(spark.range(0, 9000).selectExpr("id as seq", "id % 7 as u", "id + 50000 as v"), SPEC, 10)
    plan = cells._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.index("Generate") < plan.index("Exchange")
