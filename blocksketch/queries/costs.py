"""Registered cost and accuracy measures."""

from __future__ import annotations

import math

from ..cost import formulas as C
from ..cost import simulate as SIM
from ..sources import workloads as WL
from . import cost_sql as X
from .graph import KS, k_of_orders

Q: dict = {}
SQL: dict = {}


def _family(name: str, groups: dict[str, str], sql: str, grid=None) -> None:
    """grid: of a session and folder, what gives the parameters; the fixed grid if none does."""
    Q[name] = lambda s, d: C.long_frame(s, groups, grid(s, d) if grid else None)
    SQL[name] = X.on_orders(sql) if grid else sql


_family("bounds_own", {"phi": "phis", "io": "own_io"}, X.BOUNDS_OWN, C.orders_grid)
_family("bounds_prior", {"sketch": "prior_io", "external": "external_io"}, X.BOUNDS_PRIOR, C.orders_grid)
_family("io_formulas", {"io": "measures"}, X.measures(), C.orders_grid)


def _only(name: str, *keep: str, grid=None) -> None:
    Q[name] = lambda s, d: C.long_frame(s, {"io": "measures"}, grid(s, d) if grid else None).filter(" or ".join(f"measure = 'io/{k}'" for k in keep))
    SQL[name] = X.on_orders(X.measures(*keep)) if grid else X.measures(*keep)


_only("vsketch_grid", "vsketch", "vsketch_split")
_only("ksketch_grid", "ksketch_block", "ksketch_naive", grid=C.orders_grid)
_only("lower_bound_gap", "lower_bound", "gap", "gap_split", grid=C.orders_grid)
Q["verdict_grid"] = lambda s, d: C.verdict_grid(s)
SQL["verdict_grid"] = X.VERDICT_GRID


def _crossovers(s, d):
    from pyspark.sql import functions as F

    g = {n: F.col(n) for n in C.NAMES}
    return C.orders_grid(s, d).select("name", *[v.alias(k) for k, v in C.crossovers(g).items()])


Q["crossovers"] = _crossovers
SQL["crossovers"] = X.on_orders(X.CROSSOVERS)
Q["model_fit"] = lambda s, d: _crossovers(s, d).select("name", "model_fits", "space_below_edges")
SQL["model_fit"] = X.on_orders(X.MODEL_FIT)

_LOG = "log2(v) / log2(114000.0)"


def _sizes(s, d):
    from pyspark.sql import functions as F

    tib = lambda f: F.udf(lambda v: round(f(v) / 2**40, 4), "double")("v")
    return C.orders_grid(s, d).select(F.col("V").alias("v")).select("v", tib(C.casestudy_size).alias("sketch_tib"), tib(lambda v: C.casestudy_size(v, log_exponent=4)).alias("sketch_tib_k_log"), tib(C.adjacency_bytes).alias("adjacency_tib"))


Q["casestudy_sizes"] = _sizes
SQL["casestudy_sizes"] = f"SELECT v, round(v / 114000.0 * pow({_LOG}, 3) / 8, 4) AS sketch_tib, round(v / 114000.0 * pow({_LOG}, 4) / 8, 4) AS sketch_tib_k_log, round(v * (v - 1) / 2 * ceil(log2(v)) / 8 / pow(2, 40), 4) AS adjacency_tib FROM (SELECT CAST(count(DISTINCT o_custkey) + count(*) AS DOUBLE) AS v FROM orders GROUP BY o_orderpriority)"


def _break_even(s, d):
    """From the density of the customer-order graph of each priority, deleted orders left out."""
    from pyspark.sql import functions as F

    g = C.orders_grid(s, d)
    log2_v = F.udf(lambda x: round(math.log2(C.break_even(x)), 4), "double")
    return g.select((2 * F.col("E") / F.col("V") / (F.col("V") - 1)).alias("density")).select("density", log2_v("density").alias("log2_v"))


Q["casestudy_break_even"] = _break_even
Q["tail_bounds"] = lambda s, d: s.createDataFrame([(r, j, C.tail_bound(r, j)) for r in (1, 16, 64) for j in range(0, 12)], "rho int, j int, bound double")
SQL["tail_bounds"] = "SELECT CAST(rho AS INTEGER) AS rho, CAST(j AS INTEGER) AS j, least(1.0, rho * pow(2.0, -j)) AS bound FROM (VALUES (1), (16), (64)) r(rho), range(12) t(j)"
Q["round_volume"] = lambda s, d: s.createDataFrame([(r[0], C.round_volume(r[3], math.log2(r[1]), r[4])) for r in C.GRID], "name string, rounds double")
SQL["round_volume"] = X.ROUND_VOLUME


def _deletion_cost(s, d):
    from pyspark.sql import functions as F

    return k_of_orders(s, d).select("k", F.udf(C.deletion_cost, "double")("k").alias("cost"))


Q["deletion_cost_formula"] = _deletion_cost
SQL["deletion_cost_formula"] = f"SELECT k, k / 2.0 * log2(k) AS cost FROM ({KS})"
for _mode, _name in (("block", "io_sim_block"), ("per_update", "io_sim_per_update"), ("global_sort", "io_sim_global_sort")):
    Q[_name] = lambda s, d, m=_mode: SIM.simulate_io(WL.stream_w7(s, d), 64, 250, 4096, m)
    SQL[_name] = SIM.simulate_sql(WL.SQL_W7, 64, 250, 4096, _mode)
