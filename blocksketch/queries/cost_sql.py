"""SQL of the cost family, written from the bounds as tables of volumes, apart from the columns of cost/formulas.py.

An ingestion is a row (updates added, words of a sketch), an extraction a row of at most two sorted volumes with their factors and
one scanned volume; one expression evaluates all rows of a kind.
"""

from __future__ import annotations

from ..cost.formulas import GRID, VERDICTS

_GRID = "(VALUES " + ", ".join("('" + r[0] + "', " + ", ".join(f"CAST({x!r} AS DOUBLE)" for x in r[1:]) + ")" for r in GRID) + ") AS t(name, V, E, N, M, B, k, r, eps)"
_PARAMS = f"params AS (SELECT *, log2(V) AS lg, 1 / eps ** 2 AS q, log2(V) / eps ** 2 AS kk FROM {_GRID})"


def _sort(volume: str) -> str:
    return f"({volume}) / B * greatest(ln(({volume}) / B) / ln(M / B), 1)"


def _batches(n: str, words: str) -> str:
    return f"least({n}, {n} / B * greatest(ln(V * ({words}) / B) / ln(M / B), 1))"


def _rows(cols: str, *rows: tuple) -> str:
    return " UNION ALL ".join("SELECT params.*, " + ", ".join(f"{x} AS {c}" for x, c in zip(r, cols.split(", "))) + " FROM params" for r in rows)


_SKETCHES = _rows("problem, added, words",
    ("'connectivity'", "N", "lg ** 2"), ("'bipartiteness'", "2 * N", "lg ** 2"), ("'hypergraph'", "r * N", "(r * lg) ** 2"), ("'mst'", "N", "lg ** 2 / eps"),
    ("'k_connectivity'", "N", "k * lg ** 2"), ("'min_cut'", "N", "q * lg ** 4"), ("'sparsifier'", "N", "q * lg ** 5"), ("'densest'", "N", "q * lg ** 3"))
_EXTRACTIONS = _rows("problem, s1, f1, s2, f2, scanned",
    ("'connectivity'", "V * lg ** 2", "1", "V", "0", "0"), ("'bipartiteness'", "2 * V * lg ** 2", "1", "V", "0", "0"), ("'hypergraph'", "V * (r * lg) ** 2", "1", "V", "0", "0"), ("'mst'", "V * lg ** 2", "1 / eps", "V", "0", "0"),
    ("'k_connectivity'", "V * lg ** 2", "k", "k * V", "lg ** 4", "k * log2(k) * V * lg ** 2"), ("'min_cut'", "V * lg ** 2", "kk * log2(lg)", "V", "0", "log2(lg) * kk * log2(kk) * V * lg ** 2"),
    ("'sparsifier'", "V", "0", "V", "0", "log2(lg) * V ** 2 * lg ** 11 / eps ** 10"), ("'densest'", "q * V * lg ** 2", "V", "V", "0", "0"))
_OWN = f"""{_PARAMS}, sketches AS ({_SKETCHES}), extractions AS ({_EXTRACTIONS}),
ingested AS (SELECT name, problem, words, {_batches("added", "words")} + added * words / (M * B) + V * words / B AS io FROM sketches),
extracted AS (SELECT name, problem, f1 * ({_sort("s1")}) + f2 * ({_sort("s2")}) + scanned / B AS io FROM extractions),
own AS (SELECT name, problem, words, i.io + x.io AS io FROM ingested i JOIN extracted x USING (name, problem))"""
#: update accesses: plain accesses, then sketches of s words touched t times
_EARLIER = _rows("problem, plain, t, s",
    ("'connectivity'", f"{_sort('N')} + V", "N + V", "lg ** 2"), ("'bipartiteness'", "N + V", "N + V", "lg ** 2"), ("'hypergraph'", "N + V", "N + V", "r * lg ** 2"), ("'mst'", "N + V / eps", "N + V", "lg ** 2 / eps"),
    ("'k_connectivity'", "N + k * V", "k * N + k ** 2 * V", "lg ** 2"), ("'min_cut'", "N + q * V * lg ** 2", "q * N * lg ** 2 + V * lg ** 3 / eps ** 4", "lg ** 2"),
    ("'sparsifier'", "N + q * V * lg ** 3", "q * N * lg ** 3 + V * lg ** 4 / eps ** 4", "lg ** 2"), ("'densest'", "N * lg", "N + V", "q * lg ** 2"))
_PRIOR = f"earlier AS ({_EARLIER}), prior AS (SELECT name, problem, plain + t * s / B AS io FROM earlier)"
_EXTERNAL = " UNION ALL ".join(f"SELECT name, '{p}' AS problem, ({_sort('N')}) * lg ** {e} AS io FROM params" for p, e in (("connectivity", 0), ("bipartiteness", 0), ("mst", 0), ("k_connectivity", 4), ("min_cut", 4)))
_VALUE = "round(log2(io + 1), 6) AS log2_value"

BOUNDS_OWN = f"WITH {_OWN} SELECT name, 'phi/' || problem AS measure, round(log2(words + 1), 6) AS log2_value FROM own UNION ALL SELECT name, 'io/' || problem, {_VALUE} FROM own"
BOUNDS_PRIOR = f"WITH {_PARAMS}, {_PRIOR}, outside AS ({_EXTERNAL}) SELECT name, 'sketch/' || problem AS measure, {_VALUE} FROM prior UNION ALL SELECT name, 'external/' || problem, {_VALUE} FROM outside"

_MEASURES = f"""{_PARAMS},
parts AS (SELECT *, {_batches("N", "lg ** 2")} AS batches, {_sort("N")} AS sorted, {_sort("V * lg ** 2")} AS one FROM params),
wide AS (SELECT name, N / B AS scan_n, sorted AS sort_n, least(N, sorted) AS permute_n, batches + (N / M + V) * lg ** 2 / B AS vsketch, batches + N * lg * log2(log2(N)) / (M * B) + V * lg ** 2 / B AS vsketch_split,
         batches + N * lg / (M * B) AS lower_bound, k * (log2(k) * V * lg ** 2 / B + one) AS ksketch_block, k * (k * V * lg ** 2 / B + one) AS ksketch_naive FROM parts),
gaps AS (SELECT *, vsketch / lower_bound AS gap, vsketch_split / lower_bound AS gap_split FROM wide),
tall AS (UNPIVOT gaps ON COLUMNS(* EXCLUDE (name)) INTO NAME measure VALUE io)"""


def measures(*keep: str) -> str:
    """All formulas, or those named."""
    some = f" WHERE measure IN ({', '.join(map(repr, keep))})" if keep else ""
    return f"WITH {_MEASURES} SELECT name, 'io/' || measure AS measure, {_VALUE} FROM tall{some}"


_PRINTED = ", ".join(f"('{p}', '{v[0]}')" for p, v in VERDICTS.items())
VERDICT_GRID = f"WITH {_OWN}, {_PRIOR} SELECT name, problem, printed, prior.io > own.io AS own_is_less FROM own JOIN prior USING (name, problem) JOIN (VALUES {_PRINTED}) v(problem, printed) USING (problem)"
CROSSOVERS = f"""WITH {_PARAMS} SELECT name, k <= M * lg ** 3 AND k * V <= E AS k_beats_external, eps ** 2 * M * lg >= 1 AND eps ** 4 * E >= V * log2(lg) AS eps_beats_external, E / V >= lg ** 2 AS static_worthwhile,
N / V < lg ** 2 AS short_stream, N / V > lg ** 2 AS space_below_edges, V > M AS model_fits FROM params"""
MODEL_FIT = f"SELECT name, model_fits, space_below_edges FROM ({CROSSOVERS})"
ROUND_VOLUME = f"WITH {_PARAMS} SELECT name, 2 * N * lg / M ** 2 AS rounds FROM params"

_ORDERS = """(SELECT o_orderpriority AS name, CAST(count(DISTINCT o_custkey) + count(*) AS DOUBLE) AS V, CAST(greatest(count(*) FILTER (o_orderstatus <> 'F'), 1) AS DOUBLE) AS E, CAST(count(*) + count(*) FILTER (o_orderstatus = 'F') AS DOUBLE) AS N,
CAST(4096 AS DOUBLE) AS M, CAST(64 AS DOUBLE) AS B, CAST(2 * count(DISTINCT o_orderstatus) AS DOUBLE) AS k, CAST(count(DISTINCT o_orderstatus) AS DOUBLE) AS r, CAST(0.25 AS DOUBLE) AS eps FROM orders GROUP BY 1) AS t"""


def on_orders(sql: str) -> str:
    """The same bounds over the grid of the orders table."""
    return sql.replace(_GRID, _ORDERS)
