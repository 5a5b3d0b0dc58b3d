"""DuckDB SQL for the same questions, from the definitions: class counts of every attribute subset, dependencies as equal counts, minimality by an anti join."""

from __future__ import annotations

from itertools import combinations

from .sources.views import COLUMNS, VIEW_SQL


def _q(c: str) -> str:
    return f'"{c}"'


def lattice(source: str, columns: tuple[str, ...], max_lhs: int | None = None) -> str:
    """CTEs: src, n(n), bits(bit, name), cards(mask, card), fds(mask, bit, rhs, n_classes, n_rows): all minimal dependencies with up to max_lhs attributes on the left."""
    m = len(columns)
    most = m if max_lhs is None else min(m, max_lhs + 1)
    parts = ["SELECT 0 AS mask, CAST(count(*) > 0 AS BIGINT) AS card FROM (SELECT 1 FROM src LIMIT 1)"]
    for size in range(1, most + 1):
        for some in combinations(range(m), size):
            mask = sum(1 << i for i in some)
            parts.append(f"SELECT {mask}, count(*) FROM (SELECT DISTINCT {', '.join(_q(columns[i]) for i in some)} FROM src)")
    bits = ", ".join(f"({1 << i}, '{c}')" for i, c in enumerate(columns))
    cap = "" if max_lhs is None else f" WHERE bit_count(x.mask) <= {max_lhs}"
    return f"""WITH src AS MATERIALIZED ({source}), n AS (SELECT count(*) AS n FROM src), bits(bit, name) AS (VALUES {bits}),
cards AS MATERIALIZED ({' UNION ALL '.join(parts)}),
holds AS MATERIALIZED (
  SELECT x.mask, b.bit, b.name AS rhs, x.card AS n_classes FROM cards x JOIN bits b ON (x.mask & b.bit) = 0 JOIN cards y ON y.mask = (x.mask | b.bit) AND y.card = x.card{cap}),
fds AS (
  SELECT h.mask, h.bit, h.rhs, h.n_classes, n AS n_rows, n - h.n_classes AS redundancy, CAST(bit_count(h.mask) AS INTEGER) AS lhs_size,
         coalesce((SELECT string_agg(name, ',' ORDER BY name) FROM bits WHERE (bits.bit & h.mask) <> 0), '') AS lhs_text
  FROM holds h, n WHERE n > 0 AND NOT EXISTS (SELECT 1 FROM holds s WHERE s.bit = h.bit AND s.mask <> h.mask AND (s.mask & h.mask) = s.mask))"""


_ROW = "CAST(row_number() OVER (ORDER BY redundancy DESC, lhs_size, lhs_text, rhs) AS INTEGER) AS rank, lhs_text, rhs, lhs_size, CAST(redundancy AS BIGINT) AS redundancy, CAST(n_rows AS BIGINT) AS n_rows, CAST(n_classes AS BIGINT) AS n_classes"


def topk(view: str, k: int, max_lhs: int | None = None, columns: tuple[str, ...] | None = None, source: str | None = None) -> str:
    columns = columns or COLUMNS[view]
    return f"{lattice(source or VIEW_SQL[view], columns, max_lhs)} SELECT {_ROW} FROM fds WHERE redundancy > 0 ORDER BY redundancy DESC, lhs_size, lhs_text, rhs LIMIT {k}"


def everything(view: str, max_lhs: int | None = None, columns: tuple[str, ...] | None = None) -> str:
    return f"{lattice(VIEW_SQL[view], columns or COLUMNS[view], max_lhs)} SELECT {_ROW} FROM fds"


def over_fds(view: str, select: str, max_lhs: int | None = None) -> str:
    """Any select over the CTE fds of a view."""
    return f"{lattice(VIEW_SQL[view], COLUMNS[view], max_lhs)} {select}"


def cards(view: str, sizes: tuple[int, ...], columns: tuple[str, ...] | None = None) -> str:
    columns = columns or COLUMNS[view]
    parts = []
    for size in sizes:
        for some in combinations(columns, size):
            parts.append(f"SELECT '{','.join(sorted(some))}' AS attrs, CAST({size} AS INTEGER) AS size, CAST(count(*) AS BIGINT) AS card FROM (SELECT DISTINCT {', '.join(map(_q, some))} FROM src)")
    return f"WITH src AS MATERIALIZED ({VIEW_SQL[view]}) {' UNION ALL '.join(parts)}"


def differences(view: str) -> str:
    """attrs, support: over all pairs of rows."""
    columns = COLUMNS[view]
    names = sorted(columns)
    flags = ", ".join(f"CASE WHEN a.{_q(c)} IS DISTINCT FROM b.{_q(c)} THEN '{c}' END" for c in names)
    return f"""WITH src AS MATERIALIZED (SELECT *, row_number() OVER () AS rid FROM ({VIEW_SQL[view]}))
SELECT array_to_string(list_filter([{flags}], lambda x: x IS NOT NULL), ',') AS attrs, count(*) AS support FROM src a JOIN src b ON a.rid < b.rid GROUP BY 1"""


def class_differences(view: str) -> str:
    """The same over a relation of many rows and few different ones: pairs of classes, by the number of row pairs that each stands for."""
    columns = COLUMNS[view]
    flags = ", ".join(f"CASE WHEN a.{_q(c)} IS DISTINCT FROM b.{_q(c)} THEN '{c}' END" for c in sorted(columns))
    return f"""WITH src AS MATERIALIZED (SELECT *, row_number() OVER () AS cid FROM (SELECT {', '.join(map(_q, columns))}, count(*) AS n FROM ({VIEW_SQL[view]}) GROUP BY ALL))
SELECT attrs, CAST(sum(pairs) AS BIGINT) AS support FROM (SELECT array_to_string(list_filter([{flags}], lambda x: x IS NOT NULL), ',') AS attrs, CASE WHEN a.cid = b.cid THEN a.n * (a.n - 1) // 2 ELSE a.n * b.n END AS pairs
 FROM src a JOIN src b ON a.cid <= b.cid) WHERE pairs > 0 GROUP BY 1"""
