"""DuckDB SQL that states what the queries must return, independent of how they are computed.

A family of intents is the fixpoint of intersecting its members with rows, beginning with all attributes.
Sets are HUGEINT bit masks of up to 126 attributes, the lowest rank highest.
"""

from __future__ import annotations

from galoislake.sources.workloads import WORKLOADS, Workload

_TOP = 125


def escaped(name: str) -> str:
    return f"replace(replace({name}, '\\', '\\\\'), ',', '\\,')"


def packed(w: Workload, prefix: str = "", skip: str = "FALSE") -> str:
    """CTEs attr(name, rank), pk(obj, w), everything(f), rws(w, n). skip: objects to leave out."""
    p, key = prefix, "CAST(name AS INT)" if w.number else "name"
    return f"""
{p}inc AS MATERIALIZED (SELECT DISTINCT obj, name FROM ({w.incidence}) WHERE name IS NOT NULL),
{p}attr AS MATERIALIZED (SELECT name, CAST(row_number() OVER (ORDER BY {key}) - 1 AS INT) AS rank FROM (SELECT DISTINCT name FROM {p}inc)),
{p}bit AS (SELECT i.obj, bit_or(CAST(1 AS HUGEINT) << ({_TOP} - a.rank)) AS w FROM {p}inc i JOIN {p}attr a ON a.name = i.name GROUP BY i.obj),
{p}pk AS MATERIALIZED (SELECT o.obj, coalesce(b.w, CAST(0 AS HUGEINT)) AS w FROM ({w.objects}) o LEFT JOIN {p}bit b ON b.obj = o.obj WHERE NOT ({skip})),
{p}everything AS (SELECT coalesce(bit_or(CAST(1 AS HUGEINT) << ({_TOP} - rank)), CAST(0 AS HUGEINT)) AS f FROM {p}attr),
{p}rws AS MATERIALIZED (SELECT w, count(*) AS n FROM {p}pk GROUP BY w)"""


def family(w: Workload, prefix: str = "", skip: str = "FALSE") -> str:
    """The CTEs of packed() and fam(w)."""
    p = prefix
    return packed(w, p, skip) + f""",
{p}fam(w) AS (SELECT f FROM {p}everything UNION SELECT f.w & r.w FROM {p}fam f, {p}rws r)"""


def named(of: str, prefix: str = "", column: str = "w") -> str:
    """A SELECT of w and intent for the distinct sets of a relation."""
    p = prefix
    return f"""SELECT s.w, coalesce(string_agg({escaped('a.name')}, ',' ORDER BY a.rank), '') AS intent, CAST(count(a.name) AS INT) AS size
FROM (SELECT DISTINCT {column} AS w FROM {of}) s LEFT JOIN {p}attr a ON ((s.w >> ({_TOP} - a.rank)) & 1) = 1 GROUP BY s.w"""


def concepts_cte(w: Workload, prefix: str = "", skip: str = "FALSE") -> str:
    """All CTEs, and con(w, intent, size, support)."""
    p = prefix
    return family(w, p, skip) + f""",
{p}sup AS MATERIALIZED (SELECT f.w, CAST(coalesce(sum(r.n), 0) AS BIGINT) AS support FROM {p}fam f LEFT JOIN {p}rws r ON (r.w & f.w) = f.w GROUP BY f.w),
{p}con AS MATERIALIZED (SELECT n.w, n.intent, n.size, s.support FROM ({named(p + 'fam', p)}) n JOIN {p}sup s ON s.w = n.w)"""


def concepts(name: str, tail: str = "SELECT intent, size, support FROM con", skip: str = "FALSE") -> str:
    return f"WITH RECURSIVE {concepts_cte(WORKLOADS[name], '', skip)}\n{tail}"


def over_rows(name: str, tail: str) -> str:
    return f"WITH {packed(WORKLOADS[name])}\n{tail}"
