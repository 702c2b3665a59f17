"""DuckDB SQL for walks: bounded recursion over (vertex, state, level), then backwards over least levels."""

from __future__ import annotations

from walkengine.graph.views import VIEW_SQL
from walkengine.lang.automata import Nfa


def literal(v) -> str:
    return f"'{v}'" if isinstance(v, str) else str(v)


def search(view: str, nfa: Nfa, source, longest: int = 8) -> str:
    """CTEs e, d, reach, firsts."""
    moves = ", ".join(f"({p}, '{a}', {q})" for p, a, q in sorted(nfa.moves))
    starts = " UNION ALL ".join(f"SELECT {literal(source)}, {q}, 0" for q in sorted(nfa.initial))
    return f"""WITH RECURSIVE e AS MATERIALIZED ({VIEW_SQL[view]}), d(p, l, q) AS (VALUES {moves}),
reach(v, q, lv) AS ({starts} UNION
  SELECT e.dst, d.q, reach.lv + 1 FROM reach JOIN e ON e.src = reach.v JOIN d ON d.p = reach.q AND list_contains(e.labels, d.l) WHERE reach.lv < {longest}),
firsts AS MATERIALIZED (SELECT v, q, min(lv) AS lv FROM reach GROUP BY v, q)"""


def runs(view: str, nfa: Nfa, source, target=None, longest: int = 8) -> str:
    """The same and ``walks`` with one row for every accepting run: target, length, path."""
    final = ", ".join(map(str, sorted(nfa.final)))
    where = f" AND v = {literal(target)}" if target is not None else ""
    return f"""{search(view, nfa, source, longest)},
lam AS (SELECT v AS target, min(lv) AS l FROM firsts WHERE q IN ({final}){where} GROUP BY v),
w(target, l, v, q, lv, path) AS (
  SELECT target, l, v, q, lv, '' FROM firsts JOIN lam ON v = target AND lv = l WHERE q IN ({final})
  UNION ALL
  SELECT w.target, w.l, f.v, f.q, f.lv, CASE WHEN w.lv = w.l THEN e.edge_id::VARCHAR ELSE e.edge_id || '>' || w.path END
  FROM w JOIN e ON e.dst = w.v JOIN d ON d.q = w.q AND list_contains(e.labels, d.l) JOIN firsts f ON f.v = e.src AND f.q = d.p AND f.lv = w.lv - 1),
walks AS (SELECT target, l AS length, path AS edge_path FROM w WHERE lv = 0)"""


def walks(view: str, nfa: Nfa, source, target, longest: int = 8) -> str:
    return f"{runs(view, nfa, source, target, longest)}\nSELECT DISTINCT length::INT AS length, edge_path FROM walks"


def ranked(view: str, nfa: Nfa, source, target, longest: int = 8) -> str:
    """Walks with their rank in in-edge order read from the target."""
    return f"""{runs(view, nfa, source, target, longest)},
ranked AS (SELECT edge_path, row_number() OVER (ORDER BY list_reverse(string_split(edge_path, '>'))) - 1 AS rank FROM (SELECT DISTINCT edge_path FROM walks))"""


def cheapest(view: str, nfa: Nfa, source, target, cost: str, most: int) -> str:
    """Cheapest walks: recursion over (vertex, state, cost), then backwards along tight edges."""
    moves = ", ".join(f"({p}, '{a}', {q})" for p, a, q in sorted(nfa.moves))
    final = ", ".join(map(str, sorted(nfa.final)))
    starts = " UNION ALL ".join(f"SELECT {literal(source)}, {q}, 0::BIGINT" for q in sorted(nfa.initial))
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT edge_id, src, dst, labels, {cost} AS cost FROM ({VIEW_SQL[view]})), d(p, l, q) AS (VALUES {moves}),
reach(v, q, lv) AS ({starts} UNION
  SELECT e.dst, d.q, reach.lv + e.cost FROM reach JOIN e ON e.src = reach.v JOIN d ON d.p = reach.q AND list_contains(e.labels, d.l) WHERE reach.lv + e.cost <= {most}),
firsts AS MATERIALIZED (SELECT v, q, min(lv) AS lv FROM reach GROUP BY v, q),
lam AS (SELECT min(lv) AS l FROM firsts WHERE q IN ({final}) AND v = {literal(target)}),
w(l, v, q, lv, path, n) AS (
  SELECT l, v, q, lv, '', 0 FROM firsts, lam WHERE v = {literal(target)} AND lv = l AND q IN ({final})
  UNION ALL
  SELECT w.l, f.v, f.q, f.lv, CASE WHEN w.n = 0 THEN e.edge_id::VARCHAR ELSE e.edge_id || '>' || w.path END, w.n + 1
  FROM w JOIN e ON e.dst = w.v JOIN d ON d.q = w.q AND list_contains(e.labels, d.l) JOIN firsts f ON f.v = e.src AND f.q = d.p AND f.lv = w.lv - e.cost)
SELECT DISTINCT l::BIGINT AS cost, n::INT AS length, path AS edge_path FROM w WHERE lv = 0"""
