"""Pieces of the SQL that checks the queries in DuckDB."""

from __future__ import annotations

from tallymill.functions.counters import reads, thresholds
from tallymill.functions.hashing import WORD_KEY_SQL, hash_sql
from tallymill.functions.keyed import uniform_sql
from tallymill.functions.text import WORDS_SQL
from tallymill.params import SketchParams

KINDS = {"B": "BIGINT", "S": "VARCHAR"}


def typed(columns: str, sql: str) -> str:
    """Columns as `name:B name:D name:S`: integers, doubles of six digits, strings."""
    out = []
    for c in columns.split():
        name, kind = c.split(":")
        out.append(f"round({name}::DOUBLE, 6) AS {name}" if kind == "D" else f"{name}::{KINDS[kind]} AS {name}")
    return f"SELECT {', '.join(out)} FROM ({sql})"


def tokens_sql(table: str = "documents", doc: str = "doc_id", text: str = "text") -> str:
    return f"SELECT doc_id, unnest(ws) AS w, unnest(range(len(ws))) AS pos FROM (SELECT {doc} AS doc_id, {WORDS_SQL.format(text)} AS ws FROM {table})"


LINES = """SELECT (CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END) * 2 + (CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END) AS k,
  l_partkey AS key, l_suppkey, l_quantity FROM lineitem"""
CLICKS = "SELECT event_type AS k, user_id AS key, event_id AS event FROM events"


def cells_sql(rows: str, p: SketchParams, group: str = "k", weight: str = "1", component: str | None = None) -> str:
    """(group, i, col, cell) of rows(group, key)."""
    g = f"{group}, " if group else ""
    parts = [f"SELECT {g}{i} AS i, {hash_sql('key', i, p, component)} AS col, {weight} AS n FROM ({rows})" for i in range(p.l)]
    return f"SELECT {g}i, col, sum(n)::BIGINT AS cell FROM ({' UNION ALL '.join(parts)}) GROUP BY ALL"


def addresses_sql(rows: str, p: SketchParams, columns: str = "k, key") -> str:
    return " UNION ALL ".join(f"SELECT {columns}, {i} AS i, {hash_sql('key', i, p)} AS col FROM ({rows})" for i in range(p.l))


def query_sql(cells: str, keys: str, p: SketchParams, value: str = "cell") -> str:
    """(k, key, est): least cell, zero if absent."""
    return f"""SELECT a.k, a.key, min(coalesce(c.{value}, 0)) AS est FROM ({addresses_sql(keys, p)}) a
      LEFT JOIN ({cells}) c ON a.k = c.k AND a.i = c.i AND a.col = c.col GROUP BY a.k, a.key"""


def doubles(values: list[float]) -> str:
    return "[" + ", ".join(repr(float(v)) for v in values) + "]"


def fold_sql(draws: str, group: str, order: str, base: float, cap: int = 255) -> str:
    """(group, state) of draws(group, order, u)."""
    table = doubles(thresholds(base, cap))
    return f"""SELECT {group}, list_reduce(list_concat([0.0::DOUBLE], us), lambda s, u: CASE WHEN u < thr[s::INT + 1] AND s < {cap} THEN s + 1 ELSE s END)::INT AS state
      FROM (SELECT {group}, list(u::DOUBLE ORDER BY {order}) AS us FROM ({draws}) GROUP BY {group}), (SELECT {table} AS thr)"""


def draws_sql(rows: str, p: SketchParams, event: str = "event") -> str:
    u = uniform_sql("'ci'", f"'{p.seed}'", event, "i") if p.counter == "independent" else uniform_sql("'cc'", f"'{p.seed}'", event)
    return f"SELECT k, i, col, {event}, {u} AS u FROM ({addresses_sql(rows, p, f'k, key, {event}')})"


def conservative_sql(rows: str, p: SketchParams, order: str, u: str | None = None) -> str:
    """(k, i, col, state): an ordered fold with the cells of a group as one list of doubles."""
    at = ", ".join(f"({i * p.w} + {hash_sql('key', i, p)})::DOUBLE" for i in range(p.l))
    own = [f"s[x[{i + 1}]::INT + 1]" for i in range(p.l)]
    least = f"least({', '.join(own)})"
    takes = f"x[{p.l + 1}] < thr[{least}::INT + 1]" if u else "true"
    table = doubles(thresholds(p.base, p.cap)) if u else "[0.0]"
    size = p.l * p.w
    return f"""
    SELECT k, (j // {p.w})::INT AS i, (j % {p.w})::INT AS col, cells[j + 1]::BIGINT AS state FROM (
      SELECT k, cells, unnest(range({size})) AS j FROM (
        SELECT k, list_reduce(list_concat([list_transform(range({size}), lambda j: 0.0::DOUBLE)], steps),
          lambda s, x: CASE WHEN {takes} THEN list_transform(range({size}), lambda j: CASE WHEN s[j + 1] = {least} AND list_contains(x[1:{p.l}], j::DOUBLE) THEN s[j + 1] + 1 ELSE s[j + 1] END) ELSE s END) AS cells
        FROM (SELECT k, list([{at}{', ' + u if u else ''}] ORDER BY {order}) AS steps FROM ({rows}) GROUP BY k), (SELECT {table} AS thr)))
    WHERE cells[j + 1] > 0"""


def merge_exact_sql(x: str, y: str, seed: int, ids: str, base: float, cap: int = 255) -> str:
    u = uniform_sql("'mg'", f"'{seed}'", ids, "j::INT")
    thr = doubles(thresholds(base, cap))
    return f"list_reduce(list_concat([greatest({x}, {y})::DOUBLE], list_transform(range(least({x}, {y})), lambda j: j + {u})), lambda s, ju: CASE WHEN ju - floor(ju) < {thr}[s::INT - floor(ju)::INT + 1] AND s < {cap} THEN s + 1 ELSE s END)::INT"


def merge_round_sql(x: str, y: str, u: str, base: float, cap: int = 255) -> str:
    r = doubles(reads(base, cap))
    value = f"({r}[{x} + 1] + {r}[{y} + 1])"
    low = f"(len(list_filter({r}, lambda q: q <= {value})) - 1)"
    return f"CASE WHEN least({x}, {y}) = 0 THEN greatest({x}, {y}) ELSE {low} + CASE WHEN {u} < ({value} - {r}[{low} + 1]) / ({r}[{low} + 2] - {r}[{low} + 1]) THEN 1 ELSE 0 END END"


def start_sql(topics: int, seed: int) -> str:
    return f"SELECT doc_id, pos, v, floor({uniform_sql(repr('z0'), repr(str(seed)), repr('0'), 'doc_id', 'pos')} * {topics})::INT AS z FROM toks"


def sweep_sql(before: str, est: str, topics: int, alpha: float, beta: float, types: str, seed: int, sweep: int) -> str:
    """A sweep over the token relation named before; est names (v, z, est)."""
    u = uniform_sql("'z'", f"'{seed}'", f"'{sweep}'", "doc_id", "pos")
    return f"""
    SELECT doc_id, pos, v, coalesce(min(k) FILTER (run > {u} * total), {topics - 1}) AS z FROM (
      SELECT doc_id, pos, v, k, sum(wt) OVER (PARTITION BY doc_id, pos ORDER BY k) AS run, sum(wt) OVER (PARTITION BY doc_id, pos) AS total FROM (
        SELECT t.doc_id, t.pos, t.v, g.k, (coalesce(d.n, 0) + {alpha}) * (coalesce(e.est, 0) + {beta}) / (coalesce(c.n, 0) + {types} * {beta}) AS wt
        FROM {before} t CROSS JOIN (SELECT unnest(range({topics})) AS k) g
        LEFT JOIN (SELECT doc_id, z, count(*) AS n FROM {before} GROUP BY ALL) d ON d.doc_id = t.doc_id AND d.z = g.k
        LEFT JOIN {est} e ON e.v = t.v AND e.z = g.k
        LEFT JOIN (SELECT z, count(*) AS n FROM {before} GROUP BY ALL) c ON c.z = g.k))
    GROUP BY doc_id, pos, v"""


FINGERPRINTS = f"SELECT doc_id, pos, w, {WORD_KEY_SQL.format('w')} AS v FROM ({tokens_sql()})"
