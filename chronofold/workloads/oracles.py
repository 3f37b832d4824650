"""The same questions as plain SQL for DuckDB: one process, no chunks, other ways to compute where there are any."""

from __future__ import annotations

from collections.abc import Sequence

from ..spec import QueryWindow
from .histories import HISTORIES

TABLES = ("region", "nation", "customer", "supplier", "part")


def _list(*names: str) -> str:
    return ", ".join(n for n in names if n)


def history(name: str) -> str:
    """CTEs ending in h: the history's rows."""
    d = HISTORIES[name]
    order = ", ".join([d.at, *d.tie])
    columns = ", ".join(f"{e} AS {n}" for n, e in (d.keys | d.payload).items())
    sql = f"b AS (SELECT {columns}, {d.at} AS valid_from, coalesce(lead({d.at}) OVER (PARTITION BY {', '.join(d.keys.values())} ORDER BY {order}), TIMESTAMP '{d.horizon}') AS valid_to FROM {d.table} WHERE {d.at} IS NOT NULL), "
    sql += "h AS (SELECT * FROM b WHERE valid_from < valid_to)"
    if d.compact:
        sql = sql.replace("h AS (", "h0 AS (") + f", h AS ({islands('h0', list(d.keys), list(d.payload))})"
    return sql


def clipped(name: str, window: QueryWindow | None, dims: Sequence[str] = ()) -> str:
    """CTEs ending in c: rows cut to the window, with static attributes."""
    d = HISTORIES[name]
    joins, extra = "", ""
    for x in dims:
        on, query = d.dims[x]
        joins += f" LEFT JOIN ({query.format(**{t: t for t in TABLES})}) d_{x} ON h.{on} = d_{x}.{on}"
        extra += f", d_{x}.* EXCLUDE ({on})"
    if window is None:
        return f"WITH {history(name)}, c AS (SELECT h.*{extra} FROM h{joins})"
    low, high = f"TIMESTAMP '{window.start}'", f"TIMESTAMP '{window.end}'"
    return (
        f"WITH {history(name)}, c AS (SELECT h.* REPLACE (greatest(h.valid_from, {low}) AS valid_from, least(h.valid_to, {high}) AS valid_to){extra} "
        f"FROM h{joins} WHERE h.valid_from < {high} AND h.valid_to > {low})"
    )


def islands(source: str, ids: Sequence[str], on: Sequence[str] = (), where: str = "") -> str:
    """Maximal intervals of rows of a relation."""
    part = _list(*ids) or "0"
    same = "".join(f" AND lag({c}) OVER w IS NOT DISTINCT FROM {c}" for c in on)
    names = _list(*ids, *on)
    cond = f" WHERE {where}" if where else ""
    inner = f"SELECT {_list(names, 'valid_from', 'valid_to')}, CASE WHEN lag(valid_to) OVER w = valid_from{same} THEN 0 ELSE 1 END AS is_new FROM {source}{cond} WINDOW w AS (PARTITION BY {part} ORDER BY valid_from)"
    outer = f"SELECT *, sum(is_new) OVER (PARTITION BY {part} ORDER BY valid_from ROWS UNBOUNDED PRECEDING) AS island FROM ({inner})"
    return f"SELECT {_list(names, 'min(valid_from) AS valid_from', 'max(valid_to) AS valid_to')} FROM ({outer}) GROUP BY {_list(names, 'island')}"


def predicate(name: str, window: QueryWindow, phi: str, payload: Sequence[str] = (), dims: Sequence[str] = ()) -> str:
    return f"{clipped(name, window, dims)} {islands('c', list(HISTORIES[name].keys), payload, f'coalesce({phi}, false)')}"


def duration(name: str, window: QueryWindow, x: str, group: Sequence[str], dims: Sequence[str] = (), where: str = "true") -> str:
    g = _list(*group)
    return (
        f"{clipped(name, window, dims)}, s AS (SELECT {_list(g, f'{x} AS x')}, CAST(date_diff('microsecond', valid_from, valid_to) AS BIGINT) AS d FROM c WHERE {where}) "
        f"SELECT {_list(g, 'CAST(sum(CAST(x AS DECIMAL(18,2)) * CAST(d AS DECIMAL(20,0))) AS DECIMAL(38,2)) AS weighted_sum')}, CAST(sum(d) AS BIGINT) AS duration_us, min(x) AS x_min, max(x) AS x_max, "
        f"round(CAST(sum(CAST(x AS DECIMAL(18,2)) * CAST(d AS DECIMAL(20,0))) AS DOUBLE) / sum(d), 6) AS twa FROM s WHERE x IS NOT NULL" + (f" GROUP BY {g}" if g else "")
    )


def timeline(name: str, window: QueryWindow, phi: str, group: Sequence[str], dims: Sequence[str] = ()) -> str:
    """CTEs ending in t: counts between neighbouring instants of a group."""
    g, part = _list(*group), _list(*group) or "0"
    cut = clipped(name, window, dims)
    return (
        f"{cut}, e AS (SELECT {_list(g, 'valid_from AS tick')}, 1 AS delta FROM c WHERE coalesce({phi}, false) UNION ALL SELECT {_list(g, 'valid_to AS tick')}, -1 AS delta FROM c WHERE coalesce({phi}, false)), "
        f"s AS (SELECT {_list(g, 'tick')}, sum(delta) AS delta FROM e GROUP BY {_list(g, 'tick')}), "
        f"r AS (SELECT {_list(g, 'tick AS valid_from')}, lead(tick) OVER w AS valid_to, CAST(sum(delta) OVER w AS BIGINT) AS active FROM s WINDOW w AS (PARTITION BY {part} ORDER BY tick)), "
        f"t AS (SELECT * FROM r WHERE active > 0 AND valid_to IS NOT NULL)"
    )


def count(name: str, window: QueryWindow, phi: str, group: Sequence[str], dims: Sequence[str] = (), c: int | None = None) -> str:
    cut = timeline(name, window, phi, group, dims)
    return f"{cut} {islands('t', group, ['active'])}" if c is None else f"{cut} {islands('t', group, (), f'active > {c}')}"


def pairwise(name: str, window: QueryWindow, left: str, right: str, x: str, op: str, dims: Sequence[str] = (), both: bool = False) -> str:
    """An overlap join of the two keys' rows; ``left`` and ``right`` are SQL values."""
    key = next(iter(HISTORIES[name].keys))
    pairs = f"p AS (SELECT l.{key} AS left_key, r.{key} AS right_key, greatest(l.valid_from, r.valid_from) AS valid_from, least(l.valid_to, r.valid_to) AS valid_to, l.{x} {op} r.{x} AS holds FROM c l, c r WHERE l.{key} = {left} AND r.{key} = {right} AND l.valid_from < r.valid_to AND r.valid_from < l.valid_to)"
    ids = ["left_key", "right_key"]
    return f"{clipped(name, window, dims)}, {pairs} {islands('p', ids, ['holds']) if both else islands('p', ids, (), 'holds')}"


def _cohort(name: str, where: str) -> str:
    return f"m AS (SELECT * FROM c WHERE {where})"


def better(name: str, window: QueryWindow, where: str, reference: str, x: str, op: str, dims: Sequence[str] = ()) -> str:
    """Counts at each cut while the reference holds."""
    key = next(iter(HISTORIES[name].keys))
    return (
        f"{clipped(name, window, dims)}, {_cohort(name, where)}, q AS (SELECT DISTINCT valid_from AS tick FROM m UNION SELECT DISTINCT valid_to FROM m), g AS (SELECT tick AS valid_from, lead(tick) OVER (ORDER BY tick) AS valid_to FROM q), "
        f"r AS (SELECT g.valid_from, g.valid_to, ref.{key} AS reference_key, ref.{x} AS rx FROM g JOIN m ref ON ref.{key} = {reference} AND ref.valid_from <= g.valid_from AND g.valid_from < ref.valid_to WHERE g.valid_to IS NOT NULL), "
        f"n AS (SELECT r.reference_key, r.valid_from, r.valid_to, CAST(count(o.{key}) AS BIGINT) AS better FROM r LEFT JOIN m o ON o.{key} <> r.reference_key AND o.valid_from <= r.valid_from AND r.valid_from < o.valid_to AND o.{x} {op} r.rx GROUP BY ALL) "
        f"{islands('n', ['reference_key'], ['better'])}"
    )


def ranked(name: str, window: QueryWindow, where: str, x: str, k: int, dims: Sequence[str] = (), family: Sequence[str] = (), descending: bool = False) -> str:
    """All cuts of a cohort, the rows that hold at each, and their order."""
    key = next(iter(HISTORIES[name].keys))
    f, part = _list(*family), _list(*family) or "0"
    on = " AND ".join(["m.valid_from <= g.valid_from", "g.valid_from < m.valid_to", "g.valid_to IS NOT NULL", *(f"m.{c} = g.{c}" for c in family)])
    gf = _list(*(f"g.{c}" for c in family))
    order = f"m.{x} {'DESC' if descending else 'ASC'}, m.{key}"
    return (
        f"{clipped(name, window, dims)}, {_cohort(name, where)}, q AS (SELECT {_list(f, 'valid_from AS tick')} FROM m UNION SELECT {_list(f, 'valid_to AS tick')} FROM m), "
        f"g AS (SELECT {_list(f, 'tick AS valid_from')}, lead(tick) OVER (PARTITION BY {part} ORDER BY tick) AS valid_to FROM q), "
        f"o AS (SELECT {_list(gf, 'g.valid_from', 'g.valid_to')}, m.{key} AS key, m.{x} AS x, CAST(row_number() OVER (PARTITION BY {_list(gf, 'g.valid_from')} ORDER BY {order}) AS INT) AS rank FROM g JOIN m ON {on}), "
        f"z AS (SELECT * FROM o WHERE rank <= {k}) SELECT {_list(f, 'valid_from', 'valid_to', 'rank', 'key', 'x')} FROM ({islands('z', [*family, 'rank'], ['key', 'x'])})"
    )


def difference_gated(name: str, window: QueryWindow, brand: str, exceeding: str, evidence: str) -> str:
    """Each brand row less the union of exceeding rows, by the cuts of the key; kept for keys with evidence."""
    key = next(iter(HISTORIES[name].keys))
    return (
        f"{clipped(name, window)}, a AS (SELECT * FROM c WHERE coalesce({brand}, false)), x AS (SELECT * FROM c WHERE coalesce({exceeding}, false)), k AS (SELECT DISTINCT {key} FROM c WHERE coalesce({evidence}, false)), "
        f"q AS (SELECT {key}, valid_from AS tick FROM a UNION SELECT {key}, valid_to FROM a UNION SELECT {key}, valid_from FROM x UNION SELECT {key}, valid_to FROM x), "
        f"g AS (SELECT {key}, tick AS valid_from, lead(tick) OVER (PARTITION BY {key} ORDER BY tick) AS valid_to FROM q), "
        f"r AS (SELECT g.* FROM g WHERE g.valid_to IS NOT NULL AND EXISTS (SELECT 1 FROM a WHERE a.{key} = g.{key} AND a.valid_from <= g.valid_from AND g.valid_from < a.valid_to) "
        f"AND NOT EXISTS (SELECT 1 FROM x WHERE x.{key} = g.{key} AND x.valid_from <= g.valid_from AND g.valid_from < x.valid_to) AND g.{key} IN (SELECT {key} FROM k)) {islands('r', [key])}"
    )
