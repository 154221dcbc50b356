"""SQL that packs: balanced batches lap by lap, and first, best and fixed-bin placement item by item, as recursive
queries. They hold the operators to account on small tables; nothing else uses them."""

from __future__ import annotations


def balanced(items: str, capacity: int, ranks: int, reactivate: bool = True, recursive: bool = True, isolate: bool = True, prefix: str = "") -> str:
    """CTEs over a CTE items (id, size): {prefix}packed (id, size, bin_id, level, lap), {prefix}laps (level, lap, placed,
    marked, reactivated, active) and {prefix}bins (bin_id, load, n_items, sum_sq, is_oversize). With isolate, larger
    items have bins of their own behind all others.

    A row of the recursion is a bin of the present level. A lap numbers the open bins, emptiest first, meets them with
    the next items and is cut at the first that does not fit; bins from there on are full. Bins marked full stand behind
    the open ones, in the order in which they were marked."""
    c, p = capacity, prefix
    up = lambda x: f"((greatest(CAST(ceil({x} / {float(c)}) AS BIGINT), 1) + {ranks - 1}) // {ranks} * {ranks})"
    back = "coalesce(min(CASE WHEN NOT is_full THEN room END) OVER () < max(CASE WHEN is_full THEN room END) OVER (), false)" if reactivate else "false"
    deeper = f"""UNION ALL SELECT level + 1, -1, opened + b, CAST({c} AS BIGINT), false, b, nxt, NULL, opened + m, false, 0, false FROM (
        SELECT level, nxt, opened, m, unnest(range(m)) AS b FROM (SELECT s.level, s.nxt, s.opened, {up('t.rest')} AS m FROM (SELECT DISTINCT level, nxt, opened, bool_and(is_full) OVER () AS done FROM {p}lap) s JOIN {p}tail t ON t.place = s.nxt WHERE done))""" if recursive else ""
    lone = f"""SELECT id, size, n + row_number() OVER (ORDER BY size DESC, id) - 1 AS bin_id, NULL, NULL FROM {items}, {p}n WHERE size > {c}""" if isolate else ""
    return f"""{p}r AS (SELECT id, size, row_number() OVER (ORDER BY size DESC, id) - 1 AS place FROM {items} WHERE size <= {c}),
    {p}tail AS (SELECT place, CAST(sum(size) OVER (ORDER BY place DESC) AS BIGINT) AS rest FROM {p}r),
    {p}lap(level, lap, bin, room, is_full, turn, nxt, got, opened, back, active, marked) AS (
        SELECT CAST(0 AS BIGINT), CAST(-1 AS BIGINT), b, CAST({c} AS BIGINT), false, b, CAST(0 AS BIGINT), CAST(NULL AS BIGINT), m, false, CAST(0 AS BIGINT), false FROM (SELECT m, unnest(range(m)) AS b FROM (SELECT {up('rest')} AS m FROM {p}tail WHERE place = 0))
        UNION ALL (
        SELECT level, lap, bin, room, is_full AND NOT back, turn, front, got, opened, back, active, marked FROM (SELECT *, max(nxt) OVER () AS front, {back} AS back FROM (
            SELECT level, lap + 1 AS lap, bin, CASE WHEN k < cut AND size IS NOT NULL THEN room - size ELSE room END AS room, k >= cut AND stuck AS is_full,
                CASE WHEN k >= cut AND stuck THEN (lap + 2) * 1000000000 + k ELSE k END AS turn, nxt + least(cut, total - nxt) AS nxt, CASE WHEN k < cut AND size IS NOT NULL THEN nxt + k END AS got, opened, n AS active, k >= cut AND stuck AS marked
            FROM (SELECT *, coalesce(min(CASE WHEN size > room THEN k END) OVER (), n) AS cut, min(CASE WHEN size > room THEN k END) OVER () IS NOT NULL AS stuck FROM (
                SELECT a.*, i.size FROM (SELECT *, row_number() OVER (ORDER BY room DESC, turn) - 1 AS k, count(*) OVER () AS n FROM {p}lap WHERE NOT is_full) a LEFT JOIN {p}r i ON i.place = a.nxt + a.k))
            , (SELECT count(*) AS total FROM {p}r) WHERE nxt < total
            UNION ALL SELECT f.level, f.lap + 1, f.bin, f.room, true, f.turn, NULL, NULL, f.opened, 0, false FROM {p}lap f WHERE f.is_full AND EXISTS (SELECT 1 FROM {p}lap o WHERE NOT o.is_full AND o.nxt < (SELECT count(*) FROM {p}r))
        )) {deeper})),
    {p}n AS (SELECT coalesce(max(opened), 0) AS n FROM {p}lap),
    {p}packed(id, size, bin_id, level, lap) AS (SELECT r.id, r.size, l.bin, CAST(l.level AS INTEGER), CAST(l.lap AS INTEGER) FROM {p}r r {'JOIN' if recursive else 'LEFT JOIN'} {p}lap l ON l.got = r.place {'UNION ALL ' + lone if isolate else ''}),
    {p}laps AS (SELECT level, lap, count(got) AS placed, count_if(marked) AS marked, CAST(bool_or(back) AS BIGINT) AS reactivated, max(active) AS active FROM {p}lap WHERE lap >= 0 GROUP BY level, lap),
    {p}m AS (SELECT (greatest(n, coalesce((SELECT max(bin_id) + 1 FROM {p}packed), 0)) + {ranks - 1}) // {ranks} * {ranks} AS m, n FROM {p}n),
    {p}bins AS (SELECT b AS bin_id, CAST(coalesce(sum(size), 0) AS BIGINT) AS load, count(size) AS n_items, CAST(coalesce(sum(size * size), 0) AS BIGINT) AS sum_sq, b >= n AND count(size) > 0 AS is_oversize
        FROM (SELECT unnest(range(m)) AS b, n FROM {p}m) LEFT JOIN {p}packed ON bin_id = b GROUP BY b, n)"""


def on_ranks(bins: str, ranks: int, name: str = "sched") -> str:
    return f"{name} AS (SELECT *, bin_id // {ranks} AS step, CAST(bin_id % {ranks} AS INTEGER) AS rank FROM {bins})"


def greedy(items: str, capacity: int, rule: str, decreasing: bool) -> str:
    """A CTE dealt (id, size, bin_id) of first or best fit over items: rooms is the list of all open bins' room."""
    order = "size DESC, id" if decreasing else "id"
    fits = "list_position(list_transform(rooms, lambda x: x >= o.size), true)" if rule == "first" else "list_position(rooms, list_min(list_filter(rooms, lambda x: x >= o.size)))"
    return f"""o AS MATERIALIZED (SELECT id, size, row_number() OVER (ORDER BY {order}) AS n FROM {items}),
    walk(n, id, size, bin_id, rooms) AS (SELECT CAST(0 AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT), CAST([] AS BIGINT[])
        UNION ALL SELECT n, id, size, CAST(nxt - 1 AS BIGINT), CASE WHEN nxt > len(rooms) THEN list_append(rooms, {capacity} - size) ELSE list_transform(rooms, lambda x, i: CASE WHEN i = nxt THEN x - size ELSE x END) END
        FROM (SELECT o.n, o.id, o.size, rooms, coalesce(nullif({fits}, 0), len(rooms) + 1) AS nxt FROM walk JOIN o ON o.n = walk.n + 1)),
    dealt AS (SELECT id, size, bin_id FROM walk WHERE n > 0)"""


def emptiest(items: str, bins: int) -> str:
    """A CTE dealt (id, size, bin_id): largest items first, each to the emptiest of some bins, of equal ones the first."""
    return f"""o AS MATERIALIZED (SELECT id, size, row_number() OVER (ORDER BY size DESC, id) AS n FROM {items}),
    walk(n, id, size, bin_id, loads) AS (SELECT CAST(0 AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT), list_transform(range({bins}), lambda x: CAST(0 AS BIGINT))
        UNION ALL SELECT n, id, size, CAST(nxt - 1 AS BIGINT), list_transform(loads, lambda x, i: CASE WHEN i = nxt THEN x + size ELSE x END) FROM (SELECT o.n, o.id, o.size, loads, list_position(loads, list_min(loads)) AS nxt FROM walk JOIN o ON o.n = walk.n + 1)),
    dealt AS (SELECT id, size, bin_id FROM walk WHERE n > 0)"""
