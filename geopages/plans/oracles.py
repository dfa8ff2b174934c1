"""DuckDB fragments of the relational model: keys, pages, deltas, widths, sizes."""

from __future__ import annotations

from .fixtures import DATASETS, duck, points_sql


def cell(v: str, lo: float, hi: float) -> str:
    return f"CAST(least(65535, greatest(0, floor(({v} - ({lo})) / ({hi} - ({lo})) * 65536))) AS BIGINT)"


def spread(v: str) -> str:
    for mul, mask in ((65536, 0x0000FFFF0000FFFF), (256, 0x00FF00FF00FF00FF), (16, 0x0F0F0F0F0F0F0F0F), (4, 0x3333333333333333), (2, 0x5555555555555555)):
        v = f"(({v} | ({v} * {mul})) & {mask})" if len(v) < 400 else v
    return v


def _spread_steps(src: str, name: str, cols: tuple[str, str]) -> str:
    """CTEs that interleave two columns bit by bit, one step each."""
    out, prev = [], src
    for i, (mul, mask) in enumerate(((65536, 0x0000FFFF0000FFFF), (256, 0x00FF00FF00FF00FF), (16, 0x0F0F0F0F0F0F0F0F), (4, 0x3333333333333333), (2, 0x5555555555555555))):
        sel = ", ".join(f"(({c} | ({c} * {mul})) & {mask}) AS {c}" for c in cols)
        out.append(f"{name}{i} AS (SELECT * REPLACE ({sel}) FROM {prev})")
        prev = f"{name}{i}"
    return ", ".join(out)


def keyed(name: str, order: str) -> str:
    """CTEs that end in ``k``: (id, key) of every geometry by its box centre."""
    e = DATASETS[name].extent
    head = f"pts AS ({duck(points_sql(name))}), ctr AS (SELECT id, (min(x) + max(x)) / 2 AS cx, (min(y) + max(y)) / 2 AS cy FROM pts GROUP BY id)"
    cells = f"cel AS (SELECT id, {cell('cx', e.x_min, e.x_max)} AS hx, {cell('cy', e.y_min, e.y_max)} AS hy FROM ctr)"
    if order == "none":
        return f"{head}, k AS (SELECT id, id AS key FROM ctr)"
    if order == "shuffled":
        return f"{head}, k AS (SELECT id, id * 2654435761 % 2147483648 AS key FROM ctr)"
    if order == "z":
        return f"{head}, {cells}, {_spread_steps('cel', 'zs', ('hx', 'hy'))}, k AS (SELECT id, hx | (hy * 2) AS key FROM zs4)"
    steps, prev = "", "h16"
    for b in range(15, -1, -1):
        bx, by = f"((hx // {1 << b}) % 2)", f"((hy // {1 << b}) % 2)"
        steps += f", h{b} AS (SELECT id, CASE WHEN {by} = 0 THEN CASE WHEN {bx} = 1 THEN 65535 - hy ELSE hy END ELSE hx END AS hx, CASE WHEN {by} = 0 THEN CASE WHEN {bx} = 1 THEN 65535 - hx ELSE hx END ELSE hy END AS hy, key * 4 + xor(3 * {bx}, {by}) AS key FROM {prev})"
        prev = f"h{b}"
    return f"{head}, {cells}, h16 AS (SELECT id, hx, hy, 0::BIGINT AS key FROM cel){steps}, k AS (SELECT id, key FROM h0)"


def paged(name: str, order: str, rows: int) -> str:
    return f"{keyed(name, order)}, paged AS (SELECT *, pos // {rows} AS page, pos % {rows} AS ord FROM (SELECT pts.*, key, row_number() OVER (ORDER BY key, id, part_no, coord_no) - 1 AS pos FROM pts JOIN k USING (id) WHERE x IS NOT NULL))"


def deltas(name: str, order: str, rows: int, restart: str = "") -> str:
    """CTEs that end in ``d``: (page, ord, axis, z HUGEINT, width)."""
    extra = f", {restart}" if restart else ""
    top = "9223372036854775807"
    return f"""{paged(name, order, rows)},
bv AS (SELECT page, ord, id, 'x' AS axis, x::BIT::BIGINT AS v FROM paged UNION ALL SELECT page, ord, id, 'y', y::BIT::BIGINT FROM paged),
dd AS (SELECT page, ord, id, axis, v::HUGEINT - lag(v) OVER (PARTITION BY axis, page{extra} ORDER BY ord)::HUGEINT AS d FROM bv),
dw AS (SELECT page, ord, id, axis, CASE WHEN d > {top} THEN d - 18446744073709551616::HUGEINT WHEN d < -9223372036854775808::HUGEINT THEN d + 18446744073709551616::HUGEINT ELSE d END AS d FROM dd WHERE d IS NOT NULL),
dz AS (SELECT page, ord, id, axis, d, CASE WHEN d >= 0 THEN 2 * d ELSE -2 * d - 1 END AS z FROM dw),
d AS (SELECT *, CASE WHEN z = 0 THEN 0 ELSE length(ltrim(z::UBIGINT::BIT::VARCHAR, '0')) END AS width FROM dz),
hist AS (SELECT page, axis, width, count(*) AS cnt, sum(CASE WHEN z = 0 OR replace(ltrim(z::UBIGINT::BIT::VARCHAR, '0'), '1', '') = '' THEN 1 ELSE 0 END) AS markers FROM d GROUP BY ALL)"""


def sizes(exact: bool) -> str:
    """CTEs after ``deltas`` that end in ``s``: (page, axis, n, size, total)."""
    size = "n * total + 64 * (SELECT coalesce(sum(cnt), 0) FROM hist h WHERE h.page = t.page AND h.axis = t.axis AND h.width > n)"
    if exact:
        size += " + 64 * (SELECT coalesce(sum(markers), 0) FROM hist h WHERE h.page = t.page AND h.axis = t.axis AND h.width = n)"
        return f"tot AS (SELECT page, axis, sum(cnt)::BIGINT AS total, coalesce(sum(cnt) FILTER (width = 0), 0) AS zeros FROM hist GROUP BY ALL), s AS (SELECT page, axis, n, CASE WHEN n = 0 THEN 0 ELSE {size} END::BIGINT AS size, total FROM tot t CROSS JOIN range(65) r(n) WHERE (zeros = total AND n = 0) OR (zeros < total AND n > 0))"
    return f"tot AS (SELECT page, axis, sum(cnt)::BIGINT AS total FROM hist GROUP BY ALL), s AS (SELECT page, axis, n, ({size})::BIGINT AS size, total FROM tot t CROSS JOIN range(65) r(n))"


BEST = "best AS (SELECT page, axis, total, arg_min(n, size * 100 + n) AS n, min(size) AS bits FROM s GROUP BY ALL)"
