"""SQL building blocks for the oracles: the same steps as the operators, as CTE bodies for DuckDB."""

from __future__ import annotations

from ..spec import AXES, FieldSpec

F1_CELLS = """SELECT CAST(l_partkey % 16 AS INTEGER) AS x, CAST(l_suppkey % 8 AS INTEGER) AS y, CAST(floor((l_quantity - 1) * 8 / 50) AS INTEGER) AS z,
  CAST(4 * (year(l_shipdate) - 1995) + quarter(l_shipdate) - 1 AS INTEGER) AS t, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS v, count(*) AS n
  FROM lineitem GROUP BY 1, 2, 3, 4"""
F2_CELLS = """SELECT CAST(user_id % 16 AS INTEGER) AS x, CAST(hour(ts) AS INTEGER) AS y, CAST(floor(CAST(json_extract_string(props, '$.k') AS INTEGER) * 8 / 100) AS INTEGER) AS z,
  CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS t, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS v, count(*) AS n
  FROM events GROUP BY 1, 2, 3, 4"""


def mod_cells(m: int) -> str:
    return f"""SELECT CAST(l_partkey % {m} AS INTEGER) AS x, CAST(l_suppkey % {m} AS INTEGER) AS y, CAST(l_orderkey % {m} AS INTEGER) AS z, 0 AS t,
  CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS v, count(*) AS n FROM lineitem GROUP BY 1, 2, 3"""


def index(spec: FieldSpec) -> str:
    return f"""SELECT CAST(i % {spec.nx} AS INTEGER) AS x, CAST((i // {spec.nx}) % {spec.ny} AS INTEGER) AS y, CAST((i // {spec.nx * spec.ny}) % {spec.nz} AS INTEGER) AS z,
  CAST(i // {spec.nx * spec.ny * spec.nz} AS INTEGER) AS t FROM range({spec.voxels}) r(i)"""


def dense(cells: str, spec: FieldSpec, fill: str = "0") -> str:
    return f"SELECT x, y, z, t, coalesce(c.v, {fill}) AS v FROM ({index(spec)}) g LEFT JOIN {cells} c USING (x, y, z, t)"


def prefix(src: str, axes: tuple[str, ...] = AXES) -> str:
    out = f"SELECT x, y, z, t, v FROM {src}"
    for a in axes:
        others = ", ".join(b for b in AXES if b != a)
        out = f"SELECT x, y, z, t, CAST(sum(v) OVER (PARTITION BY {others} ORDER BY {a} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS v FROM ({out})"
    return out


def normal(src: str) -> str:
    return f"SELECT x, y, z, t, CASE WHEN hi > lo THEN 2 * (CAST(v AS DOUBLE) - lo) / (hi - lo) - 1 ELSE 0.0 END AS v FROM {src}, (SELECT CAST(min(v) AS DOUBLE) AS lo, CAST(max(v) AS DOUBLE) AS hi FROM {src})"


def down(src: str, spec: FieldSpec) -> str:
    h = spec.halved_axes()
    cols = ", ".join(f"CAST({a} // 2 AS INTEGER) AS {a}" if a in h else a for a in AXES)
    return f"SELECT {cols}, v FROM {src} WHERE " + (" AND ".join(f"{a} % 2 = 0" for a in h) or "true")


def up(src: str, fine: FieldSpec) -> str:
    out = f"SELECT x, y, z, t, v FROM {src}"
    for a in AXES:
        if a in fine.halved_axes():
            others = ", ".join(b for b in AXES if b != a)
            cols = ", ".join(f"2 * {b} + k AS {b}" if b == a else b for b in AXES)
            out = f"""SELECT {cols}, CASE WHEN k = 0 THEN v ELSE (v + nxt) / 2 END AS v
              FROM (SELECT *, coalesce(lead(v) OVER (PARTITION BY {others} ORDER BY {a}), v) AS nxt FROM ({out})), (VALUES (0), (1)) k(k) WHERE 2 * {a} + k < {fine.extents[a]}"""
    return out


def residual(fine: str, coarse_up: str) -> str:
    return f"SELECT x, y, z, t, f.v - u.v AS v FROM {fine} f JOIN {coarse_up} u USING (x, y, z, t)"


def block(spec: FieldSpec) -> str:
    gx, gy, gz = spec.blocks_per_axis
    return f"CAST(((CAST(t AS BIGINT) * {gz} + z // {spec.bz}) * {gy} + y // {spec.by}) * {gx} + x // {spec.bx} AS BIGINT)"


def energy(src: str, spec: FieldSpec) -> str:
    return f"SELECT {block(spec)} AS block_id, sqrt(sum(v * v)) AS energy FROM {src} GROUP BY 1"


F9_STEPS = """cells AS ({cells}), grid AS ({grid}), cube AS ({cube}), v1 AS ({norm})"""


def f9_ctes(cells: str = F1_CELLS, spec: FieldSpec | None = None) -> str:
    """CTEs cells, grid, cube (whole cents) and v1 (the prefix cube in [-1, 1])."""
    from ..spec import F1

    spec = spec or F1
    return F9_STEPS.format(cells=cells, grid=dense("cells", spec), cube=prefix("grid"), norm=normal("cube"))
