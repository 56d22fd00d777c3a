"""SQL of the same quantities, built from small parts; used to check the queries."""

from __future__ import annotations

from .operators.quadrature import gauss

FOUR_PI = "(4 * pi())"


def panels(n: str | int, project: bool = True, name: str = "p") -> str:
    """CTEs ending in `name`(pid, v0.., ax.. kx.. cx.. (k for the second corner: "by" is a word of SQL), gram, area, nx.., gx.., lox.., hix..) for a mesh of refinement n (an SQL value)."""
    size = "sqrt(CAST({a} AS DOUBLE) * {a} + CAST({b} AS DOUBLE) * {b} + CAST({c} AS DOUBLE) * {c})" if project else "CAST(n AS DOUBLE)"
    corners = []
    for j, p in enumerate("akc"):
        a, b, c = f"p{j}a", f"p{j}b", f"p{j}c"
        s = size.format(a=a, b=b, c=c)
        corners.append(f"(({a} + n) * (2 * n + 1) + {b} + n) * (2 * n + 1) + {c} + n AS v{j}, " + ", ".join(f"CAST({q} AS DOUBLE) / {s} + 0.0 AS {p}{x}" for q, x in zip((a, b, c), "xyz", strict=True)))
    return f"""n0 AS (SELECT CAST({n} AS BIGINT) AS n),
r0 AS (SELECT n, unnest(range(0, 8 * n * n)) AS pid FROM n0),
r1 AS (SELECT n, pid, pid // (n * n) AS face, pid % (n * n) AS k FROM r0),
r2 AS (SELECT *, CAST(floor(sqrt(CAST(k AS DOUBLE))) AS BIGINT) AS r FROM r1),
r3 AS (SELECT *, (k - r * r) // 2 AS m, (k - r * r) % 2 = 0 AS up, 1 - 2 * (face % 2) AS sx, 1 - 2 * ((face // 2) % 2) AS sy, 1 - 2 * ((face // 4) % 2) AS sz FROM r2),
r4 AS (SELECT *, CASE WHEN up THEN r + 1 - m ELSE r - m END AS ba, CASE WHEN up THEN m ELSE m + 1 END AS bb, n - r - 1 AS bc, CASE WHEN up THEN r - m ELSE r - m - 1 END AS ca, m + 1 AS cb, CASE WHEN up THEN n - r - 1 ELSE n - r END AS cc, sx * sy * sz < 0 AS odd FROM r3),
r5 AS (SELECT n, pid, sx * (r - m) AS p0a, sy * m AS p0b, sz * (n - r) AS p0c,
 sx * CASE WHEN odd THEN ca ELSE ba END AS p1a, sy * CASE WHEN odd THEN cb ELSE bb END AS p1b, sz * CASE WHEN odd THEN cc ELSE bc END AS p1c,
 sx * CASE WHEN odd THEN ba ELSE ca END AS p2a, sy * CASE WHEN odd THEN bb ELSE cb END AS p2b, sz * CASE WHEN odd THEN bc ELSE cc END AS p2c FROM r4),
r6 AS (SELECT n, pid, {", ".join(corners)} FROM r5),
r7 AS (SELECT *, (ky - ay) * (cz - kz) - (kz - az) * (cy - ky) AS ux, (kz - az) * (cx - kx) - (kx - ax) * (cz - kz) AS uy, (kx - ax) * (cy - ky) - (ky - ay) * (cx - kx) AS uz FROM r6),
r8 AS (SELECT *, sqrt(ux * ux + uy * uy + uz * uz) AS gram FROM r7),
{name} AS (SELECT n, pid, v0, v1, v2, ax, ay, az, kx, ky, kz, cx, cy, cz, gram, gram / 2 AS area, ux / gram + 0.0 AS nx, uy / gram + 0.0 AS ny, uz / gram + 0.0 AS nz,
 (ax + kx + cx) / 3.0 + 0.0 AS gx, (ay + ky + cy) / 3.0 + 0.0 AS gy, (az + kz + cz) / 3.0 + 0.0 AS gz,
 least(ax, kx, cx) AS lox, least(ay, ky, cy) AS loy, least(az, kz, cz) AS loz, greatest(ax, kx, cx) AS hix, greatest(ay, ky, cy) AS hiy, greatest(az, kz, cz) AS hiz FROM r8)"""


PART_N = "(SELECT floor(sqrt(count(*) / 8.0)) FROM part)"


def scaled(expr: str, digits: int, name: str) -> str:
    return f"CAST(round(({expr}) * 1e{digits}) AS BIGINT) AS {name}"


def touching(name: str = "near") -> str:
    return f"""inc AS (SELECT pid, unnest([v0, v1, v2]) AS vid FROM p),
{name} AS (SELECT a.pid AS i, b.pid AS j, CAST(count(*) AS INTEGER) AS cls FROM inc a JOIN inc b USING (vid) GROUP BY ALL)"""


def line(n: int, name: str) -> str:
    g, w = gauss(n)
    return f"{name} AS (SELECT * FROM (VALUES " + ", ".join(f"({float(x)!r}::DOUBLE, {float(y)!r}::DOUBLE)" for x, y in zip(g, w, strict=True)) + ") AS q(x, w))"


# Points (s, t, u, v) and Jacobians of the pieces of each case, in the variables x, a, b, c of the unit cube.
PIECES = {
    0: [("x", "x*a", "b", "b*c", "x*b")],
    1: [("x", "x*a", "x*b", "x*b*c", "x*x*x*b"), ("x*b", "x*b*c", "x", "x*a", "x*x*x*b")],
    2: [
        ("x", "x*a*c", "x*(1-a*b)", "x*a*(1-b)", "x*x*x*a*a"),
        ("x", "x*a", "x*(1-a*b*c)", "x*a*b*(1-c)", "x*x*x*a*a*b"),
        ("x*(1-a*b)", "x*a*(1-b)", "x", "x*a*b*c", "x*x*x*a*a*b"),
        ("x*(1-a*b*c)", "x*a*b*(1-c)", "x", "x*a", "x*x*x*a*a*b"),
        ("x*(1-a*b*c)", "x*a*(1-b*c)", "x", "x*a*b", "x*x*x*a*a*b"),
    ],
    3: [
        ("x", "x*(1-a+a*b)", "x*(1-a*b*c)", "x*(1-a)", "x*x*x*a*a*b"),
        ("x*(1-a*b*c)", "x*(1-a)", "x", "x*(1-a+a*b)", "x*x*x*a*a*b"),
        ("x", "x*a*(1-b+b*c)", "x*(1-a*b)", "x*a*(1-b)", "x*x*x*a*a*b"),
        ("x*(1-a*b)", "x*a*(1-b)", "x", "x*a*(1-b+b*c)", "x*x*x*a*a*b"),
        ("x*(1-a*b*c)", "x*a*(1-b*c)", "x", "x*a*(1-b)", "x*x*x*a*a*b"),
        ("x", "x*a*(1-b)", "x*(1-a*b*c)", "x*a*(1-b*c)", "x*x*x*a*a*b"),
    ],
}


def rules(regular: int, singular: int, cases=(0, 1, 2, 3)) -> str:
    """CTEs ending in rules(cls, s, t, u, v, w)."""
    out = [line(regular, "g0"), line(singular, "g1")]
    parts = []
    for c in cases:
        g = "g0" if c == 0 else "g1"
        for s, t, u, v, j in PIECES[c]:
            parts.append(f"SELECT {c} AS cls, {s} AS s, {t} AS t, {u} AS u, {v} AS v, w * ({j}) AS w FROM cube{g}")
    for g in ("g0", "g1"):
        out.append(f"cube{g} AS (SELECT p.x AS x, q.x AS a, r.x AS b, z.x AS c, p.w * q.w * r.w * z.w AS w FROM {g} p, {g} q, {g} r, {g} z)")
    return ",\n".join([*out, "rules AS (" + " UNION ALL ".join(parts) + ")"])


def entries(pairs: str, layer: str = "slp", kappa: float = 0.0, name: str = "e") -> str:
    """CTEs ending in `name`(i, j, cls, re, im) for a relation `pairs`(i, j, cls) over p and rules."""
    shared = "list_sort(list_filter([a.v0, a.v1, a.v2], lambda x: list_contains([b.v0, b.v1, b.v2], x)))"
    cols = []
    for s in "ab":
        ids = f"[{s}.v0, {s}.v1, {s}.v2]"
        order = f"list_concat(sh, list_filter({ids}, lambda x: NOT list_contains(sh, x)))"
        for k in range(3):
            pick = f"list_position({ids}, ({order})[{k + 1}])"
            for x in "xyz":
                cols.append(f"[{s}.a{x}, {s}.k{x}, {s}.c{x}][{pick}] AS {s}{k}{x}")
    d = {x: f"(a0{x} + s * (a1{x} - a0{x}) + t * (a2{x} - a1{x})) - (b0{x} + u * (b1{x} - b0{x}) + v * (b2{x} - b1{x}))" for x in "xyz"}
    scale = "w * ga * gb"
    if layer == "slp":
        base = f"1.0 / ({FOUR_PI} * r)"
        re, im = (base, "0.0") if not kappa else (f"{base} * cos({kappa} * r)", f"{base} * sin({kappa} * r)")
    else:
        base = f"(dx * nx + dy * ny + dz * nz) / ({FOUR_PI} * r2 * r)"
        re, im = (base, "0.0") if not kappa else (f"{base} * (cos({kappa} * r) + {kappa} * r * sin({kappa} * r))", f"{base} * (sin({kappa} * r) - {kappa} * r * cos({kappa} * r))")
    return f"""{name}0 AS (SELECT q.i, q.j, q.cls, CASE WHEN q.cls > 0 THEN {shared} ELSE [] END AS sh, a, b FROM {pairs} q JOIN p a ON a.pid = q.i JOIN p b ON b.pid = q.j),
{name}1 AS (SELECT i, j, cls, {", ".join(cols)}, a.gram AS ga, b.gram AS gb, b.nx AS nx, b.ny AS ny, b.nz AS nz FROM {name}0),
{name}2 AS (SELECT i, j, cls, w, ga, gb, nx, ny, nz, {d["x"]} AS dx, {d["y"]} AS dy, {d["z"]} AS dz FROM {name}1 JOIN rules USING (cls)),
{name}3 AS (SELECT *, dx * dx + dy * dy + dz * dz AS r2, sqrt(dx * dx + dy * dy + dz * dz) AS r FROM {name}2),
{name} AS (SELECT i, j, cls, sum({scale} * CASE WHEN r = 0 THEN NULL ELSE {re} END) AS re, sum({scale} * CASE WHEN r = 0 THEN NULL ELSE {im} END) AS im FROM {name}3 GROUP BY i, j, cls)"""
