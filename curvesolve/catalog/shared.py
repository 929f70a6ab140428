"""The grids and SQL fragments that several areas use."""

from __future__ import annotations

from ..functions.grid import GridSpec

#: Quantity by discount cells.
G2 = GridSpec.of_levels((4, 3))
N, P, Q, GAMMA = G2.size, 8, 3, 0.5
#: Orders by day.
G1 = GridSpec.of_levels((6,))
SCALE = 1e9


def cells_sql(spec: GridSpec) -> str:
    cols = [f"CAST((i // {s}) % {n} + 1 AS INTEGER) AS k{j + 1}" for j, (s, n) in enumerate(zip(spec.strides, spec.extents))]
    return f"SELECT CAST(i AS BIGINT) AS id, {', '.join(cols)} FROM range({spec.size}) t(i)"


def laplace_sql(spec: GridSpec) -> str:
    """(i, j, v) by a self join of neighbouring cells."""
    d = range(1, spec.d + 1)
    dist = " + ".join(f"abs(a.k{j} - b.k{j})" for j in d)
    off = " ".join(f"WHEN a.k{j} <> b.k{j} THEN {-1 / h**2!r}" for j, h in zip(d, spec.widths))
    return (f"SELECT a.id AS i, b.id AS j, CAST(CASE {off} ELSE {spec.diagonal!r} END AS DOUBLE) AS v "
            f"FROM ({cells_sql(spec)}) a JOIN ({cells_sql(spec)}) b ON {dist} <= 1")


def rhs_sql(name: str, spec: GridSpec) -> str:
    """(id, cents) on every cell."""
    if name == "B1":
        code = ["date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))"]
        table, amount, codes = "orders", "o_totalprice", [2405]
    else:
        code = ["CAST(l_quantity AS INTEGER) - 1", "CAST(round(l_discount * 100) AS INTEGER)", "CAST(round(l_tax * 100) AS INTEGER)"][:spec.d]
        table, amount, codes = "lineitem", "l_extendedprice", [50, 11, 9]
    number = " + ".join(f"(({c}) * {n} // {m}) * {s}" for c, n, m, s in zip(code, spec.extents, codes, spec.strides))
    return (f"SELECT CAST(c.i AS BIGINT) AS id, CAST(coalesce(f.cents, 0) AS BIGINT) AS cents FROM range({spec.size}) c(i) LEFT JOIN "
            f"(SELECT {number} AS id, sum(CAST(round({amount} * 100) AS BIGINT)) AS cents FROM {table} GROUP BY 1) f ON f.id = c.i")


def facts_sql(spec: GridSpec) -> str:
    """(id, facts) of the cells that hold facts of lineitem, along quantity, discount and tax."""
    code = ["CAST(l_quantity AS INTEGER) - 1", "CAST(round(l_discount * 100) AS INTEGER)", "CAST(round(l_tax * 100) AS INTEGER)"][:spec.d]
    number = " + ".join(f"(({c}) * {n} // {m}) * {s}" for c, n, m, s in zip(code, spec.extents, [50, 11, 9], spec.strides))
    return f"SELECT CAST({number} AS BIGINT) AS id, CAST(count(*) AS BIGINT) AS facts FROM lineitem GROUP BY 1"


def slices_sql(n: int, p: int) -> str:
    w, r = n // p, n % p
    return (f"SELECT CAST(s AS INTEGER) AS sub, CAST(s * {w} + least(s, {r}) AS BIGINT) AS lo, CAST({w} + (CASE WHEN s < {r} THEN 1 ELSE 0 END) AS BIGINT) AS size FROM range({p}) t(s)")


def members_sql(n: int, p: int, gamma: float) -> str:
    """(sub, pos, owner) by building each grown slice from whole and partial neighbours."""
    whole, milli = int(gamma), round((gamma - int(gamma)) * 1000)
    s = slices_sql(n, p)
    parts = [f"SELECT a.sub, x.i AS pos, b.sub AS owner FROM ({s}) a, ({s}) b, range({n}) x(i) "
             f"WHERE x.i >= b.lo AND x.i < b.lo + b.size AND least((b.sub - a.sub + {p}) % {p}, (a.sub - b.sub + {p}) % {p}) <= {whole}"]
    if milli:
        parts.append(f"SELECT a.sub, x.i, b.sub FROM ({s}) a, ({s}) b, range({n}) x(i) WHERE (a.sub - b.sub + {p}) % {p} = {whole + 1} "
                     f"AND x.i < b.lo + b.size AND x.i >= b.lo + b.size - (({milli} * b.size + 999) // 1000)")
        parts.append(f"SELECT a.sub, x.i, b.sub FROM ({s}) a, ({s}) b, range({n}) x(i) WHERE (b.sub - a.sub + {p}) % {p} = {whole + 1} "
                     f"AND x.i >= b.lo AND x.i < b.lo + ({milli} * b.size // 1000)")
    return f"SELECT DISTINCT CAST(sub AS INTEGER) AS sub, CAST(pos AS BIGINT) AS pos, CAST(owner AS INTEGER) AS owner FROM ({' UNION ALL '.join(parts)})"


def pieces_sql(n: int, p: int, q: int) -> str:
    """(pos, agg) by ranges of each piece."""
    s = slices_sql(n, p)
    piece = f"SELECT sub, lo, size, k, lo + k * (size // {q}) + least(k, size % {q}) AS a, size // {q} + (CASE WHEN k < size % {q} THEN 1 ELSE 0 END) AS m FROM ({s}) s, range({q}) t(k)"
    return f"SELECT CAST(x.i AS BIGINT) AS pos, CAST(y.sub * {q} + y.k AS BIGINT) AS agg FROM range({n}) x(i) JOIN ({piece}) y ON x.i >= y.a AND x.i < y.a + y.m"


def uniform_sql(*parts: str) -> str:
    text = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"(CAST(('0x' || substr(md5({text}), 1, 8)) AS BIGINT) / 4294967296.0)"


def exact1_sql(spec: GridSpec, digits: int = 6) -> str:
    """(id, u) of the one-dimensional problem by its Green's function."""
    n = spec.size
    h2 = (1 / (n + 1)) ** 2
    return (f"WITH b AS ({rhs_sql('B1', spec)}) SELECT CAST(x.i AS BIGINT) AS id, round(sum({h2!r} * (least(x.i, b.id) + 1) * ({n} - greatest(x.i, b.id)) / {n + 1} * b.cents / {SCALE!r}), {digits}) + 0.0 AS u "
            f"FROM range({n}) x(i), b GROUP BY x.i")


def exact2_sql(spec: GridSpec, digits: int = 6) -> str:
    """(id, u) of the two-dimensional problem by its sine expansion."""
    n1, n2 = spec.extents
    m1, m2 = n1 + 1, n2 + 1
    lam = f"({4.0 * m1 * m1} * power(sin(a * pi() / {2 * m1}), 2) + {4.0 * m2 * m2} * power(sin(b * pi() / {2 * m2}), 2))"
    return (f"WITH c AS (SELECT q.*, r.cents / {SCALE!r} AS f FROM ({cells_sql(spec)}) q JOIN ({rhs_sql('B2', spec)}) r USING (id)), "
            f"h AS (SELECT a, b, {4.0 / (m1 * m2)} * sum(f * sin(a * pi() * k1 / {m1}) * sin(b * pi() * k2 / {m2})) / {lam} AS w FROM c, range(1, {m1}) s(a), range(1, {m2}) t(b) GROUP BY a, b) "
            f"SELECT c.id, round(sum(w * sin(a * pi() * k1 / {m1}) * sin(b * pi() * k2 / {m2})), {digits}) + 0.0 AS u FROM c, h GROUP BY c.id")
