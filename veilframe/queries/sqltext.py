"""DuckDB text for the oracles: rotations, grids and releases built by SQL itself, never from our matrices."""

from __future__ import annotations

import itertools

from ..functions.rng import normal_sql, uniform_sql

KEY = "l_orderkey::VARCHAR || ':' || l_linenumber::VARCHAR || ':' || l_partkey::VARCHAR || ':' || l_suppkey::VARCHAR"
COLS = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
PLACES = (6, 3, 8, 8)
N = 4


def li(numbered: bool = False) -> str:
    """numbered: records of one key are told apart, as as_matrix(repeated="number") does."""
    if numbered:
        again = f"row_number() OVER (PARTITION BY {KEY} ORDER BY {', '.join(COLS)})"
        return f"li AS (SELECT key || CASE WHEN k > 1 THEN '#' || k::VARCHAR ELSE '' END AS key, {', '.join(f'x{i}' for i in range(N))}, cls FROM (SELECT {KEY} AS key, {', '.join(f'{c} AS x{i}' for i, c in enumerate(COLS))}, l_returnflag AS cls, {again} AS k FROM lineitem))"
    return f"li AS (SELECT {KEY} AS key, {', '.join(f'{c} AS x{i}' for i, c in enumerate(COLS))}, l_returnflag AS cls FROM lineitem)"


def mo() -> str:
    return "mo AS (SELECT count(*) AS n, " + ", ".join(f"avg(x{i}) AS m{i}, stddev_samp(x{i}) AS s{i}" for i in range(N)) + " FROM li)"


def cov() -> str:
    cells = [f"SELECT {i} AS i, {j} AS j, " + ("1::DOUBLE AS c" if i == j else f"corr(x{min(i, j)}, x{max(i, j)}) AS c FROM li") for i in range(N) for j in range(N)]
    return "cov AS (" + " UNION ALL ".join(cells) + ")"


def rot(n: int, where: str = "t NOT IN (30, 45, 60, 90, 120, 135, 150)") -> str:
    """Recursive over the planes i < j in order; m is the matrix by rows."""
    planes = ", ".join(f"({k + 1}, {i}, {j})" for k, (i, j) in enumerate(itertools.combinations(range(n), 2)))
    eye = ", ".join("1" if i == j else "0" for i in range(n) for j in range(n))
    row = f"x - x % {n}"
    return f"""angles AS (SELECT t AS theta FROM range(1, 180) r(t) WHERE {where}),
planes(k, pi, pj) AS (VALUES {planes}),
step(theta, k, m) AS (
  SELECT theta, 0, [{eye}]::DOUBLE[] FROM angles
  UNION ALL
  SELECT theta, step.k + 1, list_transform(range(0, {n * n}), lambda x: CASE WHEN x % {n} = pi THEN m[{row} + pi + 1] * cos(radians(theta)) + m[{row} + pj + 1] * sin(radians(theta))
    WHEN x % {n} = pj THEN m[{row} + pj + 1] * cos(radians(theta)) - m[{row} + pi + 1] * sin(radians(theta)) ELSE m[x + 1] END)
  FROM step JOIN planes ON planes.k = step.k + 1
), rot AS (SELECT theta, m FROM step WHERE k = {n * (n - 1) // 2})"""


def grid(form: str = "exact", reflection: str = "single") -> str:
    sign = "CASE WHEN j = axis - 1 THEN -1 ELSE 1 END" if reflection == "single" else "CASE WHEN j = axis - 1 THEN 1 ELSE -1 END"
    return f"""a AS (SELECT theta, axis, i, j, m[i * {N} + j + 1] * {sign} AS a FROM rot, range(1, {N + 1}) ax(axis), range(0, {N}) ri(i), range(0, {N}) rj(j)),
v AS (SELECT x.theta, x.axis, x.i, sum(x.a * cov.c * y.a) AS v FROM a x JOIN cov ON cov.i = x.j JOIN a y ON y.theta = x.theta AND y.axis = x.axis AND y.i = x.i AND y.j = cov.j GROUP BY ALL),
s AS (SELECT a.theta, a.axis, a.i, sum(a.a * cov.c) AS s FROM a JOIN cov ON a.i = cov.i AND a.j = cov.j GROUP BY ALL),
grid AS (SELECT axis::INT AS axis, theta::INT AS theta_deg, min(1 + v {'+ s' if form == 'printed' else '- 2 * s'}) AS phi FROM v JOIN s USING (theta, axis, i) GROUP BY ALL)"""


def pick(selection: str = "maximin") -> str:
    if selection == "global_max":
        return "pick AS (SELECT theta_deg, axis, round(phi, 9) AS phi_opt FROM grid ORDER BY round(phi, 9) DESC, theta_deg, axis LIMIT 1)"
    order = "round(phi, 9), axis" if selection == "maximin" else "round(phi, 9) DESC, axis"
    return f"""pick AS (SELECT theta_deg, axis, phi_opt FROM (
  SELECT theta_deg, axis, min(round(phi, 9)) OVER (PARTITION BY theta_deg) AS phi_opt, row_number() OVER (PARTITION BY theta_deg ORDER BY {order}) AS k FROM grid) WHERE k = 1 ORDER BY phi_opt DESC, theta_deg LIMIT 1)"""


def base(form: str = "exact", selection: str = "maximin", reflection: str = "single", numbered: bool = False) -> str:
    return f"WITH RECURSIVE {li(numbered)}, {mo()}, {cov()}, {rot(N)}, {grid(form, reflection)}, {pick(selection)}"


def moved(reflection: str = "single", seed: str = "smp") -> str:
    other = ("-1", "1") if reflection == "single" else ("1", "-1")
    z = [f"(CASE WHEN axis = {j + 1} THEN {other[0]} ELSE {other[1]} END * (x{j} - m{j}) / s{j} + {uniform_sql(seed, 'shift', chr(39) + 't' + chr(39), j)})" for j in range(N)]
    cells = ", ".join(" + ".join(f"m[{i * N + j + 1}] * {z[j]}" for j in range(N)) + f" AS y{i}" for i in range(N))
    return f"moved AS (SELECT key, cls, {', '.join(f'x{i}' for i in range(N))}, {cells} FROM li, mo, pick JOIN rot ON rot.theta = pick.theta_deg)"


def expanded(sigma: float = 0.3, seed: str = "smp") -> str:
    cells = ", ".join(f"y{i} + sign(y{i}) * abs({sigma}::DOUBLE * {normal_sql(seed, 'noise', 'key', i)}) AS e{i}" if sigma else f"y{i} AS e{i}" for i in range(N))
    return f"expanded AS (SELECT key, cls, {', '.join(f'x{i}' for i in range(N))}, {cells} FROM moved)"


def released(sigma: float = 0.3, reflection: str = "single", seed: str = "smp", **how) -> str:
    back = ", ".join(f"e{i} * s{i} + m{i} AS r{i}" for i in range(N))
    return f"{base(reflection=reflection, **how)}, {moved(reflection, seed)}, {expanded(sigma, seed)}, rel AS (SELECT key, cls, {', '.join(f'x{i}' for i in range(N))}, {back} FROM expanded, mo)"


def values(prefix: str, source: str, extra: str = "cls") -> str:
    return f" SELECT {', '.join(f'round({prefix}{i}, {p}) AS {c}' for i, (c, p) in enumerate(zip(COLS, PLACES, strict=True)))}{', ' + extra if extra else ''} FROM {source}"
