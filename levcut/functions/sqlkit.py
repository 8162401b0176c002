"""Linear algebra of small matrices in DuckDB SQL, for the twins of queries.

A matrix is one row of a CTE with a column of lists of lists; loops are
recursive CTEs of one row a step, so nothing here grows with the data but the
sums that make the matrix.
"""

from __future__ import annotations


def _trace(m: str) -> str:
    return f"list_sum(list_transform(range(1, len({m}) + 1), lambda z_: {m}[z_][z_]))"


def times(left: str, right_rows: str) -> str:
    """Rows of left times the transpose of right."""
    return f"list_transform({left}, lambda r_: list_transform({right_rows}, lambda c_: list_dot_product(r_, c_)))"


def apply(matrix: str, vector: str) -> str:
    return f"list_transform({matrix}, lambda r_: list_dot_product(r_, {vector}))"


def matrix(source: str, name: str = "mat", i: str = "i", j: str = "j", s: str = "s") -> str:
    """CTE ``name`` (m, names) of a complete symmetric table (i, j, s)."""
    return f"{name} AS (SELECT list(row_ ORDER BY {i}) AS m, list({i} ORDER BY {i}) AS names FROM (SELECT {i}, list({s} ORDER BY {j}) AS row_ FROM {source} GROUP BY {i}))"


def eigen(k: int, source: str = "mat", name: str = "eig", squarings: int = 40) -> str:
    """CTE ``name`` (lam, vec): the k leading eigenpairs of source.m, positive semidefinite.

    The matrix is squared and scaled until one direction is left, which is then
    taken out; the entry of largest magnitude of a vector is positive.
    """
    period = squarings + 1
    steps = f"{name}_steps"
    return f"""{steps} AS (
  SELECT 0 AS t, m AS g, list_transform(m, lambda r_: list_transform(r_, lambda x_: x_ / {_trace("m")})) AS p, []::DOUBLE[] AS lam, []::DOUBLE[][] AS vec FROM {source}
  UNION ALL
  SELECT t + 1, g2, CASE WHEN done THEN list_transform(g2, lambda r_: list_transform(r_, lambda x_: x_ / {_trace("g2")}))
                         ELSE list_transform(sq, lambda r_: list_transform(r_, lambda x_: x_ / {_trace("sq")})) END, lam2, vec2
  FROM (SELECT *, CASE WHEN done THEN list_transform(g, lambda r_, i_: list_transform(r_, lambda x_, j_: x_ - l * v[i_] * v[j_])) ELSE g END AS g2,
          CASE WHEN done THEN list_append(lam, l) ELSE lam END AS lam2, CASE WHEN done THEN list_append(vec, v) ELSE vec END AS vec2
    FROM (SELECT *, list_dot_product(v, {apply("g", "v")}) AS l
      FROM (SELECT *, list_transform(col, lambda x_: x_ / sqrt(list_dot_product(col, col))) AS v
        FROM (SELECT *, p[list_position({_diagonal("p")}, list_max({_diagonal("p")}))] AS col
          FROM (SELECT *, t % {period} = {squarings} AS done, {times("p", "p")} AS sq FROM {steps} WHERE t < {k * period})))))),
{name} AS (SELECT lam, list_transform(vec, lambda v_: CASE WHEN list_max(v_) < -list_min(v_) THEN list_transform(v_, lambda x_: -x_) ELSE v_ END) AS vec
  FROM {steps} WHERE t = {k * period})"""


def _diagonal(m: str) -> str:
    return f"list_transform(range(1, len({m}) + 1), lambda z_: {m}[z_][z_])"


def inverse(source: str, name: str, column: str = "m") -> str:
    """CTE ``name`` (m): the inverse of source.column, positive definite, by elimination."""
    steps = f"{name}_steps"
    return f"""{steps} AS (
  SELECT 0 AS t, list_transform({column}, lambda r_, i_: list_concat(r_, list_transform(range(1, len({column}) + 1), lambda z_: (z_ = i_)::INT::DOUBLE))) AS m FROM {source}
  UNION ALL
  SELECT t + 1, list_transform(m, lambda r_, i_: CASE WHEN i_ = t + 1 THEN list_transform(r_, lambda x_: x_ / r_[t + 1])
    ELSE list_transform(r_, lambda x_, j_: x_ - r_[t + 1] * m[t + 1][j_] / m[t + 1][t + 1]) END)
  FROM {steps} WHERE t < len(m)),
{name} AS (SELECT list_transform(m, lambda r_: r_[len(m) + 1 :]) AS m FROM {steps} WHERE t = len(m))"""


def pivots(k: int, source: str = "mat", name: str = "piv") -> str:
    """CTE ``name`` (chosen, rest): k places by largest residual diagonal, and the matrix with them projected out."""
    steps = f"{name}_steps"
    free = "list_transform(g, lambda r_, z_: CASE WHEN list_contains(chosen, z_) THEN -1.0 ELSE r_[z_] END)"
    return f"""{steps} AS (
  SELECT 0 AS t, m AS g, []::BIGINT[] AS chosen FROM {source}
  UNION ALL
  SELECT t + 1, list_transform(g, lambda r_, i_: list_transform(r_, lambda x_, j_: x_ - g[b][i_] * g[b][j_] / g[b][b])), list_append(chosen, b)
  FROM (SELECT *, list_position({free}, list_max({free})) AS b FROM {steps} WHERE t < {k})),
{name} AS (SELECT chosen, g AS rest FROM {steps} WHERE t = {k})"""


def moments(rows: str, xs: list[str], y: str, name: str, weight: str = "1.0") -> str:
    """CTE ``name`` (m, b, n): A'WA, A'Wy and the sum of weights."""
    a = ", ".join("[" + ", ".join(f"sum({weight} * {p} * {q})" for q in xs) + "]" for p in xs)
    b = ", ".join(f"sum({weight} * {p} * {y})" for p in xs)
    return f"{name} AS (SELECT [{a}] AS m, [{b}] AS b, sum({weight}) AS n, sum({weight} * {y} * {y}) AS yy FROM {rows})"


def solved(system: str, name: str) -> str:
    """CTE ``name`` (x): the solution of a moments() system."""
    inv = f"{name}_inverse"
    return inverse(system, inv) + f",\n{name} AS (SELECT {apply('i_.m', 's_.b')} AS x FROM {inv} i_, {system} s_)"


def walk(name: str, seed: str, step: str, rounds: int) -> str:
    """CTE ``name`` (t, ...): rounds of a step over the rows of the round before."""
    return f"{name} AS ({seed}\n  UNION ALL\n  {step.format(t=f'{name}.t < {rounds}', me=name)})"
