"""SQL for DuckDB that finds the spectra of an array's unfoldings by itself, to check ours with.

A Gram matrix is summed from cells and brought to diagonal form by cyclic plane rotations
in a recursive query; its diagonal is the spectrum.
"""

from __future__ import annotations

#: Rounds over all pairs of rows; enough for matrices of some tens of rows.
ROUNDS = 7


def gram(cells: str, n: int, mode: int) -> str:
    others = " AND ".join(f"x.i_{k + 1} = y.i_{k + 1}" for k in range(n) if k != mode)
    return f"SELECT x.i_{mode + 1} AS i, y.i_{mode + 1} AS j, sum(x.v * y.v)::DOUBLE AS s FROM {cells} x JOIN {cells} y ON {others} GROUP BY ALL"


def diagonal(tag: str, matrix: str) -> str:
    """Common table expressions that end with d<tag>(x, pos): the eigenvalues of a symmetric matrix (i, j, s), falling."""
    turned = "list_transform(a, lambda r: list_transform(r, lambda x, j: CASE WHEN j = p THEN c * x - s * r[q] WHEN j = q THEN s * r[p] + c * x ELSE x END))"
    both = "list_transform(b, lambda r, i: CASE WHEN i = p THEN list_transform(r, lambda x, j: c * x - s * b[q][j]) WHEN i = q THEN list_transform(r, lambda x, j: s * b[p][j] + c * x) ELSE r END)"
    half = "(a[q][q] - a[p][p]) / (2 * a[p][q])"
    tangent = f"CASE WHEN a[p][q] = 0 THEN 0.0 ELSE CASE WHEN {half} < 0 THEN -1 ELSE 1 END / (abs({half}) + sqrt(({half}) * ({half}) + 1)) END"
    return f"""m{tag} AS MATERIALIZED (SELECT list(r ORDER BY i) a FROM (SELECT i, list(s ORDER BY j) r FROM ({matrix}) GROUP BY i)),
 k{tag} AS MATERIALIZED (SELECT coalesce(list([p, q] ORDER BY p, q), []) pr FROM (SELECT unnest(range(1, len(a) + 1)) p FROM m{tag}) x, (SELECT unnest(range(1, len(a) + 1)) q FROM m{tag}) y WHERE p < q),
 it{tag}(n, a) AS (SELECT 0, a FROM m{tag} UNION ALL SELECT n + 1, {both} FROM (SELECT n, p, q, c, s, {turned} b
  FROM (SELECT n, a, p, q, 1 / sqrt(t * t + 1) c, t / sqrt(t * t + 1) s FROM (SELECT n, a, p, q, {tangent} t
   FROM (SELECT n, a, pr[n % len(pr) + 1][1] p, pr[n % len(pr) + 1][2] q FROM it{tag}, k{tag} WHERE n < {ROUNDS} * len(pr)))))),
 d{tag} AS MATERIALIZED (SELECT x, row_number() OVER (ORDER BY x DESC) pos FROM (SELECT unnest(list_transform(range(1, len(a) + 1), lambda i: greatest(a[i][i], 0.0))) x FROM it{tag}, k{tag} WHERE n = {ROUNDS} * len(pr)))"""


def standardised(base: str, n: int, variable: int | None) -> str:
    """Common table expressions that end with z: the cells (i_1 .., v), standardised along `variable` if there is one."""
    if variable is None:
        return f"z AS MATERIALIZED ({base})"
    name = f"i_{variable + 1}"
    names = ", ".join(f"c.i_{k + 1}" for k in range(n))
    return f"""c AS MATERIALIZED ({base}), st AS (SELECT {name} AS var, avg(v) mu, stddev_pop(v) sigma FROM c GROUP BY 1),
 z AS MATERIALIZED (SELECT {names}, (c.v - mu) / CASE WHEN sigma >= 1e-10 THEN sigma ELSE 1 END AS v FROM c JOIN st ON var = c.{name})"""


def curves(base: str, n: int, variable: int | None, modes: list[int]) -> str:
    """WITH ... e(mode, pos, tail): what each rank of each mode leaves out, as a share of the energy."""
    steps = [standardised(base, n, variable)] + [diagonal(str(m + 1), gram("z", n, m)) for m in modes]
    tails = " UNION ALL ".join(f"SELECT {m + 1} AS mode, CAST(pos AS INTEGER) AS pos, coalesce(sum(x) OVER (ORDER BY pos ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) / sum(x) OVER () AS tail FROM d{m + 1}" for m in modes)
    return f"WITH RECURSIVE {', '.join(steps)}, e AS ({tails})"
