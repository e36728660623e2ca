"""Queries for every method, variant, baseline, measure and experiment, and the SQL that checks them.

Whole-number arrays give whole-number results; others are rounded to six places on
quantities of order one. Eigenvectors are never shown: their sign is free, so spectra,
projectors, decoded cells or certificates are.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corefold import spectra_sql
from corefold.functions import measures as ms
from corefold.functions import spectrum as sp
from corefold.functions import tensor as tn
from corefold.functions.tensor import Cells, Chunks, TensorSpec
from corefold.operators import baselines, decode, prepare
from corefold.operators import block_kernels as bk
from corefold.operators import decompose as dc
from corefold.operators import sql_kernels as sk
from corefold.plans import costmodel as cm
from corefold.plans import planner
from corefold.sources import arrays, synthetic
from corefold.sources.tables import explode_vector, load_table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

LINE = """SELECT CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS i_1, CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END AS i_2,
 month(l_shipdate) - 1 AS i_3, l_linenumber - 1 AS i_4, year(l_shipdate) - 1995 AS i_5, CAST(l_quantity AS BIGINT) AS q FROM lineitem"""
A4 = f"WITH a AS (SELECT CAST(i_1 AS INTEGER) i_1, CAST(i_2 AS INTEGER) i_2, CAST(i_3 AS INTEGER) i_3, CAST(i_4 AS INTEGER) i_4, CAST(sum(q) AS BIGINT) v FROM ({LINE}) GROUP BY 1, 2, 3, 4)"


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def rounded(column: str, digits: int = 6) -> F.Column:
    return (F.round(column, digits) + F.lit(0.0)).alias(column)


# ---- arrays -------------------------------------------------------------------------


def _cells(make: Callable[[SparkSession, str], Cells]) -> Query:
    return lambda spark, sf: make(spark, sf).df


def _rounded_cells(make: Callable[[SparkSession, str], Cells]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        cells = make(spark, sf)
        return cells.df.select(*tn.index_columns(cells.spec.order), rounded("v", 4))

    return run


def _grid(sizes: list[int | str]) -> str:
    """All index tuples in SQL; a size may be an expression."""
    parts = ", ".join(f"(SELECT CAST(range AS INTEGER) i_{k + 1} FROM range(0, {s}))" for k, s in enumerate(sizes))
    return f"(SELECT * FROM {parts})"


def _filled(sizes: list, cells: str, value: str, zero: str) -> str:
    n = len(sizes)
    names = ", ".join(f"i_{k + 1}" for k in range(n))
    return f"SELECT {names}, {value} v FROM {_grid(sizes)} LEFT JOIN ({cells}) USING ({names})".replace("@", f"coalesce(s, {zero})")


TRADE = """SELECT s_nationkey, p_brand, l_returnflag, year(l_shipdate) - 1995 AS y, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS m,
 l_quantity, l_extendedprice, l_discount, l_tax FROM lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey"""
BRANDS = "(SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS bi FROM (SELECT DISTINCT p_brand FROM part))"


def _measures(source: str, ids: str) -> str:
    names = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    return " UNION ALL ".join(f"SELECT {ids}, {i} AS var, CAST({m} AS DOUBLE) AS val FROM ({source})" for i, m in enumerate(names))


TRADE4 = _filled([25, 25, 4, 83], f"SELECT s_nationkey i_1, bi i_2, var i_3, m i_4, sum(val) s FROM ({_measures(TRADE, 's_nationkey, p_brand, m')}) JOIN {BRANDS} USING (p_brand) GROUP BY ALL", "@", "0.0")
TRADE5 = _filled([25, 25, 3, 4, 7], f"SELECT s_nationkey i_1, bi i_2, CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END i_3, var i_4, y i_5, sum(val) s FROM ({_measures(TRADE, 's_nationkey, p_brand, l_returnflag, y')}) JOIN {BRANDS} USING (p_brand) GROUP BY ALL", "@", "0.0")
GRID5_SOURCE = "SELECT l_suppkey % 10 a, l_partkey % 10 b, l_orderkey % 10 c, year(l_shipdate) - 1995 y, l_quantity, l_extendedprice, l_discount, l_tax FROM lineitem"
GRID5 = _filled([10, 10, 10, 4, 7], f"SELECT a i_1, b i_2, c i_3, var i_4, y i_5, sum(val) s FROM ({_measures(GRID5_SOURCE, 'a, b, c, y')}) GROUP BY ALL", "@", "0.0")
PULSE_TYPES = "(SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 ti FROM (SELECT DISTINCT event_type FROM events))"
PULSE_ROWS = """SELECT hour(ts) h, dayofweek(ts) d, event_type, 0 var, 1.0::DOUBLE val FROM events UNION ALL
 SELECT hour(ts), dayofweek(ts), event_type, 1, CAST(value AS DOUBLE) FROM events UNION ALL
 SELECT hour(ts), dayofweek(ts), event_type, 2, CAST(json_extract_string(props, '$.k') AS DOUBLE) FROM events"""
PULSE4 = _filled([24, 7, "(SELECT count(DISTINCT event_type) FROM events)", 3], f"SELECT h i_1, d i_2, ti i_3, var i_4, sum(val) s FROM ({PULSE_ROWS}) JOIN {PULSE_TYPES} USING (event_type) GROUP BY ALL", "@", "0.0")


def _round_v(sql: str, n: int, digits: int = 4) -> str:
    names = ", ".join(f"i_{k + 1}" for k in range(n))
    return f"SELECT {names}, round(v, {digits}) + 0.0 AS v FROM ({sql})"


def _modular(dims: tuple[int, ...]) -> str:
    a, b, c, d = dims
    return _filled(list(dims), f"SELECT l_suppkey % {a} i_1, l_partkey % {b} i_2, l_orderkey % {c} i_3, datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % {d} i_4, sum(CAST(l_quantity AS BIGINT)) s FROM lineitem GROUP BY ALL", "CAST(@ AS BIGINT)", "0")


TEXT4 = _filled(
    ["(SELECT count(DISTINCT lang) FROM documents)", "(SELECT count(DISTINCT source) FROM documents)", 8, 3],
    """SELECT li i_1, si i_2, least(7, floor(log2(n_chars + 1) / 2)) i_3, coalesce(quality, 2) i_4, count(*) s FROM documents LEFT JOIN labels USING (doc_id)
 JOIN (SELECT lang, row_number() OVER (ORDER BY lang) - 1 li FROM (SELECT DISTINCT lang FROM documents)) USING (lang)
 JOIN (SELECT source, row_number() OVER (ORDER BY source) - 1 si FROM (SELECT DISTINCT source FROM documents)) USING (source) GROUP BY ALL""",
    "CAST(@ AS BIGINT)",
    "0",
)

query("cells_ship4", f"{A4} SELECT * FROM a")(_cells(arrays.ship4))
query("cells_ship5", _filled([3, 2, 12, 7, 7], f"SELECT i_1, i_2, i_3, i_4, i_5, sum(q) s FROM ({LINE}) GROUP BY ALL", "CAST(@ AS BIGINT)", "0"))(_cells(arrays.ship5))
query("cells_trade4v", _round_v(TRADE4, 4))(_rounded_cells(arrays.trade4v))
query("cells_trade5v", _round_v(TRADE5, 5))(_rounded_cells(arrays.trade5v))
query("cells_grid5v", _round_v(GRID5, 5))(_rounded_cells(arrays.grid5v))
query("cells_pulse4v", _round_v(PULSE4, 4))(_rounded_cells(arrays.pulse4v))
query("cells_cube4", _modular((10, 10, 10, 10)))(_cells(arrays.cube4))
query("cells_skew4", _modular((5, 50, 50, 50)))(_cells(arrays.skew4))
query("cells_text4", TEXT4)(_cells(arrays.text4))
query(
    "cells_vec4",
    """WITH n AS (SELECT label, vec_id, embedding, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 r FROM embeddings),
 e AS (SELECT label, r, unnest(range(0, 64)) p, unnest(embedding) x FROM n)
 SELECT CAST(label AS INTEGER) i_1, CAST(r AS INTEGER) i_2, CAST(p % 8 AS INTEGER) i_3, CAST(p // 8 AS INTEGER) i_4, CAST(x AS DOUBLE) v FROM e""",
)(_cells(arrays.vec4))
query("cells_vec2", "SELECT CAST(vec_id AS INTEGER) i_1, CAST(p AS INTEGER) i_2, CAST(x AS DOUBLE) v FROM (SELECT vec_id, unnest(range(0, 64)) p, unnest(embedding) x FROM embeddings)")(_cells(arrays.vec2))


# ---- algebra ------------------------------------------------------------------------

_E = "CAST(sum(v * v) AS BIGINT)"


@query("norm_ship4", f"{A4} SELECT {_E} AS norm_sq FROM a")
def norm_ship4(spark: SparkSession, sf: str) -> DataFrame:
    return sk.norm_sq(arrays.ship4(spark, sf))


@query("norm_blocks", f"{A4} SELECT {_E} AS norm_sq FROM a")
def norm_blocks(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, [(round(bk.norm_sq(_blocks(arrays.ship4(spark, sf)))),)], "norm_sq long")


def _energy(kind: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        names = tn.index_columns(4)
        grouped = getattr(arrays.ship4(spark, sf).df, kind)(*names)
        return grouped.agg(F.grouping_id().cast("long").alias("level"), F.sum(F.col("v") * F.col("v")).alias("energy")).select(*[F.coalesce(n, F.lit(-1)).alias(n) for n in names], "level", "energy")

    return run


for _kind in ("cube", "rollup"):
    query(f"energy_{_kind}", f"{A4} SELECT {', '.join(f'coalesce(i_{k}, -1) AS i_{k}' for k in range(1, 5))}, CAST(grouping(i_1, i_2, i_3, i_4) AS BIGINT) AS level, {_E} AS energy FROM a GROUP BY {_kind.upper()} (i_1, i_2, i_3, i_4)")(_energy(_kind))


def _unfold(mode: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        cells = arrays.ship4(spark, sf)
        row, col = tn.unfold_index(cells.spec, mode)
        return cells.df.select(*tn.index_columns(4), row.alias("row"), col.alias("col"), tn.offset(cells.spec).alias("place"))

    return run


def _fold(mode: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        cells = arrays.ship4(spark, sf)
        row, col = tn.unfold_index(cells.spec, mode)
        flat = cells.df.select(row.alias("row"), col.alias("col"), "v")
        return flat.select(*tn.fold_index(cells.spec, mode), "v")

    return run


_DIMS = (3, 2, 12, 7)
for _m in range(4):
    _col = " + ".join(f"i_{k + 1} * {w}" for k, w in enumerate(tn.unfold_weights(_DIMS, _m)) if w)
    query(f"unfold_ship4_m{_m + 1}", f"{A4} SELECT i_1, i_2, i_3, i_4, i_{_m + 1} AS row, CAST({_col} AS BIGINT) AS col, CAST(i_1 + 3 * i_2 + 6 * i_3 + 72 * i_4 AS BIGINT) AS place FROM a")(_unfold(_m))
query("fold_ship4_m2", f"{A4} SELECT * FROM a")(_fold(1))


def _blocks(cells: Cells, block: tuple[int, ...] | None = None) -> Chunks:
    return bk.to_chunks(cells, block)


def _gram_sql(cells: str, n: int, mode: int, value: str) -> str:
    others = " AND ".join(f"x.i_{k + 1} = y.i_{k + 1}" for k in range(n) if k != mode)
    return f"SELECT CAST(x.i_{mode + 1} AS INTEGER) AS i, CAST(y.i_{mode + 1} AS INTEGER) AS j, {value} AS s FROM ({cells}) x JOIN ({cells}) y ON {others} GROUP BY ALL"


def _gram_rows(spark: SparkSession, s: np.ndarray, exact: bool = True, scale: float = 1.0) -> DataFrame:
    rows = [(i, j, round(s[i, j]) if exact else float(s[i, j] / scale)) for i in range(len(s)) for j in range(len(s))]
    out = frame(spark, rows, f"i int, j int, s {'long' if exact else 'double'}")
    return out if exact else out.select("i", "j", rounded("s"))


def _gram4(mode: int, block: tuple[int, ...], impl: str = "auto", symmetric: bool = True) -> Query:
    return lambda spark, sf: _gram_rows(spark, bk.gram(_blocks(arrays.ship4(spark, sf), block), mode, impl, symmetric))


_LONG = "CAST(sum(x.v * y.v) AS BIGINT)"
for _m in range(4):
    _sql = f"{A4} {_gram_sql('SELECT * FROM a', 4, _m, _LONG)}"
    query(f"gram_ship4_m{_m + 1}", _sql)(_gram4(_m, _DIMS))
    query(f"gram_relational_m{_m + 1}", _sql)(partial(lambda spark, sf, mode: sk.gram(arrays.ship4(spark, sf), mode), mode=_m))
    query(f"gram_exchange_m{_m + 1}", _sql)(_gram4(_m, (2, 1, 5, 3), "exchange"))
query("gram_full_m3", SQL["gram_ship4_m3"])(_gram4(2, (2, 1, 5, 3), "exchange", symmetric=False))
_SHIP5 = SQL["cells_ship5"]
query("gram_ship5_m5", _gram_sql(_SHIP5, 5, 4, _LONG))(lambda spark, sf: _gram_rows(spark, bk.gram(_blocks(arrays.ship5(spark, sf), (3, 2, 6, 7, 7)), 4)))
query("gram_pulse_m3", f"SELECT i, j, round(s / (SELECT sum(v * v) FROM ({PULSE4})), 6) + 0.0 AS s FROM ({_gram_sql(PULSE4, 4, 2, 'sum(x.v * y.v)')})")(
    lambda spark, sf: (lambda c: _gram_rows(spark, bk.gram(c, 2), False, bk.norm_sq(c)))(_blocks(arrays.pulse4v(spark, sf)))
)
query("gram_vec2", f"SELECT i, j, round(s / (SELECT sum(v * v) FROM ({SQL['cells_vec2']})), 6) + 0.0 AS s FROM ({_gram_sql(SQL['cells_vec2'], 2, 1, 'sum(x.v * y.v)')})")(
    lambda spark, sf: (lambda c: _gram_rows(spark, bk.gram(c, 1), False, bk.norm_sq(c)))((lambda a: _blocks(a, (256, 64)))(arrays.vec2(spark, sf)))
)


def _ttm(matrix: np.ndarray, mode: int, block: tuple[int, ...], reduce: str = "auto") -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        out = bk.to_cells(bk.ttm(_blocks(arrays.ship4(spark, sf), block), matrix, mode, reduce=reduce, out_block=2))
        return out.df.select(*tn.index_columns(4), F.round("v").cast("long").alias("v"))

    return run


_POOL = np.kron(np.eye(4), np.ones((1, 3)))
_DIFF = np.eye(12)[1:] - np.eye(12)[:-1]
_QUARTER = f"{A4} SELECT i_1, i_2, CAST(i_3 // 3 AS INTEGER) AS i_3, i_4, CAST(sum(v) AS BIGINT) AS v FROM a GROUP BY ALL"
query("ttm_sum_m3", _QUARTER)(_ttm(_POOL, 2, _DIMS))
query("ttm_blocked_m3", _QUARTER)(_ttm(_POOL, 2, (3, 2, 5, 7), "blocked"))
query("ttm_single_m3", _QUARTER)(_ttm(_POOL, 2, (3, 2, 5, 7), "single"))
query("ttm_relational_m3", _QUARTER)(lambda spark, sf: sk.ttm(arrays.ship4(spark, sf), sk.factor_rows(spark, _POOL, exact=True), 2, 4).df)
query("ttm_diff_m3", f"{A4} SELECT x.i_1, x.i_2, CAST(x.i_3 - 1 AS INTEGER) AS i_3, x.i_4, CAST(x.v - y.v AS BIGINT) AS v FROM a x JOIN a y ON x.i_1 = y.i_1 AND x.i_2 = y.i_2 AND x.i_4 = y.i_4 AND x.i_3 = y.i_3 + 1")(_ttm(_DIFF, 2, _DIMS))


@query("ttm_cosine_m3", f"{A4} SELECT i_1, i_2, CAST(k AS INTEGER) AS i_3, i_4, round(sum(v * cos(pi() * k * (2 * i_3 + 1) / 24)) / (SELECT sum(v) FROM a), 6) + 0.0 AS v FROM a, (SELECT range k FROM range(0, 12)) GROUP BY i_1, i_2, k, i_4")
def ttm_cosine_m3(spark: SparkSession, sf: str) -> DataFrame:
    k, i = np.arange(12)[:, None], np.arange(12)[None, :]
    cells = arrays.ship4(spark, sf)
    out = bk.to_cells(bk.ttm(_blocks(cells), np.cos(np.pi * k * (2 * i + 1) / 24), 2))
    total = cells.df.agg(F.sum("v").cast("double").alias("t"))
    return out.df.crossJoin(F.broadcast(total)).select("i_1", "i_2", "i_3", "i_4", (F.col("v") / F.col("t")).alias("v")).select("i_1", "i_2", "i_3", "i_4", rounded("v"))


@query("ttm_chain_commute", f"{A4}, p AS (SELECT i_1, i_2, CAST(i_3 // 3 AS INTEGER) AS i_3, CAST(0 AS INTEGER) AS i_4, CAST(sum(v) AS BIGINT) AS v FROM a GROUP BY i_1, i_2, i_3 // 3) SELECT *, 0 AS gap FROM p")
def ttm_chain_commute(spark: SparkSession, sf: str) -> DataFrame:
    chunks = _blocks(arrays.ship4(spark, sf), (3, 2, 5, 4))
    mats = {2: _POOL, 3: np.ones((1, 7))}
    names = tn.index_columns(4)
    a, b = (bk.to_cells(bk.ttm_chain(chunks, mats, order=o)).df for o in ([2, 3], [3, 2]))
    both = a.join(b.withColumnRenamed("v", "w"), names)
    return both.select(*names, F.round("v").cast("long").alias("v"), F.round(F.abs(F.col("v") - F.col("w"))).cast("int").alias("gap"))


# ---- spectra ------------------------------------------------------------------------

_G2 = f"{A4}, g AS (SELECT sum(CASE WHEN i_2 = 0 THEN v * v ELSE 0 END)::DOUBLE a, sum(CASE WHEN i_2 = 1 THEN v * v ELSE 0 END)::DOUBLE d FROM a), o AS (SELECT sum(x.v * y.v)::DOUBLE b FROM a x JOIN a y ON x.i_1 = y.i_1 AND x.i_3 = y.i_3 AND x.i_4 = y.i_4 WHERE x.i_2 = 0 AND y.i_2 = 1)"
_EIG2 = f"{_G2}, e AS (SELECT (a + d) / 2 + sqrt(((a - d) / 2) ** 2 + b * b) hi, (a + d) / 2 - sqrt(((a - d) / 2) ** 2 + b * b) lo, a + d t FROM g, o)"


def _mode_spectrum(mode: int, method: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        chunks = _blocks(arrays.ship4(spark, sf), (3, 2, 6, 7))
        _, found = dc.leading_left_vectors(chunks, mode, method=method)
        total = float(found.values.sum())
        return frame(spark, [(i + 1, float(v / total)) for i, v in enumerate(found.values)], "pos int, share double").select("pos", rounded("share"))

    return run


_EIG2_OUT = f"{_EIG2} SELECT CAST(1 AS INTEGER) pos, round(hi / t, 6) share FROM e UNION ALL SELECT 2, round(lo / t, 6) FROM e"
for _method in ("gram", "tsqr", "svd"):
    query(f"eig_ship4_m2_{_method}", _EIG2_OUT)(_mode_spectrum(1, _method))


def _power_sql(mode: int, size: int) -> str:
    """Leading eigenvalue and projector by power iteration in SQL."""
    g = _gram_sql("SELECT * FROM a", 4, mode, "CAST(sum(x.v * y.v) AS DOUBLE)")
    return f"""{A4.replace('WITH a', 'WITH RECURSIVE a')}, g AS ({g}), m AS (SELECT i, list(s ORDER BY j) r FROM g GROUP BY i),
 rows_ AS (SELECT list(r ORDER BY i) rs FROM m),
 it(n, v) AS (SELECT 0, list_transform(range(0, {size}), lambda x: 1.0::DOUBLE) UNION ALL
  SELECT n + 1, (SELECT list_transform(w, lambda x: x / sqrt(list_sum(list_transform(w, lambda y: y * y)))) FROM (SELECT list_transform(rs, lambda r: list_inner_product(r, v)) w FROM rows_)) FROM it WHERE n < 60),
 f AS (SELECT v FROM it WHERE n = 60)"""


def _projector(mode: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        u, _ = dc.leading_left_vectors(_blocks(arrays.ship4(spark, sf)), mode, rank=1)
        p = u @ u.T
        return frame(spark, [(i, j, float(p[i, j])) for i in range(len(p)) for j in range(len(p))], "i int, j int, p double").select("i", "j", rounded("p"))

    return run


for _m, _n in ((0, 3), (3, 7)):
    query(f"proj_ship4_m{_m + 1}", f"{_power_sql(_m, _n)} SELECT CAST(i AS INTEGER) i, CAST(j AS INTEGER) j, round(v[i + 1] * v[j + 1], 6) + 0.0 AS p FROM f, (SELECT range i FROM range(0, {_n})), (SELECT range j FROM range(0, {_n}))")(_projector(_m))

    def _leading(spark: SparkSession, sf: str, mode: int = _m) -> DataFrame:
        _, found = dc.leading_left_vectors(_blocks(arrays.ship4(spark, sf)), mode)
        return frame(spark, [(float(found.values[0] / found.values.sum()),)], "share double").select(rounded("share"))

    query(f"eig_ship4_m{_m + 1}", f"{_power_sql(_m, _n)} SELECT round(list_sum(list_transform(range(0, {_n}), lambda k: (rs[k + 1] .list_inner_product(v)) * v[k + 1])) / (SELECT sum(v * v) FROM a), 6) AS share FROM f, rows_")(_leading)


@query("curve_ship4", f"{_EIG2} SELECT 2 AS mode, CAST(1 AS INTEGER) pos, round(sqrt(greatest(lo, 0) / t), 6) rel_tail, (sqrt(lo / t) <= 0.2 / 2) AS under_line FROM e UNION ALL SELECT 2, 2, 0.0, true FROM e")
def curve_ship4(spark: SparkSession, sf: str) -> DataFrame:
    found = bk.grams(_blocks(arrays.ship4(spark, sf)), [1])
    curve = ms.mode_error_curve(ms.spectrum_frame(spark, {m: sp.from_gram(s).values for m, s in found.items()}))
    return curve.select("mode", "pos", rounded("rel_tail"), (F.col("rel_tail") <= 0.2 / 2).alias("under_line"))


@query("rank_ship4", f"{_EIG2} SELECT eps, CAST(CASE WHEN sqrt(lo / t) <= eps / 2 THEN 1 ELSE 2 END AS INTEGER) AS rank FROM e, (SELECT unnest([0.3, 0.1, 0.05]::DOUBLE[]) eps)")
def rank_ship4(spark: SparkSession, sf: str) -> DataFrame:
    s = bk.gram(_blocks(arrays.ship4(spark, sf)), 1)
    curve = ms.mode_error_curve(ms.spectrum_frame(spark, {1: sp.from_gram(s).values})).cache()
    out = None
    for eps in (0.3, 0.1, 0.05):
        one = ms.rank_at(curve, eps, 4).select(F.lit(eps).alias("eps"), "rank")
        out = one if out is None else out.unionByName(one)
    return out


def _curves(make: Callable[[SparkSession, str], Cells], variable: int | None, modes: list[int]) -> Query:
    """E2: error curves of some modes, with the threshold line of 0.3."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        cells = make(spark, sf)
        cells = prepare.standardize(cells, variable)[0] if variable is not None else cells
        found = {m: sp.from_gram(s).values for m, s in bk.grams(_blocks(cells), modes).items()}
        n = cells.spec.order
        return ms.mode_error_curve(ms.spectrum_frame(spark, found)).select("mode", "pos", rounded("rel_tail"), (F.col("rel_tail") <= 0.3 / n**0.5).alias("under_line"))

    return run


#: Arrays of the accuracy experiments: how they are made, their SQL, their order, the variable's mode, modes short enough for the SQL's rotations.
SPECTRAL = {
    "ship4": (arrays.ship4, A4.removeprefix("WITH a AS (")[:-1], 4, None, [0, 1, 2, 3]),
    "trade4v": (arrays.trade4v, TRADE4, 4, 2, [0, 1, 2]),
    "trade5v": (arrays.trade5v, TRADE5, 5, 3, [0, 1, 2, 3, 4]),
    "grid5v": (arrays.grid5v, GRID5, 5, 3, [0, 1, 2, 3, 4]),
    "pulse4v": (arrays.pulse4v, PULSE4, 4, 3, [0, 1, 2, 3]),
}
for _name, (_make, _base, _n, _var, _short) in SPECTRAL.items():
    _sql = f"{spectra_sql.curves(_base, _n, _var, _short)} SELECT CAST(mode AS INTEGER) AS mode, pos, round(sqrt(greatest(tail, 0)), 6) AS rel_tail, sqrt(greatest(tail, 0)) <= 0.3 / sqrt({_n}) AS under_line FROM e"
    query(f"e2_curves_{_name}", _sql)(_curves(_make, _var, _short))
query("e2_curves_trade4v_months")(_curves(arrays.trade4v, 2, [3]))


# ---- standardising ------------------------------------------------------------------


def _stats(make: Callable[[SparkSession, str], Cells], mode: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        stats = prepare.slice_stats(make(spark, sf), mode)
        return stats.select("var", "n", rounded("mu", 4), rounded("sigma", 4), "scaled")

    return run


def _standard(make: Callable[[SparkSession, str], Cells], mode: int) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        cells = prepare.standardize(make(spark, sf), mode)[0]
        return cells.df.select(*tn.index_columns(cells.spec.order), rounded("v", 4))

    return run


for _name, _make, _base, _n, _var in (("trade4v", arrays.trade4v, TRADE4, 4, 3), ("trade5v", arrays.trade5v, TRADE5, 5, 4), ("grid5v", arrays.grid5v, GRID5, 5, 4), ("pulse4v", arrays.pulse4v, PULSE4, 4, 4)):
    _st = f"s AS (SELECT i_{_var} AS var, count(*) n, avg(v) mu, stddev_pop(v) sigma FROM c GROUP BY 1)"
    _names = ", ".join(f"i_{k + 1}" for k in range(_n))
    query(f"stats_{_name}", f"WITH c AS ({_base}), {_st} SELECT var, n, round(mu, 4) + 0.0 AS mu, round(sigma, 4) AS sigma, sigma >= 1e-10 AS scaled FROM s")(_stats(_make, _var - 1))
    query(f"standardize_{_name}", f"WITH c AS ({_base}), {_st} SELECT {_names}, round((v - mu) / CASE WHEN sigma >= 1e-10 THEN sigma ELSE 1 END, 4) + 0.0 AS v FROM c JOIN s ON var = i_{_var}")(_standard(_make, _var - 1))


@query("standardize_undo", f"{A4} SELECT * FROM a")
def standardize_undo(spark: SparkSession, sf: str) -> DataFrame:
    cells, stats = prepare.standardize(arrays.ship4(spark, sf), 0)
    back = prepare.unstandardize(cells, stats, 0)
    return back.df.select(*tn.index_columns(4), F.round("v").cast("long").alias("v"))


@query("gram_one_scan_standardized", f"WITH {spectra_sql.standardised(GRID5, 5, 3)} SELECT true AS agree, round(sum(v * v) / count(*), 6) AS trace_share FROM z")
def gram_one_scan_standardized(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.grid5v(spark, sf)
    once = prepare.gram_standardized(_blocks(cells), 0, 3)
    twice = bk.gram(_blocks(prepare.standardize(cells, 3)[0]), 0)
    return frame(spark, [(bool(np.abs(once - twice).max() <= 1e-8 * np.trace(twice)), float(round(np.trace(once) / cells.spec.size, 6)))], "agree boolean, trace_share double")


# ---- decompositions -----------------------------------------------------------------


def _long_cells(cells: Cells) -> DataFrame:
    return cells.df.select(*tn.index_columns(cells.spec.order), F.round("v").cast("long").alias("v"))


@query("sthosvd_margins_decode", f"{A4}, t AS (SELECT sum(v)::DOUBLE t FROM a), m1 AS (SELECT i_1, sum(v)::DOUBLE x FROM a GROUP BY 1), m2 AS (SELECT i_2, sum(v)::DOUBLE x FROM a GROUP BY 1), m3 AS (SELECT i_3, sum(v)::DOUBLE x FROM a GROUP BY 1), m4 AS (SELECT i_4, sum(v)::DOUBLE x FROM a GROUP BY 1) SELECT i_1, i_2, i_3, i_4, '1,1,1,1' AS ranks, round(m1.x / t * m2.x / t * m3.x / t * m4.x / t * 1000, 6) AS v FROM m1, m2, m3, m4, t")
def sthosvd_margins_decode(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.ship4(spark, sf)
    model = dc.st_hosvd(_blocks(arrays.margins(cells)), eps=1e-6)
    total = cells.df.agg(F.sum("v")).first()[0]
    back = decode.reconstruct_cells(model)
    return back.df.select(*tn.index_columns(4), F.lit(",".join(map(str, model.ranks))).alias("ranks"), (F.col("v") / total * 1000).alias("v")).select("i_1", "i_2", "i_3", "i_4", "ranks", rounded("v"))


_FULL = (3, 2, 12, 7)
_METHODS = {
    "sthosvd": lambda c: dc.st_hosvd(c, ranks=_FULL),
    "thosvd": lambda c: dc.t_hosvd(c, ranks=_FULL),
    "hooi": lambda c: dc.hooi(c, ranks=_FULL, max_sweeps=1),
    "sthosvd_tsqr": lambda c: dc.st_hosvd(c, ranks=_FULL, spectral="tsqr"),
    "sthosvd_order": lambda c: dc.st_hosvd(c, ranks=_FULL, order=(2, 0, 3, 1)),
}
for _name, _method in _METHODS.items():
    query(f"{_name}_full_decode", f"{A4} SELECT * FROM a")(partial(lambda spark, sf, method: _long_cells(decode.reconstruct_cells(method(_blocks(arrays.ship4(spark, sf), (3, 2, 6, 7))))), method=_method))


@query("sthosvd_energy", f"{A4} SELECT {_E} AS norm_sq, true AS energy_kept, true AS within_eps FROM a")
def sthosvd_energy(spark: SparkSession, sf: str) -> DataFrame:
    model = dc.st_hosvd(_blocks(arrays.ship4(spark, sf)), eps=0.1)
    return frame(spark, [(round(model.norm_sq), ms.check_energy(model) < 1e-10, model.norm_rms <= 0.1)], "norm_sq long, energy_kept boolean, within_eps boolean")


@query("hooi_monotone", f"{A4} SELECT {_E} AS norm_sq, true AS falling, true AS not_worse FROM a")
def hooi_monotone(spark: SparkSession, sf: str) -> DataFrame:
    model = dc.hooi(_blocks(arrays.ship4(spark, sf)), ranks=(2, 1, 6, 4), max_sweeps=4)
    trace = ms.fit_trace(model)
    slack = 1e-12 * model.norm_sq
    return frame(spark, [(round(model.norm_sq), all(b <= a + slack for a, b in zip(trace, trace[1:], strict=False)), trace[-1] <= trace[0] + slack)], "norm_sq long, falling boolean, not_worse boolean")


@query("bound_chain", f"{A4} SELECT {_E} AS norm_sq, true AS t_within_bound, true AS st_within_bound, true AS hooi_within_bound FROM a")
def bound_chain(spark: SparkSession, sf: str) -> DataFrame:
    chunks = dc.materialize(_blocks(arrays.ship4(spark, sf)))
    ranks = (2, 1, 6, 4)
    t, s, h = dc.t_hosvd(chunks, ranks=ranks), dc.st_hosvd(chunks, ranks=ranks), dc.hooi(chunks, ranks=ranks, max_sweeps=2)
    bound = ms.thosvd_bound(t.spectra, ranks, t.norm_sq)
    return frame(spark, [(round(t.norm_sq), *(m.norm_rms <= bound for m in (t, s, h)))], "norm_sq long, t_within_bound boolean, st_within_bound boolean, hooi_within_bound boolean")


@query("methods_at_fixed_ranks")
def methods_at_fixed_ranks(spark: SparkSession, sf: str) -> DataFrame:
    chunks = dc.materialize(_blocks(arrays.ship4(spark, sf)))
    rows = []
    for ranks in ((1, 1, 1, 1), (2, 1, 6, 4), (3, 2, 7, 4)):
        t = dc.t_hosvd(chunks, ranks=ranks)
        rows += [(str(ranks), "t_hosvd", t.norm_rms), (str(ranks), "bound", ms.thosvd_bound(t.spectra, ranks, t.norm_sq)), (str(ranks), "st_hosvd", dc.st_hosvd(chunks, ranks=ranks).norm_rms), (str(ranks), "hooi_1", dc.hooi(chunks, ranks=ranks, max_sweeps=1).norm_rms)]
    return frame(spark, rows, "ranks string, method string, norm_rms double").select("ranks", "method", rounded("norm_rms"))


@query("n_ranks", "SELECT unnest([1, 2, 3, 4]) AS mode, 1 AS rank")
def n_ranks(spark: SparkSession, sf: str) -> DataFrame:
    chunks = _blocks(arrays.margins(arrays.ship4(spark, sf)))
    return frame(spark, [(m + 1, sp.numerical_rank(sp.from_gram(s).values, 1e-10)) for m, s in bk.grams(chunks).items()], "mode int, rank int")


# ---- decoding -----------------------------------------------------------------------


def _decode(select: dict[int, object]) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        model = dc.st_hosvd(_blocks(arrays.ship4(spark, sf)), ranks=_FULL)
        return _long_cells(decode.reconstruct_cells(model, select))

    return run


for _name, _select, _where in (
    ("one_variable", {0: 1}, "i_1 = 1"),
    ("steps", {2: [2, 5, 11]}, "i_3 IN (2, 5, 11)"),
    ("stride", {3: slice(0, None, 2)}, "i_4 % 2 = 0"),
    ("box", {2: range(3, 8), 3: range(1, 4)}, "i_3 BETWEEN 3 AND 7 AND i_4 BETWEEN 1 AND 3"),
    ("combo", {0: [0, 2], 1: 1, 2: range(0, 6), 3: slice(0, None, 3)}, "i_1 IN (0, 2) AND i_2 = 1 AND i_3 < 6 AND i_4 % 3 = 0"),
):
    query(f"decode_{_name}", f"{A4} SELECT * FROM a WHERE {_where}")(_decode(_select))
    query(f"slice_{_name}", f"{A4} SELECT * FROM a WHERE {_where}")(partial(lambda spark, sf, select: tn.slice_cells(arrays.ship4(spark, sf), select), select=_select))


@query("decode_points", f"{A4} SELECT * FROM a WHERE (i_1 + i_2 + i_3 + i_4) % 5 = 0")
def decode_points(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.ship4(spark, sf)
    model = dc.st_hosvd(_blocks(cells), ranks=_FULL)
    places = cells.df.filter(F.pmod(F.col("i_1") + F.col("i_2") + F.col("i_3") + F.col("i_4"), F.lit(5)) == 0)
    return decode.decode_cells(model, places).withColumn("v", F.round("v").cast("long"))


@query("decode_pooled", _QUARTER)
def decode_pooled(spark: SparkSession, sf: str) -> DataFrame:
    model = dc.st_hosvd(_blocks(arrays.ship4(spark, sf)), ranks=_FULL)
    return _long_cells(decode.reconstruct_cells(model, weights={2: _POOL}))


# ---- sizes and measures -------------------------------------------------------------

PUBLISHED = {
    "ignition-4": ((672, 672, 33, 627), (297, 279, 29, 153)),
    "jet-5": ((460, 700, 360, 35, 16), (306, 232, 239, 35, 16)),
    "flame-5": ((500, 500, 500, 11, 50), (81, 129, 127, 7, 32)),
}


def _ratio_sql(sets: dict) -> str:
    one = lambda n, d, r: f"SELECT '{n}' AS array_name, ({' * '.join(f'{x}.0::DOUBLE' for x in d)}) / ({' * '.join(f'{x}.0::DOUBLE' for x in r)} + {' + '.join(f'{x}.0::DOUBLE * {y}' for x, y in zip(d, r, strict=True))}) AS ratio"
    return f"SELECT array_name, round(ratio, 6) AS ratio, round(1 - 1 / ratio, 6) AS saved FROM ({' UNION ALL '.join(one(n, d, r) for n, (d, r) in sets.items())})"


@query("ratio_published", _ratio_sql(PUBLISHED))
def ratio_published(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(n, ms.compression_ratio(d, r), ms.saved_fraction(d, r)) for n, (d, r) in PUBLISHED.items()]
    return frame(spark, rows, "array_name string, ratio double, saved double").select("array_name", rounded("ratio"), rounded("saved"))


TABLE_SIZES = {"ship4": ((3, 2, 12, 7), (3, 2, 7, 4)), "trade4v": ((25, 25, 4, 83), (10, 10, 4, 20)), "grid5v": ((10, 10, 10, 4, 7), (4, 4, 4, 4, 7)), "cube4": ((24,) * 4, (6,) * 4), "skew4": ((5, 50, 50, 50), (2, 2, 20, 20))}


@query("ratio_tables", _ratio_sql(TABLE_SIZES))
def ratio_tables(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(n, ms.compression_ratio(d, r), ms.saved_fraction(d, r)) for n, (d, r) in TABLE_SIZES.items()]
    return frame(spark, rows, "array_name string, ratio double, saved double").select("array_name", rounded("ratio"), rounded("saved"))


@query("bytes_tables", """SELECT 'published-8TB' AS array_name, 512::BIGINT * 512 * 512 * 64 * 128 * 8 AS bytes, 512::BIGINT * 512 * 512 * 64 * 8 AS bytes_per_step
 UNION ALL SELECT 'trade4v', (SELECT count(*) FROM nation) * (SELECT count(DISTINCT p_brand) FROM part) * 4 * 83 * 8, (SELECT count(*) FROM nation) * (SELECT count(DISTINCT p_brand) FROM part) * 4 * 8
 UNION ALL SELECT 'vec2', (SELECT count(*) FROM embeddings) * 64 * 8, 64 * 8""")
def bytes_tables(spark: SparkSession, sf: str) -> DataFrame:
    nations = load_table(spark, sf, "nation").count()
    brands = load_table(spark, sf, "part").select(F.countDistinct("p_brand")).first()[0]
    vectors = load_table(spark, sf, "embeddings").count()
    sets = [("published-8TB", (512, 512, 512, 64, 128)), ("trade4v", (nations, brands, 4, 83)), ("vec2", (64, vectors))]
    return frame(spark, [(n, ms.bytes_of(d), ms.bytes_of(d[:-1])) for n, d in sets], "array_name string, bytes long, bytes_per_step long")


_MARGIN = f"{A4}, t AS (SELECT sum(v)::DOUBLE t FROM a), m1 AS (SELECT i_1, sum(v)::DOUBLE x1 FROM a GROUP BY 1), m2 AS (SELECT i_2, sum(v)::DOUBLE x2 FROM a GROUP BY 1), m3 AS (SELECT i_3, sum(v)::DOUBLE x3 FROM a GROUP BY 1), m4 AS (SELECT i_4, sum(v)::DOUBLE x4 FROM a GROUP BY 1), d AS (SELECT a.*, v - x1 / t * x2 / t * x3 / t * x4 / t * t AS e FROM a JOIN m1 USING (i_1) JOIN m2 USING (i_2) JOIN m3 USING (i_3) JOIN m4 USING (i_4), t)"


@query("err_norms", f"{_MARGIN} SELECT round(sqrt(sum(e * e) / sum(v * v)), 6) AS norm_rms, round(max(abs(e)), 4) AS max_abs FROM d")
def err_norms(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.ship4(spark, sf)
    x = Cells(cells.df.withColumn("v", F.col("v").cast("double")), cells.spec)
    return ms.error_measures(x, arrays.margins(cells)).select(rounded("norm_rms"), rounded("max_abs", 4))


@query("err_pointwise_topk", f"{_MARGIN} SELECT i_1, i_2, i_3, i_4, round(abs(e), 4) AS err FROM d ORDER BY abs(e) DESC LIMIT 10")
def err_pointwise_topk(spark: SparkSession, sf: str) -> DataFrame:
    cells, names = arrays.ship4(spark, sf), tn.index_columns(4)
    both = cells.df.join(arrays.margins(cells).df.withColumnRenamed("v", "w"), names)
    return both.select(*names, F.abs(F.col("v") - F.col("w")).alias("err")).orderBy(F.desc("err")).limit(10).select(*names, rounded("err", 4))


@query("pca_vec_variance", "SELECT round(sum(x), 6) AS variance, round(sum(x) / 64, 6) AS mean_share FROM (SELECT var_pop(e::DOUBLE) x FROM (SELECT unnest(range(0, 64)) p, unnest(embedding) e FROM embeddings) GROUP BY p)")
def pca_vec_variance(spark: SparkSession, sf: str) -> DataFrame:
    values, _ = baselines.pca(explode_vector(load_table(spark, sf, "embeddings"), "embedding", ids=("vec_id",)).withColumnRenamed("vec_id", "row"), 64)
    return frame(spark, [(float(values.sum()), float(values.sum() / 64))], "variance double, mean_share double").select(rounded("variance"), rounded("mean_share"))


@query("baseline_svd_rank")
def baseline_svd_rank(spark: SparkSession, sf: str) -> DataFrame:
    """Truncated two-way SVD of the vectors: rank and error for some tolerances."""
    found = sp.from_gram(bk.gram(_blocks(arrays.vec2(spark, sf), (256, 64)), 1))
    total = found.values.sum()
    rows = []
    for eps in (0.1, 0.3, 0.5, 0.9):
        r = sp.rank_for_budget(found.values, eps**2 * total)
        rows.append((eps, r, float(np.sqrt(found.tails[r] / total))))
    return frame(spark, rows, "eps double, rank int, norm_rms double").select("eps", "rank", rounded("norm_rms"))


@query("uncompressed", f"{A4} SELECT count(*) AS words, 1.0::DOUBLE AS ratio, 0.0::DOUBLE AS norm_rms FROM a")
def uncompressed(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.ship4(spark, sf).df.agg(F.count("*").alias("words")).select("words", F.lit(1.0).alias("ratio"), F.lit(0.0).alias("norm_rms"))
