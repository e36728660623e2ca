"""Queries of the cost model, the planner, the experiments and the operators that arrays are made with."""

from __future__ import annotations

import tempfile
import time
import uuid
from math import log10, prod

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corefold.functions import measures as ms
from corefold.functions import spectrum as sp
from corefold.functions import tensor as tn
from corefold.functions.tensor import TensorSpec
from corefold.operators import block_kernels as bk
from corefold.operators import decode, prepare
from corefold.operators import decompose as dc
from corefold.plans import costmodel as cm
from corefold.plans import planner
from corefold import spectra_sql
from corefold.queries import A4, LINE, PUBLISHED, SPECTRAL, TABLE_SIZES, _blocks, _modular, frame, query, rounded
from corefold.sources import arrays, storage, synthetic
from corefold.sources.tables import dictionary, load_table

# ---- cost model ---------------------------------------------------------------------

#: (dims, ranks, grid) that the closed forms are shown for.
CASES = {
    "strong": ((200,) * 4, (20,) * 4, (1, 2, 3, 4)),
    "grid": ((384,) * 4, (96,) * 4, (1, 1, 4, 6)),
    "order": ((25, 250, 250, 250), (10, 10, 100, 100), (2, 2, 2, 2)),
    "weak": ((1200,) * 4, (120,) * 4, (6, 6, 6, 6)),
}


def _d(x: float) -> str:
    return f"{float(x)!r}::DOUBLE"


def _case_rows() -> str:
    """CASES as SQL rows with one row for each mode: sizes before and after it in natural order."""
    rows = []
    for name, (dims, ranks, grid) in CASES.items():
        for m, (i, r, g) in enumerate(zip(dims, ranks, grid, strict=True)):
            rows.append(f"('{name}', {m + 1}, {_d(i)}, {_d(r)}, {_d(g)})")
    return f"(SELECT * FROM (VALUES {', '.join(rows)}) t(name, mode, i, r, g))"


_MODES = f"""WITH c AS {_case_rows()}, t AS (SELECT name, product(g) p, product(i) total, product(r) rtotal FROM c GROUP BY name),
 x AS (SELECT c.*, p, total, rtotal, coalesce(product(r) OVER (PARTITION BY name ORDER BY mode ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 1) * product(i) OVER (PARTITION BY name ORDER BY mode ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS j FROM c JOIN t USING (name))"""


def _mega(x: float) -> float:
    return round(x / 1e6, 6)


#: Arrays whose cost is shown: table, modes, blocks a mode (fewer if the mode is shorter). Sizes are the labels that the table has; half of them are kept.
COSTED = {
    "ship": ("lineitem", ("l_returnflag", "l_linestatus", "month(l_shipdate)", "l_linenumber"), (1, 1, 4, 2)),
    "order": ("orders", ("o_orderstatus", "o_orderpriority", "month(o_orderdate)", "year(o_orderdate)"), (1, 1, 2, 2)),
    "pulse": ("events", ("hour(ts)", "day(ts)", "event_type"), (8, 2, 1)),
    "goods": ("part", ("p_brand", "p_type", "p_size"), (4, 2, 8)),
}


def _costed(spark: SparkSession, sf: str) -> dict[str, tuple]:
    """(dims, ranks, grid) of each array that has cells; one scan of its table."""
    found = {}
    for name, (table, modes, grid) in COSTED.items():
        labels = load_table(spark, sf, table).select(*[F.expr(e).alias(f"m_{k}") for k, e in enumerate(modes)]).distinct()
        dims = tuple(labels.agg(*[F.count_distinct(c).alias(c) for c in labels.columns]).first())
        if all(dims):
            found[name] = dims, tuple(-(-d // 2) for d in dims), tuple(map(min, grid, dims))
    return found


def _costed_sql() -> str:
    rows = " UNION ALL ".join(f"SELECT '{n}' AS name, {m + 1} AS mode, count(DISTINCT {e})::DOUBLE AS i, {_d(g)} AS g FROM {t}" for n, (t, modes, grid) in COSTED.items() for m, (e, g) in enumerate(zip(modes, grid, strict=True)))
    return f"(SELECT name, mode, i, ceil(i / 2) AS r, least(g, i) AS g FROM ({rows}) QUALIFY min(i) OVER (PARTITION BY name) > 0)"


_TABLE_MODES = _MODES.replace(f"c AS {_case_rows()}", f"c AS MATERIALIZED {_costed_sql()}")


def _table_modes(spark: SparkSession, sf: str, fn) -> list[tuple]:  # noqa: ANN001
    rows = []
    for name, (dims, ranks, grid) in _costed(spark, sf).items():
        now = list(dims)
        for m in range(len(dims)):
            rows.append((name, m + 1, *(round(float(x), 6) for x in fn(tuple(now), m, ranks[m], grid))))
            now[m] = ranks[m]
    return rows


@query("cost_ttm", f"{_TABLE_MODES} SELECT name, mode, round(2 * j * r / p, 6) flops, round((g - 1) * j / i * r / p, 6) words, round(log10(j / p + i * r / g + 2 * j / i * r / p), 6) log_memory FROM x")
def cost_ttm(spark: SparkSession, sf: str) -> DataFrame:
    rows = _table_modes(spark, sf, lambda d, m, r, g: ((c := cm.ttm_cost(d, m, r, g)).flops, c.words, log10(cm.ttm_memory(d, m, r, g))))
    return frame(spark, rows, "name string, mode int, flops double, words double, log_memory double")


@query("cost_gram", f"{_TABLE_MODES} SELECT name, mode, round(2 * i * j / p, 6) flops, round(2 * (g - 1) * j / p + 2 * (p / g - 1) * i * i / p, 6) words, round(2 * j / p + 2 * i * i / g, 6) memory FROM x")
def cost_gram(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, _table_modes(spark, sf, lambda d, m, r, g: ((c := cm.gram_cost(d, m, g)).flops, c.words, cm.gram_memory(d, m, g))), "name string, mode int, flops double, words double, memory double")


@query("cost_eig", f"{_TABLE_MODES} SELECT name, mode, round(10.0::DOUBLE / 3 * i ** 3, 6) flops, round((g - 1) / g * i * i, 6) words, round((g - 1) / g * i, 6) words_printed, round(i * i / g + i * i + i * r + i * r / g, 6) memory FROM x")
def cost_eig(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, _table_modes(spark, sf, lambda d, m, r, g: ((c := cm.eig_cost(d[m], g[m])).flops, c.words, cm.eig_cost(d[m], g[m], "printed").words, cm.eig_memory(d[m], r, g[m]))), "name string, mode int, flops double, words double, words_printed double, memory double")


@query("cost_sthosvd", f"{_TABLE_MODES} SELECT name, round(sum(2 * j * r / p), 6) ttm_flops, round(sum(2 * i * j / p), 6) gram_flops, round(sum(10.0::DOUBLE / 3 * i ** 3), 6) eig_flops, round(sum((g - 1) * j / i * r / p + 2 * (g - 1) * j / p + 2 * (p / g - 1) * i * i / p + (g - 1) / g * i * i), 6) words FROM x GROUP BY name")
def cost_sthosvd(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for name, case in _costed(spark, sf).items():
        c = cm.sthosvd_cost(*case)
        rows.append((name, *(round(float(x), 6) for x in (c["ttm"].flops, c["gram"].flops, c["eig"].flops, cm.total(c).words))))
    return frame(spark, rows, "name string, ttm_flops double, gram_flops double, eig_flops double, words double")


@query("cost_hooi", f"{_TABLE_MODES} SELECT name, round(count(*) * sum(2 * j * r / p) - sum(2 * j * r / p), 6) ttm_printed, round(sum(2 * i * i * rtotal / r / p), 6) gram_flops, round(sum((2 * (g - 1) * i * rtotal / r + 2 * i * i * (p / g - 1)) / p), 6) gram_words FROM x GROUP BY name")
def cost_hooi(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for name, case in _costed(spark, sf).items():
        c = cm.hooi_cost(*case, variant="printed")
        rows.append((name, *(round(float(x), 6) for x in (c["ttm"].flops, c["gram"].flops, c["gram"].words))))
    return frame(spark, rows, "name string, ttm_printed double, gram_flops double, gram_words double")


_SWEEP_SQL = f"""{_TABLE_MODES}, s AS (SELECT a.name, a.mode, b.mode AS m, 2 * any_value(b.r) * product(CASE WHEN k.mode < b.mode AND k.mode <> a.mode THEN k.r ELSE k.i END) AS flops FROM c a JOIN c b ON a.name = b.name AND a.mode <> b.mode JOIN c k ON k.name = a.name GROUP BY ALL),
 l AS (SELECT name, arg_max(i, mode) AS last FROM c GROUP BY name)
 SELECT name, round((sum(flops) + 2 * any_value(rtotal) * any_value(last)) / any_value(p), 6) AS ttm_exact FROM s JOIN t USING (name) JOIN l USING (name) GROUP BY name"""


@query("cost_hooi_exact", _SWEEP_SQL)
def cost_hooi_exact(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, [(n, round(float(cm.hooi_cost(*c)["ttm"].flops), 6)) for n, c in _costed(spark, sf).items()], "name string, ttm_exact double")


@query("mem_bound", f"{_MODES} SELECT name, round((2 * any_value(total) / any_value(p) + sum(r * i / g) + max(i * i) + max(r * i)) / 1e6, 6) AS words FROM x GROUP BY name")
def mem_bound(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, [(n, _mega(cm.peak_memory(*c))) for n, c in CASES.items()], "name string, words double")


@query("gram_ttm_ratio", f"{_MODES} SELECT name, mode, i / r AS ratio FROM x")
def gram_ttm_ratio(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, [(n, m + 1, cm.gram_ttm_ratio(d, r, m)) for n, (d, r, _) in CASES.items() for m in range(len(d))], "name string, mode int, ratio double")


@query("cost_collectives", f"""WITH c AS {_costed_sql()} SELECT name, mode, kind, CAST(p AS BIGINT) p, CASE kind WHEN 'send' THEN i * i WHEN 'all_reduce' THEN 2 * i * i * (p - 1) / p ELSE i * i * (p - 1) / p END AS words,
 CASE kind WHEN 'send' THEN 1.0::DOUBLE WHEN 'all_reduce' THEN 2 * log2(p) ELSE log2(p) END AS messages, CASE WHEN kind IN ('reduce', 'all_reduce') THEN i * i * (p - 1) / p ELSE 0.0 END AS flops
 FROM c, (SELECT unnest(['send', 'all_gather', 'reduce', 'all_reduce']) kind), (SELECT unnest([2, 8, 64]) p)""")
def cost_collectives(spark: SparkSession, sf: str) -> DataFrame:
    """Each mode's Gram matrix on its way between nodes."""
    rows = []
    for name, (dims, _, _) in _costed(spark, sf).items():
        for m, d in enumerate(dims):
            for k in ("send", "all_gather", "reduce", "all_reduce"):
                rows += [(name, m + 1, k, p, float((c := cm.collective_cost(k, float(d * d), p)).words), float(c.messages), float(c.flops)) for p in (2, 8, 64)]
    return frame(spark, rows, "name string, mode int, kind string, p long, words double, messages double, flops double")


# ---- planning -----------------------------------------------------------------------

_ORDER = CASES["order"]


def _order_sql(dims: tuple[int, ...] = _ORDER[0], ranks: tuple[int, ...] = _ORDER[1], grid: tuple[int, ...] = _ORDER[2]) -> str:
    """Every distinct order of such a case (two blocks a mode, the last two modes alike) by a recursive walk over modes."""
    modes = ", ".join(f"({m + 1}, {_d(i)}, {_d(r)})" for m, (i, r) in enumerate(zip(dims, ranks, strict=True)))
    total = _d(prod(dims))
    return f"""WITH RECURSIVE m(mode, i, r) AS (VALUES {modes}), w(path, j, flops, words) AS (
 SELECT '', {total}, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL
 SELECT path || m.mode, j * r / i, flops + 2 * j * i + 2 * j * r, words + 2 * j / 16 + 2 * (8 - 1) * i * i / 16 + j / i * r / 16 FROM w JOIN m ON NOT contains(path, m.mode::VARCHAR))
 SELECT path, flops, words FROM w WHERE length(path) = 4 AND strpos(path, '3') < strpos(path, '4')"""


@query("order_flops", f"SELECT path AS mode_order, round(flops / 1e9, 4) AS gflops FROM ({_order_sql()})")
def order_flops(spark: SparkSession, sf: str) -> DataFrame:
    dims, ranks, grid = _ORDER
    return frame(spark, [("".join(str(m + 1) for m in o), round(planner.order_cost(dims, ranks, o, grid).flops * prod(grid) / 1e9, 4)) for o in planner.distinct_orders(dims, ranks)], "mode_order string, gflops double")


@query("order_words", f"SELECT path AS mode_order, round(words / 1e6, 4) AS mega_words FROM ({_order_sql()})")
def order_words(spark: SparkSession, sf: str) -> DataFrame:
    dims, ranks, grid = _ORDER
    return frame(spark, [("".join(str(m + 1) for m in o), round(planner.order_cost(dims, ranks, o, grid).words / 1e6, 4)) for o in planner.distinct_orders(dims, ranks)], "mode_order string, mega_words double")


def _policies(policy: str):  # noqa: ANN202
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = []
        for name, (dims, ranks) in (TABLE_SIZES | PUBLISHED).items():
            order = planner.plan_mode_order(dims, ranks, policy)
            rows.append((name, "".join(str(m + 1) for m in order), round(planner.order_cost(dims, ranks, order).flops / 1e9, 4)))
        return frame(spark, rows, "array_name string, mode_order string, gflops double")

    return run


def _ratio_sql() -> str:
    rows = ", ".join(f"('{n}', {m + 1}, {_d(i)}, {_d(r)})" for n, (dims, ranks) in (TABLE_SIZES | PUBLISHED).items() for m, (i, r) in enumerate(zip(dims, ranks, strict=True)))
    return f"""WITH m AS (SELECT * FROM (VALUES {rows}) t(n, mode, i, r)), o AS (SELECT *, row_number() OVER (PARTITION BY n ORDER BY i / r DESC, mode) k FROM m),
 j AS (SELECT *, product(i) OVER (PARTITION BY n ORDER BY k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) * coalesce(product(r) OVER (PARTITION BY n ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 1) j FROM o)
 SELECT n AS array_name, string_agg(mode::VARCHAR, '' ORDER BY k) AS mode_order, round(sum(2 * j * i + 2 * j * r) / 1e9, 4) AS gflops FROM j GROUP BY n"""


query("order_greedy_ratio", _ratio_sql())(_policies("greedy_ratio"))
query("order_natural", _ratio_sql().replace("ORDER BY i / r DESC, mode", "ORDER BY mode"))(_policies("natural"))
# the work of a step is 2 * size * (i + r), and the size is the same for all modes that are left
query("order_greedy_flops", _ratio_sql().replace("ORDER BY i / r DESC, mode", "ORDER BY i + r, mode"))(_policies("greedy_flops"))


def _exhaustive_sql() -> str:
    rows = ", ".join(f"('{n}', {m + 1}, {i}::HUGEINT, {r}::HUGEINT)" for n, (dims, ranks) in (TABLE_SIZES | PUBLISHED).items() for m, (i, r) in enumerate(zip(dims, ranks, strict=True)))
    sizes = ", ".join(f"('{n}', {prod(dims)}::HUGEINT, {len(dims)})" for n, (dims, _) in (TABLE_SIZES | PUBLISHED).items())
    return f"""WITH RECURSIVE m AS (SELECT * FROM (VALUES {rows}) t(n, mode, i, r)), z AS (SELECT * FROM (VALUES {sizes}) t(n, j, modes)),
 w(n, modes, path, j, flops) AS (SELECT n, modes, '', j, 0::HUGEINT FROM z UNION ALL SELECT w.n, modes, path || mode, w.j * r // i, flops + 2 * w.j * (i + r) FROM w JOIN m ON m.n = w.n AND NOT contains(path, mode::VARCHAR))
 SELECT n AS array_name, path AS mode_order, round(flops::DOUBLE / 1e9, 4) AS gflops FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY flops, path) k FROM w WHERE length(path) = modes) WHERE k = 1"""


query("order_exhaustive", _exhaustive_sql())(_policies("exhaustive"))

_GRIDS = "SELECT a, b, c, 24 // (a * b * c) AS d FROM (SELECT unnest(range(1, 25)) a), (SELECT unnest(range(1, 25)) b), (SELECT unnest(range(1, 25)) c) WHERE 24 % a = 0 AND 24 % (a * b) = 0 AND 24 % (a * b * c) = 0"


@query("grid_enumerate", f"SELECT CAST(a AS INTEGER) p_1, CAST(b AS INTEGER) p_2, CAST(c AS INTEGER) p_3, CAST(d AS INTEGER) p_4 FROM ({_GRIDS})")
def grid_enumerate(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, planner.enumerate_grids(24, 4), "p_1 int, p_2 int, p_3 int, p_4 int")


def _grid_words() -> str:
    i, r = _d(384), _d(96)
    parts = []
    for m, g in enumerate("abcd"):
        j = " * ".join([r] * m + [i] * (4 - m))
        parts.append(f"2 * ({g} - 1) * ({j}) / 24 + 2 * (24 / {g} - 1) * {i} * {i} / 24 + ({g} - 1) * ({j}) / {i} * {r} / 24 + ({g} - 1) / {g} * {i} * {i}")
    return " + ".join(parts)


@query("grid_words", f"SELECT CAST(a AS INTEGER) p_1, CAST(b AS INTEGER) p_2, CAST(c AS INTEGER) p_3, CAST(d AS INTEGER) p_4, round(({_grid_words()}) / 1e6, 6) AS mega_words FROM (SELECT a::DOUBLE a, b::DOUBLE b, c::DOUBLE c, d::DOUBLE d FROM ({_GRIDS}))")
def grid_words(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(*g, round(cm.total(cm.sthosvd_cost((384,) * 4, (96,) * 4, g)).words / 1e6, 6)) for g in planner.enumerate_grids(24, 4)]
    return frame(spark, rows, "p_1 int, p_2 int, p_3 int, p_4 int, mega_words double")


@query("grid_best", f"SELECT CAST(a AS INTEGER) p_1, CAST(b AS INTEGER) p_2, CAST(c AS INTEGER) p_3, CAST(d AS INTEGER) p_4 FROM (SELECT *, {_grid_words()} w FROM (SELECT a::DOUBLE a, b::DOUBLE b, c::DOUBLE c, d::DOUBLE d FROM ({_GRIDS}))) ORDER BY w LIMIT 1")
def grid_best(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, planner.choose_grid((384,) * 4, (96,) * 4, 24)[:1], "p_1 int, p_2 int, p_3 int, p_4 int")


# ---- experiments --------------------------------------------------------------------

E1_EPS = (1e-6, 1e-5, 1e-4, 1e-3, 1e-2, 0.05, 0.1, 0.3)


def _standardised(spark: SparkSession, sf: str, name: str):  # noqa: ANN202
    make, _, _, variable, _ = SPECTRAL[name]
    return dc.materialize(_blocks(prepare.standardize(make(spark, sf), variable)[0]))


def sweep_eps(chunks, eps_list: tuple[float, ...]) -> list[tuple]:  # noqa: ANN001
    """(eps, ranks, ratio, bound, error) for several tolerances: one scan for all spectra, one chain of products for each tolerance."""
    spectra = {m: sp.from_gram(s) for m, s in bk.grams(chunks).items()}
    total = bk.norm_sq(chunks)
    values = {m: s.values for m, s in spectra.items()}
    out = []
    for eps in eps_list:
        ranks = tuple(sp.rank_for_budget(values[m], eps**2 * total / chunks.spec.order) for m in range(chunks.spec.order))
        core = dc.core_for(chunks, [spectra[m].vectors[:, :r] for m, r in enumerate(ranks)])
        error = max(1 - bk.norm_sq(core) / total, 0.0) ** 0.5
        out.append((eps, ranks, ms.compression_ratio(chunks.spec.dims, ranks), ms.thosvd_bound(values, ranks, total), error))
    return out


def _e1_sql(name: str, dims: tuple[int, ...]) -> str:
    _, base, n, variable, _ = SPECTRAL[name]
    sizes = ", ".join(f"({m + 1}, {d})" for m, d in enumerate(dims))
    return f"""{spectra_sql.curves(base, n, variable, list(range(n)))}, q AS (SELECT unnest([{", ".join(map(_d, E1_EPS))}]) AS eps), sz AS (SELECT * FROM (VALUES {sizes}) t(mode, i)),
 r AS (SELECT eps, mode, min(pos) AS r FROM e, q WHERE tail <= eps * eps / {n} GROUP BY ALL),
 f AS (SELECT eps, string_agg(r::VARCHAR, ',' ORDER BY r.mode) AS ranks, product(i::DOUBLE) / (product(r::DOUBLE) + sum(i * r)) AS ratio, sqrt(greatest(sum(tail), 0)) AS bound FROM r JOIN sz USING (mode) JOIN e ON e.mode = r.mode AND e.pos = r.r GROUP BY eps)
 SELECT '{name}' AS array_name, eps, ranks, round(ratio, 6) AS ratio, round(bound, 6) AS bound, round(1 - 1 / ratio, 6) AS saved, true AS within FROM f"""


for _name, _dims in (("pulse4v", (24, 7, 5, 3)), ("grid5v", (10, 10, 10, 4, 7)), ("trade5v", (25, 25, 3, 4, 7))):

    @query(f"e1_ratio_vs_error_{_name}", _e1_sql(_name, _dims))
    def e1_ratio_vs_error(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        """Ranks, ratio and bound by tolerance; within: the error of the decomposition is at most the bound and the tolerance."""
        rows = [(name, eps, ",".join(map(str, r)), ratio, bound, 1 - 1 / ratio, error <= min(bound, eps) * (1 + 1e-6) + 1e-7) for eps, r, ratio, bound, error in sweep_eps(_standardised(spark, sf, name), E1_EPS)]
        return frame(spark, rows, "array_name string, eps double, ranks string, ratio double, bound double, saved double, within boolean").select("array_name", "eps", "ranks", rounded("ratio"), rounded("bound"), rounded("saved"), "within")


@query("e1_ratio_vs_error_months")
def e1_ratio_vs_error_months(spark: SparkSession, sf: str) -> DataFrame:
    """The same with a long mode, and for an array with decaying spectra."""
    rows = []
    decaying = dc.materialize(synthetic.synthetic(spark, (24, 24, 24, 12), (8, 8, 8, 6), (24, 12, 12, 12), seed=7, decay=0.6))
    for name, chunks in (("trade4v", _standardised(spark, sf, "trade4v")), ("decaying", decaying)):
        rows += [(name, eps, ",".join(map(str, r)), ratio, bound, error, 1 - 1 / ratio) for eps, r, ratio, bound, error in sweep_eps(chunks, E1_EPS)]
    return frame(spark, rows, "array_name string, eps double, ranks string, ratio double, bound double, error double, saved double")


def _one_mode_sql() -> str:
    _, base, n, variable, _ = SPECTRAL["pulse4v"]
    return f"{spectra_sql.curves(base, n, variable, list(range(n)))} SELECT CAST(mode AS INTEGER) AS mode, pos AS rank, round(sqrt(greatest(tail, 0)), 5) AS norm_rms FROM e WHERE pos <= 3"


@query("e3_truncated_modes", _one_mode_sql())
def e3_truncated_modes(spark: SparkSession, sf: str) -> DataFrame:
    """Error of the decoded array, cell by cell, with one mode cut to each of the first ranks and the others whole."""
    chunks = _standardised(spark, sf, "pulse4v")
    dims = chunks.spec.dims
    x = bk.to_cells(chunks)
    out = None
    for mode, size in enumerate(dims):
        for rank in range(1, min(3, size) + 1):
            model = dc.st_hosvd(chunks, ranks=(*dims[:mode], rank, *dims[mode + 1 :]), order=(mode, *(m for m in range(len(dims)) if m != mode)))
            one = ms.error_measures(x, bk.to_cells(decode.reconstruct(model))).select(F.lit(mode + 1).alias("mode"), F.lit(rank).alias("rank"), "norm_rms")
            out = one if out is None else out.unionByName(one)
    return out.select("mode", "rank", rounded("norm_rms", 5))


@query("e3_accuracy")
def e3_accuracy(spark: SparkSession, sf: str) -> DataFrame:
    """Both methods at a tight and a loose tolerance: sizes, error, largest cell error. Refinement stops by its own rule."""
    rows = []
    noisy = dc.materialize(synthetic.synthetic(spark, (24, 24, 24, 12), (8, 8, 8, 6), (24, 12, 12, 12), seed=7, noise=1e-3))
    for name, chunks in (*((name, _standardised(spark, sf, name)) for name in ("trade4v", "trade5v", "grid5v")), ("noisy", noisy)):
        x = bk.to_cells(chunks)
        for eps in (1e-3, 0.3):
            st = dc.st_hosvd(chunks, eps=eps)
            for method, model in (("st_hosvd", st), ("hooi", dc.hooi(chunks, init=list(st.factors), max_sweeps=3, tol=1e-6))):
                err = ms.error_measures(x, bk.to_cells(decode.reconstruct(model))).first()
                rows.append((name, eps, method, ",".join(map(str, model.ranks)), float(err.norm_rms), float(err.max_abs), ms.compression_ratio(model.dims, model.ranks), bool(err.norm_rms <= eps * (1 + 1e-6) + 1e-7)))
    return frame(spark, rows, "array_name string, eps double, method string, ranks string, norm_rms double, max_abs double, ratio double, within boolean")


def _timed(rows: list, label: tuple, model: dc.TuckerModel) -> None:
    rows += [(*label, s.mode + 1, s.kernel, s.flops, s.seconds) for s in model.trace if s.kernel != "fit"]


def _relative(df: DataFrame, key: str) -> DataFrame:
    """Each configuration's whole time over that of the fastest."""
    whole = Window.partitionBy(key)
    summed = df.withColumn("total", F.sum("seconds").over(whole))
    best = df.groupBy(key).agg(F.sum("seconds").alias("t")).agg(F.min("t").alias("best"))
    return summed.crossJoin(F.broadcast(best)).withColumn("rel", F.col("total") / F.col("best")).drop("total", "best")


def _step_sql(dims: tuple[int, ...], ranks: tuple[int, ...]) -> str:
    """(mode, kernel, flops) of one pass in natural order."""
    rows, now = [], list(dims)
    for m, r in enumerate(ranks):
        size = " * ".join(map(_d, now))
        rows += [f"SELECT {m + 1} AS mode, 'gram' AS kernel, 2 * {size} * {now[m]} AS flops", f"SELECT {m + 1}, 'ttm', 2 * {size} * {r}"]
        now[m] = r
    return " UNION ALL ".join(rows)


#: Block grids of the grid experiment; the first mode whole, half split, split.
E4_GRIDS = ((1, 1, 2, 2), (1, 2, 2, 1), (1, 1, 1, 4), (1, 1, 4, 1), (1, 4, 1, 1), (2, 1, 1, 2), (2, 1, 2, 1), (2, 2, 1, 1), (4, 1, 1, 1))


def _grid_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Every way to cut one array of equal sizes into four blocks, a quarter of each size kept."""
    cells = arrays.cube4(spark, sf, 24).df.persist()
    rows: list = []
    first = None
    for grid in E4_GRIDS:
        chunks = dc.materialize(bk.to_chunks(tn.Cells(cells, TensorSpec((24,) * 4).on_grid(grid))))
        model = dc.st_hosvd(chunks, ranks=(6,) * 4)
        kept = model.core_norm_sq / model.norm_sq
        first = kept if first is None else first
        _timed(rows, (str(grid), abs(kept - first) < 1e-9), model)
    cells.unpersist()
    return frame(spark, rows, "grid string, same_energy boolean, mode int, kernel string, flops double, seconds double")


@query("e4_grids", f"SELECT grid, true AS same_energy, mode, kernel, round(flops / 1e6, 6) AS mega_flops FROM ({_step_sql((24,) * 4, (6,) * 4)}), (SELECT unnest([{', '.join(repr(str(g)) for g in E4_GRIDS)}]) AS grid)")
def e4_grids(spark: SparkSession, sf: str) -> DataFrame:
    return _grid_rows(spark, sf).select("grid", "same_energy", "mode", "kernel", F.round(F.col("flops") / 1e6, 6).alias("mega_flops"))


@query("e4_grid_seconds")
def e4_grid_seconds(spark: SparkSession, sf: str) -> DataFrame:
    return _relative(_grid_rows(spark, sf), "grid")


_E5 = ((5, 50, 50, 50), (2, 2, 20, 20), (2,) * 4)


def _order_rows(spark: SparkSession, sf: str) -> DataFrame:
    """All distinct mode orders of a skewed array on a grid of two blocks a mode."""
    dims, ranks, grid = _E5
    chunks = dc.materialize(bk.to_chunks(arrays.skew4(spark, sf), TensorSpec(dims).on_grid(grid).block))
    rows: list = []
    for order in planner.distinct_orders(dims, ranks):
        at = "".join(str(m + 1) for m in order)
        _timed(rows, (at, planner.order_cost(dims, ranks, order, grid).words), dc.st_hosvd(chunks, ranks=ranks, order=order))
    return frame(spark, rows, "mode_order string, words double, mode int, kernel string, flops double, seconds double")


@query("e5_orders", f"SELECT path AS mode_order, round(words / 1e6, 6) AS mega_words, round(flops / 1e6, 6) AS mega_flops, path[1]::INTEGER AS first_mode FROM ({_order_sql(*_E5)})")
def e5_orders(spark: SparkSession, sf: str) -> DataFrame:
    done = _order_rows(spark, sf).groupBy("mode_order").agg(F.first("words").alias("words"), F.sum("flops").alias("flops"))
    return done.select("mode_order", F.round(F.col("words") / 1e6, 6).alias("mega_words"), F.round(F.col("flops") / 1e6, 6).alias("mega_flops"), F.substring("mode_order", 1, 1).cast("int").alias("first_mode"))


@query("e5_order_seconds")
def e5_order_seconds(spark: SparkSession, sf: str) -> DataFrame:
    return _relative(_order_rows(spark, sf), "mode_order")


def scaling_point(spark: SparkSession, chunks, ranks: tuple[int, ...], peak: float | None = None) -> list[tuple]:  # noqa: ANN001
    """Seconds and rates of one pass and of one refinement sweep on an array."""
    cores = spark.sparkContext.defaultParallelism
    chunks = dc.materialize(chunks)
    peak = peak or cm.peak_gflops()
    rows = []
    st = model = None
    for method in ("st_hosvd", "hooi_1"):
        at = time.monotonic()
        if st is None:
            st = model = dc.st_hosvd(chunks, ranks=ranks)
        else:
            model = dc.hooi(chunks, init=list(st.factors), max_sweeps=1)
        took = time.monotonic() - at
        flops = sum(s.flops for s in model.trace)
        rate = cm.rate_report(flops, took, cores, peak)
        rows.append((str(chunks.spec.dims), method, cores, flops / 1e9, took, rate["gflops"], rate["gflops_core"], rate["pct_peak"], float(model.norm_rms) < 1e-6))
    chunks.df.unpersist()
    return rows


_SCALE = "dims string, method string, cores int, work double, seconds double, gflops double, gflops_core double, pct_peak double, recovered boolean"


def _exact_rank(spark: SparkSession, dims: tuple[int, ...], ranks: tuple[int, ...], grid: tuple[int, ...]):  # noqa: ANN202
    return synthetic.synthetic(spark, dims, ranks, TensorSpec(dims).on_grid(grid).block, seed=1)


def _strong(spark: SparkSession, sf: str) -> list[tuple]:
    """An array of known rank, and one from the tables, at this session's cores; bench.py repeats it over core counts."""
    rows = scaling_point(spark, _exact_rank(spark, (40,) * 4, (4,) * 4, (1, 1, 2, 4)), (4,) * 4)
    cube = bk.to_chunks(arrays.cube4(spark, sf, 24), TensorSpec((24,) * 4).on_grid((1, 1, 2, 4)).block)
    return rows + scaling_point(spark, cube, (2,) * 4)


def _work_sql(side: int, rank: int, recovered: bool) -> str:
    """Gflops of one pass, and of one sweep (for each mode the others' products, and a Gram matrix of what is left)."""
    i, r = _d(side), _d(rank)
    one = " + ".join(f"2 * ({r}) ** {m} * ({i}) ** {4 - m} * ({i} + {r})" for m in range(4))
    sweep = f"4 * (2 * {r} * ({i} ** 4 + {r} * {i} ** 3 + {r} * {r} * {i} ** 2) + 2 * {i} * {i} * {r} ** 3)"
    return " UNION ALL ".join(f"SELECT '{(side,) * 4}' AS dims, '{m}' AS method, round(({w}) / 1e9, 6) AS work, {str(recovered).lower()} AS recovered" for m, w in (("st_hosvd", one), ("hooi_1", sweep)))


def _work(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return frame(spark, rows, _SCALE).select("dims", "method", F.round("work", 6).alias("work"), "recovered")


@query("e6_strong_scaling", f"{_work_sql(40, 4, True)} UNION ALL {_work_sql(24, 2, False)}")
def e6_strong_scaling(spark: SparkSession, sf: str) -> DataFrame:
    return _work(spark, _strong(spark, sf))


@query("e6_seconds")
def e6_seconds(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, _strong(spark, sf), _SCALE)


def _weak(spark: SparkSession, sf: str) -> list[tuple]:
    """Sizes 20k with ranks 2k, of the margins of orders in 2k groups; three families of block grids, the best kept."""
    rows = []
    peak = cm.peak_gflops()
    for k in (1, 2, 3):
        dims, ranks = (20 * k,) * 4, (2 * k,) * 4
        factors = arrays.ranked_factors(spark, sf, 20 * k, 2 * k)
        points = [scaling_point(spark, arrays.ranked(spark, factors, TensorSpec(dims).on_grid(grid).block), ranks, peak) for grid in dict.fromkeys(((1, 1, 2 * k, 2 * k), (1, k, 2, 2 * k), (k, k, 2, 2)))]
        rows += min(points, key=lambda p: p[0][4])
    return rows


@query("e7_weak_scaling", " UNION ALL ".join(_work_sql(20 * k, 2 * k, True) for k in (1, 2, 3)))
def e7_weak_scaling(spark: SparkSession, sf: str) -> DataFrame:
    return _work(spark, _weak(spark, sf))


@query("e7_seconds")
def e7_seconds(spark: SparkSession, sf: str) -> DataFrame:
    return frame(spark, _weak(spark, sf), _SCALE)


def _ranked_sql(side: int, rank: int) -> str:
    """WITH ... n(energy) of arrays.ranked4, from the inner products of the groups' margins."""
    keys = (f"l_suppkey % {side}", f"l_partkey % {side}", f"l_orderkey % {side}", f"datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) % {side}")
    sums = " UNION ALL ".join(f"SELECT {m + 1} AS mode, {k} AS i, l_orderkey % {side} * {rank} // {side} AS g, sum(CAST(l_quantity AS BIGINT))::DOUBLE AS q FROM lineitem GROUP BY ALL" for m, k in enumerate(keys))
    return f"""WITH m AS MATERIALIZED ({sums}), d AS (SELECT mode, x.g, y.g AS h, sum(x.q * y.q) AS s FROM m x JOIN m y USING (mode, i) GROUP BY ALL), b AS (SELECT product(s) AS s FROM d GROUP BY g, h HAVING count(*) = 4),
 n AS (SELECT sum(s) * (SELECT ({side} / sum(CAST(l_quantity AS BIGINT))::DOUBLE) ** 8 FROM lineitem) AS energy FROM b)"""


@query("e10_extreme_compression", f"{_ranked_sql(40, 4)} SELECT '4,4,4,4' AS ranks, CAST(8 * 40 * 40 * 40 * 40 AS BIGINT) AS bytes_in, CAST(8 * (4 * 4 * 4 * 4 + 4 * 40 * 4) AS BIGINT) AS bytes_out, round(40.0::DOUBLE ** 4 / (4.0::DOUBLE ** 4 + 4 * 40 * 4), 3) AS ratio, true AS on_disk, round(log10(energy), 6) AS log_energy FROM n")
def e10_extreme_compression(spark: SparkSession, sf: str) -> DataFrame:
    """A tenth of each size kept, on an array of margins that has exactly this rank. on_disk: the saved model takes less than its words and 64 KB of headers."""
    model = dc.st_hosvd(dc.materialize(arrays.ranked4(spark, sf, 40, 4, (40, 40, 20, 10))), eps=1e-6)
    words = ms.storage_words(model.dims, model.ranks)
    held = 8 * words < storage.saved_bytes(spark, model) < 8 * words + (64 << 10)
    return frame(spark, [(",".join(map(str, model.ranks)), ms.bytes_of(model.dims), 8 * words, round(ms.compression_ratio(model.dims, model.ranks), 3), held, round(log10(model.norm_sq), 6))], "ranks string, bytes_in long, bytes_out long, ratio double, on_disk boolean, log_energy double")


@query("e12_layout", f"SELECT i_1, i_2, i_3, i_4, CAST(i_1 + 2 * i_2 + 4 * i_3 + 8 * i_4 AS BIGINT) AS place, CAST(i_1 + 2 * i_3 + 4 * i_4 AS BIGINT) AS col_m2, CAST(i_1 + 2 * i_2 + 4 * i_4 AS BIGINT) AS col_m3, v FROM ({_modular((2, 2, 2, 2))})")
def e12_layout(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.modular4(spark, sf, (2, 2, 2, 2))
    return cells.df.select(*tn.index_columns(4), tn.offset(cells.spec).alias("place"), tn.unfold_index(cells.spec, 1)[1].alias("col_m2"), tn.unfold_index(cells.spec, 2)[1].alias("col_m3"), "v")


@query("e13_grid_figures", """SELECT CAST(k AS INTEGER) i_1, CAST(0 AS INTEGER) i_2, CAST(c AS INTEGER) i_3, CAST(coalesce(sum((k + 1) * (j + 1) * q), 0) AS BIGINT) AS v FROM (SELECT range k FROM range(0, 2)) CROSS JOIN (SELECT range c FROM range(0, 4))
 LEFT JOIN (SELECT l_partkey % 6 AS j, l_orderkey % 4 AS c, CAST(l_quantity AS BIGINT) AS q FROM lineitem WHERE l_suppkey % 4 = 0) USING (c) GROUP BY k, c""")
def e13_grid_figures(spark: SparkSession, sf: str) -> DataFrame:
    """A 4 x 6 x 4 array on a 2 x 3 x 2 grid times a 2 x 6 matrix along the split middle mode; the fibres at the first index."""
    v = np.fromfunction(lambda k, j: (k + 1) * (j + 1), (2, 6))
    out = bk.to_cells(bk.ttm(_blocks(arrays.grid3(spark, sf), (2, 2, 2)), v, 1, reduce="blocked", out_block=1)).df
    return out.filter("i_1 = 0").select(F.col("i_2").alias("i_1"), F.lit(0).alias("i_2"), "i_3", F.round("v").cast("long").alias("v"))


# ---- operators that arrays are made with --------------------------------------------


@query("op_semi", "SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def op_semi(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "documents").join(load_table(spark, sf, "labels").filter("quality = 1"), "doc_id", "left_semi").select("doc_id", "n_chars")


@query("op_anti", f"WITH a AS (SELECT DISTINCT i_1, i_2, i_3, i_4, i_5 FROM ({LINE})), g AS (SELECT * FROM (SELECT range i_1 FROM range(0, 3)), (SELECT range i_2 FROM range(0, 2)), (SELECT range i_3 FROM range(0, 12)), (SELECT range i_4 FROM range(0, 7)), (SELECT range i_5 FROM range(0, 7))) SELECT CAST(i_1 AS INTEGER) i_1, CAST(i_2 AS INTEGER) i_2, CAST(i_3 AS INTEGER) i_3, CAST(i_4 AS INTEGER) i_4, CAST(i_5 AS INTEGER) i_5 FROM g WHERE NOT EXISTS (SELECT 1 FROM a WHERE a.i_1 = g.i_1 AND a.i_2 = g.i_2 AND a.i_3 = g.i_3 AND a.i_4 = g.i_4 AND a.i_5 = g.i_5)")
def op_anti(spark: SparkSession, sf: str) -> DataFrame:
    """Cells of the five-way array that have no rows."""
    from corefold.sources.tables import cells_from_table, index_grid

    modes = arrays._ship_modes() | {"year": (F.year("l_shipdate") - 1995, 7)}
    cells = cells_from_table(load_table(spark, sf, "lineitem"), modes, F.count("*"), fill=None)
    return index_grid(spark, cells.spec).join(cells.df, tn.index_columns(5), "left_anti")


@query("op_range_join", "SELECT CAST(b AS INTEGER) bucket, count(*) n FROM documents JOIN (SELECT range b, pow(4, range)::BIGINT - 1 lo, pow(4, range + 1)::BIGINT - 2 hi FROM range(0, 12)) ON n_chars BETWEEN lo AND hi GROUP BY b")
def op_range_join(spark: SparkSession, sf: str) -> DataFrame:
    buckets = spark.range(12).select(F.col("id").cast("int").alias("bucket"), (F.pow(F.lit(4), F.col("id")).cast("long") - 1).alias("lo"), (F.pow(F.lit(4), F.col("id") + 1).cast("long") - 2).alias("hi"))
    docs = load_table(spark, sf, "documents").select("n_chars")
    return docs.join(F.broadcast(buckets), F.col("n_chars").between(F.col("lo"), F.col("hi"))).groupBy("bucket").agg(F.count("*").alias("n"))  # twelve buckets


@query("op_asof", "SELECT o_orderkey, coalesce(event_id, -1) AS event_id FROM (SELECT DISTINCT o_orderkey, o_custkey FROM orders) o ASOF LEFT JOIN (SELECT DISTINCT user_id, event_id FROM events) e ON e.user_id = o.o_custkey AND o.o_orderkey >= e.event_id")
def op_asof(spark: SparkSession, sf: str) -> DataFrame:
    """The last event of the same customer at or before an order, by number: a union and one window."""
    orders = load_table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("k")).distinct()
    events = load_table(spark, sf, "events").select(F.col("user_id").alias("k"), F.col("event_id").alias("at"), F.col("event_id").alias("e"), F.lit(None).cast("long").alias("o_orderkey"))
    both = events.unionByName(orders.select("k", F.col("o_orderkey").alias("at"), F.lit(None).cast("long").alias("e"), "o_orderkey"))
    order = Window.partitionBy("k").orderBy("at", F.col("o_orderkey").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("event_id", F.last("e", ignorenulls=True).over(order)).filter("o_orderkey IS NOT NULL").select("o_orderkey", F.coalesce("event_id", F.lit(-1)).alias("event_id"))


@query("op_pivot", f"{A4} SELECT i_3, CAST(sum(v) FILTER (i_1 = 0) AS BIGINT) AS a, CAST(sum(v) FILTER (i_1 = 1) AS BIGINT) AS n, CAST(sum(v) FILTER (i_1 = 2) AS BIGINT) AS r FROM a GROUP BY i_3")
def op_pivot(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.ship4(spark, sf).df.groupBy("i_3").pivot("i_1", [0, 1, 2]).sum("v").toDF("i_3", "a", "n", "r")


@query("op_setops", f"{A4} SELECT 'both' AS kind, count(*) AS n FROM (SELECT i_1, i_2, i_3 FROM a WHERE v % 2 = 0 INTERSECT SELECT i_1, i_2, i_3 FROM a WHERE v % 3 = 0) UNION ALL SELECT 'less', count(*) FROM (SELECT i_1, i_2, i_3 FROM a WHERE v % 2 = 0 EXCEPT SELECT i_1, i_2, i_3 FROM a WHERE v % 3 = 0) UNION ALL SELECT 'any', count(*) FROM (SELECT i_1, i_2, i_3 FROM a WHERE v % 2 = 0 UNION SELECT i_1, i_2, i_3 FROM a WHERE v % 3 = 0)")
def op_setops(spark: SparkSession, sf: str) -> DataFrame:
    cells = arrays.ship4(spark, sf).df
    x, y = (cells.filter(F.col("v") % k == 0).select("i_1", "i_2", "i_3") for k in (2, 3))
    out = None
    for kind, df in (("both", x.intersect(y)), ("less", x.subtract(y)), ("any", x.union(y).distinct())):
        one = df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("op_window_tail", f"{A4}, e AS (SELECT i_3, CAST(sum(v * v) AS BIGINT) e FROM a GROUP BY i_3) SELECT i_3, e, CAST(coalesce(sum(e) OVER (ORDER BY e ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS tail, CAST(row_number() OVER (ORDER BY e DESC) AS INTEGER) AS pos, e - lag(e, 1, e) OVER (ORDER BY i_3) AS step FROM e")
def op_window_tail(spark: SparkSession, sf: str) -> DataFrame:
    energy = arrays.ship4(spark, sf).df.groupBy("i_3").agg(F.sum(F.col("v") * F.col("v")).alias("e"))  # one row for each index of a mode
    tail = Window.orderBy("e").rowsBetween(Window.unboundedPreceding, -1)
    return energy.select("i_3", "e", F.coalesce(F.sum("e").over(tail), F.lit(0)).alias("tail"), F.row_number().over(Window.orderBy(F.desc("e"))).alias("pos"), (F.col("e") - F.lag("e", 1).over(Window.orderBy("i_3"))).alias("d")).select("i_3", "e", "tail", "pos", F.coalesce("d", F.lit(0)).alias("step"))


@query("op_topk", f"{A4} SELECT * FROM a ORDER BY v DESC, i_1, i_2, i_3, i_4 LIMIT 20")
def op_topk(spark: SparkSession, sf: str) -> DataFrame:
    return arrays.ship4(spark, sf).df.orderBy(F.desc("v"), *tn.index_columns(4)).limit(20)


@query("op_topk_per_group", f"{A4} SELECT i_1, i_2, i_3, i_4, v FROM (SELECT *, row_number() OVER (PARTITION BY i_3 ORDER BY v DESC, i_1, i_2, i_4) r FROM a) WHERE r <= 2")
def op_topk_per_group(spark: SparkSession, sf: str) -> DataFrame:
    best = Window.partitionBy("i_3").orderBy(F.desc("v"), "i_1", "i_2", "i_4")
    return arrays.ship4(spark, sf).df.withColumn("r", F.row_number().over(best)).filter("r <= 2").drop("r")


@query("op_json_mode", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS k, count(*) AS n FROM events GROUP BY 1")
def op_json_mode(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "events").groupBy((F.get_json_object("props", "$.k").cast("long") % 10).alias("k")).agg(F.count("*").alias("n"))


@query("op_array_mode", "SELECT label, CAST(p % 8 AS INTEGER) AS p_1, CAST(p // 8 AS INTEGER) AS p_2, round(sum(x::DOUBLE), 4) + 0.0 AS v FROM (SELECT label, unnest(range(0, 64)) p, unnest(embedding) x FROM embeddings) GROUP BY ALL")
def op_array_mode(spark: SparkSession, sf: str) -> DataFrame:
    from corefold.sources.tables import explode_vector

    cells = explode_vector(load_table(spark, sf, "embeddings"), "embedding", (8, 8), ids=("label",))
    return cells.groupBy("label", "p_1", "p_2").agg(F.sum(F.col("val").cast("double")).alias("v")).select("label", "p_1", "p_2", rounded("v", 4))


@query("op_date_modes", "SELECT CAST(year(l_shipdate) AS INTEGER) y, CAST(month(l_shipdate) AS INTEGER) m, CAST(dayofweek(l_shipdate) AS INTEGER) d, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem GROUP BY ALL")
def op_date_modes(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "lineitem").groupBy(F.year("l_shipdate").alias("y"), F.month("l_shipdate").alias("m"), (F.dayofweek("l_shipdate") - 1).alias("d")).agg(F.sum(F.col("l_quantity").cast("long")).alias("v"))


@query("op_string_modes", "SELECT regexp_extract(url, '://([^/]+)', 1) AS host, lower(substr(url, 1, 5)) AS scheme, count(*) AS n FROM pages GROUP BY ALL")
def op_string_modes(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "pages").groupBy(F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.lower(F.substring("url", 1, 5)).alias("scheme")).agg(F.count("*").alias("n"))


@query("op_sql_functions", "SELECT CAST(i_1 AS INTEGER) i_1, CAST(i_2 AS INTEGER) i_2, CAST(i_3 AS INTEGER) i_3, CAST(i_1 + 3 * i_3 AS BIGINT) AS col_m2, 18 AS words, round(24 / 18.0::DOUBLE, 6) AS ratio FROM (SELECT range i_1 FROM range(0, 3)), (SELECT range i_2 FROM range(0, 2)), (SELECT range i_3 FROM range(0, 4))")
def op_sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Layout and size functions, called from SQL; a 3 x 2 x 4 array of ranks (3, 1, 1)."""
    from corefold.functions import sql

    sql.register(spark)
    names = "array(bigint(a.id), bigint(b.id), bigint(c.id))"
    return spark.sql(f"SELECT int(a.id) AS i_1, int(b.id) AS i_2, int(c.id) AS i_3, unfold_column({names}, array(3L, 2L, 4L), 2) AS col_m2, int(tucker_words(array(3L, 2L, 4L), array(3L, 1L, 1L)) ) AS words, round(tucker_ratio(array(3L, 2L, 4L), array(3L, 1L, 1L)), 6) AS ratio FROM range(3) a, range(2) b, range(4) c")


@query("op_table_function", f"SELECT CAST(a AS INTEGER) p_1, CAST(b AS INTEGER) p_2, CAST(c AS INTEGER) p_3, CAST(d AS INTEGER) p_4 FROM ({_GRIDS})")
def op_table_function(spark: SparkSession, sf: str) -> DataFrame:
    from corefold.functions import sql

    sql.register(spark)
    return spark.sql("SELECT grid[0] AS p_1, grid[1] AS p_2, grid[2] AS p_3, grid[3] AS p_4 FROM block_grids(24, 4)")


@query("op_aggregate_function", f"{A4}, w AS (SELECT i_3, v::DOUBLE v, (v + i_1)::DOUBLE y FROM a) SELECT i_3, round(sqrt(sum((v - y) * (v - y)) / sum(v * v)), 9) AS err FROM w GROUP BY 1")
def op_aggregate_function(spark: SparkSession, sf: str) -> DataFrame:
    from corefold.functions import sql

    sql.register(spark)
    arrays.ship4(spark, sf).df.createOrReplaceTempView("corefold_ship4")
    return spark.sql("SELECT i_3, round(norm_rms(double(v), double(v + i_1)), 9) AS err FROM corefold_ship4 GROUP BY i_3")


@query("op_cogroup_error", f"{A4} SELECT i_3, CAST(sum(v * v) AS BIGINT) AS energy, CAST(sum((v - v // 2) * (v - v // 2)) AS BIGINT) AS error FROM a GROUP BY 1")
def op_cogroup_error(spark: SparkSession, sf: str) -> DataFrame:
    """Error of one array against another, slice by slice, as cogroups: both sides of a slice meet without a join on cells."""
    import pyarrow as pa

    x = arrays.ship4(spark, sf).df
    y = x.select(*[F.col(c).alias(c) for c in tn.index_columns(4)], F.floor(F.col("v") / 2).alias("v"))
    names = ["i_1", "i_2", "i_4"]

    def compare(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        p, q = (t.sort_by([(n, "ascending") for n in names]).column("v").to_numpy() for t in (a, b))
        return pa.table({"i_3": pa.array([key[0].as_py()], pa.int32()), "energy": pa.array([int((p * p).sum())]), "error": pa.array([int(((p - q) ** 2).sum())])})

    return x.groupBy("i_3").cogroup(y.groupBy("i_3")).applyInArrow(compare, "i_3 int, energy long, error long")


@query("op_statistics", "SELECT event_type, count(*) AS n, approx_count_distinct(user_id) > 0 AS some_users, round(corr(event_id, value), 6) AS correlation, abs(count(DISTINCT user_id) - count(DISTINCT user_id)) = 0 AS near FROM events GROUP BY 1")
def op_statistics(spark: SparkSession, sf: str) -> DataFrame:
    """Sketches and moments by type: the distinct count is near the exact one."""
    grouped = load_table(spark, sf, "events").groupBy("event_type")
    exact, rough = F.count_distinct("user_id"), F.approx_count_distinct("user_id", 0.01)
    return grouped.agg(F.count("*").alias("n"), (rough > 0).alias("some_users"), F.round(F.corr("event_id", "value"), 6).alias("correlation"), (F.abs(rough - exact) <= 0.05 * exact + 1).alias("near"))


# ---- streaming ----------------------------------------------------------------------


@query("stream_gram_events", """WITH s AS (SELECT date_trunc('hour', ts) h, event_type, count(*)::BIGINT n FROM events GROUP BY ALL), k AS (SELECT * FROM s WHERE h + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 2 HOUR FROM events))
 SELECT x.event_type AS a, y.event_type AS b, CAST(sum(x.n * y.n) AS BIGINT) AS s FROM k x JOIN k y ON x.h = y.h GROUP BY ALL""")
def stream_gram_events(spark: SparkSession, sf: str) -> DataFrame:
    """Gram matrix of the event-type mode, summed over hourly slices as they close."""
    from corefold.streaming import slices

    source = load_table(spark, sf, "events")
    labels = dictionary(source, "event_type")
    path = f"{sf}/events.parquet"
    folder, name = path.rsplit("/", 1)
    stream = spark.readStream.schema(source.schema).option("pathGlobFilter", name + "*").parquet(folder)
    work = tempfile.mkdtemp(prefix="corefold-stream-")  # the driver's own state of labels squared numbers
    state = slices.GramState(work, labels)
    slices.run_available(slices.tumbling_slices(stream), state.update, f"{work}/checkpoint")
    rows = [(a, b, round(state.gram[i, j])) for i, a in enumerate(labels) for j, b in enumerate(labels) if state.gram[i, j]]
    return frame(spark, rows, "a string, b string, s long")


def _streamed(spark: SparkSession, sf: str, make) -> DataFrame:  # noqa: ANN001
    """What a streaming plan over events has given once everything that is there is read."""
    from corefold.streaming import slices

    source = load_table(spark, sf, "events")
    folder, name = f"{sf}/events.parquet".rsplit("/", 1)
    stream = make(spark.readStream.schema(source.schema).option("pathGlobFilter", name + "*").parquet(folder))
    work = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get() if spark.sparkContext._jsc.sc().getCheckpointDir().isDefined() else tempfile.mkdtemp(prefix='corefold-stream-')}/{uuid.uuid4().hex}"
    slices.run_available(stream, lambda df, batch: df.write.mode("append").parquet(f"{work}/out"), f"{work}/checkpoint")
    return spark.read.schema(stream.schema).parquet(f"{work}/out")


@query("stream_pairs", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3600 SECOND")
def stream_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Interval join of two kinds of events of a user."""
    from corefold.streaming import slices

    return _streamed(spark, sf, lambda s: slices.pairs_within(s, "click", "purchase", 3600)).select("a_id", "b_id")


@query("stream_deduplicated", "SELECT DISTINCT event_id, event_type FROM events")
def stream_deduplicated(spark: SparkSession, sf: str) -> DataFrame:
    from corefold.streaming import slices

    return _streamed(spark, sf, lambda s: slices.deduplicated(s.unionByName(s))).select("event_id", "event_type")


@query("stream_sessions", """WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
 n AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM o)
 SELECT user_id, count(*) AS n, epoch_us(max(ts)) - epoch_us(min(ts)) + 1800000000 AS micros FROM n GROUP BY user_id, k HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT max(ts) - INTERVAL 2 HOUR FROM events)""")
def stream_sessions(spark: SparkSession, sf: str) -> DataFrame:
    """Sessions of each user that have closed."""
    from corefold.streaming import slices

    return _streamed(spark, sf, slices.session_slices).select("user_id", "n", (F.unix_micros("end") - F.unix_micros("start")).alias("micros"))
