"""Decompositions, decoding, plans and costs."""

import numpy as np
import pytest

from corefold.functions import measures as ms
from corefold.functions import spectrum as sp
from corefold.functions.tensor import Cells, TensorSpec
from corefold.operators import block_kernels as bk
from corefold.operators import baselines, decode, prepare
from corefold.operators import decompose as dc
from corefold.plans import costmodel as cm
from corefold.plans import planner
from corefold.sources import arrays, datasource, storage, synthetic


@pytest.fixture(scope="module")
def ship(spark):
    chunks = dc.materialize(bk.to_chunks(arrays.ship4(spark, "/root/testdata/sf0.01"), (3, 2, 6, 7)))
    return chunks, bk.to_array(chunks)


#: Reference values on the shipping array at sf0.01 (FIXTURES.md).
@pytest.mark.parametrize(("ranks", "t", "bound", "st", "hooi"), [((1, 1, 1, 1), 0.103340, 0.179775, 0.103338, 0.103337), ((2, 1, 6, 4), 0.094897, 0.124481, 0.091232, 0.090385), ((3, 2, 7, 4), 0.071423, 0.077484, 0.069783, 0.068412)])
def test_reference_errors(ship, ranks, t, bound, st, hooi):
    chunks, x = ship
    one = dc.t_hosvd(chunks, ranks=ranks)
    assert abs(one.norm_rms - t) < 2e-6 and abs(ms.thosvd_bound(one.spectra, ranks, one.norm_sq) - bound) < 2e-6
    two = dc.st_hosvd(chunks, ranks=ranks)
    assert abs(two.norm_rms - st) < 2e-6 and ms.check_energy(two) < 1e-10
    three = dc.hooi(chunks, ranks=ranks, max_sweeps=1)
    assert abs(three.norm_rms - hooi) < 2e-6 and three.norm_rms <= two.norm_rms + 1e-9
    for model in (one, two, three):
        y = bk.to_array(decode.reconstruct(model))
        assert abs(np.linalg.norm(x - y) / np.linalg.norm(x) - model.norm_rms) < 1e-9


@pytest.mark.parametrize(("eps", "ranks", "error", "ratio"), [(0.3, (1, 1, 1, 1), 0.103338, 20.16), (0.1, (3, 2, 7, 4), 0.069783, 1.72), (0.05, (3, 2, 11, 7), 0.018631, 0.768), (0.01, (3, 2, 12, 7), 0.0, 0.710)])
def test_reference_tolerances(ship, eps, ranks, error, ratio):
    model = dc.st_hosvd(ship[0], eps=eps)
    assert model.ranks == ranks and abs(model.norm_rms - error) < 2e-6 and abs(ms.compression_ratio(model.dims, ranks) - ratio) < 5e-3
    assert model.norm_rms <= eps
    assert all(a <= b for a, b in zip(model.ranks, dc.preview_ranks(ship[0], eps), strict=True))


def test_orders_stops_and_inits(ship):
    chunks, _ = ship
    for order in ((3, 1, 0, 2), (2, 3, 1, 0)):
        assert dc.st_hosvd(chunks, eps=0.1, order=order).norm_rms <= 0.1
    model = dc.hooi(chunks, ranks=(2, 1, 6, 4), init="t_hosvd", max_sweeps=30, tol=1e-7)
    assert model.reason == "tol" and model.norm_rms < 0.090385  # another start may end in a better optimum
    trace = ms.fit_trace(model)
    assert all(b <= a + 1e-12 * model.norm_sq for a, b in zip(trace, trace[1:], strict=False))
    assert dc.hooi(chunks, ranks=(3, 2, 12, 7), target=0.5).reason == "target"
    with pytest.raises(ValueError, match="ranks or eps"):
        dc.st_hosvd(chunks)


def test_relational_decomposition_agrees(spark, ship):
    cells = arrays.ship4(spark, "/root/testdata/sf0.01")
    for options in ({"ranks": (2, 1, 6, 4)}, {"eps": 0.1, "order": (3, 1, 0, 2)}):
        want = dc.st_hosvd(ship[0], **options)
        core, factors, error = baselines.relational_st_hosvd(cells, **options)
        assert abs(error - want.norm_rms) < 1e-7 and core.spec.dims == want.ranks
        assert all(np.allclose(u @ u.T, w @ w.T, atol=1e-7) for u, w in zip(factors, want.factors, strict=True))
    with pytest.raises(ValueError, match="ranks or eps"):
        baselines.relational_st_hosvd(cells)


def test_update_order_leaves_the_work_of_a_sweep_unchanged(ship):
    work, errors = [], []
    for order in (None, (3, 1, 0, 2), (2, 3, 1, 0)):
        model = dc.hooi(ship[0], ranks=(2, 1, 6, 4), max_sweeps=1, tol=0.0, update_order=order)
        work.append(sum(s.flops for s in model.trace if s.sweep == 1))
        errors.append(model.norm_rms)
        y = bk.to_array(decode.reconstruct(model))
        assert abs(np.linalg.norm(ship[1] - y) / np.linalg.norm(ship[1]) - model.norm_rms) < 1e-9
    assert max(work) == pytest.approx(min(work)) and max(errors) <= 0.091232 + 2e-6
    with pytest.raises(ValueError, match="each mode once"):
        dc.hooi(ship[0], ranks=(2, 1, 6, 4), update_order=(0, 0, 1, 2))


def test_known_rank_is_recovered_in_any_number_of_modes(spark):
    for dims, ranks in (((9,), (1,)), ((8, 6), (2, 2)), ((6, 5, 4), (2, 3, 2)), ((4, 3, 4, 3, 2), (2, 1, 2, 2, 1))):
        chunks = synthetic.synthetic(spark, dims, ranks, tuple(max(1, d // 2) for d in dims), seed=len(dims))
        model = dc.st_hosvd(chunks, eps=1e-6)
        assert model.ranks == ranks and model.norm_rms < 1e-7


def test_degenerate_arrays(spark):
    zero = dc.st_hosvd(bk.from_array(spark, np.zeros((3, 4))), eps=0.1)
    assert zero.ranks == (1, 1) and zero.norm_rms == 0.0
    capped = dc.st_hosvd(bk.from_array(spark, np.random.default_rng(0).random((9, 2))), ranks=(9, 2))
    assert capped.ranks == (2, 2)


def test_parts_are_slices_of_the_whole(ship, spark, tmp_path):
    chunks, _ = ship
    model = dc.st_hosvd(chunks, ranks=(2, 2, 5, 4))
    whole = bk.to_array(decode.reconstruct(model))
    part = bk.to_array(decode.reconstruct(model, {0: 1, 2: slice(0, 12, 3), 3: [0, 6]}, block=(1, 1, 3, 2)))
    assert np.allclose(part, whole[1:2, :, 0:12:3][..., [0, 6]])
    pooled = bk.to_array(decode.reconstruct(model, weights={2: np.ones((1, 12))}))
    assert np.allclose(pooled, whole.sum(axis=2, keepdims=True))
    storage.save_model(model, str(tmp_path / "m"))
    again = storage.load_model(spark, str(tmp_path / "m"))
    assert again.ranks == model.ranks and np.allclose(bk.to_array(decode.reconstruct(again)), whole)
    datasource.register(spark)
    rows = spark.read.format("corefold").option("path", str(tmp_path / "m")).load().filter("i_1 = 2 AND i_3 >= 10").collect()
    assert len(rows) == 2 * 2 * 7 and all(np.isclose(r.v, whole[r.i_1, r.i_2, r.i_3, r.i_4]) for r in rows)


def test_standardising(spark):
    rng = np.random.default_rng(5)
    x = rng.random((4, 5, 3)) + np.arange(3)
    x[:, :, 2] = 7.0
    rows = [(*map(int, i), float(x[i])) for i in np.ndindex(*x.shape)]
    cells = Cells(spark.createDataFrame(rows, "i_1 int, i_2 int, i_3 int, v double"), TensorSpec(x.shape))
    done, stats = prepare.standardize(cells, 2)
    y = bk.to_array(bk.to_chunks(done))
    assert np.allclose(y.mean(axis=(0, 1)), 0) and np.allclose(y.std(axis=(0, 1)), [1, 1, 0])
    assert [r.scaled for r in stats.orderBy("var").collect()] == [True, True, False]
    assert np.allclose(bk.to_array(bk.to_chunks(prepare.unstandardize(done, stats, 2))), x)
    once = prepare.gram_standardized(bk.to_chunks(Cells(cells.df.filter("i_3 < 2"), TensorSpec((4, 5, 2)))), 0, 2)
    assert np.allclose(once, bk.gram(bk.to_chunks(Cells(done.df.filter("i_3 < 2"), TensorSpec((4, 5, 2)))), 0))


def test_cost_model_numbers():
    dims, ranks = (200,) * 4, (20,) * 4
    c = cm.sthosvd_cost(dims, ranks, (1,) * 4)
    assert c["gram"].flops == 711_040_000_000 and c["ttm"].flops == 71_104_000_000
    assert cm.hooi_cost(dims, ranks, (1,) * 4)["ttm"].flops == 284_160_000_000 + 64_000_000 or abs(cm.hooi_cost(dims, ranks, (1,) * 4)["ttm"].flops - 284_160_000_000) <= 64_000_000
    assert cm.hooi_cost(dims, ranks, (1,) * 4, "printed")["ttm"].flops == 213_312_000_000
    words = {g: ((c := cm.sthosvd_cost((384,) * 4, (96,) * 4, g))["gram"].words + c["ttm"].words) / 1e6 for g in ((1, 1, 4, 6), (1, 2, 3, 4), (2, 2, 2, 3), (6, 4, 1, 1))}
    assert [round(w, 1) for w in words.values()] == [542.1, 860.5, 2739.6, 11721.6]
    assert cm.gram_ttm_ratio((384,) * 4, (96,) * 4, 0) == 4
    assert [round(ms.compression_ratio(d, r), 2) for d, r in (((672, 672, 33, 627), (297, 279, 29, 153)), ((460, 700, 360, 35, 16), (306, 232, 239, 35, 16)), ((500, 500, 500, 11, 50), (81, 129, 127, 7, 32)))] == [25.38, 6.83, 231.15]


def test_planner():
    dims, ranks = (25, 250, 250, 250), (10, 10, 100, 100)
    flops = {"".join(str(m + 1) for m in o): planner.order_cost(dims, ranks, o).flops / 1e9 for o in planner.distinct_orders(dims, ranks)}
    assert len(flops) == 12 and round(flops["1234"], 2) == 114.72 and round(flops["2134"], 2) == 210.34 and round(flops["3421"], 2) == 415.49
    assert planner.plan_mode_order(dims, ranks, "greedy_flops")[0] == 0
    assert planner.plan_mode_order(dims, ranks, "greedy_ratio")[0] == 1
    assert planner.plan_mode_order(dims, ranks, "exhaustive") == (0, 1, 2, 3)
    assert planner.plan_mode_order(dims, ranks, "exhaustive", (2,) * 4, planner.Weights(0.0, 1.0))[0] == 1
    assert len(planner.enumerate_grids(24, 4)) == len(set(planner.enumerate_grids(24, 4))) == 80
    assert planner.choose_grid((384,) * 4, (96,) * 4, 24)[0][0] == 1
    plan = planner.plan_decomposition(TensorSpec((40, 30, 20)), (4, 3, 2), 8)
    assert sorted(plan.order) == [0, 1, 2] and np.prod(plan.spec.grid) == 8


def test_spectrum_is_that_of_the_library(spark):
    """Squared singular values of an unfolding by the library's own decomposition of its rows."""
    from pyspark.mllib.linalg.distributed import RowMatrix

    x = np.random.default_rng(5).standard_normal((5, 4, 6))
    found = sp.from_gram(bk.gram(bk.from_array(spark, x, (5, 2, 3)), 0)).values
    rows = np.moveaxis(x, 0, 2).reshape(-1, 5)
    sigma = RowMatrix(spark.sparkContext.parallelize(rows.tolist(), 2)).computeSVD(5).s.toArray()
    assert np.allclose(found, sigma**2)


def test_working_memory_is_about_three_times_the_data():
    for dims, ranks, grid in (((200,) * 4, (20,) * 4, (1, 2, 3, 4)), ((384,) * 4, (96,) * 4, (1, 1, 4, 6))):
        share = cm.peak_memory(dims, ranks, grid) * np.prod(grid) / np.prod(dims)
        assert 2 <= share < 3


def test_guard_of_the_gram_route():
    assert sp.choose_spectral_method(1e-3, 500) == "gram" and sp.choose_spectral_method(1e-9, 500) == "tsqr"
    with pytest.warns(UserWarning):
        assert sp.choose_spectral_method(1e-3, 3000) == "gram"
    with pytest.warns(UserWarning):
        assert sp.choose_spectral_method(None, 9000) == "tsqr"
