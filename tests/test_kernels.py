"""Kernels, layout and spectra against plain NumPy."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from corefold.functions import spectrum as sp
from corefold.functions import tensor as tn
from corefold.functions.tensor import Cells, TensorSpec
from corefold.operators import block_kernels as bk
from corefold.operators import sql_kernels as sk
from corefold.sources import storage, synthetic


def unfolded(x, mode):
    return np.moveaxis(x, mode, 0).reshape(x.shape[mode], -1, order="F")


@given(st.lists(st.integers(1, 4), min_size=1, max_size=5).map(tuple))
@settings(max_examples=50, deadline=None)
def test_unfold_columns_are_a_bijection(dims):
    for mode in range(len(dims)):
        weights = tn.unfold_weights(dims, mode)
        seen = {(i[mode], sum(a * w for a, w in zip(i, weights, strict=True))) for i in np.ndindex(*dims)}
        assert len(seen) == np.prod(dims)
        assert max(c for _, c in seen) == np.prod(dims) // dims[mode] - 1


def test_unfolding_of_the_small_cube_does_not_collide():
    weights = tn.unfold_weights((2, 2, 2), 0)
    assert sorted(sum(a * w for a, w in zip((0, *i), weights, strict=True)) for i in np.ndindex(2, 2)) == [0, 1, 2, 3]


@pytest.mark.parametrize(("dims", "block"), [((5, 7, 3), (2, 3, 2)), ((4, 6, 4), (2, 2, 2)), ((6,), (4,)), ((3, 4), (3, 2)), ((2, 3, 2, 3, 2), (1, 2, 2, 2, 1)), ((1, 5, 1), (1, 2, 1))])
def test_products_and_grams_on_any_grid(spark, dims, block):
    x = np.random.default_rng(1).standard_normal(dims)
    chunks = bk.from_array(spark, x, block)
    assert np.allclose(bk.to_array(chunks), x)
    assert np.isclose(bk.norm_sq(chunks), (x**2).sum())
    for mode in range(len(dims)):
        v = np.random.default_rng(2).standard_normal((3, dims[mode]))
        want = np.moveaxis(np.tensordot(v, x, (1, mode)), 0, mode)
        for reduce in ("single", "blocked"):
            assert np.allclose(bk.to_array(bk.ttm(chunks, v, mode, reduce=reduce, out_block=2)), want)
        assert np.allclose(bk.to_array(bk.ttm(chunks, v.T, mode, transpose=True)), want)
        g = unfolded(x, mode) @ unfolded(x, mode).T
        assert np.allclose(bk.gram(chunks, mode), g)
        assert np.allclose(bk.gram(chunks, mode, "exchange", symmetric=False), g)
        r = bk.tsqr(chunks, mode)
        assert np.allclose(r.T @ r, g)


def test_local_gram_of_a_split_mode_is_refused(spark):
    chunks = bk.from_array(spark, np.ones((4, 4)), (2, 4))
    with pytest.raises(ValueError, match="split"):
        bk.gram(chunks, 0, impl="local")


def test_unsplit_products_shuffle_nothing(spark):
    chunks = bk.from_array(spark, np.ones((4, 4, 4)), (4, 2, 2))
    plan = bk.ttm(chunks, np.ones((2, 4)), 0).df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    plan = bk.ttm(chunks, np.ones((2, 4)), 1).df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" in plan


def test_cells_and_chunks_round_trip_with_holes(spark):
    df = spark.createDataFrame([(0, 0, 1.0), (4, 2, 2.0)], "i_1 int, i_2 int, v double")
    chunks = bk.to_chunks(Cells(df, TensorSpec((5, 3))), (2, 2))
    x = bk.to_array(chunks)
    assert x.shape == (5, 3) and x[4, 2] == 2 and x.sum() == 3 and chunks.df.count() == 6
    back = {(r.i_1, r.i_2): r.v for r in bk.to_cells(chunks).df.collect()}
    assert len(back) == 15 and back[4, 2] == 2
    assert np.array_equal(bk.to_array(bk.regrid(chunks, (5, 1))), x)
    names = tn.index_columns(2)
    row, col = tn.unfold_index(chunks.spec, 1)
    flat = bk.to_cells(chunks).df.select(row.alias("row"), col.alias("col"), "v")
    again = {tuple(r[n] for n in names): r.v for r in flat.select(*tn.fold_index(chunks.spec, 1), "v").collect()}
    assert again == back


def test_relational_kernels_are_exact(spark):
    x = np.random.default_rng(3).integers(0, 9, (3, 4, 2))
    rows = [(*map(int, i), int(x[i])) for i in np.ndindex(*x.shape)]
    cells = Cells(spark.createDataFrame(rows, "i_1 int, i_2 int, i_3 int, v long"), TensorSpec(x.shape))
    for mode in range(3):
        g = unfolded(x, mode) @ unfolded(x, mode).T
        assert {(r.i, r.j): r.s for r in sk.gram(cells, mode).collect()} == {(i, j): int(g[i, j]) for i in range(len(g)) for j in range(len(g))}
        assert all(r.i <= r.j for r in sk.gram(cells, mode, symmetric=True).collect())


def test_rank_rule_and_signs():
    assert sp.rank_for_budget(np.array([4.0, 3.0, 2.0, 1.0]), 3.0) == 2  # equality keeps the smaller
    assert sp.rank_for_budget(np.zeros(3), 0.0) == 1
    assert sp.rank_for_budget(np.array([1.0, 1.0]), 99.0) == 1
    u, found = sp.leading_eigenvectors(np.array([[2.0, 1.0], [1.0, 2.0]]), rank=1)
    assert np.allclose(found.values, [3, 1]) and np.all(u > 0)
    assert sp.choose_spectral_method(1e-9, 10) == "tsqr" and sp.choose_spectral_method(1e-3, 10) == "gram"
    assert np.array_equal(sp.row_subset(np.eye(5), 2, 1), np.eye(5)[2:4])


def test_triangle_route_sees_tails_that_squaring_loses(spark):
    rng = np.random.default_rng(0)
    u, v = np.linalg.qr(rng.standard_normal((16, 16)))[0], np.linalg.qr(rng.standard_normal((256, 16)))[0]
    x = (u * 10.0 ** -np.arange(16)) @ v.T
    chunks = bk.from_array(spark, x, (16, 64))
    small = np.sqrt(sp.from_triangle(bk.tsqr(chunks, 0), 16).values)[10]
    squared = np.sqrt(sp.from_gram(bk.gram(chunks, 0)).values)[10]
    assert abs(small / 1e-10 - 1) < 1e-3 < abs(squared / 1e-10 - 1)


def test_files(spark, tmp_path):
    chunks = synthetic.synthetic(spark, (6, 5, 4), (2, 2, 2), (3, 5, 2), seed=4)
    x = bk.to_array(chunks)
    storage.write_chunks(chunks, str(tmp_path / "c"))
    assert np.array_equal(bk.to_array(storage.read_chunks(spark, str(tmp_path / "c"))), x)
    some = storage.slice_chunks(storage.read_chunks(spark, str(tmp_path / "c")), 0, 4, 5)
    assert {r.b_1 for r in some.df.collect()} == {1}
    assert "PushedFilters: [IsNotNull(b_1)" in some.df._jdf.queryExecution().executedPlan().toString()
    raw = tmp_path / "raw"
    raw.mkdir()
    for at in np.ndindex(2, 1):
        x[at[0] * 3 : at[0] * 3 + 3].astype("<f8").ravel(order="F").tofile(raw / f"{at[0]}_0_0.f64")
    assert np.array_equal(bk.to_array(storage.read_raw_blocks(spark, str(raw), TensorSpec((6, 5, 4), (3, 5, 4)))), x)
