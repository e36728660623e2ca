"""Decompositions into a core and one orthonormal factor for each mode.

The driver loops over modes; each step is one aggregation (Gram matrix or triangle) and
one map (projection). Only mode-length matrices reach the driver.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import numpy as np

from corefold.functions import spectrum as sp
from corefold.functions.tensor import Chunks
from corefold.operators import block_kernels as bk
from corefold.plans.costmodel import gram_flops, ttm_flops


@dataclass(frozen=True)
class Step:
    sweep: int
    mode: int
    kernel: str
    flops: float
    seconds: float
    fit_sq: float | None = None


@dataclass
class TuckerModel:
    """core: chunks of the shrunk array; factors[n]: length x rank, orthonormal columns."""

    core: Chunks
    factors: list[np.ndarray]
    dims: tuple[int, ...]
    norm_sq: float
    core_norm_sq: float
    spectra: dict[int, np.ndarray] = field(default_factory=dict)
    discarded: dict[int, float] = field(default_factory=dict)
    trace: list[Step] = field(default_factory=list)
    reason: str = ""

    @property
    def ranks(self) -> tuple[int, ...]:
        return tuple(u.shape[1] for u in self.factors)

    @property
    def residual_sq(self) -> float:
        """Squared error by the difference of norms."""
        return max(self.norm_sq - self.core_norm_sq, 0.0)

    @property
    def norm_rms(self) -> float:
        """Relative error; by discarded energies where the difference of norms has no digits left."""
        if self.norm_sq == 0:
            return 0.0
        direct = self.residual_sq / self.norm_sq
        if direct < 1e-12 and self.discarded:
            direct = sum(self.discarded.values()) / self.norm_sq
        return float(np.sqrt(direct))


def materialize(chunks: Chunks, instead_of: Chunks | None = None) -> Chunks:
    """Cut lineage after a step: a checkpoint in the shared folder where the session has one, else cached blocks.

    instead_of: an earlier step that is needed no more.
    """
    made = _kept(chunks)
    if instead_of is not None:
        instead_of.df.unpersist()
    return made


def _kept(chunks: Chunks) -> Chunks:
    df = chunks.df
    if df.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        return replace(chunks, df=df.checkpoint())
    kept = df.persist()
    kept.count()
    return replace(chunks, df=kept)


def _spectrum(chunks: Chunks, mode: int, method: str, **options: object) -> sp.Spectrum:
    if method == "gram":
        return sp.from_gram(bk.gram(chunks, mode, **options))
    if method == "tsqr":
        return sp.from_triangle(bk.tsqr(chunks, mode), chunks.spec.dims[mode])
    if method == "svd":
        array = bk.to_array(chunks)
        return sp.from_unfolding(np.moveaxis(array, mode, 0).reshape(array.shape[mode], -1, order="F"))
    raise ValueError(f"no spectral method {method!r}")


def leading_left_vectors(chunks: Chunks, mode: int, rank: int | None = None, method: str = "gram") -> tuple[np.ndarray, sp.Spectrum]:
    found = _spectrum(chunks, mode, method)
    return found.vectors[:, : rank or len(found.values)], found


def n_rank(chunks: Chunks, mode: int, tol: float = 1e-12) -> int:
    return sp.numerical_rank(_spectrum(chunks, mode, "gram").values, tol)


def _check(chunks: Chunks, ranks: tuple[int, ...] | None, eps: float | None) -> None:
    if ranks is None and eps is None:
        raise ValueError("give ranks or eps")
    if ranks is not None and len(ranks) != chunks.spec.order:
        raise ValueError("one rank for each mode")


def _pick(found: sp.Spectrum, mode: int, ranks: tuple[int, ...] | None, budget_sq: float, most: int) -> int:
    wanted = ranks[mode] if ranks is not None else sp.rank_for_budget(found.values, budget_sq)
    return max(1, min(wanted, most, len(found.values)))


def st_hosvd(chunks: Chunks, eps: float | None = None, ranks: tuple[int, ...] | None = None, order: tuple[int, ...] | None = None, spectral: str = "auto", checkpoint: bool = True) -> TuckerModel:
    """Mode by mode: spectrum of the array as it is by now, rank, projection. The last array is the core."""
    _check(chunks, ranks, eps)
    spec = chunks.spec
    order = tuple(range(spec.order)) if order is None else tuple(order)
    if sorted(order) != list(range(spec.order)):
        raise ValueError("order must name each mode once")
    total = bk.norm_sq(chunks)
    budget = (eps or 0.0) ** 2 * total / spec.order
    method = sp.choose_spectral_method(eps, max(spec.dims), bk.GRAM_LIMIT) if spectral == "auto" else spectral
    factors: list[np.ndarray] = [np.zeros((0, 0))] * spec.order
    trace, spectra, lost, now = [], {}, {}, chunks
    for mode in order:
        at = time.monotonic()
        found = _spectrum(now, mode, method)
        trace.append(Step(0, mode, "gram", gram_flops(now.spec.dims, mode), time.monotonic() - at))
        r = _pick(found, mode, ranks, budget, now.spec.co_size(mode))
        factors[mode], spectra[mode], lost[mode] = found.vectors[:, :r], found.values, float(found.tails[r])
        at = time.monotonic()
        flops = ttm_flops(now.spec.dims, mode, r)
        before, now = now, bk.ttm(now, factors[mode], mode, transpose=True)
        if checkpoint:
            now = materialize(now, before if before is not chunks else None)
        trace.append(Step(0, mode, "ttm", flops, time.monotonic() - at))
    return TuckerModel(now, factors, spec.dims, total, bk.norm_sq(now), spectra, lost, trace)


def t_hosvd(chunks: Chunks, eps: float | None = None, ranks: tuple[int, ...] | None = None, spectral: str = "auto") -> TuckerModel:
    """All spectra from the original array (by Gram matrices those of unsplit modes in one scan), then one chain of products."""
    _check(chunks, ranks, eps)
    spec = chunks.spec
    total = bk.norm_sq(chunks)
    budget = (eps or 0.0) ** 2 * total / spec.order
    method = sp.choose_spectral_method(eps, max(spec.dims), bk.GRAM_LIMIT) if spectral == "auto" else spectral
    found = {m: sp.from_gram(s) for m, s in bk.grams(chunks).items()} if method == "gram" else {m: _spectrum(chunks, m, method) for m in range(spec.order)}
    picked = {m: _pick(f, m, ranks, budget, spec.co_size(m)) for m, f in found.items()}
    factors = [found[m].vectors[:, : picked[m]] for m in range(spec.order)]
    core = materialize(bk.ttm_chain(chunks, dict(enumerate(factors)), transpose=True))
    return TuckerModel(core, factors, spec.dims, total, bk.norm_sq(core), {m: f.values for m, f in found.items()}, {m: float(f.tails[picked[m]]) for m, f in found.items()})


def core_for(chunks: Chunks, factors: list[np.ndarray]) -> Chunks:
    """The best core for given orthonormal factors."""
    return bk.ttm_chain(chunks, dict(enumerate(factors)), transpose=True)


def hooi(chunks: Chunks, eps: float | None = None, ranks: tuple[int, ...] | None = None, init: str | list[np.ndarray] = "st_hosvd", max_sweeps: int = 10, tol: float = 1e-8, target: float | None = None, inner_order: str = "greedy", spectral: str = "auto", update_order: tuple[int, ...] | None = None) -> TuckerModel:
    """Alternating refinement at fixed ranks; the residual never rises.

    update_order: in which order a sweep renews the factors; it does not change a sweep's work.

    Stops at `target` (relative error), when a sweep gains less than `tol` of the
    energy, or after `max_sweeps`. The core is one product more on the last array.
    """
    spec = chunks.spec
    modes = tuple(range(spec.order)) if update_order is None else tuple(update_order)
    if sorted(modes) != list(range(spec.order)):
        raise ValueError("update_order must name each mode once")
    method = sp.choose_spectral_method(eps, max(spec.dims), bk.GRAM_LIMIT) if spectral == "auto" else spectral
    if isinstance(init, str):
        start = {"st_hosvd": st_hosvd, "t_hosvd": t_hosvd}[init](chunks, eps=eps, ranks=ranks, spectral=spectral)
        factors, total, trace = list(start.factors), start.norm_sq, list(start.trace)
        before = start.residual_sq
        core, core_sq, spectra = start.core, start.core_norm_sq, start.spectra
    else:
        factors, total, trace, spectra = list(init), bk.norm_sq(chunks), [], {}
        core = materialize(core_for(chunks, factors))
        core_sq = bk.norm_sq(core)
        before = max(total - core_sq, 0.0)
    picked = [u.shape[1] for u in factors]
    trace.append(Step(0, -1, "fit", 0.0, 0.0, before))
    reason = "max_sweeps"
    held: Chunks | None = None
    for sweep in range(1, max_sweeps + 1):
        for mode in modes:
            others = [m for m in range(spec.order) if m != mode]
            if inner_order == "greedy":
                others.sort(key=lambda m: -(spec.dims[m] / picked[m]))
            at, flops, now, dims = time.monotonic(), 0.0, chunks, list(spec.dims)
            for m in others:
                flops += ttm_flops(tuple(dims), m, picked[m])
                dims[m] = picked[m]
                now = bk.ttm(now, factors[m], m, transpose=True)
            held = now = materialize(now, held)
            trace.append(Step(sweep, mode, "ttm", flops, time.monotonic() - at))
            at = time.monotonic()
            found = _spectrum(now, mode, method)
            factors[mode], spectra[mode] = found.vectors[:, : picked[mode]], found.values
            trace.append(Step(sweep, mode, "gram", gram_flops(now.spec.dims, mode), time.monotonic() - at))
        core = materialize(bk.ttm(now, factors[modes[-1]], modes[-1], transpose=True))
        core_sq = bk.norm_sq(core)
        after = max(total - core_sq, 0.0)
        trace.append(Step(sweep, -1, "fit", 0.0, 0.0, after))
        gain, before = before - after, after
        if total and target is not None and np.sqrt(after / total) <= target:
            reason = "target"
            break
        if gain < tol * total:
            reason = "tol"
            break
    return TuckerModel(core, factors, spec.dims, total, core_sq, spectra, {}, trace, reason)


def preview_ranks(chunks: Chunks, eps: float) -> tuple[int, ...]:
    """Upper bounds of the ranks for a tolerance, from one scan."""
    total = bk.norm_sq(chunks)
    budget = eps**2 * total / chunks.spec.order
    return tuple(sp.rank_for_budget(sp.from_gram(s).values, budget) for _, s in sorted(bk.grams(chunks).items()))
