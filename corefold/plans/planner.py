"""Order of modes, blocks and spectral method, chosen before anything runs."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import permutations

from corefold.functions.spectrum import choose_spectral_method
from corefold.functions.tensor import TensorSpec
from corefold.plans.costmodel import Cost, gram_flops, hooi_cost, peak_memory, sthosvd_cost, total, ttm_flops

#: Modes up to which every order is tried.
EXHAUSTIVE = 6


@dataclass(frozen=True)
class Weights:
    """What a flop and a word count when costs are compared."""

    flops: float = 1.0
    words: float = 0.0


def order_cost(dims: tuple[int, ...], ranks: tuple[int, ...], order: tuple[int, ...], grid: tuple[int, ...] | None = None) -> Cost:
    """Gram matrices and products; eigenvectors do not depend on the order."""
    shares = sthosvd_cost(dims, ranks, grid or (1,) * len(dims), order)
    return shares["gram"] + shares["ttm"]


def distinct_orders(dims: tuple[int, ...], ranks: tuple[int, ...]) -> list[tuple[int, ...]]:
    """Orders that differ in more than the names of alike modes: these keep their natural order."""
    out, seen = [], set()
    for order in permutations(range(len(dims))):
        kind = tuple((dims[m], ranks[m]) for m in order)
        if kind not in seen:
            seen.add(kind)
            out.append(order)
    return out


def plan_mode_order(dims: tuple[int, ...], ranks: tuple[int, ...], policy: str = "natural", grid: tuple[int, ...] | None = None, weights: Weights = Weights()) -> tuple[int, ...]:  # noqa: B008
    """'natural'; 'greedy_flops' (least work now); 'greedy_ratio' (most shrinkage first); 'exhaustive'."""
    n = len(dims)
    if policy == "natural":
        return tuple(range(n))
    if policy == "greedy_ratio":
        return tuple(sorted(range(n), key=lambda m: (-dims[m] / ranks[m], m)))
    if policy == "greedy_flops":
        now, left, order = list(dims), set(range(n)), []
        while left:
            best = min(left, key=lambda m: (gram_flops(tuple(now), m) + ttm_flops(tuple(now), m, ranks[m]), m))
            order.append(best)
            left.remove(best)
            now[best] = ranks[best]
        return tuple(order)
    if policy == "exhaustive":
        if n > EXHAUSTIVE:
            raise ValueError(f"{n} modes have too many orders")
        price = lambda o: (c := order_cost(dims, ranks, o, grid)).flops * weights.flops + c.words * weights.words
        return min(distinct_orders(dims, ranks), key=lambda o: (price(o), o))
    raise ValueError(f"no policy {policy!r}")


def enumerate_grids(p: int, n: int) -> list[tuple[int, ...]]:
    """All ways to write p as a product of n factors, in order."""
    if n == 1:
        return [(p,)]
    return [(d, *rest) for d in range(1, p + 1) if p % d == 0 for rest in enumerate_grids(p // d, n - 1)]


def choose_grid(dims: tuple[int, ...], ranks: tuple[int, ...], p: int, order: tuple[int, ...] | None = None, sweeps: int = 0, candidates: int = 4) -> list[tuple[int, ...]]:
    """The grids that move fewest words (one-pass decomposition and sweeps), best first; ties by memory.

    The first processed mode comes out unsplit, as its Gram matrix dominates.
    """
    fits = [g for g in enumerate_grids(p, len(dims)) if all(b <= r for b, r in zip(g, ranks, strict=True))] or enumerate_grids(p, len(dims))

    def words(grid: tuple[int, ...]) -> float:
        once = total(sthosvd_cost(dims, ranks, grid, order)).words
        return once + sweeps * total(hooi_cost(dims, ranks, grid)).words

    return sorted(fits, key=lambda g: (words(g), peak_memory(dims, ranks, g), g))[:candidates]


@dataclass(frozen=True)
class DecompPlan:
    order: tuple[int, ...]
    spec: TensorSpec
    spectral: str
    cost: Cost


def plan_decomposition(spec: TensorSpec, ranks: tuple[int, ...], parallelism: int, eps: float | None = None, policy: str = "exhaustive") -> DecompPlan:
    order = plan_mode_order(spec.dims, ranks, policy if spec.order <= EXHAUSTIVE else "greedy_flops")
    grid = choose_grid(spec.dims, ranks, parallelism, order)[0]
    return DecompPlan(order, spec.on_grid(grid), choose_spectral_method(eps, max(spec.dims)), order_cost(spec.dims, ranks, order, grid))
