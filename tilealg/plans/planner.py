"""Choice of grid and placement from the operands' shapes and counts of cells."""

from __future__ import annotations

import math
from dataclasses import dataclass

from tilealg.operators.cells import Cells
from tilealg.operators.grid import TileGrid


@dataclass(frozen=True)
class ProductPlan:
    grid: TileGrid
    placement: str
    cost: float


def preset(kind: str, a: int, b: int, c: int, workers: int) -> TileGrid:
    """Grids for the products of the learners: the short edge of factors stays whole, long inner edges are cut."""
    wide = 2 * workers
    cuts = {"tall": (1, wide, 1), "left_tall": (wide, 1, 1), "kernel": (max(2, workers // 2), 1, max(2, workers // 2)), "plain": (workers, 1, 1)}
    m, n, k = cuts[kind]
    return TileGrid.of(a, b, c, m, n, k)


def plan_product(a: Cells, b: Cells, workers: int, tile_bytes: int = 256 << 20, weights: tuple[float, float, float] = (1.0, 0.2, 1.0), placements: tuple[str, ...] = ("row", "tile", "random")) -> ProductPlan:
    """Least cost over powers of two of m, n, k.

    Cells count as many as their bound, where the operand carries one.  Cost: copies moved, scalar products by busy places, and partial cells (moved again under random placement).
    Grids that leave workers idle cost more by it; those whose product tile passes ``tile_bytes`` are left out.  Powers
    go up to twice the workers, or to what ``tile_bytes`` asks for, so that some grid is always left.
    """
    na, nb = a.bound(), b.bound()
    da, db = na / max(1, a.rows * a.cols), nb / max(1, b.rows * b.cols)
    flops = na * nb / max(1, a.cols)
    filled = 1 - (1 - min(1.0, da * db)) ** a.cols
    best = None
    needed = math.ceil(math.sqrt(8 * a.rows * b.cols / tile_bytes)) if a.rows and b.cols else 1
    powers = [1 << e for e in range(0, max(2, workers, needed).bit_length() + 1)]
    for m in powers:
        for n in (1, 2, 4):
            for k in powers:
                grid = TileGrid.of(a.rows, a.cols, b.cols, m, n, k)
                if (grid.m, grid.n, grid.k) != (m, n, k) or 8 * (a.rows / m) * (b.cols / k) > tile_bytes:
                    continue
                for placement in placements:
                    slots = {"row": m, "tile": m * k, "random": m * n * k}[placement]
                    part = filled * a.rows * b.cols * min(n, max(1.0, flops / max(1.0, filled * a.rows * b.cols)))
                    cost = weights[0] * (k * na + m * nb) + weights[1] * flops / min(slots, workers) * workers / 4 + weights[2] * (part if placement == "random" else 0)
                    if best is None or cost < best.cost:
                        best = ProductPlan(grid, placement, cost)
    if best is None:
        # Edges so short that no power of two fits them: a stripe for each row and column.
        return ProductPlan(TileGrid.of(a.rows, a.cols, b.cols, max(1, a.rows), 1, max(1, b.cols)), placements[0], float(k_cost(a, b, na, nb)))
    return best


def k_cost(a: Cells, b: Cells, na: int, nb: int) -> int:
    """Copies of the finest grid."""
    return b.cols * na + a.rows * nb
