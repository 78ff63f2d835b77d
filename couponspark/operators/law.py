"""Any law of coupons: classes of cells, each with a number of cells and a mass per cell, all masses summing to one."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class CouponLaw:
    cells: tuple[int, ...]
    mass: tuple[float, ...]

    def __post_init__(self) -> None:
        total = float(np.dot(self.cells, self.mass))
        if abs(total - 1) > 1e-9 or min(self.mass) <= 0:
            raise ValueError(f"masses sum to {total}, not to 1")

    @staticmethod
    def bitmap(k: int) -> CouponLaw:
        return CouponLaw((k,), (1 / k,))

    @staticmethod
    def matrix(k: int, columns: int) -> CouponLaw:
        return CouponLaw((k,) * columns, tuple(2.0 ** -min(j, columns - 1) / k for j in range(1, columns + 1)))

    def expected(self, m: float) -> float:
        return float(-np.dot(self.cells, np.expm1(m * np.log1p(-np.minimum(np.array(self.mass), 1 - 1e-16)))))

    def count_inverse(self, collected: float) -> float:
        """The count whose expected number of coupons is ``collected``; infinite if all are."""
        if collected <= 0:
            return 0.0
        if collected >= sum(self.cells):
            return float("inf")
        lo, hi = 0.0, 1.0
        while self.expected(2.0**hi) < collected:
            hi *= 2
        for _ in range(80):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if self.expected(2.0**mid) < collected else (lo, mid)
        return 2.0 ** ((lo + hi) / 2)

    def code_length(self, collected: tuple[int, ...]) -> float:
        """The count with the shortest ideal code of a state with these numbers of coupons in each class."""
        s, n, l = np.array(collected, float), np.array(self.cells, float), np.log1p(-np.minimum(np.array(self.mass), 1 - 1e-16))
        if not s.any():
            return 0.0
        lo, hi = 0.0, 120.0
        for _ in range(80):
            mid = (lo + hi) / 2
            with np.errstate(over="ignore", divide="ignore", invalid="ignore"):
                full = np.where(s > 0, s / np.expm1(-(2.0**mid) * l), 0.0)
            lo, hi = (mid, hi) if (l * (n - s - full)).sum() > 0 else (lo, mid)
        return 2.0 ** ((lo + hi) / 2)

    def history(self, classes: list[int]) -> float:
        """Sum of one over the mass not collected, along the classes of the novelties in order."""
        rest, total = 1.0, 0.0
        for c in classes:
            total += 1 / rest
            rest -= self.mass[c]
        return total
