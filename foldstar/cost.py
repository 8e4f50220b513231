"""Counts of scalar multiplications and additions, joined (M) and factored (F), and their limits."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Dims:
    """n_e x d_e entity; attribute blocks (n_i, d_i); pair counts of links for stars (optional)."""

    n_e: int
    d_e: int
    blocks: tuple[tuple[int, int], ...]

    @property
    def d(self) -> int:
        return self.d_e + sum(w for _, w in self.blocks)

    @property
    def parts(self) -> int:
        return self.n_e * self.d_e + sum(n * w for n, w in self.blocks)

    @property
    def tuple_ratio(self) -> float:
        return self.n_e / max(n for n, _ in self.blocks)

    @property
    def feature_ratio(self) -> float:
        return sum(w for _, w in self.blocks) / self.d_e if self.d_e else float("inf")


def ops(op: str, dims: Dims, mode: str, m: int = 1, include_lower: bool = False) -> float:
    """op: scalar, aggregate, lmm, rmm, gram, ginv; mode: M or F."""
    n, d, whole, parts = dims.n_e, dims.d, dims.n_e * dims.d, dims.parts
    if op in ("scalar", "aggregate"):
        return whole if mode == "M" else parts
    if op in ("lmm", "rmm"):
        return m * (whole if mode == "M" else parts)
    if op == "gram":
        if mode == "M":
            return d * d * n / 2
        cost = dims.d_e**2 * n / 2 + sum(w * w * k / 2 + dims.d_e * w * k for k, w in dims.blocks)
        for i, (k1, w1) in enumerate(dims.blocks):
            for k2, w2 in dims.blocks[i + 1 :]:
                cost += n * min(w1, w2) + (k2 if w1 <= w2 else k1) * w1 * w2
        return cost + (n * dims.d_e if include_lower else 0)
    if op == "ginv":
        if n > d:
            return 7 * n * d * d + 20 * d**3 if mode == "M" else 27 * d**3 + ops("gram", dims, "F") + d * parts
        if mode == "M":
            return 7 * n * n * d + 20 * n**3
        return 27 * n**3 + n * n * dims.d_e / 2 + sum(k * k * w / 2 for k, w in dims.blocks) + n * parts
    raise ValueError(op)


def algorithm(name: str, dims: Dims, mode: str, iters: int = 20, k: int = 10) -> float:
    """Iterative algorithms: scoring and folding each round, and work on n rows that nothing factors."""
    if name in ("logistic", "linreg_gd"):
        return iters * 2 * ops("lmm", dims, mode)
    if name == "linreg_normal":
        return ops("gram", dims, mode) + ops("rmm", dims, mode) + dims.d**3
    if name == "linreg_cofactor":
        return ops("gram", dims, mode) + ops("rmm", dims, mode) + iters * dims.d**2
    if name == "kmeans":
        return iters * (2 * ops("lmm", dims, mode, k) + dims.n_e * k)
    if name == "gnmf":
        return iters * (2 * ops("lmm", dims, mode, k) + 2 * dims.n_e * k * k)
    raise ValueError(name)


def speedup(op: str, dims: Dims, m: int = 1) -> float:
    return ops(op, dims, "M", m) / ops(op, dims, "F", m)


def limit(op: str, tuple_ratio: float, feature_ratio: float, of: str) -> float:
    """Limit of the speed-up as the tuple ratio ("TR") or the feature ratio ("FR") grows, one attribute table."""
    if op in ("scalar", "aggregate", "lmm", "rmm"):
        return 1 + feature_ratio if of == "TR" else tuple_ratio
    if op == "gram":
        return (1 + feature_ratio) ** 2 if of == "TR" else tuple_ratio
    if op == "ginv":
        if of == "TR":
            return 14 * (1 + feature_ratio) ** 2 / (2 * feature_ratio + 3)
        return 14 * tuple_ratio**2 / (1 + 2 * tuple_ratio)
    raise ValueError(op)


def invertible_possible(tuple_ratio: float, feature_ratio: float) -> bool:
    """A square T can only be invertible if the tuple ratio is at most 1 / feature ratio + 1."""
    return tuple_ratio <= ((1 / feature_ratio if feature_ratio else float("inf")) + 1) * (1 + 1e-12)
