"""Division of the dimensions into subspaces and halves."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass


@dataclass(frozen=True)
class SubspacePlan:
    """Disjoint dimension lists that cover 0..d-1. All but the last hold d // n_sub dimensions; the last takes the rest."""

    d: int
    dims: tuple[tuple[int, ...], ...]
    kind: str = "contiguous"
    seed: int | None = None

    def __post_init__(self):
        flat = [i for part in self.dims for i in part]
        if sorted(flat) != list(range(self.d)):
            raise ValueError("a plan covers every dimension once")
        if any(not part for part in self.dims):
            raise ValueError("a subspace has at least one dimension")

    @property
    def n_sub(self) -> int:
        return len(self.dims)

    def parts(self, m: int = 2) -> list[tuple[int, ...]]:
        """m parts of each subspace, in order: part p of subspace s is number m * s + p. The first parts take the odd dimensions."""
        out = []
        for dims in self.dims:
            if len(dims) < m:
                raise ValueError(f"a subspace of {len(dims)} dimensions has no {m} parts")
            at = 0
            for p in range(m):
                size = len(dims) // m + (p < len(dims) % m)
                out.append(dims[at : at + size])
                at += size
        return out

    def halves(self) -> list[tuple[int, ...]]:
        return self.parts(2)


def _divide(order: list[int], n_sub: int, kind: str, seed: int | None) -> SubspacePlan:
    d = len(order)
    if not 1 <= n_sub <= d:
        raise ValueError("between one subspace and one per dimension")
    size = d // n_sub
    cuts = [order[i * size : (i + 1) * size] for i in range(n_sub - 1)] + [order[(n_sub - 1) * size :]]
    return SubspacePlan(d, tuple(tuple(c) for c in cuts), kind, seed)


def plan_contiguous(d: int, n_sub: int) -> SubspacePlan:
    return _divide(list(range(d)), n_sub, "contiguous", None)


def plan_random(d: int, n_sub: int, seed: int = 0) -> SubspacePlan:
    """Rounds of sampling without replacement: dimensions in the order of a keyed digest, which SQL can repeat."""
    order = sorted(range(d), key=lambda i: hashlib.md5(f"{seed}:{i}".encode()).hexdigest())
    return _divide(order, n_sub, "random", seed)


def single_subspace(d: int, s: int, seed: int = 0) -> tuple[int, ...]:
    """One random subspace of s dimensions."""
    if not 1 <= s <= d:
        raise ValueError("between one dimension and all")
    return tuple(sorted(range(d), key=lambda i: hashlib.md5(f"{seed}:{i}".encode()).hexdigest())[:s])
