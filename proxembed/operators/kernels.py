"""Pair updates in numpy: in sample order, or whole mini-batches."""

from __future__ import annotations

import numpy as np


def step_scalar(dot: np.ndarray | float, sign: np.ndarray | float, lr: float, neg_weight: float) -> np.ndarray | float:
    """Towards each other for positives, apart for negatives."""
    s = 1 / (1 + np.exp(-np.clip(dot, -30, 30)))
    return np.where(np.asarray(sign) > 0, lr * (1 - s), -lr * neg_weight * s)


def apply_pair(u: np.ndarray, c: np.ndarray, g: float, lr: float, decay: float) -> tuple[np.ndarray, np.ndarray]:
    """New vertex vector, and the change of the context, which is taken from the old vertex vector."""
    return u + g * c - lr * decay * u, g * u - lr * decay * c


def waves(first: np.ndarray, second: np.ndarray | None = None) -> np.ndarray:
    """For each item in order, one more than the latest wave of an earlier item that shares its row (of either table).

    Items of a wave touch no row twice, and an item's wave follows those that it must wait for.
    """
    seen: dict[int, int] = {}
    out = np.empty(len(first), dtype=np.int64)
    if second is None:
        for k, a in enumerate(first.tolist()):
            out[k] = seen[a] = seen.get(a, -1) + 1
        return out
    other: dict[int, int] = {}
    for k, (a, b) in enumerate(zip(first.tolist(), second.tolist(), strict=True)):
        x, y = seen.get(a, -1), other.get(b, -1)
        out[k] = seen[a] = other[b] = (x if x > y else y) + 1
    return out


def run_exact(U: np.ndarray, C: np.ndarray, iu: np.ndarray, ic: np.ndarray, sign: np.ndarray, lr: float, neg_weight: float, decay: float, frozen: np.ndarray | None = None) -> None:
    """Pairs one after another; with `frozen`, contexts are read from C and their changes summed there instead.

    Pairs that share no row don't see each other, so they are taken in waves: the rows end as in sample order.
    """
    wave = waves(iu, ic if frozen is None else None)
    order = np.argsort(wave, kind="stable")
    fade = np.asarray(lr * decay, U.dtype)
    for part in np.split(order, np.flatnonzero(np.diff(wave[order])) + 1) if len(order) else []:
        a, b = iu[part], ic[part]
        u, c = U[a], C[b]
        g = step_scalar(np.einsum("ij,ij->i", u, c), sign[part], lr, neg_weight)[:, None].astype(U.dtype)
        U[a] = u + g * c - fade * u
        if frozen is None:
            C[b] = c + (g * u - fade * c)
        else:
            np.add.at(frozen, b, g * u - fade * c)


def run_mini(U: np.ndarray, C: np.ndarray, iu: np.ndarray, ic: np.ndarray, sign: np.ndarray, lr: float, neg_weight: float, decay: float, frozen: np.ndarray | None = None, size: int = 0) -> None:
    """All pairs of a slice read the slice's first values; changes are summed."""
    size = size or max(1, len(iu))
    for k in range(0, len(iu), size):
        a, b = iu[k : k + size], ic[k : k + size]
        u, c = U[a], C[b]
        g = step_scalar(np.einsum("ij,ij->i", u, c), sign[k : k + size], lr, neg_weight)[:, None].astype(U.dtype)
        np.add.at(U, a, g * c - np.asarray(lr * decay, U.dtype) * u)
        np.add.at(C if frozen is None else frozen, b, g * u - np.asarray(lr * decay, U.dtype) * c)
