"""Sums of kernel values by label, of rows against columns, where K is not kept: from moments if the kernel has them, else from values made a strip at a time."""

from __future__ import annotations

import numpy as np

from ..functions.kernels import KernelSpec
from ..plans.layout import StoreSpec
from .gram import STRIP_BYTES, product

#: Moments of all clusters may take this many bytes in a task.
MOMENT_BYTES = 1 << 28
#: Columns of a symmetric matrix that are met at once.
HALF = 128


def has_moments(kernel: KernelSpec) -> bool:
    """Whether sums of kernel values follow from counts, sums and outer products of the rows: (gamma <x, y> + coef0) ** 2 and <x, y>."""
    return kernel.blocks is None and (kernel.name == "linear" or kernel.name == "polynomial" and kernel.degree == 2)


def fits(kernel: KernelSpec, k: int, dim: int) -> bool:
    return has_moments(kernel) and (kernel.name == "linear" or k * dim * dim * 8 <= MOMENT_BYTES)


class Moments:
    """Count, sum and sum of outer products of each label's rows: exact, at k * d * d work a column whatever the number of rows."""

    def __init__(self, k: int, dim: int, kernel: KernelSpec):
        self.kernel = kernel
        self.n, self.first = np.zeros(k), np.zeros((k, dim))
        self.second = None if kernel.name == "linear" else np.zeros((k, dim, dim))

    def add(self, x: np.ndarray, labels: np.ndarray) -> None:
        order = np.argsort(labels, kind="stable")
        starts = np.flatnonzero(np.diff(labels[order], prepend=-1))
        for lo, hi in zip(starts, [*starts[1:], len(order)]):
            cl, rows = labels[order[lo]], x[order[lo:hi]]
            self.n[cl] += hi - lo
            self.first[cl] += rows.sum(axis=0)
            if self.second is not None:
                self.second[cl] += rows.T @ rows

    def sums(self, y: np.ndarray) -> np.ndarray:
        """k x len(y): sums of each label's values with the rows of ``y``."""
        single = self.first @ y.T
        if self.second is None:
            return single
        gamma, c = self.kernel.gamma, self.kernel.coef0
        double = np.stack([forms(y, m) for m in self.second])
        return gamma * gamma * double + 2 * gamma * c * single + c * c * self.n[:, None]


def forms(y: np.ndarray, m: np.ndarray) -> np.ndarray:
    """y m y of every row of ``y``; of a wide symmetric ``m`` only the lower half is read."""
    dim = len(m)
    if dim < 4 * HALF:
        return np.einsum("ij,ij->i", y @ m, y)
    out = np.zeros(len(y))
    for lo in range(0, dim, HALF):
        own, hi = y[:, lo : lo + HALF], lo + HALF
        near = own @ m[lo:hi, lo:hi]
        if hi < dim:
            near += 2 * (y[:, hi:] @ m[hi:, lo:hi])
        out += np.einsum("ij,ij->i", near, own)
    return out


class Strips:
    """The same for any kernel: rows stay, values are made and summed a strip at a time."""

    def __init__(self, k: int, kernel: KernelSpec, store: StoreSpec, how: str):
        self.k, self.kernel, self.store, self.how = k, kernel, store, how
        self.rows: list[tuple] = []

    def add(self, x: np.ndarray, labels: np.ndarray) -> None:
        self.rows.append((x, labels))

    def sums(self, y: np.ndarray) -> np.ndarray:
        from .engines import label_sums

        out = np.zeros((self.k, len(y)))
        step = max(1, STRIP_BYTES // (8 * len(y)))
        for x, labels in self.rows:
            for lo in range(0, len(x), step):
                out += label_sums(product(x[lo : lo + step], y, self.kernel, self.store), labels[lo : lo + step], self.k, self.how, self.store.summed)
        return out


def summer(k: int, dim: int, kernel: KernelSpec, store: StoreSpec, how: str):
    return Moments(k, dim, kernel) if fits(kernel, k, dim) else Strips(k, kernel, store, how)
