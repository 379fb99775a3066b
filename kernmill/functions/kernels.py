"""Kernels: one definition as a Spark column, a numpy block and DuckDB text."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class KernelSpec:
    """A kernel value as a function of the inner product b and both squared norms."""

    name: str = "polynomial"
    gamma: float = 1.0
    coef0: float = 1.0
    degree: int = 2
    columns: Callable | None = None
    blocks: Callable | None = None

    @property
    def psd(self) -> bool:
        """Whether the kernel is surely positive semi-definite, so that the objective cannot rise."""
        return self.name in ("linear", "rbf", "cosine") or self.name == "polynomial" and self.coef0 >= 0 and self.gamma >= 0

    def column(self, b: Column, ni: Column, nj: Column) -> Column:
        if self.columns is not None:
            return self.columns(b, ni, nj)
        y = self.gamma * b + self.coef0
        if self.name == "linear":
            return b
        if self.name == "polynomial":
            return y * y if self.degree == 2 else F.pow(y, F.lit(self.degree))
        if self.name == "rbf":
            return F.exp(-self.gamma * (ni + nj - 2 * b))
        if self.name == "sigmoid":
            return F.tanh(y)
        if self.name == "cosine":
            return F.when((ni > 0) & (nj > 0), b / F.sqrt(ni * nj)).otherwise(F.lit(0.0))
        raise ValueError(f"no such kernel: {self.name}")

    def block(self, b: np.ndarray, ni: np.ndarray, nj: np.ndarray) -> np.ndarray:
        """Values of a block of inner products with rows' and columns' squared norms."""
        if self.blocks is not None:
            return self.blocks(b, ni, nj)
        if self.name == "linear":
            return b
        if self.name == "polynomial":
            y = self.gamma * b + self.coef0
            return y * y if self.degree == 2 else y**self.degree
        if self.name == "rbf":
            return np.exp(-self.gamma * (ni[:, None] + nj[None, :] - 2 * b))
        if self.name == "sigmoid":
            return np.tanh(self.gamma * b + self.coef0)
        if self.name == "cosine":
            norm = np.sqrt(ni[:, None] * nj[None, :])
            return np.divide(b, norm, out=np.zeros_like(b), where=norm > 0)
        raise ValueError(f"no such kernel: {self.name}")

    def sql(self, b: str, ni: str = "ni", nj: str = "nj") -> str:
        """The same as SQL text over names of b and the norms."""
        y = f"({self.gamma!r} * {b} + {self.coef0!r})"
        return {
            "linear": b,
            "polynomial": f"{y} * {y}" if self.degree == 2 else f"pow({y}, {self.degree})",
            "rbf": f"exp(-{self.gamma!r} * ({ni} + {nj} - 2 * {b}))",
            "sigmoid": f"tanh({y})",
            "cosine": f"CASE WHEN {ni} > 0 AND {nj} > 0 THEN {b} / sqrt({ni} * {nj}) ELSE 0.0 END",
        }[self.name]


def linear() -> KernelSpec:
    return KernelSpec("linear")


def polynomial(gamma: float = 1.0, coef0: float = 1.0, degree: int = 2) -> KernelSpec:
    return KernelSpec("polynomial", gamma, coef0, degree)


def rbf(gamma: float = 1.0) -> KernelSpec:
    return KernelSpec("rbf", gamma)


def sigmoid(gamma: float = 1.0, coef0: float = 0.0) -> KernelSpec:
    return KernelSpec("sigmoid", gamma, coef0)


def cosine() -> KernelSpec:
    return KernelSpec("cosine")


def custom(columns: Callable, blocks: Callable) -> KernelSpec:
    """A user's kernel: f(b, ni, nj) for columns and for numpy blocks."""
    return KernelSpec("custom", columns=columns, blocks=blocks)


def dot(x: Column, y: Column) -> Column:
    """Inner product of two array columns."""
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v)
