"""Choice of an engine from sizes, kernel and budgets."""

from __future__ import annotations

from dataclasses import dataclass

from ..functions.kernels import KernelSpec


@dataclass(frozen=True)
class Plan:
    engine: str
    reason: str
    exact: bool = True


def lift_dim(d: int) -> int:
    return (d + 1) * (d + 2) // 2


def choose(n: int, d: int, k: int, workers: int, kernel: KernelSpec, storage_bytes: float = 1e14, flops_budget: float = 1e18, sweeps: int = 100, symmetric: bool = True, allow_approx: bool = False) -> Plan:
    """linear -> lloyd; a small exact lift -> lift; K within storage -> mixed_15d; K within time -> fused; else landmark where approximation is allowed."""
    if kernel.name == "linear":
        return Plan("lloyd", "a linear kernel needs n * k * d work, not n * n")
    if kernel.name == "polynomial" and kernel.degree == 2 and kernel.gamma > 0 and kernel.coef0 >= 0 and lift_dim(d) * k * n < n * n:
        return Plan("lift", f"the kernel is an inner product of {lift_dim(d)} terms, cheaper than n * n values")
    need = 4.0 * n * n * (0.5 if symmetric else 1.0)
    if need <= storage_bytes:
        return Plan("mixed_15d", f"K takes {need:.3g} bytes, within {storage_bytes:.3g}")
    work = 2.0 * n * n * d * sweeps
    if work <= flops_budget * workers:
        return Plan("fused", f"K is too large to keep, but {work:.3g} operations recompute it in every sweep")
    if allow_approx:
        return Plan("landmark", f"K would take {need:.3g} bytes; landmarks approximate it", False)
    raise ValueError(f"exact clustering needs {need:.3g} bytes or {work:.3g} operations; allow_approx=True permits landmarks")


def explain(n: int, d: int, k: int, workers: int, kernel: KernelSpec, **budget) -> str:
    root = workers**0.5
    lines = [f"{name}: K words {kw:.4g}, sweep words {sw:.4g}" for name, kw, sw in (
        ("1d", workers * n * d, n), ("h1d", n * n / workers + n * d / root, n), ("2d", n * d / root, n * (k + 1) / root + n), ("1.5d", n * d / root, n * (k + 1) / root))]
    plan = choose(n, d, k, workers, kernel, **budget)
    return "\n".join([f"engine: {plan.engine} ({plan.reason})", *lines])
