"""Exact integer caps and size rules."""

from __future__ import annotations

from decimal import ROUND_FLOOR, Decimal


def _floor(x: Decimal) -> int:
    return int(x.to_integral_value(ROUND_FLOOR))


def block_cap(total: int, k: int, eps: float, heaviest: int = 0, rule: str = "ceil", extra: float = 0.0) -> int:
    """Largest allowed block weight. ``ceil``: (1 + eps) * ceil(total / k), the form
    for unit weights; ``atomic``: (1 + eps) * total / k + heaviest node."""
    factor = 1 + Decimal(str(eps)) + Decimal(str(extra))
    if rule == "atomic":
        return _floor(factor * total / k) + heaviest
    if rule != "ceil":
        raise ValueError(f"unknown rule {rule!r}")
    return _floor(factor * -(-total // k))


def level_cap(level: int, levels: int, total: int, k: int, eps: float, delta: float, cycle: int = 1) -> int:
    """Cap of a level, 1 the finest: in the first cycle coarse levels get an extra
    ``delta / (levels - level + 1)``."""
    extra = Decimal(str(delta)) / (levels - level + 1) if cycle == 1 and level > 1 else Decimal(0)
    return _floor((1 + Decimal(str(eps)) + extra) * -(-total // k))


def cluster_cap(cap: int, heaviest: int, f: int = 18) -> int:
    """Bound on a cluster's weight while coarsening."""
    return max(heaviest, cap // f)


def stop_nodes(n: int, k: int) -> int:
    """Coarsening goes on while a level has at least this many nodes."""
    return max(60 * k, n // (60 * k))


def ensemble_size(k: int) -> int:
    """Clusterings to overlay for k blocks."""
    return 18 if k < 16 else 7 if k <= 32 else 3
