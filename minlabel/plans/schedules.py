"""Which order each iteration takes."""

from __future__ import annotations

from collections.abc import Callable, Sequence

HIGH = 1024


def schedule(method: str, order: int = HIGH, warmup: int = 2, orders: Sequence[int] | Callable | None = None) -> Callable[[int], int]:
    """Iteration (from 1) -> order."""
    if method == "order1":
        return lambda k: 1
    if method in ("order2", "sync2"):
        return lambda k: 2
    if method == "orderm":
        if order < 3:
            raise ValueError("orderm takes an order of 3 or more")
        return lambda k: order
    if method == "low_then_high":
        return lambda k: 1 if k <= warmup else order
    if method == "alternate":
        return lambda k: 1 if k % 2 else order
    if method == "schedule":
        if orders is None:
            raise ValueError("a schedule needs orders")
        return orders if callable(orders) else lambda k: orders[min(k, len(orders)) - 1]
    raise ValueError(f"no schedule {method}")
