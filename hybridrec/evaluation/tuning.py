"""Grid search on validation accuracy."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor


def grid_search(score: Callable[[dict], float], grid: Iterable[dict], workers: int = 2) -> tuple[dict, list[tuple[dict, float]]]:
    """Best parameters, first among equals, and the whole curve. Points are independent jobs, so a few run at once."""
    points = list(grid)
    with ThreadPoolExecutor(workers) as pool:
        curve = list(zip(points, pool.map(score, points), strict=True))
    return max(curve, key=lambda x: x[1])[0], curve
