"""Parameter searches by safeguarded bisection: the measures aren't monotone in the parameter."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

#: Releases that are measured at the same time: one has stages of few tasks.
AT_ONCE = 6
#: Steps of a bisection whose possible midpoints are measured together.
LEVELS = 3


def beside(f: Callable, some: Iterable) -> list:
    """f of each, several at a time; results in order."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(f, some))


def grid_of(low: float, high: float, grid: int) -> list[float]:
    return [low + (high - low) * i / grid for i in range(grid + 1)]


def search(measure: Callable[[float], float], feasible: Callable[[float], bool], low: float, high: float, larger: bool = True, steps: int = 8, grid: int = 0, prefer: Callable[[float, float], float] | None = None, ahead: Callable[[list[float]], object] | None = None) -> tuple[float, float] | None:
    """The best feasible parameter seen and its measure. larger: whether larger parameters are wanted (and make the measure less often feasible).

    prefer: a rank of (parameter, measure), least first, in place of the extreme parameter. Bisects as if the measure were monotone, remembers the best feasible probe, and scans a grid if asked to or if none was feasible.
    The points of a grid that is asked for are sure to be measured, so they are measured first, several at a time. ahead: makes the measures of several
    parameters ready at once; it gets the grid, and all midpoints that the next LEVELS steps of a bisection can meet."""
    best: tuple[float, float] | None = None
    seen: dict[float, float] = {}

    def probe(x: float) -> bool:
        nonlocal best
        if x not in seen:
            seen[x] = measure(x)
        ok = feasible(seen[x])
        if ok and (best is None or (prefer(x, seen[x]) < prefer(*best) if prefer else (x > best[0]) == larger)):
            best = (x, seen[x])
        return ok

    if grid:
        points = grid_of(low, high, grid)
        if ahead:
            ahead(points)
        seen.update(zip(points, beside(measure, points), strict=True))
    a, b = low, high
    for step in range(steps):
        if ahead and step % LEVELS == 0:
            spans, met = [(a, b)], []
            for _ in range(min(LEVELS, steps - step)):
                met += [(x + y) / 2 for x, y in spans]
                spans = [half for x, y in spans for half in ((x, (x + y) / 2), ((x + y) / 2, y))]
            ahead(met)
        mid = (a + b) / 2
        if probe(mid) == larger:
            a = mid
        else:
            b = mid
    if grid or best is None:
        for x in grid_of(low, high, grid or 8):
            probe(x)
    return best
