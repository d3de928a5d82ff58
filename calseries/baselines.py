"""An in-memory array engine: one float array per series on a shared index, as scripts keep them.

A baseline for times and a reference for tests; it holds whole series on one machine and is no path of the engine."""

from __future__ import annotations

from array import array
from collections.abc import Callable


class ArrayEngine:
    """Dense series as float arrays of one length; ``generic`` calls a function for every window, the others are written
    for their operator."""

    def __init__(self, series: dict[str, list[float]]):
        self.series = {k: array("d", v) for k, v in series.items()}

    def generic(self, name: str, w: int, fn: Callable[[array], float]) -> array:
        x = self.series[name]
        return array("d", (fn(x[max(0, t + 1 - w) : t + 1]) for t in range(len(x))))

    def mavg(self, name: str, w: int) -> array:
        """One addition and one subtraction an entry."""
        x, out, total = self.series[name], array("d"), 0.0
        for t, v in enumerate(x):
            total += v - (x[t - w] if t >= w else 0.0)
            out.append(total / min(t + 1, w))
        return out

    def rsi(self, name: str, w: int) -> array:
        """From the second entry on; NaN where nothing changed."""
        x, out = self.series[name], array("d")
        steps = [b - a for a, b in zip(x, x[1:], strict=False)]
        for t in range(len(steps)):
            window = steps[max(0, t + 1 - w) : t + 1]
            gain, loss = sum(d for d in window if d > 0), -sum(d for d in window if d < 0)
            out.append(100 * gain / (gain + loss) if gain + loss else float("nan"))
        return out

    def xavg(self, name: str, w: int) -> array:
        x, q, out = self.series[name], 1 - 2.0 / (w + 1), array("d")
        weights = [q**k for k in range(w)]
        for t in range(len(x)):
            n = min(t + 1, w)
            out.append(sum(weights[k] * x[t - k] for k in range(n)) / sum(weights[:n]))
        return out

    def macd(self, name: str, short: int, long: int) -> array:
        return array("d", (a - b for a, b in zip(self.xavg(name, short), self.xavg(name, long), strict=True)))
