"""The cost model: arithmetic, messages and words of a sweep on p processes in a square grid, and the trace of phases."""

from __future__ import annotations

import math
import time
from collections import defaultdict
from contextlib import contextmanager
from dataclasses import dataclass, field


@dataclass(frozen=True)
class CostModel:
    """alpha: seconds a message, beta: seconds a word, gamma: seconds an operation."""

    alpha: float = 1e-6
    beta: float = 1e-9
    gamma: float = 1e-9

    def total(self, operations: float, messages: float, words: float) -> float:
        return self.gamma * operations + self.alpha * messages + self.beta * words

    def spmspv(self, n: int, m: int, p: int, searches: int = 1) -> dict:
        """Bound of all products of one sweep: every edge once, frontiers gathered along a grid dimension and sent along the other."""
        words = m / p + n / math.sqrt(p)
        messages = searches * math.sqrt(p)
        return {"operations": m / p, "messages": messages, "words": words, "seconds": self.total(m / p, messages, words)}

    def sort(self, n: int, p: int, searches: int = 1) -> dict:
        """Bound of all ranks of one sweep; the frontiers of a sweep add up to n."""
        operations = n * math.log2(max(2, n)) / p
        return {"operations": operations, "messages": searches * p, "words": n / p, "seconds": self.total(operations, searches * p, n / p)}

    def ordering(self, n: int, m: int, p: int, searches: int) -> dict:
        """Root search (products only) and one ordering sweep (products and ranks)."""
        a, b = self.spmspv(n, m, p, searches + 1), self.sort(n, p, 1)
        return {k: a[k] + b[k] for k in a}


PHASES = ("root_product", "root_other", "order_product", "order_sort", "order_other")


@dataclass
class Trace:
    """Seconds of named phases; a phase ends with an action, so that lazy work is counted where it belongs."""

    phases: dict = field(default_factory=lambda: defaultdict(float))
    searches: int = 0

    @contextmanager
    def phase(self, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.phases[name] += time.perf_counter() - began

    @property
    def total(self) -> float:
        return sum(self.phases.values())


def speedups(seconds: dict[int, float]) -> dict[int, tuple[float, float]]:
    """cores: (speedup, efficiency) against the fewest cores measured."""
    base = min(seconds)
    return {p: (seconds[base] / s, seconds[base] / s * base / p) for p, s in sorted(seconds.items())}
