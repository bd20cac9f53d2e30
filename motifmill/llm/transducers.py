"""Small weighted finite-state transducers over the reals: composition and sums over paths.

An arc reads a symbol, writes a symbol and multiplies the path's weight; the weight that a
machine gives to a sequence is the sum over its accepting paths.  Machines are kept dense,
one matrix for each (symbol read, symbol written), so that composition is a Kronecker
product cut down to the states that can be reached and can accept.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np


class Transducer:
    """arcs: (from, read, written, to, weight); states are numbers, 0 is the start."""

    def __init__(self, size: int, arcs: Iterable[tuple[int, str, str, int, float]], final: dict[int, float]):
        self.size = size
        self.arcs: dict[tuple[str, str], np.ndarray] = {}
        for a, read, written, b, weight in arcs:
            self.arcs.setdefault((read, written), np.zeros((size, size)))[a, b] += weight
        self.final = np.zeros(size)
        for state, weight in final.items():
            self.final[state] = weight

    def then(self, other: Transducer) -> Transducer:
        """This machine, and other on what it writes."""
        out = Transducer(self.size * other.size, (), {})
        for (read, middle), x in self.arcs.items():
            for (taken, written), y in other.arcs.items():
                if middle == taken:
                    both = np.kron(x, y)
                    out.arcs[read, written] = out.arcs.get((read, written), 0) + both
        out.final = np.kron(self.final, other.final)
        return out.trimmed()

    def trimmed(self) -> Transducer:
        links = sum(m != 0 for m in self.arcs.values())

        def closure(start: np.ndarray, step: np.ndarray) -> np.ndarray:
            known = start
            while True:
                more = known | (known @ step > 0)
                if (more == known).all():
                    return known
                known = more

        begin = np.arange(self.size) == 0
        keep = np.flatnonzero((closure(begin, links) & closure(self.final != 0, links.T)) | begin)
        out = Transducer(len(keep), (), {})
        out.arcs = {k: m[np.ix_(keep, keep)] for k, m in self.arcs.items()}
        out.final = self.final[keep]
        return out

    def reading(self, symbol: str) -> np.ndarray:
        """Weights of one step that reads symbol, whatever it writes."""
        return sum((m for (read, _), m in self.arcs.items() if read == symbol), np.zeros((self.size, self.size)))

    def weight(self, symbols: Iterable[str]) -> float:
        """Sum over the accepting paths that read these symbols."""
        state = (np.arange(self.size) == 0).astype(float)
        for s in symbols:
            state = state @ self.reading(s)
        return float(state @ self.final)
