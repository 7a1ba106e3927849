"""A union-find over the rows of one bounded block."""

from __future__ import annotations

import numpy as np


class Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def link(self, pairs_a: np.ndarray, pairs_b: np.ndarray) -> None:
        for a, b in zip(pairs_a.tolist(), pairs_b.tolist()):
            ra, rb = self.find(a), self.find(b)
            if ra < rb:
                self.up[rb] = ra
            elif rb < ra:
                self.up[ra] = rb

    def roots(self) -> np.ndarray:
        return np.fromiter((self.find(i) for i in range(len(self.up))), dtype=np.int64, count=len(self.up))
