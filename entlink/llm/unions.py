"""Union-find over positions of sorted arrays."""

from __future__ import annotations

import numpy as np


class Classes:
    """Union-find over the leaves of one sorted array, with vectorised reads."""

    def __init__(self, n: int):
        self.parent = np.arange(n)
        self.root = np.arange(n)
        self.changes = np.arange(n)

    def find(self, x: int) -> int:
        p = self.parent
        while p[x] != x:
            p[x] = p[p[x]]
            x = p[x]
        return int(x)

    def link(self, a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
        made = []
        for x, y in zip(a.tolist(), b.tolist()):
            rx, ry = self.find(x), self.find(y)
            if rx != ry:
                self.parent[max(rx, ry)] = min(rx, ry)
                made.append((x, y))
        if made:
            root = self.parent.copy()
            while not np.array_equal(root, root[root]):
                root = root[root]
            self.root = root
            self.changes = np.concatenate(([0], np.cumsum(root[1:] != root[:-1])))
        return made

    def one_class(self, alo, ahi, blo, bhi):
        """Whether all leaves of both ranges are in one class already."""
        flat = (self.changes[alo] == self.changes[ahi - 1]) & (self.changes[blo] == self.changes[bhi - 1])
        return flat & (self.root[alo] == self.root[blo])
