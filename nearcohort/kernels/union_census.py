"""Disjoint sets that carry keyword counts and sizes."""

from __future__ import annotations


class UnionCensus:
    """Union by size with path halving; each root knows its members' keyword counts."""

    def __init__(self, hold, n_keywords: int, weight=None):
        self.hold, self.k, self.weight = hold, n_keywords, weight
        self.up: dict[int, int] = {}
        self.size: dict[int, int] = {}
        self.count: dict[int, list[int]] = {}
        self.total: dict[int, float] = {}

    def add(self, v: int) -> None:
        if v not in self.up:
            self.up[v], self.size[v] = v, 1
            c = [0] * self.k
            for i in self.hold[v]:
                c[i] += 1
            self.count[v] = c
            self.total[v] = self.weight[v] if self.weight is not None else 0.0

    def find(self, v: int) -> int:
        up = self.up
        while up[v] != v:
            up[v] = v = up[up[v]]
        return v

    def union(self, a: int, b: int) -> int | None:
        """Root of the united set, None if they were one set already."""
        self.add(a)
        self.add(b)
        a, b = self.find(a), self.find(b)
        if a == b:
            return None
        if self.size[a] < self.size[b]:
            a, b = b, a
        self.up[b] = a
        self.size[a] += self.size.pop(b)
        self.total[a] += self.total.pop(b)
        mine = self.count[a]
        for i, x in enumerate(self.count.pop(b)):
            mine[i] += x
        return a

    def roots(self) -> list[int]:
        return list(self.size)
