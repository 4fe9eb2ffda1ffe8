"""Trees as Euler tours in treaps: link, cut, connectivity and aggregates in O(log n)."""

from __future__ import annotations

import random


class _Node:
    __slots__ = ("up", "left", "right", "pri", "vertex", "arc", "mark", "size", "count", "total", "any")

    def __init__(self, pri, vertex=None, arc=None, count=None):
        self.up = self.left = self.right = None
        self.pri, self.vertex, self.arc = pri, vertex, arc
        self.mark = False  # a vertex with loose edges here, or an arc whose edge is at this level
        self.size = 1 if vertex is not None else 0
        self.count = count
        self.total = 0.0
        self.any = False


class EulerForest:
    """A forest over integer vertices; ``hold[v]`` lists the keywords of v, ``weight[v]`` its weight (both optional)."""

    def __init__(self, hold=None, n_keywords: int = 0, seed: int = 7, weight=None):
        self.hold, self.k, self.weight = hold, n_keywords if hold is not None else 0, weight
        self.vertex: dict[int, _Node] = {}
        self.arcs: dict[tuple[int, int], _Node] = {}
        self.rand = random.Random(seed).random

    # -- treap ------------------------------------------------------------------------
    def _own(self, n: _Node):
        if self.k and n.vertex is not None:
            c = [0] * self.k
            for i in self.hold[n.vertex]:
                c[i] += 1
            return c
        return None

    def _pull(self, n: _Node) -> None:
        size, any_ = (1 if n.vertex is not None else 0), n.mark
        count = self._own(n) if self.k else None
        total = self.weight[n.vertex] if self.weight is not None and n.vertex is not None else 0.0
        for c in (n.left, n.right):
            if c is not None:
                size += c.size
                total += c.total
                any_ = any_ or c.any
                if self.k and c.count is not None:
                    count = [a + b for a, b in zip(count, c.count, strict=True)] if count else list(c.count)
        n.size, n.any, n.count, n.total = size, any_, count, total

    def _merge(self, a: _Node | None, b: _Node | None) -> _Node | None:
        if a is None or b is None:
            return a or b
        if a.pri > b.pri:
            a.right = self._merge(a.right, b)
            a.right.up = a
            self._pull(a)
            return a
        b.left = self._merge(a, b.left)
        b.left.up = b
        self._pull(b)
        return b

    def _split(self, n: _Node, after: bool) -> tuple[_Node | None, _Node | None]:
        """Cut the sequence before (or after) node ``n``; climbs from n to its root."""
        came, n_up = n, n.up
        if after:
            low, high = n, n.right
            n.right = None
        else:
            low, high = n.left, n
            n.left = None
        for x in (low, high):
            if x is not None:
                x.up = None
        self._pull(n)
        while n_up is not None:
            p = n_up
            n_up = p.up
            if p.left is came:
                p.up, p.left = None, high
                if high is not None:
                    high.up = p
                high = p
            else:
                p.up, p.right = None, low
                if low is not None:
                    low.up = p
                low = p
            self._pull(p)
            came = p
        return low, high

    @staticmethod
    def _root(n: _Node) -> _Node:
        while n.up is not None:
            n = n.up
        return n

    # -- forest -----------------------------------------------------------------------
    def node(self, v: int) -> _Node:
        n = self.vertex.get(v)
        if n is None:
            n = self.vertex[v] = _Node(self.rand(), vertex=v)
            self._pull(n)
        return n

    def root(self, v: int) -> _Node:
        return self._root(self.node(v))

    def connected(self, u: int, v: int) -> bool:
        return self.root(u) is self.root(v)

    def _from(self, v: int) -> _Node:
        low, high = self._split(self.node(v), after=False)
        return self._merge(high, low)

    def link(self, u: int, v: int) -> None:
        a, b = self._from(u), self._from(v)
        there = self.arcs[u, v] = _Node(self.rand(), arc=(u, v))
        back = self.arcs[v, u] = _Node(self.rand(), arc=(v, u))
        self._merge(self._merge(a, there), self._merge(b, back))

    def cut(self, u: int, v: int) -> None:
        a, b = self.arcs.pop((u, v)), self.arcs.pop((v, u))
        low, _ = self._split(a, after=False)
        # is b in what comes before a, or after it
        if low is not None and self._root(b) is low:
            a, b = b, a
            # sequence is low' b' mid then the part that starts with the old a
            head, rest = self._split(a, after=False)
            _, mid = self._split(a, after=True)
            _, tail = self._split(b, after=True)
            self._merge(head, tail)
            return
        _, rest = self._split(a, after=True)
        mid, _ = self._split(b, after=False)
        _, tail = self._split(b, after=True)
        self._merge(low, tail)

    def set_mark(self, n: _Node, value: bool) -> None:
        if n.mark != value:
            n.mark = value
            while n is not None:
                self._pull(n)
                n = n.up

    def marked(self, root: _Node):
        """Marked nodes of a tour; found by descending into marked parts only."""
        stack = [root]
        while stack:
            n = stack.pop()
            if n is None or not n.any:
                continue
            if n.mark:
                yield n
            stack += (n.left, n.right)

    def members(self, root: _Node):
        stack = [root]
        while stack:
            n = stack.pop()
            if n is None:
                continue
            if n.vertex is not None:
                yield n.vertex
            stack += (n.left, n.right)
