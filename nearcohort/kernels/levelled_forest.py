"""Spanning forest under edge deletions, with edge levels and keyword counts per tree.

Every edge has a level, 0 at first.  Forest i spans the edges of level i and above and is
part of forest i-1.  When a tree edge of level l goes, it is cut in the forests l to 0; from
level l down, the smaller side lifts its own tree edges by a level and looks through its
loose edges of that level: those inside the side are lifted, the first that leaves the side
becomes the substitute.  An edge is lifted at most log2(V) times.
"""

from __future__ import annotations

from nearcohort.kernels.euler_tour import EulerForest


class LevelledForest:
    def __init__(self, hold, n_keywords: int, weight=None):
        self.levels = [EulerForest(hold, n_keywords, weight=weight)]
        self.level: dict[tuple[int, int], int] = {}
        self.tree: set[tuple[int, int]] = set()
        self.loose: list[dict[int, set[int]]] = [{}]
        self.lifts = self.searches = 0

    @staticmethod
    def _key(u: int, v: int) -> tuple[int, int]:
        return (u, v) if u < v else (v, u)

    def _forest(self, i: int) -> EulerForest:
        while len(self.levels) <= i:
            self.levels.append(EulerForest(seed=11 + len(self.levels)))
            self.loose.append({})
        return self.levels[i]

    def add(self, u: int, v: int) -> None:
        """A new edge, at level 0."""
        e = self._key(u, v)
        self.level[e] = 0
        if self.levels[0].connected(u, v):
            self._loosen(e, 0)
        else:
            self._plant(e, 0)

    def _plant(self, e: tuple[int, int], level: int) -> None:
        """Make e a tree edge of ``level``: part of the forests 0 to level."""
        self.tree.add(e)
        for i in range(level + 1):
            self._forest(i).link(*e)
        self._flag(e, level, True)

    def _flag(self, e, i: int, value: bool) -> None:
        f = self._forest(i)
        f.set_mark(f.arcs[e], value)

    def _loosen(self, e: tuple[int, int], i: int) -> None:
        f = self._forest(i)
        for a, b in (e, e[::-1]):
            s = self.loose[i].setdefault(a, set())
            s.add(b)
            f.set_mark(f.node(a), True)

    def _tighten(self, e: tuple[int, int], i: int) -> None:
        f = self.levels[i]
        for a, b in (e, e[::-1]):
            s = self.loose[i][a]
            s.discard(b)
            if not s:
                f.set_mark(f.node(a), False)

    def delete(self, u: int, v: int) -> bool:
        """Remove an edge; True if its tree fell into two."""
        e = self._key(u, v)
        top = self.level.pop(e)
        if e not in self.tree:
            self._tighten(e, top)
            return False
        self.tree.discard(e)
        for i in range(top + 1):
            self.levels[i].cut(u, v)
        self.searches += 1
        return not any(self._substitute(u, v, i) for i in range(top, -1, -1))

    def _substitute(self, u: int, v: int, i: int) -> bool:
        f = self._forest(i)
        a, b = f.root(u), f.root(v)
        side = a if a.size <= b.size else b
        self._forest(i + 1)
        for n in [n for n in f.marked(side) if n.arc is not None]:
            e = n.arc
            f.set_mark(n, False)
            self.level[self._key(*e)] = i + 1
            self.levels[i + 1].link(*e)
            self._flag(e, i + 1, True)
            self.lifts += 1
        for n in [n for n in f.marked(side) if n.vertex is not None]:
            x = n.vertex
            for w in list(self.loose[i].get(x, ())):
                e = self._key(x, w)
                self._tighten(e, i)
                if f.root(w) is side:
                    self.level[e] = i + 1
                    self._loosen(e, i + 1)
                    self.lifts += 1
                else:
                    self.level[e] = i
                    self._plant(e, i)
                    return True
        return False

    def tree_of(self, v: int):
        return self.levels[0].root(v)

    def census(self, v: int) -> tuple[list[int], int, float]:
        """Keyword counts, size and weight of the tree of v; no member is visited."""
        r = self.tree_of(v)
        return (r.count or [0] * self.levels[0].k), r.size, r.total

    def members(self, v: int) -> list[int]:
        return list(self.levels[0].members(self.tree_of(v)))

    def check(self) -> None:
        """Assert nesting, spanning and the size bound of every level (for tests)."""
        n = max(1, len(self.levels[0].vertex))
        for i, f in enumerate(self.levels):
            want = {e for e in self.tree if self.level[e] >= i}
            assert {self._key(*a) for a in f.arcs} == want, "forest edges"
            for e, lv in self.level.items():
                if lv >= i:
                    assert f.connected(*e), "spanning"
            for v in f.vertex:
                assert f.root(v).size <= max(1, n // 2**i), "size bound"
