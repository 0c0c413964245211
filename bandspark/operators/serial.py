"""One-task kernels: level structures, root search and frontier ordering over compressed columns, in numpy; narrow frontiers vertex by vertex.

Local vertex numbers follow the order of the ids, so ties by number are ties by id.
"""

from __future__ import annotations

from array import array
from concurrent.futures import ThreadPoolExecutor

import numpy as np


#: Frontiers of at most so many vertices are expanded vertex by vertex: the fixed cost of array calls is that of about so many.
NARROW = 16


class Columns:
    """Compressed columns of the edges given (both directions), with their vertices and degrees. 4 bytes an edge once they are sorted."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, vertices: np.ndarray | None = None):
        ids = np.unique(np.concatenate([src, dst] if vertices is None else [src, dst, vertices]))
        self._fill(ids, np.searchsorted(ids, src).astype(np.int64) << 32 | np.searchsorted(ids, dst))

    @classmethod
    def packed(cls, ids: np.ndarray, keys: np.ndarray) -> "Columns":
        """From sorted ids and edges between their places, ``src << 32 | dst`` each; the keys are sorted in place."""
        out = cls.__new__(cls)
        out._fill(ids, keys)
        return out

    def _fill(self, ids: np.ndarray, keys: np.ndarray) -> None:
        keys.sort()
        self.ids = ids
        self.start = np.searchsorted(keys, np.arange(len(ids) + 1, dtype=np.int64) << 32)
        self.degree = np.diff(self.start)
        self.rows = np.empty(len(keys), np.int32)
        np.bitwise_and(keys, 0xFFFFFFFF, out=self.rows, casting="unsafe")
        self._seq, self._mark = np.empty(len(ids), np.int32), np.empty(len(ids), np.int32)

    def neighbours(self, f: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All neighbours of the vertices in f, in their order, and for each the place of its vertex in f."""
        n = self.degree[f]
        parent = np.repeat(np.arange(len(f)), n)
        at = np.repeat(self.start[f] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return self.rows[at], parent

    def levels(self, root: int | np.ndarray, level: np.ndarray, k: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """(vertices level by level, where each level starts and the last ends); writes their levels (entries of its component must be -1 before).

        Instead of a root, all vertices of level ``k`` may be given, with those of smaller levels written already. The vertices are a view that the next call overwrites."""
        seq, rows, start = self._seq, memoryview(self.rows), memoryview(self.start)
        out, known = memoryview(seq), memoryview(level)
        first = np.atleast_1d(root)
        seq[: len(first)], level[first] = first, k
        a, b, cut = 0, len(first), array("q", [0])
        while a < b:
            cut.append(b)
            k, e = k + 1, b
            if b - a <= NARROW:
                for u in out[a:b].tolist():
                    for w in rows[start[u] : start[u + 1]].tolist():
                        if known[w] < 0:
                            known[w] = k
                            out[e] = w
                            e += 1
            else:
                near, _ = self.neighbours(seq[a:b])
                new = self._once(near[level[near] < 0])[0]
                e = b + len(new)
                level[new], seq[b:e] = k, new
            a, b = b, e
        return seq[:b], np.array(cut)

    def last_vertex(self, last: np.ndarray, shrink: str) -> int:
        """The vertex of a last level that the next search starts from."""
        last = np.sort(last)
        return int(last[np.argmin(self.degree[last])] if shrink == "min_degree" else last[0])  # the first of equals has the smallest id

    def search(self, start: int, variant: str, shrink: str, level: np.ndarray) -> tuple[int, int, int, int, np.ndarray]:
        """(root, depth of the last search, searches, hop, starts of the root's levels); ``level`` is written for the root returned."""
        root, depth, runs = start, -1, 0
        while True:
            seq, cut = self.levels(root, level)
            runs += 1
            deep, hop = len(cut) - 2, self.last_vertex(seq[cut[-2] :], shrink)
            if variant == "first" or deep <= depth:
                break
            level[seq] = -1
            root, depth = hop, deep
        if variant == "algebraic":
            level[seq] = -1
            _, cut = self.levels(hop, level)
            return hop, deep, runs, hop, cut
        return root, deep, runs, hop, cut

    def find_root(self, start: int, variant: str = "classic", shrink: str = "min_degree") -> tuple[int, int, int]:
        """(root, depth of the last search, searches). ``first`` keeps the start; ``algebraic`` takes one more hop after the last search."""
        return self.search(start, variant, shrink, np.full(len(self.ids), -1, np.int32))[:3]

    def _once(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each of v once, and the first place where it stands."""
        places = np.arange(len(v), dtype=np.int32)
        self._mark[v[::-1]] = places[::-1]  # the last written stays
        at = np.flatnonzero(self._mark[v] == places)
        return v[at], at

    def _children(self, f: np.ndarray, seen: np.ndarray, shift: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Unseen neighbours of a frontier, each once, and the place of its smallest parent."""
        near, parent = self.neighbours(f)
        fresh = seen[near] == 0
        v, at = np.unique(near[fresh], return_index=True)  # the first place is that of the smallest parent
        return v, parent[fresh][at] + shift

    def order(self, root: int, sort: str = "degree", threads: int = 1, seen: np.ndarray | None = None) -> np.ndarray:
        """The vertices of root's component in forward frontier order. sort: ``degree`` (parent, degree, id), ``parent`` (parent, id), ``level`` (id), ``end`` (degree, id).

        With more threads, each expands a share of a wide frontier; the result is the same. ``seen``: marks that calls for other components share."""
        seen = np.zeros(len(self.ids), np.uint8) if seen is None else seen
        seq, rows, start = self._seq, memoryview(self.rows), memoryview(self.start)
        out, met, degree_of = memoryview(seq), memoryview(seen), memoryview(self.degree).__getitem__
        out[0], met[root] = root, 1
        a, b = 0, 1
        pool = ThreadPoolExecutor(threads) if threads > 1 else None
        while a < b:
            e = b
            if b - a <= NARROW and sort in ("degree", "parent"):
                for u in out[a:b].tolist():
                    kids = [w for w in rows[start[u] : start[u + 1]].tolist() if not met[w]]
                    if sort == "degree" and len(kids) > 1:
                        kids.sort(key=degree_of)  # equals stay in the order of ids
                    for w in kids:
                        met[w] = 1
                        out[e] = w
                        e += 1
                a, b = b, e
                continue
            f = seq[a:b]
            if pool and len(f) >= threads:
                cut = np.linspace(0, len(f), threads + 1).astype(int).tolist()
                shares = list(pool.map(lambda ab: self._children(f[ab[0] : ab[1]], seen, ab[0]), zip(cut, cut[1:])))  # noqa: B023
                v, p = (np.concatenate(x) for x in zip(*shares))
                v, at = np.unique(v, return_index=True)  # shares are in the order of parents
                p = p[at]
            else:
                near, parent = self.neighbours(f)
                fresh = np.flatnonzero(seen[near] == 0)
                v, at = self._once(near[fresh])
                p = parent[fresh[at]]  # the first place is that of the smallest parent
            keys = {"degree": (v, self.degree[v], p), "parent": (v, p), "level": (v,), "end": (v, self.degree[v])}[sort]
            e = b + len(v)
            seq[b:e] = v[np.lexsort(keys)]
            seen[v] = 1
            a, b = b, e
        if pool:
            pool.shutdown()
        return seq[:b].copy()


def order_components(src, dst, comp_of_src, variant: str, shrink: str = "min_degree", sort: str = "degree", vertices=None, comp_of_vertices=None, given: dict | None = None, threads: int = 1):
    """For every component: arrays comp, v, place (forward, from 0), level, and one row each of (comp, root, depth, searches, width, hop)."""
    g = Columns(src, dst, vertices)
    comp = np.empty(len(g.ids), np.int64)
    comp[np.searchsorted(g.ids, src)] = comp_of_src
    if vertices is not None:
        comp[np.searchsorted(g.ids, vertices)] = comp_of_vertices
    return order_columns(g, comp, variant, shrink, sort, given, threads)


def order_columns(g: Columns, comp: np.ndarray, variant: str, shrink: str = "min_degree", sort: str | None = "degree", given: dict | None = None, threads: int = 1):
    """The same of columns whose vertices have the components ``comp``. Without ``sort`` places are left out (-1)."""
    n = len(g.ids)
    names, firsts = np.unique(comp, return_index=True)  # the first vertex of each has the smallest id
    level, seen = np.full(n, -1, np.int32), np.zeros(n, np.uint8)
    seqs, place, heads, done = np.empty(n, np.int32), np.full(n, -1, np.int32), [], 0
    for c, first in zip(names.tolist(), firsts.tolist()):
        if given and c in given:
            root, runs = int(np.searchsorted(g.ids, given[c])), 0
            seq, cut = g.levels(root, level)
            hop = g.last_vertex(seq[cut[-2] :], shrink)
        else:
            root, _, runs, hop, cut = g.search(first, variant, shrink, level)
            seq = g._seq[: cut[-1]]
        if sort:
            seq = g.order(root, sort, threads, seen)
            place[done : done + len(seq)] = np.arange(len(seq))
        seqs[done : done + len(seq)] = seq
        done += len(seq)
        heads.append((c, int(g.ids[root]), len(cut) - 2, runs, int(np.diff(cut).max()), int(g.ids[hop])))
    return [comp[seqs], g.ids[seqs], place, level[seqs]], heads


def profile_of(src: np.ndarray, dst: np.ndarray, label: np.ndarray) -> tuple[int, int]:
    """(bandwidth, profile) of labels indexed by vertex, for checks."""
    i, j = label[src], label[dst]
    low = np.arange(len(label))
    np.minimum.at(low, i, j)
    beta = np.arange(len(label)) - low
    return int(beta.max(initial=0)), int(beta.sum())
