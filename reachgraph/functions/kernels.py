"""Reachability inside one graph that fits a task, on arrays.

A graph is condensed to the DAG of its strongly connected components. Sets of
sources are bit rows that travel along the DAG, level by level, so that all
sources of a block move at once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

#: Bytes that the bit rows of one block of sources may take.
BLOCK_BYTES = 32 << 20

#: Pairs that are unpacked from bit rows at a time.
CHUNK = 2 << 20

#: Sources that walk together, and pairs of source and component that they may reach; beyond, bit rows take over.
WALK, WALK_PAIRS = 1 << 16, 1 << 20


def set_bits(rows: np.ndarray, row: np.ndarray, bit: np.ndarray) -> None:
    """Set bits of bit rows, in place."""
    np.bitwise_or.at(rows, (row, bit // 64), np.uint64(1) << (bit % 64).astype(np.uint64))


def equal_columns(rows: np.ndarray, size: int) -> np.ndarray:
    """For each of the ``size`` bits of bit rows, the first bit that is set in the same rows; -1 where it is set in none."""
    out, chunk = np.empty((size, -(-len(rows) // 8)), dtype=np.uint8), max(8, CHUNK // max(1, size) // 8 * 8)
    for lo in range(0, len(rows), chunk):
        found = np.unpackbits(rows[lo : lo + chunk].view(np.uint8), axis=1, bitorder="little")[:, :size]
        out[:, lo // 8 : lo // 8 + -(-len(found) // 8)] = np.packbits(found, axis=0, bitorder="little").T
    if not out.shape[1]:
        return np.full(size, -1, dtype=np.int64)
    _, first, which = np.unique(out.view(f"V{out.shape[1]}").ravel(), return_index=True, return_inverse=True)
    return np.where(out.any(axis=1), first[which], -1)


def _peel(n: int, src: np.ndarray, dst: np.ndarray, open_: np.ndarray) -> list[np.ndarray]:
    """Open vertices without an edge from an open one, then those that these leave without one, and so on."""
    inner = open_[src] & open_[dst]
    src, dst = src[inner], dst[inner]
    by = np.argsort(src, kind="stable")
    targets, offsets = dst[by], np.searchsorted(src[by], np.arange(n + 1))
    degree = np.bincount(dst, minlength=n)
    layers = []
    front = np.flatnonzero(open_ & (degree == 0))
    while len(front):
        layers.append(front)
        count = offsets[front + 1] - offsets[front]
        step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        met = targets[np.repeat(offsets[front], count) + step]
        np.subtract.at(degree, met, 1)
        met = np.unique(met)
        front = met[degree[met] == 0]
    return layers


def components(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Strongly connected component of each vertex 0..n-1; an edge never leads to a larger number.

    What leads to no cycle and what no cycle leads to is peeled off in layers of
    whole arrays; only the core between them is walked vertex by vertex.
    """
    comp = np.full(n, -1, dtype=np.int64)
    sinks = _peel(n, dst, src, np.ones(n, dtype=bool))
    low = 0
    for layer in sinks:
        comp[layer] = low + np.arange(len(layer))
        low += len(layer)
    roots = _peel(n, src, dst, comp < 0)
    count = sum(map(len, roots))
    core = comp < 0
    for layer in roots:
        core[layer] = False
    names = np.flatnonzero(core)
    inner = core[src] & core[dst]
    found = _walk(len(names), np.searchsorted(names, src[inner]), np.searchsorted(names, dst[inner]))
    comp[names] = low + found
    high = low + (int(found.max()) + 1 if len(found) else 0) + count
    for layer in roots:
        high -= len(layer)
        comp[layer] = high + np.arange(len(layer))
    return comp


def _walk(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Components of a graph by one depth-first walk."""
    by = np.argsort(src, kind="stable")
    targets = dst[by].tolist()
    offsets = np.searchsorted(src[by], np.arange(n + 1)).tolist()
    seen, low, comp = [0] * n, [0] * n, [-1] * n
    clock, count = 0, 0
    stack: list[int] = []
    for root in range(n):
        if seen[root]:
            continue
        clock += 1
        seen[root] = low[root] = clock
        stack.append(root)
        path, at = [root], [offsets[root]]
        while path:
            v, i = path[-1], at[-1]
            if i < offsets[v + 1]:
                at[-1] += 1
                w = targets[i]
                if not seen[w]:
                    clock += 1
                    seen[w] = low[w] = clock
                    stack.append(w)
                    path.append(w)
                    at.append(offsets[w])
                elif comp[w] < 0 and seen[w] < low[v]:
                    low[v] = seen[w]
                continue
            path.pop()
            at.pop()
            if path and low[v] < low[path[-1]]:
                low[path[-1]] = low[v]
            if low[v] == seen[v]:
                while True:
                    w = stack.pop()
                    comp[w] = count
                    if w == v:
                        break
                count += 1
    return np.array(comp, dtype=np.int64)


def meet(who: np.ndarray, comp: np.ndarray, at: np.ndarray, value: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(who, value) of all values whose component ``at``, ascending, is that of who; about ``CHUNK`` pairs at a time."""
    low, high = np.searchsorted(at, comp, "left"), np.searchsorted(at, comp, "right")
    total = np.concatenate([[0], np.cumsum(high - low)])
    lo = 0
    while lo < len(who):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + CHUNK, "right")) - 1)
        count = high[lo:hi] - low[lo:hi]
        yield np.repeat(who[lo:hi], count), value[np.repeat(low[lo:hi] - (total[lo:hi] - total[lo]), count) + np.arange(count.sum())]
        lo = hi


def joined(who: np.ndarray, comp: np.ndarray, at: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All that ``meet`` finds; ``at`` need not be in order."""
    by = np.argsort(at, kind="stable")
    got = list(meet(who, comp, at[by], value[by]))
    return tuple(np.concatenate(side) for side in zip(*got, strict=True)) if got else (who[:0], value[:0])


@dataclass
class Dag:
    """Condensed graph: vertices in ascending order, their components, DAG edges ordered for propagation."""

    verts: np.ndarray
    comp: np.ndarray
    cyclic: np.ndarray  # per component: has it a path to itself
    src: np.ndarray
    dst: np.ndarray
    level: np.ndarray  # per edge: longest way from a root to its source

    @classmethod
    def of(cls, src: np.ndarray, dst: np.ndarray, extra: np.ndarray | None = None) -> Dag:
        """Condense the graph of these edges; ``extra`` vertices need not have edges."""
        verts = np.unique(np.concatenate([src, dst, np.empty(0, dtype=np.int64) if extra is None else extra]))
        s, d = np.searchsorted(verts, src), np.searchsorted(verts, dst)
        comp = components(len(verts), s, d)
        n = int(comp.max()) + 1 if len(comp) else 0
        cyclic = np.bincount(comp, minlength=n) > 1 if n else np.zeros(0, dtype=bool)
        cyclic[comp[s[s == d]]] = True
        cs, cd = comp[s], comp[d]
        pairs = np.unique(cs[cs != cd] * max(1, n) + cd[cs != cd])  # one number each, which takes far less room to sort than rows
        cs, cd = pairs // max(1, n), pairs % max(1, n)
        depth = np.zeros(n, dtype=np.int64)
        for i, layer in enumerate(_peel(n, cs, cd, np.ones(n, dtype=bool))):
            depth[layer] = i
        level = depth[cs]
        order = np.lexsort((cd, level))
        return cls(verts, comp, cyclic, cs[order], cd[order], level[order])

    def place(self, vertices: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which of the vertices are in the graph, their components)."""
        if not len(self.verts):
            return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        at = np.minimum(np.searchsorted(self.verts, vertices), len(self.verts) - 1)
        known = np.flatnonzero(self.verts[at] == vertices)
        return known, self.comp[at[known]]

    def spread(self, rows: np.ndarray) -> np.ndarray:
        """Bit rows by component, propagated along all edges, in place."""
        if not len(self.src):
            return rows
        ends = np.flatnonzero(np.diff(self.level)) + 1
        for a, b in zip(np.concatenate([[0], ends]), np.concatenate([ends, [len(self.level)]]), strict=True):
            dst = self.dst[a:b]
            starts = np.flatnonzero(np.concatenate([[True], dst[1:] != dst[:-1]]))
            rows[dst[starts]] |= np.bitwise_or.reduceat(rows[self.src[a:b]], starts, axis=0)
        return rows

    def walk(self, number: np.ndarray, start: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray] | None:
        """Distinct (number, component) reached from components ``start[i]`` by number ``number[i]``, themselves included; None beyond ``most`` pairs.

        Costs what is reached, not sources times components, so it is the way
        for graphs in which little is reached.
        """
        n = np.int64(max(1, len(self.cyclic)))
        if not hasattr(self, "_out"):
            by = np.argsort(self.src, kind="stable")
            self._out = self.dst[by], np.searchsorted(self.src[by], np.arange(n + 1))
        to, offsets = self._out
        seen = front = np.unique(number * n + start)
        while len(front):
            i, c = front // n, front % n
            low, count = offsets[c], offsets[c + 1] - offsets[c]
            total = int(count.sum())
            if total > 4 * most:
                return None
            step = np.arange(total) - np.repeat(np.cumsum(count) - count, count)
            after = np.unique(np.repeat(i, count) * n + to[np.repeat(low, count) + step])
            at = np.minimum(np.searchsorted(seen, after), len(seen) - 1)
            front = after[seen[at] != after]
            if len(seen) + len(front) > most:
                return None
            seen = np.insert(seen, np.searchsorted(seen, front), front)
        return seen // n, seen % n

    def reach(self, sources: np.ndarray, starts: np.ndarray, targets: np.ndarray, empty_path: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (source, target) such that a path leads from one of the source's starts to the target.

        ``sources[i]`` starts at vertex ``starts[i]``. Without ``empty_path`` a
        start reaches itself only over a cycle.
        """
        got = list(self.reach_by_blocks(sources, starts, targets, empty_path))
        if not got:
            return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        s, t = (np.concatenate(side) for side in zip(*got, strict=True))
        return s, t

    def reach_by_blocks(self, sources: np.ndarray, starts: np.ndarray, targets: np.ndarray, empty_path: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """What ``reach`` finds, at most about ``CHUNK`` pairs at a time."""
        known, comp = self.place(starts)
        names, number = np.unique(sources[known], return_inverse=True)
        ends, end_comp = self.place(targets)
        ends = targets[ends]
        own = np.stack([sources[known], starts[known]], axis=1)
        block = self.block()
        by = np.argsort(number, kind="stable")
        number, comp, own = number[by], comp[by], own[by]
        by = np.argsort(end_comp, kind="stable")
        ends, end_comp = ends[by], end_comp[by]
        wide, lo, sparse = WALK, 0, True
        while lo < len(names):
            # as many sources as are worth a walk, else a block of bit rows
            size = min(wide, len(names) - lo)
            mine = slice(*np.searchsorted(number, [lo, lo + size]))
            walked = self.walk(number[mine], comp[mine], WALK_PAIRS) if sparse else None
            if walked is None and size > block:
                wide = max(block, size // 4)
                continue
            sparse = walked is not None
            if sparse:
                for s, t in meet(*walked, end_comp, ends):
                    s = names[s]
                    if not empty_path:
                        self_hit = self._alone(s, t, own, comp)
                        s, t = s[~self_hit], t[~self_hit]
                    if len(s):
                        yield s, t
                lo += size
                continue
            size = min(block, size)
            mine = slice(*np.searchsorted(number, [lo, lo + size]))
            rows = np.zeros((len(self.cyclic), (size + 63) // 64), dtype=np.uint64)
            set_bits(rows, comp[mine], number[mine] - lo)
            rows = self.spread(rows)
            chunk = max(1, CHUNK // size)
            for at in range(0, len(ends), chunk):
                found = np.unpackbits(rows[end_comp[at : at + chunk]].view(np.uint8), axis=1, bitorder="little")[:, :size]
                t, s = np.nonzero(found)
                if not len(s):
                    continue
                s, t = names[lo + s], ends[at + t]
                if not empty_path:
                    # a start that reaches itself only by staying where it is
                    self_hit = self._alone(s, t, own, comp)
                    s, t = s[~self_hit], t[~self_hit]
                yield s, t
            lo += size

    def block(self, more: int = 0) -> int:
        """Sources whose bit rows over this graph and ``more`` rows are made at a time."""
        return max(64, BLOCK_BYTES // max(1, 8 * (len(self.cyclic) + more)) * 64)

    def heads(self, sources: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(distinct sources in the graph, the smallest source in the component of each)."""
        sources = np.unique(sources)
        at, comp = self.place(sources)
        sources = sources[at]
        _, first, which = np.unique(comp, return_index=True, return_inverse=True)
        return sources, sources[first[which]]

    def _alone(self, s: np.ndarray, t: np.ndarray, own: np.ndarray, comp: np.ndarray) -> np.ndarray:
        """Hits (s, t) where t is a start of s on no cycle, and no other start of s leads there."""
        if (own[:, 0] != own[:, 1]).any():
            raise ValueError("sources must start at themselves where the empty path does not count")
        _, ct = self.place(t)
        return (s == t) & ~self.cyclic[ct]
