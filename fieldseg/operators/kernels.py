"""NumPy kernels of one block: sorted global ids in, one dense array for each attribute."""

from __future__ import annotations

import numpy as np


def place(ids: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Positions of the wanted ids in the sorted ids; -1 where absent."""
    if not len(ids):
        return np.full(len(wanted), -1, np.int64)
    at = np.searchsorted(ids, wanted)
    at[at == len(ids)] = 0
    return np.where(ids[at] == wanted, at, -1)


def compress_local(d: np.ndarray, in_place: bool = True) -> int:
    """Double the local pointers until nothing moves; only vertices that still move are touched.  Returns the rounds."""
    rounds, live = 0, np.arange(len(d))
    while True:
        old = d[live]
        far = d[old]
        moving = far != old
        if not moving.any():
            return rounds
        rounds += 1
        if in_place:
            live = live[moving]
            d[live] = far[moving]
        else:
            fresh = d.copy()
            fresh[live] = far
            d[:] = fresh
            live = live[moving]


def double(ids: np.ndarray, ptr: np.ndarray, in_place: bool = True) -> tuple[np.ndarray, int]:
    """Pointers among (unsorted) ids followed to their ends; a target that is no id is an end."""
    order = np.argsort(ids, kind="stable")
    sorted_ids, target = ids[order], ptr[order]
    d = place(sorted_ids, target)
    outside = d < 0
    # a target from outside becomes an end of its own behind the ids
    ends = np.unique(target[outside])
    d[outside] = len(ids) + np.searchsorted(ends, target[outside])
    d = np.concatenate([d, len(ids) + np.arange(len(ends))])
    rounds = compress_local(d, in_place)
    names = np.concatenate([sorted_ids, ends])
    out = np.empty_like(ptr)
    out[order] = names[d[: len(ids)]]
    return out, rounds


class GridNeighbours:
    """Local neighbours of the ids of a block on a grid, one stencil step at a time."""

    def __init__(self, dims: tuple[int, ...], stencil: list[tuple[int, ...]]):
        self.dims, self.steps = dims, stencil

    def __call__(self, ids: np.ndarray):
        """(from, to) local positions for each step; every pair of neighbours in the block comes up twice."""
        coords, rest = [], ids
        for a, n in enumerate(self.dims):
            last = a == len(self.dims) - 1
            coords.append(rest if last else rest % n)
            rest = rest if last else rest // n
        for step in self.steps:
            ok, shift, stride = np.ones(len(ids), bool), 0, 1
            for c, s, n in zip(coords, step, self.dims):
                if s:
                    ok &= (c + s >= 0) & (c + s < n)
                shift += s * stride
                stride *= n
            src = np.flatnonzero(ok)
            dst = place(ids, ids[src] + shift)
            yield src[dst >= 0], dst[dst >= 0]


class EdgeNeighbours:
    """The same from an explicit list of pairs of global ids."""

    def __init__(self, src: np.ndarray, dst: np.ndarray):
        self.src, self.dst = src, dst

    def __call__(self, ids: np.ndarray):
        a, b = place(ids, self.src), place(ids, self.dst)
        ok = (a >= 0) & (b >= 0)
        yield a[ok], b[ok]
        yield b[ok], a[ok]


def steepest_local(ids: np.ndarray, rank: np.ndarray, neighbours, ghost: np.ndarray, up: bool) -> np.ndarray:
    """Local pointer of each vertex to the extreme of its closed star by rank; ghosts point to themselves."""
    best = np.arange(len(ids))
    key = rank if up else -rank
    most = key.copy()
    for src, dst in neighbours(ids):
        if len(src) > 1 and not (src[1:] > src[:-1]).all():
            order = np.lexsort((key[dst], src))
            src, dst = src[order], dst[order]
            last = np.concatenate([src[1:] != src[:-1], [True]])
            src, dst = src[last], dst[last]
        better = key[dst] > most[src]
        s, t = src[better], dst[better]
        most[s], best[s] = key[t], t
    best[ghost] = np.flatnonzero(ghost)
    return best


def local_components(ids: np.ndarray, neighbours, limit: int | None = None) -> tuple[np.ndarray, int]:
    """Local position of the largest id of each vertex's component in the block: hook to larger neighbours, compress, repeat.

    Ids ascend, so positions compare as ids do.  With `limit`, so many hooking passes over roots run and no more.
    """
    d = np.arange(len(ids))
    pairs = [p for p in neighbours(ids) if len(p[0])]
    for src, dst in pairs:
        np.maximum.at(d, src, dst)
    rounds = compress_local(d)
    passes = 0
    while limit is None or passes < limit:
        grown = d.copy()
        for src, dst in pairs:
            differ = d[dst] > d[src]
            np.maximum.at(grown, d[src[differ]], d[dst[differ]])
        if (grown == d).all():
            break
        d = grown
        rounds += compress_local(d)
        passes += 1
    return d, rounds


def breadth_first(ids: np.ndarray, neighbours) -> np.ndarray:
    """Component number of each vertex by waves that start at the lowest vertex not reached yet."""
    n = len(ids)
    src = np.concatenate([np.zeros(0, np.int64), *(p[0] for p in neighbours(ids))]) if n else np.zeros(0, np.int64)
    dst = np.concatenate([np.zeros(0, np.int64), *(p[1] for p in neighbours(ids))]) if n else np.zeros(0, np.int64)
    order = np.argsort(src, kind="stable")
    src, dst = src[order], dst[order]
    first = np.searchsorted(src, np.arange(n + 1))
    label, number = np.full(n, -1, np.int64), 0
    for seed in range(n):
        if label[seed] >= 0:
            continue
        label[seed] = number
        front = np.array([seed])
        while len(front):
            reach = np.unique(np.concatenate([dst[first[v] : first[v + 1]] for v in front]))
            front = reach[label[reach] < 0]
            label[front] = number
        number += 1
    return label


def union_find(src: np.ndarray, dst: np.ndarray) -> dict[int, int]:
    """Largest id of the component of each end, by union with path halving."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in zip(src.tolist(), dst.tolist()):
        a, b = find(a), find(b)
        if a != b:
            parent[min(a, b)] = max(a, b)
    return {x: find(x) for x in list(parent)}
