"""The graph kernel that runs inside a worker: labelled insertion, virtual merged neighbours, greedy walks.

A shard's objects are rows of one matrix.  A graph is a list of directed edges ``src, dst, begin,
end`` over them; an edge is visible at version v if begin <= v <= end.  Everything is
deterministic: objects enter by (version, id), candidates are ordered by (distance, row).

Two builders make the same graph.  ``GrowingGraph`` inserts one object at a time.  ``grow`` uses that, with the nearest
of all earlier members as candidates, what an object links to depends on vectors alone, and what
becomes of a vertex' list only on the objects that link to it, in their order: it finds all candidates by blocked matrix
products, prunes them in blocks, and replays each vertex' events, all vertices at once.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np

OPEN = np.iinfo(np.int32).max
REPLAYED = 1024  # lists that are pruned at once
CANDIDATES = 12_800  # and candidates of lists
COMPARED = 500_000  # changes of edges that are compared at once
MANY = 48  # lists from which on places are found in all at once
SPARE = 8  # candidates beside those asked for
PLACES = 32  # of a list, whose vectors and mutual distances are held; 64 at most
EXACT_ROWS = 8192  # of a node, whose candidates are sought in double precision


@dataclass
class Counters:
    """Work that a walk did."""

    distances: int = 0
    hops: int = 0
    edges: int = 0
    unqualified: int = 0
    exhausted: int = 0  # walks that expanded all they met
    missed: int = 0  # qualifying members that such walks left unreached


def squared(vectors: np.ndarray, q: np.ndarray) -> np.ndarray:
    d = vectors - q
    return np.einsum("ij,ij->i", d, d)


def summed(vectors: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Squared distances, added up component by component as SQL does, so that near ties fall alike."""
    out = np.zeros(len(vectors))
    for j in range(vectors.shape[1]):
        gap = vectors[:, j] - q[j]
        out += gap * gap
    return out


def rounding(x: np.ndarray, number: type = np.float64) -> float:
    """What a squared distance by products can err by, for a sum of the two squares of one."""
    return 8 * (x.shape[-1] + 8) * float(np.finfo(number).eps)


def shadows(x: np.ndarray, by: np.ndarray, rows: np.ndarray, dist: np.ndarray) -> np.ndarray:
    """For lists of rows: whether each of ``by`` is nearer to each of ``rows`` than ``dist`` says.

    Where rounding of the products could turn that, as among copies of vectors, the distance is computed as ``squared`` does, so that all builders decide alike.
    """
    v = x.take(rows, axis=0)
    y = v if by is rows else x.take(by, axis=0)
    square = np.einsum("ijk,ijk->ij", v, v)
    own = square if by is rows else np.einsum("ijk,ijk->ij", y, y)
    gap = y @ v.transpose(0, 2, 1)
    gap *= -2
    gap += own[:, :, None]
    gap += (square - dist)[:, None, :]
    out = gap < 0
    slack = rounding(x) * (own.max(axis=1, initial=0) + 2 * square.max(axis=1, initial=0))
    close = np.flatnonzero(np.abs(gap, out=gap) <= slack[:, None, None])
    for c in range(0, len(close), CANDIDATES):
        i, j, k = np.unravel_index(close[c : c + CANDIDATES], out.shape)
        step = y[i, j] - v[i, k]
        out[i, j, k] = np.einsum("ij,ij->i", step, step) < dist[i, k]
    return out


def rng_prune(base: np.ndarray, candidates: np.ndarray, distance: np.ndarray, vectors: np.ndarray, most: int) -> np.ndarray:
    """Of candidates by rising distance those that no kept one is nearer to than the base vector is; at most ``most``."""
    candidates = np.asarray(candidates)
    near = shadows(vectors, candidates[None], candidates[None], np.asarray(distance)[None])[0]
    shadow = np.zeros(len(candidates), bool)
    kept = []
    for i in range(len(candidates)):
        if not shadow[i]:
            kept.append(i)
            if len(kept) == most:
                break
            shadow |= near[i]
    return candidates[kept]


def nearest_before(x: np.ndarray, ef: int, start: int = 0, block: int = 256, chunk: int = 8192) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For rows from ``start`` on, in blocks: the block's first row, and of each row its ``ef`` nearest earlier rows by (distance, row) and their squared distances.

    Places without a row are -1 and infinite.  Blocks meet the earlier rows in chunks; past the first chunk only what is nearer than the worst kept is merged.
    Some more are kept than asked for; a row whose last ones lie so close together that products cannot tell them apart is sought again with all of these.
    """
    square, one = np.einsum("ij,ij->i", x, x), np.ones(len(x))
    number = np.float64 if len(x) <= EXACT_ROWS else np.float32  # distances of the chosen are computed anew
    left, right = np.column_stack([x, square, one]).astype(number), np.column_stack([-2 * x, one, square]).astype(number).T.copy()
    width = ef + SPARE

    def product(rows, c: int, e: int) -> np.ndarray:
        d = left[rows] @ right[:, c:e]
        first = np.arange(len(x))[rows]
        if len(first) and e > first[0]:
            d[np.arange(c, e)[None, :] >= first[:, None]] = np.inf
        return d

    for a in range(start, len(x), block):
        b = min(len(x), a + block)
        best = np.full((b - a, width), -1)
        dist = np.full((b - a, width), np.inf, number)
        for c in range(0, b, chunk):
            e = min(b, c + chunk)
            d = product(slice(a, b), c, e)
            if not c:
                at = np.argpartition(d, min(width, e) - 1, axis=1)[:, :width]
                more, index = np.take_along_axis(d, at, axis=1), at
            else:
                row, col = np.nonzero(d < dist.max(axis=1)[:, None])
                if not len(row):
                    continue
                count = np.bincount(row, minlength=b - a)
                place = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
                more, index = np.full((b - a, count.max()), np.inf, number), np.full((b - a, count.max()), -1)
                more[row, place], index[row, place] = d[row, col], col + c
            both, which = np.concatenate([dist, more], axis=1), np.concatenate([best, index], axis=1)
            at = np.argpartition(both, width - 1, axis=1)[:, :width]
            dist, best = np.take_along_axis(both, at, axis=1), np.take_along_axis(which, at, axis=1)
        best[~np.isfinite(dist)] = -1
        gap = x[best] - x[a:b, None, :]
        dist = np.where(best >= 0, np.einsum("ijk,ijk->ij", gap, gap), np.inf)
        order = np.lexsort((best, dist), axis=-1)
        best, dist = np.take_along_axis(best, order, axis=1), np.take_along_axis(dist, order, axis=1)
        slack = rounding(x, number) * (square[a:b] + square[:b].max())
        again = np.flatnonzero(np.isfinite(dist[:, -1]) & (dist[:, ef - 1] + 2 * slack >= dist[:, -1]))
        best, dist = best[:, :ef], dist[:, :ef]
        for p in range(0, len(again), 16):
            rows = again[p : p + 16]
            limit = dist[rows, -1] + slack[rows]
            row, col = (np.concatenate(z) for z in zip(*((r, k + c) for c in range(0, b, chunk) for r, k in [np.nonzero(product(rows + a, c, min(b, c + chunk)) <= limit[:, None])]), strict=True))
            exact = np.empty(len(row))
            for c in range(0, len(row), CANDIDATES):
                gap = x[col[c : c + CANDIDATES]] - x[rows[row[c : c + CANDIDATES]] + a]
                exact[c : c + CANDIDATES] = np.einsum("ij,ij->i", gap, gap)
            order = np.lexsort((col, exact, row))
            at = np.searchsorted(row[order], np.arange(len(rows)))[:, None] + np.arange(ef)
            best[rows], dist[rows] = col[order][at], exact[order][at]
        yield a, best, dist


class Scan:
    """The ``ef`` nearest earlier rows of each row, as a scan of all with ``squared`` and an order by (distance, row) gives them, found in blocks.

    Products in single precision leave out what is farther by more than their error; the distances of the rest are computed anew.
    """

    def __init__(self, x: np.ndarray, ef: int):
        self.x, self.ef, self.square = x, ef, np.einsum("ij,ij->i", x, x)
        self.number = np.float32 if len(x) and self.square.max() < 1e30 else np.float64
        self.earlier = np.column_stack([-2 * x, np.ones(len(x)), self.square]).astype(self.number).T.copy()

    def block(self, a: int, b: int, chunk: int = 8192) -> list[np.ndarray]:
        """The lists of the rows from ``a`` to ``b``."""
        x, ef, n = self.x, min(self.ef, b), b - a
        now = np.column_stack([x[a:b], self.square[a:b], np.ones(n)]).astype(self.number)
        slack = (3 * rounding(x, self.number) * (self.square[a:b] + self.square[:b].max())).astype(self.number)
        best, limit, hits = np.full((n, ef), np.inf, self.number), np.full(n, np.inf, self.number), []
        for c in range(0, b, chunk):
            e = min(b, c + chunk)
            d = now @ self.earlier[:, c:e]
            if e > a:
                d[np.arange(c, e)[None, :] >= np.arange(a, b)[:, None]] = np.inf
            if c:
                row, col = np.nonzero(d <= limit[:, None])
                if not len(row):
                    continue
                count = np.bincount(row, minlength=n)
                more = np.full((n, count.max()), np.inf, self.number)
                more[row, np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)] = d[row, col]
            else:
                more = np.partition(d, ef - 1, axis=1)[:, :ef] if e > ef else d
            best = np.partition(np.concatenate([best, more], axis=1), ef - 1, axis=1)[:, :ef]
            limit = best.max(axis=1) + slack
            if not c:
                row, col = np.nonzero(d <= limit[:, None])
            hits.append((row, col + c, d[row, col]))
        row, col, d = (np.concatenate(p) for p in zip(*hits, strict=True))
        keep = np.flatnonzero((d <= limit[row]) & (col < row + a))
        row, col = row[keep], col[keep]
        exact = np.empty(len(row))
        for c in range(0, len(row), CANDIDATES):
            gap = x[col[c : c + CANDIDATES]] - x[row[c : c + CANDIDATES] + a]
            exact[c : c + CANDIDATES] = np.einsum("ij,ij->i", gap, gap)
        order = np.lexsort((col, exact, row))
        begins = np.searchsorted(row[order], np.arange(n + 1))
        return [col[order[p : min(q, p + ef)]] for p, q in zip(begins, begins[1:], strict=False)]


def nearer(x: np.ndarray, rows: np.ndarray, dist: np.ndarray) -> np.ndarray:
    """For lists of rows, as bits of whole bytes: to which others of its list each row is nearer than ``dist`` says."""
    return np.packbits(shadows(x, rows, rows, dist), axis=2, bitorder="little")


def kept_of(x: np.ndarray, found: np.ndarray, dist: np.ndarray, most: int, prune: bool) -> np.ndarray:
    """``rng_prune`` for many lists at once (by rising distance, -1 where empty): which places stay.

    Lists are taken some places at a time, those that are full no further; the next place that stays is found in all lists at once.
    """
    valid = found >= 0
    if not prune:
        return valid & (np.cumsum(valid, axis=1) <= most)
    n, width = found.shape
    keep, count, kept = np.zeros(found.shape, bool), np.zeros(n, int), np.zeros((n, most), np.int64)
    for a in range(0, width, PLACES):
        of = np.flatnonzero((count < most) & valid[:, a : a + PLACES].any(axis=1))
        if not len(of):
            continue
        rows, d, shadow, held = found[of, a : a + PLACES], dist[of, a : a + PLACES], ~valid[of, a : a + PLACES], count[of]
        if a:
            by = kept[of, : held.max()]
            shadow |= (shadows(x, by, rows, d) & (np.arange(by.shape[1]) < held[:, None])[:, :, None]).any(axis=1)
        bits = np.zeros((len(of), rows.shape[1], 8), np.uint8)
        packed = nearer(x, rows, d)
        bits[:, :, : packed.shape[2]] = packed
        bits = bits.view(np.uint64)[:, :, 0]
        packed = np.packbits(shadow, axis=1, bitorder="little")
        free = np.zeros((len(of), 8), np.uint8)
        free[:, : packed.shape[1]] = packed
        free = ~free.view(np.uint64)[:, 0] & np.uint64(2 ** rows.shape[1] - 1)
        live = np.flatnonzero(free)
        while len(live):
            now = free[live]
            low = now & (~now + np.uint64(1))
            at = np.frexp(low.astype(float))[1] - 1
            into = of[live]
            keep[into, a + at] = True
            kept[into, held[live]] = rows[live, at]
            held[live] += 1
            now &= ~(bits[live, at] | low)
            free[live] = now
            live = live[(now != 0) & (held[live] < most)]
        count[of] = held
    return keep


def grow(x: np.ndarray, version: np.ndarray, cuts: np.ndarray, most: int, ef: int, prune: bool = True, fresh: np.ndarray | None = None, old: np.ndarray | None = None) -> np.ndarray:
    """Rows ``src, dst, begin, end`` (places) of the graphs of several nodes, whose members stand one after the other in order of insertion.

    ``cuts`` holds where nodes begin and the end.  ``old`` are the rows that members up to ``fresh`` (a place a node) have already.
    """
    n = len(x)
    source, target, gap = [], [], []
    for k, (a, b) in enumerate(zip(cuts.tolist(), cuts[1:].tolist(), strict=False)):
        for first, found, dist in nearest_before(x[a:b], ef, 0 if fresh is None else int(fresh[k]) - a):
            step = max(1, CANDIDATES // ef)
            for c in range(0, len(found), step):
                row, place = np.nonzero(kept_of(x[a:b], found[c : c + step], dist[c : c + step], most, prune))
                source.append(row + c + first + a)
                target.append(found[row + c, place] + a)
                gap.append(dist[row + c, place])
    if not source and old is None:
        return np.zeros((0, 4), np.int64)
    source, target, gap = (np.concatenate(p) if p else np.zeros(0, int) for p in (source, target, gap))
    slot, away, since, held = np.full((n, most + 1), -1), np.full((n, most + 1), np.inf), np.zeros((n, most + 1), np.int64), np.zeros(n, int)
    closed = []
    if old is not None and len(old):
        closed.append(old[old[:, 3] != OPEN])
        live = old[old[:, 3] == OPEN]
        live = live[np.argsort(live[:, 0], kind="stable")]
        place = np.arange(len(live)) - np.searchsorted(live[:, 0], live[:, 0])
        step = x[live[:, 0]] - x[live[:, 1]]
        slot[live[:, 0], place], away[live[:, 0], place], since[live[:, 0], place] = live[:, 1], np.einsum("ij,ij->i", step, step), live[:, 2]
        held += np.bincount(live[:, 0], minlength=n)
    place = np.arange(len(source)) - np.searchsorted(source, source)  # sources rise
    slot[source, place], away[source, place], since[source, place] = target, gap, version[source]
    held += np.bincount(source, minlength=n)
    order = np.lexsort((source, target))
    source, target, gap = source[order], target[order], gap[order]
    turn = np.arange(len(target)) - np.searchsorted(target, target)  # of a vertex' events
    by_turn = np.argsort(turn, kind="stable")
    ends = np.append(np.searchsorted(turn[by_turn], np.arange(turn.max() + 1)), len(turn)) if len(turn) else np.zeros(1, int)
    for a, b in zip(ends, ends[1:], strict=False):
        at = by_turn[a:b]
        t, s = target[at], source[at]
        slot[t, held[t]], away[t, held[t]], since[t, held[t]] = s, gap[at], version[s]
        held[t] += 1
        over = held[t] > most
        for c in range(0, int(over.sum()), REPLAYED):
            u, now = t[over][c : c + REPLAYED], version[s[over][c : c + REPLAYED]]
            by = np.lexsort((slot[u], away[u]), axis=-1)
            found, dist, begin = (np.take_along_axis(z[u], by, axis=1) for z in (slot, away, since))
            keep = kept_of(x, found, dist, most, prune)
            row, place = np.nonzero(~keep & (begin < now[:, None]))
            closed.append(np.column_stack([u[row], found[row, place], begin[row, place], now[row] - 1]))
            by = np.argsort(~keep, axis=1, kind="stable")
            count = keep.sum(axis=1)
            gone = np.arange(most + 1)[None, :] >= count[:, None]
            found, dist, begin = (np.take_along_axis(z, by, axis=1) for z in (found, dist, begin))
            found[gone], dist[gone] = -1, np.inf
            slot[u], away[u], since[u], held[u] = found, dist, begin, count
    row, place = np.nonzero(np.arange(most + 1)[None, :] < held[:, None])
    live = np.column_stack([row, slot[row, place], since[row, place], np.full(len(row), OPEN)])
    return np.concatenate([*closed, live]).astype(np.int64)


class GrowingGraph:
    """A proximity graph that objects enter in order, with the life span of every edge.

    Candidates of an insertion are the ``ef`` nearest members, found by a walk over the graph or, with ``scan``, among all.
    Without ``labels`` only the lists are kept, so that nothing can be removed.
    """

    def __init__(self, vectors: np.ndarray, most: int, ef: int, prune: bool = True, scan: bool = False, labels: bool = True):
        self.vectors, self.most, self.ef, self.prune, self.scan, self.labels = vectors, most, ef, prune, scan, labels
        self.rows: dict[int, None] = {}  # in order
        self.out: dict[int, dict[int, int]] = {}  # open edges: target -> begin
        self.into: dict[int, set[int]] = {}  # their sources
        self.closed: list[tuple[int, int, int, int]] = []

    def candidates(self, row: int) -> tuple[np.ndarray, np.ndarray]:
        q = self.vectors[row]
        if self.scan or len(self.rows) <= self.ef:
            found = np.fromiter(self.rows, np.int64, len(self.rows))
            d = squared(self.vectors[found], q)
        else:
            best = walk(q, self.vectors, [next(iter(self.rows))], lambda u: list(self.out[u]), self.ef, Counters())
            found, d = np.array([r for _, r in best]), np.array([x for x, _ in best])
        order = np.lexsort((found, d))[: self.ef]
        return found[order], d[order]

    def pruned(self, row: int, found: np.ndarray, d: np.ndarray) -> list[int]:
        return (rng_prune(self.vectors[row], found, d, self.vectors, self.most) if self.prune else found[: self.most]).tolist()

    def pruned_each(self, rows: list[int], lists: list[list[int]], prune: bool = True) -> list[list[int]]:
        """``pruned`` for several rows, each with a list that is not sorted."""
        size = np.array([len(c) for c in lists])
        of, place = spread(np.zeros(len(rows), np.int64), size)
        at = np.fromiter(chain.from_iterable(lists), np.int64, len(of))
        gap = self.vectors[at] - self.vectors[np.array(rows)].take(of, axis=0)
        d = np.einsum("ij,ij->i", gap, gap)
        order = np.lexsort((at, d, of))
        found, dist = np.zeros((len(rows), size.max()), np.int64), np.full((len(rows), size.max()), -1.0)
        found[of, place], dist[of, place] = at[order], d[order]
        if not prune:
            return [f[: min(n, self.most)] for f, n in zip(found.tolist(), size.tolist(), strict=True)]
        bits = nearer(self.vectors, found, dist)
        words = np.zeros((*found.shape, -(-bits.shape[2] // 8) * 8), np.uint8)
        words[:, :, : bits.shape[2]] = bits
        words = words.view(np.uint64)
        if words.shape[2] == 1 and len(rows) >= MANY:
            return self.kept_many(found, size, words[:, :, 0])
        marks = words[:, :, 0].tolist()
        for j in range(1, words.shape[2]):
            marks = [[a | b << 64 * j for a, b in zip(one, more, strict=True)] for one, more in zip(marks, words[:, :, j].tolist(), strict=True)]
        out = []
        for f, mark, n in zip(found.tolist(), marks, size.tolist(), strict=True):
            kept, free = [], (1 << n) - 1
            while free and len(kept) < self.most:
                low = free & -free
                place = low.bit_length() - 1
                kept.append(f[place])
                free &= ~(mark[place] | low)
            out.append(kept)
        return out

    def kept_many(self, found: np.ndarray, size: np.ndarray, marks: np.ndarray) -> list[list[int]]:
        """Of lists by rising distance, of 64 places at most, what stays where each one kept drops those in its marks; the next of all lists at once."""
        free = ~np.uint64(0) >> (64 - size).astype(np.uint64)
        free[size == 0] = 0
        kept, held = np.zeros((len(found), self.most), np.int64), np.zeros(len(found), np.int64)
        live = np.flatnonzero(free)
        for j in range(self.most):
            now = free[live]
            low = now & (~now + np.uint64(1))
            place = np.frexp(low.astype(float))[1] - 1
            kept[live, j] = found[live, place]
            held[live] += 1
            now &= ~(marks[live, place] | low)
            free[live] = now
            live = live[now != 0]
        return [k[:n] for k, n in zip(kept.tolist(), held.tolist(), strict=True)]

    def trim(self, rows: list[int], versions: list[int]) -> None:
        if not rows:
            return
        for row, version, kept in zip(rows, versions, self.pruned_each(rows, [list(self.out[r]) for r in rows], self.prune), strict=True):
            if not self.labels:
                self.out[row] = dict.fromkeys(kept)
                continue
            keep = set(kept)
            for t in [t for t in self.out[row] if t not in keep]:
                self.close(row, t, version)

    def link(self, row: int, target: int, version: int) -> None:
        if target not in self.out[row]:
            self.out[row][target] = version
            self.into[target].add(row)

    def close(self, row: int, target: int, version: int) -> None:
        begin = self.out[row].pop(target)
        self.into[target].discard(row)
        if begin < version:
            self.closed.append((row, target, begin, version - 1))

    def insert(self, row: int, version: int) -> None:
        self.insert_each([row], [version], [self.pruned(row, *self.candidates(row)) if self.rows else []])

    def insert_each(self, rows: list[int], versions: list[int], nears: list[list[int]]) -> None:
        """An insertion in each of several graphs without a common vertex, given what the rows link to."""
        over, at = [], []
        for row, version, near in zip(rows, versions, nears, strict=True):
            self.out[row] = dict.fromkeys(near, version)
            if self.labels:
                self.into[row] = set(near)
                for t in near:
                    self.into[t].add(row)
            for t in near:
                targets = self.out[t]
                targets[row] = version
                if len(targets) > self.most:
                    over.append(t)
                    at.append(version)
            self.rows[row] = None
        self.trim(over, at)

    def scans(self, order: np.ndarray, block: int = 256) -> Iterator[list[int]]:
        """What each of the rows links to that enter a graph in this order, its candidates being the nearest of all before it; sought in blocks."""
        scan = Scan(self.vectors[order], self.ef)
        for a in range(0, len(order), block):
            b = min(len(order), a + block)
            lists = self.linked(order, a, scan.block(a, b))
            if b == len(order):
                scan = None  # a graph that waits for others holds its last lists alone
            yield from lists

    def linked(self, order: np.ndarray, first: int, candidates: list[np.ndarray]) -> list[list[int]]:
        """Of candidates (places in an order) of the rows from ``first`` on those that are kept."""
        out: list[list[int]] = [[] for _ in candidates]
        some, step = [i for i, c in enumerate(candidates) if len(c)], max(1, CANDIDATES // self.ef)
        for a in range(0, len(some), step):
            part = some[a : a + step]
            for i, near in zip(part, self.pruned_each(order[[first + i for i in part]].tolist(), [order[candidates[i]].tolist() for i in part], self.prune), strict=True):
                out[i] = near
        return out

    def remove(self, row: int, version: int) -> None:
        """Ends a vertex before ``version``; its neighbours are linked among one another instead."""
        lost = sorted(self.into[row])
        for t in list(self.out[row]):
            self.close(row, t, version)
        for s in lost:
            self.close(s, row, version)
        del self.rows[row]
        others = [(s, [t for t in {*self.out[s], *lost} if t != s]) for s in lost]
        others = [(s, c) for s, c in others if c]
        if not others:
            return
        for (s, _), kept in zip(others, self.pruned_each(*map(list, zip(*others, strict=True))), strict=True):
            for t in kept:
                self.link(s, t, version)
        over = [s for s, _ in others if len(self.out[s]) > self.most]
        self.trim(over, [version] * len(over))

    def live(self) -> list[tuple[int, int]]:
        return [(s, t) for s, ts in self.out.items() for t in ts]

    def edges(self) -> np.ndarray:
        """Rows ``src, dst, begin, end``."""
        live = [(s, t, b, OPEN) for s, ts in self.out.items() for t, b in ts.items()]
        return np.array(sorted(self.closed + live), np.int64).reshape(-1, 4)


def differing(first: tuple[np.ndarray, ...], second: tuple[np.ndarray, ...]) -> int:
    """In how many versions, summed over all pairs, only one of two sets of edges has a pair.

    A set is given by its changes: pair, version, and 1 (is there from then on) or -1; whatever comes goes again.
    """
    out, parts = 0, 1 + (len(first[0]) + len(second[0])) // COMPARED
    for k in range(parts):
        some = [tuple(c[of] for c in changes) for changes in (first, second) for of in [changes[0] % parts == k]]
        pair, version = (np.concatenate([a, b]) for a, b in zip(*(s[:2] for s in some), strict=True))
        order = np.lexsort((version, pair))
        steps = [np.concatenate([some[0][2], 0 * some[1][2]]), np.concatenate([0 * some[0][2], some[1][2]])]
        has = [np.cumsum(s[order], dtype=np.int64) > 0 for s in steps]
        out += int(((has[0] != has[1])[:-1] * np.diff(version[order].astype(np.int64))).sum())
    return out


def static_graph(vectors: np.ndarray, rows: np.ndarray, most: int, ef: int) -> np.ndarray:
    """A graph of the ``ef`` nearest members each, pruned, without insertion order; rows ``src, dst, begin, end``."""
    v, found = vectors[rows], []
    square = np.einsum("ij,ij->i", v, v)
    width = min(ef, len(rows) - 1)
    for a in range(0, len(rows), 256) if width > 0 else ():
        d = square[a : a + 256, None] + square[None, :] - 2 * (v[a : a + 256] @ v.T)
        d[np.arange(len(d)), np.arange(a, a + len(d))] = np.inf
        near = np.argpartition(d, width - 1, axis=1)[:, :width]
        gap = v[near] - v[a : a + 256, None, :]
        dist = np.einsum("ijk,ijk->ij", gap, gap)
        order = np.lexsort((near, dist), axis=-1)
        near, dist = np.take_along_axis(near, order, axis=1), np.take_along_axis(dist, order, axis=1)
        row, place = np.nonzero(kept_of(v, near, dist, most, True))
        found.append(np.column_stack([rows[row + a], rows[near[row, place]]]))
    pairs = np.concatenate(found) if found else np.zeros((0, 2), np.int64)
    pairs = np.unique(np.concatenate([pairs, pairs[:, ::-1]]), axis=0)
    return np.column_stack([pairs, np.zeros(len(pairs), np.int64), np.full(len(pairs), OPEN)])


def walk(q: np.ndarray, vectors: np.ndarray, seeds: Iterable[int], neighbours, ef: int, work: Counters, seen: set[int] | None = None) -> list[tuple[float, int]]:
    """The greedy search: the nearest open vertex is expanded until it is farther than the ef-th best.

    Returns pairs (squared distance, row) by rising distance; ``seen`` collects all rows met.
    """
    start = sorted(set(seeds))
    if not start:
        return []
    seen = set() if seen is None else seen
    seen.update(start)
    work.distances += len(start)
    frontier = list(zip(squared(vectors[start], q).tolist(), start, strict=True))
    heapq.heapify(frontier)
    best = [(-x, -r) for x, r in frontier]
    heapq.heapify(best)
    while len(best) > ef:
        heapq.heappop(best)
    while frontier:
        x, u = heapq.heappop(frontier)
        if len(best) >= ef and x > -best[0][0]:
            break
        work.hops += 1
        near = [v for v in neighbours(u) if v not in seen]
        if not near:
            continue
        seen.update(near)
        work.distances += len(near)
        gap = vectors[near] - q
        for d, v in zip(np.einsum("ij,ij->i", gap, gap).tolist(), near, strict=True):
            if len(best) < ef:
                heapq.heappush(best, (-d, -v))
                heapq.heappush(frontier, (d, v))
            elif (-d, -v) > best[0]:
                heapq.heapreplace(best, (-d, -v))
                heapq.heappush(frontier, (d, v))
    else:
        work.exhausted += 1
    return sorted((-x, -r) for x, r in best)


def spread(first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For runs of ``count`` places from ``first`` on: which run each place is of, and the place."""
    run = np.repeat(np.arange(len(count)), count)
    return run, np.arange(len(run)) + np.repeat(first - (np.cumsum(count) - count), count)


def first_of_each(query: np.ndarray, row: np.ndarray, table: np.ndarray, most: int) -> np.ndarray:
    """Which pairs (by rising query) are the first of their kind, at most ``most`` a query; ``table`` has a place for each query and row."""
    place, flat, at = np.arange(len(row)), table.reshape(-1), query * table.shape[1] + row
    flat[at[::-1].copy()] = place[::-1].copy()  # the last one written stays; without copies the order would be turned back
    keep = np.flatnonzero(flat[at] == place)
    kept = query[keep]
    return keep[np.arange(len(keep)) - np.searchsorted(kept, kept) < most]


def walk_many(q: np.ndarray, vectors: np.ndarray, seeds: list[list[int]], neighbours, ef: int, seen: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[Counters]]:
    """``walk`` for many queries at once, an expansion of each a round: rows and squared distances a query, in no order (-1 and infinite where none), and its work.

    ``neighbours(queries, rows)`` gives pairs (place among the queries, row) by rising place; ``seen`` (queries by rows) is filled.
    Which of equally distant rows stay at the edge of the width is open.
    """
    n = len(q)
    ef = min(ef, len(vectors))
    width = min(ef, 64)
    row, dist, fresh = np.full((n, width), -1), np.full((n, width), np.inf), np.zeros((n, width), bool)
    held, dropped, work = np.zeros(n, int), np.zeros(n, bool), np.zeros((4, n), int)
    limit = np.full(n, np.inf)  # the worst of a full width

    def add(query: np.ndarray, rows: np.ndarray) -> None:
        nonlocal row, dist, fresh, width
        new = ~seen[query, rows]
        query, rows = query[new], rows[new]
        if not len(rows):
            return
        seen[query, rows] = True
        gap = vectors[rows] - q[query]
        d = np.einsum("ij,ij->i", gap, gap)
        work[0] += np.bincount(query, minlength=n)
        near = d <= limit[query]  # the others cannot enter a full width
        query, rows, d = query[near], rows[near], d[near]
        if not len(rows):
            return
        count = np.bincount(query, minlength=n)
        if width < ef and (held + count).max() > width:
            more = min(ef, int((held + count).max()) * 2) - width
            row, dist, fresh = (np.concatenate([x, np.full((n, more), fill, x.dtype)], axis=1) for x, fill in ((row, -1), (dist, np.inf), (fresh, False)))
            width += more
        place = np.arange(len(rows)) - np.searchsorted(query, query)
        fits = (held + count)[query] <= width
        a, at = query[fits], (held[query] + place)[fits]
        row[a, at], dist[a, at], fresh[a, at] = rows[fits], d[fits], True
        over = np.flatnonzero(held + count > width)
        filled = np.flatnonzero((count > 0) & (held + count == ef))
        held[:] = np.minimum(held + count, width)
        limit[filled] = dist[filled].max(axis=1) if width == ef else np.inf
        if not len(over):
            return
        for j in range(int(count[over].max())):  # each query's next one takes the place of its worst
            now = np.flatnonzero(~fits & (place == j))
            who = query[now]
            at = dist[who].argmax(axis=1)
            enters = d[now] < dist[who, at]
            dropped[who[~enters]] = True
            who, at, now = who[enters], at[enters], now[enters]
            dropped[who] |= fresh[who, at]
            row[who, at], dist[who, at], fresh[who, at] = rows[now], d[now], True
        limit[over] = dist[over].max(axis=1)

    start = [sorted(set(s)) for s in seeds]
    add(np.repeat(np.arange(n), [len(s) for s in start]), np.array([r for s in start for r in s], np.int64))
    active = np.flatnonzero(held)
    while len(active):
        whole = len(active) == n
        near = np.where(fresh if whole else fresh[active], dist if whole else dist[active], np.inf)
        at = near.argmin(axis=1)
        on = np.isfinite(near[np.arange(len(active)), at])
        work[2, active[~on & ~dropped[active]]] += 1
        active, at = active[on], at[on]
        if len(active):
            fresh[active, at] = False
            work[1, active] += 1
            place, rows, looked = neighbours(active, row[active, at])
            work[3, active] += looked
            add(active[place], rows)
    return row, dist, [Counters(distances=a, hops=b, exhausted=c, edges=d) for a, b, c, d in work.T.tolist()]


@dataclass
class Edges:
    """Edges by source and level (root first); ``start`` has a place for each vertex and level, and one more."""

    levels: int
    start: np.ndarray
    dst: np.ndarray
    begin: np.ndarray
    end: np.ndarray

    @staticmethod
    def of(n: int, rows: np.ndarray, levels: int = 1) -> Edges:
        """From rows ``level, src, dst, begin, end``."""
        rows = rows.reshape(-1, 5)
        order = np.lexsort((rows[:, 2], rows[:, 0], rows[:, 1]))
        place = rows[order, 1].astype(np.int64) * levels + rows[order, 0]
        return Edges(levels, np.searchsorted(place, np.arange(n * levels + 1)).astype(np.int32), *(np.ascontiguousarray(rows[order, k].astype(np.int32)) for k in (2, 3, 4)))

    def at(self, u: int, low: int = 0, high: int | None = None) -> slice:
        """Edges of ``u`` at levels from ``low`` to ``high``."""
        first = u * self.levels
        return slice(self.start[first + low], self.start[first + (self.levels if high is None else high + 1)])

    @staticmethod
    def merged(n: int, parts: list[tuple[np.ndarray, ...]]) -> Edges:
        """From the levels' arrays ``src, dst, begin, end``, each by rising src."""
        levels = len(parts)
        count = np.zeros((n, levels), np.int64)
        for j, (src, *_) in enumerate(parts):
            count[:, j] = np.bincount(src, minlength=n)
        start = np.concatenate([[0], np.cumsum(count)])
        out = [np.empty(start[-1], np.int32) for _ in range(3)]
        for j, (src, *columns) in enumerate(parts):
            at = start[src.astype(np.int64) * levels + j] + np.arange(len(src)) - np.searchsorted(src, src)
            for o, c in zip(out, columns, strict=True):
                o[at] = c
        return Edges(levels, start.astype(np.int32 if start[-1] < 2**31 else np.int64), *out)

    def packed(self) -> bytes:
        """Level count, sizes, and the arrays."""
        return np.array([self.levels, len(self.start), self.start.itemsize], "<i8").tobytes() + b"".join(a.tobytes() for a in (self.start, self.dst, self.begin, self.end))

    @staticmethod
    def unpacked(data: bytes) -> Edges:
        levels, n, size = np.frombuffer(data, "<i8", 3).tolist()
        start = np.frombuffer(data, f"<i{size}", n, 24)
        m = (len(data) - 24 - n * size) // 12
        return Edges(levels, start, *(np.frombuffer(data, "<i4", m, 24 + n * size + 4 * m * k) for k in range(3)))

    def rows(self) -> np.ndarray:
        place = np.repeat(np.arange(len(self.start) - 1), np.diff(self.start))
        return np.column_stack([place % self.levels, place // self.levels, self.dst, self.begin, self.end])

    def parts(self, most: int) -> Iterator[np.ndarray]:
        """``rows``, some at a time."""
        for a in range(0, len(self.dst), most):
            b = min(len(self.dst), a + most)
            place = np.searchsorted(self.start, np.arange(a, b), side="right") - 1
            yield np.column_stack([place % self.levels, place // self.levels, self.dst[a:b], self.begin[a:b], self.end[a:b]])

    def crowded(self, most: int) -> int:
        """How many vertices of a level have over ``most`` edges at a version where one of theirs begins, each such version for itself."""
        place = np.repeat(np.arange(len(self.start) - 1, dtype=np.int64), np.diff(self.start)) << 32
        begin, end = np.sort(place + self.begin), np.sort(place + self.end)
        at = np.unique(begin)
        return int((np.searchsorted(begin, at, side="right") - np.searchsorted(end, at) > most).sum())

    @property
    def count(self) -> int:
        return len(self.dst)

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.start, self.dst, self.begin, self.end))


@dataclass
class Shard:
    """Objects of a worker: ids, vectors, interval ends; ``tie`` orders insertions of one version (the ids, or the order of arrival)."""

    ids: np.ndarray
    vectors: np.ndarray
    left: np.ndarray
    right: np.ndarray
    tie: np.ndarray | None = None

    def __post_init__(self):
        if self.tie is None:
            self.tie = self.ids

    def __len__(self) -> int:
        return len(self.ids)

    def take(self, rows: np.ndarray) -> Shard:
        return Shard(self.ids[rows], self.vectors[rows], self.left[rows], self.right[rows], self.tie[rows])


def ranked(ids: np.ndarray, distance: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((ids, distance))[:k]
    return ids[order], distance[order]
