"""Search methods over a worker's shard: the versioned tree of graphs with its storage variants, and the baselines.

Every method has ``build`` and ``search``; ``search`` takes a vector, an interval, a mask, k and the
walk's width, and returns rows by rising distance with the work done.  The mechanics of the
baselines follow general knowledge of each kind and are simplified; none approximates a mask it
is not made for: it refuses it.
"""

from __future__ import annotations

import math
import time
from array import array
from bisect import bisect_right
from collections.abc import Iterable
from copy import copy

import numpy as np

from rangeann.functions.predicates import ORIENTATIONS, Box, atomic_plan, atoms_of, plan
from rangeann.functions.tree import cover, height_of, span
from rangeann.plans.kernel import OPEN, Counters, Edges, GrowingGraph, Shard, first_of_each, grow, spread, squared, static_graph, walk, walk_many

SMALL = 16  # members up to which a node is scanned and has no graph
BUCKETS = 4096  # leaves of a tree at most; more key values share leaves
CHECKED = 4096  # members whose distances a check computes at once
TOGETHER = 4_194_304  # marks of met rows, a query and object each, that searches of many queries hold at once
HUBS = 32  # one vertex in so many is in the next hub level

Found = tuple[np.ndarray, np.ndarray, Counters]  # rows, squared distances, work


def qualifies(mask: int, left: np.ndarray, right: np.ndarray, lq, rq) -> np.ndarray:
    """Which intervals meet the mask; ends of queries may be arrays that broadcast against theirs."""
    out = np.zeros(np.broadcast_shapes(np.shape(left), np.shape(lq)), bool)
    for a in atoms_of(mask):
        out |= {1: (left <= lq) & (lq <= right) & (right <= rq), 2: (left <= lq) & (rq <= right), 3: (lq <= left) & (left <= rq) & (rq <= right), 4: (lq <= left) & (right <= rq)}[a]
    return out


class Method:
    name = ""
    masks: tuple[int, ...] = tuple(range(1, 16))
    point_objects = point_queries = False
    filters = True  # the mask holds

    def __init__(self, m: int = 16, ef_con: int = 100, **options):
        self.m, self.ef_con, self.options = m, ef_con, options
        self.build_s = 0.0

    def build(self, shard: Shard) -> Method:
        start = time.perf_counter()
        self.shard = shard
        self.prepare()
        self.build_s = time.perf_counter() - start
        return self

    def prepare(self) -> None:
        raise NotImplementedError

    def admit(self, mask: int, lq, rq) -> None:
        if mask not in self.masks:
            raise ValueError(f"{self.name} answers masks {self.masks}, not {mask}")
        if self.point_queries and lq != rq:
            raise ValueError(f"{self.name} answers queries of one point only")
        if self.point_objects and (self.shard.left != self.shard.right).any():
            raise ValueError(f"{self.name} holds points, not intervals")

    def search(self, q: np.ndarray, lq, rq, mask: int, k: int, ef: int) -> Found:
        self.admit(mask, lq, rq)
        return self.find(q, lq, rq, mask, k, ef)

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        raise NotImplementedError

    def search_many(self, asked: list[tuple], mask: int, k: int, ef: int) -> list[Found]:
        """``search`` for queries ``(vector, lq, rq)``, in blocks whose marks are bounded."""
        for _, lq, rq in asked:
            self.admit(mask, lq, rq)
        step = block_of(len(self.shard))
        return [f for a in range(0, len(asked), step) for f in self.find_many(asked[a : a + step], mask, k, ef)]

    def find_many(self, asked: list[tuple], mask: int, k: int, ef: int) -> list[Found]:
        return [self.find(q, lq, rq, mask, k, ef) for q, lq, rq in asked]

    def top(self, pairs: Iterable[tuple[float, int]], k: int, work: Counters) -> Found:
        pairs = sorted(set(pairs), key=lambda p: (p[0], self.shard.ids[p[1]]))[:k]
        return np.array([r for _, r in pairs], np.int64), np.array([d for d, _ in pairs]), work

    @property
    def size(self) -> int:
        """Bytes besides ids and vectors."""
        return sum(e.nbytes for e in self.graphs())

    @property
    def edge_count(self) -> int:
        return sum(e.count for e in self.graphs())

    def graphs(self) -> list[Edges]:
        return []


def block_of(n: int) -> int:
    """How many queries a search over so many objects takes at once."""
    return max(1, min(512, TOGETHER // max(1, n)))


def columns(asked: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Vectors and, as columns, the ends of queries."""
    return np.array([q for q, _, _ in asked], float), np.array([a for _, a, _ in asked])[:, None], np.array([b for _, _, b in asked])[:, None]


def pairs_of(row: np.ndarray, dist: np.ndarray) -> list[tuple[float, int]]:
    """A query's answers of ``walk_many`` by rising distance."""
    held = np.flatnonzero(row >= 0)
    order = held[np.lexsort((row[held], dist[held]))]
    return list(zip(dist[order].tolist(), row[order].tolist(), strict=True))


def grown(shard: Shard, rows: Iterable[int], m: int, ef: int, prune: bool = True) -> np.ndarray:
    """Rows ``level 0, src, dst, begin, end`` of a graph without versions."""
    rows = np.fromiter(rows, np.int64)
    e = grow(shard.vectors[rows], np.zeros(len(rows), np.int64), np.array([0, len(rows)]), m, ef, prune)
    e = e[e[:, 3] == OPEN]
    return np.column_stack([np.zeros(len(e), np.int64), rows[e[:, 0]], rows[e[:, 1]], e[:, 2:]])


def open_neighbours(e: Edges):
    return lambda u: e.dst[e.at(u)].tolist()


class Exact(Method):
    """Filter, then all distances."""

    name = "pre_filter"

    def prepare(self) -> None:
        pass

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s = self.shard
        rows = np.flatnonzero(qualifies(mask, s.left, s.right, lq, rq))
        d = squared(s.vectors[rows], q)
        order = np.lexsort((s.ids[rows], d))[:k]
        return rows[order], d[order], Counters(distances=len(rows))


# --- the versioned tree of graphs -------------------------------------------------------


class Domain:
    """Versions and keys of one orientation: ranks of the different version values in order of insertion, and the tree's leaves.

    A leaf is a key value or, beyond ``buckets`` of them, a range of about equally many objects; ``low`` and ``high`` are its least
    and greatest key.  Given ``cuts`` (of an index that grows) leaves keep their least keys, and later values fall into them.
    """

    def __init__(self, shard: Shard, orient: str, buckets: int = BUCKETS, cuts: np.ndarray | None = None):
        attribute, self.sign, key = ORIENTATIONS[orient]
        self.orient = orient
        of = {"l": shard.left, "r": shard.right}
        self.keys = of[key]
        self.versions, rank = np.unique(self.sign * of[attribute], return_inverse=True)
        self.version = rank + 1
        if cuts is None:
            cuts = np.unique(self.keys)
            if len(cuts) > buckets:
                cuts = np.unique(np.sort(self.keys)[np.arange(buckets) * len(self.keys) // buckets])
        self.cuts = cuts
        self.leaf = np.maximum(np.searchsorted(cuts, self.keys, side="right"), 1)
        self.height = height_of(len(cuts))
        self.low, self.high = cuts.copy(), cuts.copy()
        np.minimum.at(self.low, self.leaf - 1, self.keys)
        np.maximum.at(self.high, self.leaf - 1, self.keys)

    def version_at(self, bound, strict: bool) -> int:
        """The last version that a bound admits."""
        return int(np.searchsorted(self.versions, self.sign * bound, side="left" if strict else "right"))

    def leaves(self, low, high, low_strict: bool, high_strict: bool) -> tuple[int, int, list[int]]:
        """First and last leaf that lie wholly within a key interval (None: open), and the leaves that it cuts."""
        first = 1 if low is None else int(np.searchsorted(self.low, low, side="right" if low_strict else "left")) + 1
        last = len(self.cuts) if high is None else int(np.searchsorted(self.high, high, side="left" if high_strict else "right"))
        begins = 1 if low is None else int(np.searchsorted(self.high, low, side="right" if low_strict else "left")) + 1
        ends = len(self.cuts) if high is None else int(np.searchsorted(self.low, high, side="left" if high_strict else "right"))
        return first, last, sorted({k for k in (begins, ends) if begins <= k <= ends and not first <= k <= last})

    def part(self, rows: np.ndarray) -> Domain:
        """The same versions and leaves with some of the objects."""
        out = copy(self)
        out.keys, out.version, out.leaf = self.keys[rows], self.version[rows], self.leaf[rows]
        return out

    def node(self, level: int) -> np.ndarray:
        return (self.leaf - 1) >> (self.height - level)


def level_edges(shard: Shard, domain: Domain, level: int, m: int, ef_con: int, small: int = SMALL, graph: str = "grown", fresh: np.ndarray | None = None, old: np.ndarray | None = None) -> np.ndarray:
    """Rows ``level, src, dst, begin, end`` of all graphs of one level of the tree.

    ``graph`` is "grown" (labelled insertion), "walked" (the same with candidates by a walk), or "static_rng" (no insertions: made anew
    for each of a few spans of versions).  Where the rows ``old`` hold all but the objects marked ``fresh``, which come last, only those are inserted.
    """
    version, node = domain.version, domain.node(level)
    order = np.lexsort((shard.tie, version, node))
    begins = np.flatnonzero(np.diff(node[order], prepend=-1))
    sizes = np.diff(np.append(begins, len(order)))
    wanted = sizes > small
    if not wanted.any():
        return np.zeros((0, 5), np.int64)
    if graph != "grown":
        parts = [(walked if graph == "walked" else rebuilt)(shard, order[a : a + n], version, m, ef_con) for a, n in zip(begins[wanted], sizes[wanted], strict=True)]
        e = np.concatenate(parts)
        return np.column_stack([np.full(len(e), level), e])
    members = order[np.repeat(wanted, sizes)]
    cuts = np.concatenate([[0], np.cumsum(sizes[wanted])])
    start = None
    if old is not None:
        before = np.add.reduceat((~fresh[members]).astype(np.int64), cuts[:-1])  # members that are not fresh
        start = cuts[:-1] + np.where(before > small, before, 0)  # a node that outgrows scanning begins from nothing
        place = np.empty(len(shard), np.int64)
        place[members] = np.arange(len(members))
        old = np.column_stack([place[old[:, 1]], place[old[:, 2]], old[:, 3:]]) if len(old) else np.zeros((0, 4), np.int64)
    e = grow(shard.vectors[members], version[members], cuts, m, ef_con, fresh=start, old=old)
    return np.column_stack([np.full(len(e), level), members[e[:, 0]], members[e[:, 1]], e[:, 2:]])


def walked(shard: Shard, members: np.ndarray, version: np.ndarray, m: int, ef_con: int, scan: bool = False) -> np.ndarray:
    """A node's graph by one insertion after the other."""
    g = GrowingGraph(shard.vectors, m, ef_con, scan=scan)
    for r in members.tolist():
        g.insert(r, int(version[r]))
    return g.edges()


def seen_edges(shard: Shard, domain: Domain, level: int, m: int, ef_con: int) -> tuple[np.ndarray, ...]:
    """Changes, as ``differing`` takes them, of what the lists of one level hold at the end of each version, by single insertions; their labels are not read.

    Nodes share no vertex, so each of them takes its next object in the same round.  As in ``grow``, vertices are numbered as they come, and of equally distant ones the first is the nearer.
    """
    version, node, n = domain.version, domain.node(level), len(shard)
    order = np.lexsort((shard.tie, version, node))
    parts = sorted(np.split(np.arange(n), np.flatnonzero(np.diff(node[order])) + 1), key=len, reverse=True)
    g = GrowingGraph(shard.vectors[order], m, ef_con, scan=True, labels=False)
    nears = [g.scans(p) for p in parts]
    rows, versions = [p.tolist() for p in parts], [[*version[order[p]].tolist(), 0] for p in parts]
    touched: list[set[int]] = [set() for _ in parts]
    before: dict[int, tuple[int, ...]] = {}
    pair, runs = array("q"), []

    some = len(parts)
    for i in range(len(rows[0])):
        while len(rows[some - 1]) <= i:
            some -= 1
        near = [next(f) for f in nears[:some]]
        g.insert_each([r[i] for r in rows[:some]], [v[i] for v in versions[:some]], near)
        for k in range(some):
            touched[k].add(rows[k][i])
            touched[k].update(near[k])
            v = versions[k][i]
            if versions[k][i + 1] != v:
                come, gone = [], []
                for u in touched[k]:
                    old, now = before.get(u, ()), tuple(g.out[u])
                    if old != now:
                        before[u], first = now, u * n
                        come += [first + t for t in now if t not in old]
                        gone += [first + t for t in old if t not in now]
                for changes, sign in ((come, 1), (gone, -1)):
                    pair.extend(changes)
                    runs.append((v, sign, len(changes)))
                touched[k].clear()
    left = [u * n + t for u, targets in before.items() for t in targets]
    pair.extend(left)
    at, step, count = np.array([*runs, (len(domain.versions) + 1, -1, len(left))]).T
    source, target = np.divmod(np.frombuffer(pair, np.int64), n)
    return order[source] * n + order[target], np.repeat(at.astype(np.int32), count), np.repeat(step.astype(np.int8), count)


def label_changes(e: np.ndarray, n: int, last: int) -> tuple[np.ndarray, ...]:
    """Changes, as ``differing`` takes them, that the labels of rows ``level, src, dst, begin, end`` state up to a last version."""
    e = e[(e[:, 3] <= e[:, 4]) & (e[:, 3] <= last)]
    pair, one = e[:, 1] * n + e[:, 2], np.ones(len(e), np.int8)
    return np.concatenate([pair, pair]), np.concatenate([e[:, 3], np.minimum(e[:, 4], last) + 1]).astype(np.int32), np.concatenate([one, -one])


def rebuilt(shard: Shard, members: np.ndarray, version: np.ndarray, m: int, ef_con: int, spans: int = 8) -> np.ndarray:
    """A node's graphs by a builder that cannot insert: one for each span of its versions, over all that is born by the span's end."""
    born = version[members]
    ends = np.unique(born[np.linspace(0, len(born) - 1, spans + 1).astype(int)[1:]])
    found = []
    for k, end in enumerate(ends):
        e = static_graph(shard.vectors, members[born <= end], m, ef_con)
        first = 0 if k == 0 else ends[k - 1] + 1
        begin = np.maximum(first, np.maximum(version[e[:, 0]], version[e[:, 1]]))
        found.append(np.column_stack([e[:, :2], begin, np.full(len(e), OPEN if k == len(ends) - 1 else end)]))
    return np.concatenate(found)


def hub_level(ids: np.ndarray) -> np.ndarray:
    """In how many hub levels an object is: geometric, by a hash of its id."""
    h = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    share = ((h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(11)).astype(np.float64) / 2**53
    return np.floor(np.log(np.maximum(share, 1e-18)) / -math.log(HUBS)).astype(int)


class SharedTree:
    """The tree by path copying: an insertion touches the nodes of one path; at the end of a version each touched node gets a new copy of its graph, all others stay shared.

    Made by single insertions, without labels.  ``copies`` has for each node (level, number) its copies: version and edges.
    """

    def __init__(self, shard: Shard, domain: Domain, m: int, ef_con: int):
        self.copies: dict[tuple[int, int], list[tuple[int, list[tuple[int, int]]]]] = {}
        self.nodes = np.stack([domain.node(j) for j in range(domain.height + 1)])
        graphs: dict[tuple[int, int], GrowingGraph] = {}
        order = np.lexsort((shard.tie, domain.version))
        for v in np.unique(domain.version).tolist():
            touched = set()
            for r in order[domain.version[order] == v].tolist():
                for path in enumerate(self.nodes[:, r].tolist()):
                    graphs.setdefault(path, GrowingGraph(shard.vectors, m, ef_con, scan=True)).insert(r, v)
                    touched.add(path)
            for path in touched:
                self.copies.setdefault(path, []).append((v, graphs[path].live()))

    def rows(self) -> np.ndarray:
        """Rows ``level, src, dst, begin, end``: a copy's edges from its version to the one before its node's next copy."""
        out = []
        for (level, _), copies in self.copies.items():
            for (v, e), nxt in zip(copies, [v for v, _ in copies[1:]] + [None], strict=True):
                out += [(level, s, t, v, OPEN if nxt is None else nxt - 1) for s, t in e]
        return np.array(out, np.int64).reshape(-1, 5)


def snapshots(shard: Shard, orient: str, m: int, ef_con: int, buckets: int = BUCKETS) -> np.ndarray:
    """A whole tree for each recorded version, built from that version's objects alone; rows ``level, src, dst, begin, end``."""
    whole = Domain(shard, orient, buckets)
    out = [np.zeros((0, 5), np.int64)]
    stamps = np.unique(whole.version).tolist()
    for v, nxt in zip(stamps, [*stamps[1:], None], strict=True):
        keep = np.flatnonzero(whole.version <= v)
        part = shard.take(keep)
        domain = Domain(part, orient, buckets, whole.cuts)
        for j in range(domain.height + 1):
            e = level_edges(part, domain, j, m, ef_con, 0)
            e = e[e[:, 4] == OPEN]
            out.append(np.column_stack([e[:, 0], keep[e[:, 1]], keep[e[:, 2]], np.full(len(e), v), np.full(len(e), OPEN if nxt is None else nxt - 1)]))
    return np.concatenate(out)


def margin(d: float) -> float:
    """A squared distance with room for the order in which its parts are added."""
    return d * (1 + 1e-9)


class Oriented:
    """One orientation of the tree, ready for searching: its edges, and each level's members by node and birth.

    Nothing in a search is linear in the objects: nodes are found by binary search among a level's members, the first
    of which is its entry; how many of them a version has is another binary search.
    """

    def __init__(self, shard: Shard, domain: Domain, edges: Edges, m: int, small: int = SMALL, hubs: list | None = None):
        self.shard, self.domain, self.edges, self.m, self.small, self.hubs = shard, domain, edges, m, small, hubs or []
        self.version, self.keys, self.height = domain.version, domain.keys, domain.height
        born = np.lexsort((shard.tie, self.version))
        self.members, self.nodes, self.births = [], [], []
        for j in range(self.height + 1):
            node = domain.node(j)[born]
            order = np.argsort(node, kind="stable")
            self.members.append(born[order])
            self.nodes.append(node[order])
            self.births.append(self.version[born[order]])

    def bounds(self, box: Box, lq, rq) -> tuple:
        """The box's version, the cover of its whole leaves, the leaves that it cuts, and its key interval as a test."""
        ends = {"lq": lq, "rq": rq}
        d = self.domain
        x = len(d.versions) if box.version is None else d.version_at(ends[box.version], box.version_strict)
        low, high = (None if e is None else ends[e] for e in (box.low, box.high))
        first, last, cut = d.leaves(low, high, box.low_strict, box.high_strict)
        nodes = [n for n in cover(first, last, self.height)] if first <= last else []
        return x, nodes, [(1 << self.height) + k - 1 for k in cut], (low, high, box.low_strict, box.high_strict)

    def alive(self, node: int, x: int) -> np.ndarray:
        """A node's members at a version, first-born first."""
        level = node.bit_length() - 1
        a, b = np.searchsorted(self.nodes[level], [node - (1 << level), node - (1 << level) + 1])
        return self.members[level][a : a + np.searchsorted(self.births[level][a:b], x, side="right")]

    def inside(self, rows: np.ndarray, interval: tuple) -> np.ndarray:
        low, high, low_strict, high_strict = interval
        k = self.keys[rows]
        fine = np.ones(len(rows), bool)
        if low is not None:
            fine &= (k > low) if low_strict else (k >= low)
        if high is not None:
            fine &= (k < high) if high_strict else (k <= high)
        return fine

    def find(self, q: np.ndarray, x: int, nodes: list[int], cut: list[int], interval: tuple, k: int, ef: int, mode: str = "layered", exact_below: int = 0, residual: np.ndarray | None = None, check: bool = False) -> tuple[list[tuple[float, int]], Counters]:
        """Rows by rising distance; with ``residual`` (a mark for each object) the walk passes all members and is widened until k marked ones are found.

        With ``check`` the walk's answers are a bound, and what of the qualifying members they miss within it is added, in no order.
        """
        work, s, e = Counters(), self.shard, self.edges
        held = [(n, self.alive(n, x)) for n in nodes]
        held = [(n, rows) for n, rows in held if len(rows)]
        for n in cut:
            rows = self.alive(n, x)
            rows = rows[self.inside(rows, interval)]
            if len(rows):
                held.append((n, rows))
        total = sum(len(rows) for _, rows in held)
        if not total:
            return [], work
        if total <= exact_below:
            rows = np.concatenate([rows for _, rows in held])
            rows = rows if residual is None else rows[residual[rows]]
            work.distances += len(rows)
            return sorted(zip(squared(s.vectors[rows], q).tolist(), rows.tolist(), strict=True))[: max(k, ef)], work
        held.sort(key=lambda h: span(h[0], self.height))
        starts, levels = [span(n, self.height)[0] for n, _ in held], [n.bit_length() - 1 for n, _ in held]
        leaf, m, layered = self.domain.leaf, self.m, mode == "layered"
        whole = set(nodes)
        seeds: list[int] = []
        for n, rows in held:
            if n not in whole or len(rows) <= self.small:
                seeds += rows.tolist()
            else:
                seeds.append(self.descend(q, n, x, int(rows[0]), work) if self.hubs else int(rows[0]))

        def neighbours(u: int) -> list[int]:
            level = levels[bisect_right(starts, leaf[u]) - 1]
            at = e.at(u, 0 if layered else level, level)
            dst = e.dst[at]
            work.edges += len(dst)
            dst = dst[(e.begin[at] <= x) & (e.end[at] >= x)]
            dst = dst[self.inside(dst, interval)]
            return list(dict.fromkeys(dst.tolist()))[:m]

        width = max(k, ef)
        while True:
            seen: set[int] = set()
            ended = work.exhausted
            best = walk(q, s.vectors, seeds, neighbours, width, work, seen)
            marked = best if residual is None else [(d, r) for d, r in best if residual[r]]
            if residual is None or check or len(marked) >= k or work.exhausted > ended or width >= total:
                break
            width *= 2
        met = np.fromiter(seen, np.int64, len(seen))
        fine = self.inside(met, interval) & (self.version[met] <= x)
        work.unqualified += int((~fine).sum())
        if work.exhausted > ended:
            work.missed += total - int(fine.sum())
        if check:
            rows = np.concatenate([rows for _, rows in held])
            marked = self.checked(q, rows if residual is None else rows[residual[rows]], marked, k, work)
        return marked, work

    def find_many(self, q: np.ndarray, bounds: list[tuple], k: int, ef: int, mode: str = "layered") -> list[tuple[list[tuple[float, int]], Counters]]:
        """``find`` without further conditions for many queries of one box, which walk together."""
        n, s, e = len(q), self.shard, self.edges
        known: dict[tuple, list] = {}  # equal bounds have the same members
        for x, nodes, cut, interval in bounds:
            key = x, *nodes, None, *cut, interval
            if key not in known:
                own = [(v, True, self.alive(v, x)) for v in nodes]
                for v in cut:
                    rows = self.alive(v, x)
                    own.append((v, False, rows[self.inside(rows, interval)]))
                known[key] = sorted((h for h in own if len(h[2])), key=lambda h: span(h[0], self.height))
        held = [known[x, *nodes, None, *cut, interval] for x, nodes, cut, interval in bounds]
        extra = [Counters() for _ in held]  # of the way through hubs
        seeds: list[list[int]] = [[] for _ in held]
        for i, own in enumerate(held):
            for v, whole, rows in own:
                if not whole or len(rows) <= self.small:
                    seeds[i] += rows.tolist()
                else:
                    seeds[i].append(self.descend(q[i], v, bounds[i][0], int(rows[0]), extra[i]) if self.hubs else int(rows[0]))
        most = max(1, max(map(len, held), default=1))
        starts, level = np.full((n, most), np.iinfo(np.int64).max), np.zeros((n, most), np.int64)
        for i, own in enumerate(held):
            starts[i, : len(own)], level[i, : len(own)] = [span(v, self.height)[0] for v, _, _ in own], [v.bit_length() - 1 for v, _, _ in own]
        version = np.array([b[0] for b in bounds])
        low, high, low_strict, high_strict = (np.array([b[3][c] for b in bounds]) if bounds[0][3][c] is not None else None for c in range(4))
        low_strict, high_strict = bool(low_strict[0]), bool(high_strict[0])

        def inside(rows: np.ndarray, a, b) -> np.ndarray:
            return self.inside(rows, (a, b, low_strict, high_strict))

        seen, table = np.zeros((n, len(s)), bool), np.zeros((n, len(s)), np.int32)

        def neighbours(query: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            at = level[query, np.maximum((starts[query] <= self.domain.leaf[rows][:, None]).sum(axis=1) - 1, 0)]
            first = rows * e.levels
            a, b = e.start[first if mode == "layered" else first + at].astype(np.int64), e.start[first + at + 1].astype(np.int64)
            of, place = spread(a, b - a)
            dst, x = e.dst[place], version[query][of]
            fine = (e.begin[place] <= x) & (e.end[place] >= x)
            of, dst = of[fine], dst[fine]
            own = query[of]
            fine = inside(dst, None if low is None else low[own], None if high is None else high[own])
            of, dst = of[fine], dst[fine]
            keep = first_of_each(of, dst, table, self.m)
            return of[keep], dst[keep], b - a

        row, dist, work = walk_many(q, s.vectors, seeds, neighbours, max(k, ef), seen)
        met, rows = np.nonzero(seen)
        fine = inside(rows, None if low is None else low[met], None if high is None else high[met]) & (self.version[rows] <= version[met])
        count, good = np.bincount(met, minlength=n), np.bincount(met[fine], minlength=n)
        for i, w in enumerate(work):
            w.distances, w.hops = w.distances + extra[i].distances, w.hops + extra[i].hops
            w.unqualified = int(count[i] - good[i])
            if w.exhausted:
                w.missed = sum(len(rows) for _, _, rows in held[i]) - int(good[i])
            w.exhausted += extra[i].exhausted
        return [(pairs_of(row[i], dist[i]), work[i]) for i in range(n)]

    def checked(self, q: np.ndarray, rows: np.ndarray, found: list[tuple[float, int]], k: int, work: Counters) -> list[tuple[float, int]]:
        """``found`` (by rising distance) and all other ``rows`` that may be among the k nearest."""
        rest = rows[~np.isin(rows, np.array([r for _, r in found], np.int64))]
        work.distances += len(rest)
        near = np.array([d for d, _ in found[:k]])
        out = list(found)
        for a in range(0, len(rest), CHECKED):
            part = rest[a : a + CHECKED]
            d = squared(self.shard.vectors[part], q)
            fine = np.flatnonzero(d <= margin(near[k - 1])) if len(near) >= k else np.arange(len(part))
            out += zip(d[fine].tolist(), part[fine].tolist(), strict=True)
            near = np.sort(np.concatenate([near, d[fine]]))[:k]
        return out

    def descend(self, q: np.ndarray, node: int, x: int, entry: int, work: Counters) -> int:
        """A nearer entry to a node, by greedy steps through its hub graphs from the top."""
        level = node.bit_length() - 1
        for tree, rows, place in reversed(self.hubs):
            own = tree.alive(node, x)
            if not len(own):
                continue
            e = tree.edges

            def near(u: int, e=e) -> list[int]:
                at = e.at(u, level, level)
                return e.dst[at][(e.begin[at] <= x) & (e.end[at] >= x)].tolist()

            start = int(place[entry]) if place[entry] >= 0 else int(own[0])
            entry = int(rows[walk(q, tree.shard.vectors, [start], near, 1, work)[0][1]])
        return entry


def tree_edges(shard: Shard, domain: Domain, m: int, ef_con: int, small: int, graph: str = "grown") -> Edges:
    rows = np.concatenate([level_edges(shard, domain, j, m, ef_con, small, graph) for j in range(domain.height + 1)])
    return Edges.of(len(shard), rows, domain.height + 1)


def hub_trees(shard: Shard, domain: Domain, m: int, ef_con: int) -> list[tuple[Oriented, np.ndarray, np.ndarray]]:
    """The hub levels, lowest first: a tree over the objects in each, their rows, and each row's place among them (-1: none)."""
    level, out = hub_level(shard.ids), []
    for j in range(1, int(level.max(initial=0)) + 1):
        rows = np.flatnonzero(level >= j)
        part, own = shard.take(rows), domain.part(rows)
        place = np.full(len(shard), -1)
        place[rows] = np.arange(len(rows))
        out.append((Oriented(part, own, tree_edges(part, own, max(4, m // 2), ef_con, 0), m, 0), rows, place))
    return out


class VersionedTree(Method):
    """The tree of graphs, in up to three orientations; ``variant`` says how it is made and stored."""

    name = "vtg"

    def prepare(self) -> None:
        o, s = self.options, self.shard
        self.small = o.get("small", SMALL)
        self.orient: dict[str, Oriented] = {}
        variant, buckets = o.get("variant", "labelled"), o.get("buckets", BUCKETS)
        for name in o.get("orientations", ORIENTATIONS):
            domain = Domain(s, name, buckets)
            if variant != "labelled" and len(s) * len(domain.versions) > o.get("snapshot_limit", 400_000):
                raise ValueError(f"the {variant} variant is too large here; use the labelled one")
            if variant == "shared":
                edges = Edges.of(len(s), SharedTree(s, domain, self.m, self.ef_con).rows(), domain.height + 1)
            elif variant == "snapshot":
                edges = Edges.of(len(s), snapshots(s, name, self.m, self.ef_con, buckets), domain.height + 1)
            else:
                edges = tree_edges(s, domain, self.m, self.ef_con, self.small, o.get("graph", "grown"))
            hubs = hub_trees(s, domain, self.m, self.ef_con) if o.get("levels") == "hier" else None
            self.orient[name] = Oriented(s, domain, edges, self.m, self.small, hubs)

    def boxes(self, mask: int) -> list[Box]:
        return plan(mask)

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        o, work, found = self.options, Counters(), []
        for box in self.boxes(mask):
            tree = self.orient[box.orient]
            got, w = tree.find(q, *tree.bounds(box, lq, rq), k, ef, o.get("mode", "layered"), o.get("exact_below", 0))
            found += got
            for c in vars(work):
                setattr(work, c, getattr(work, c) + getattr(w, c))
        return self.top(found, k, work)

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        o = self.options
        if o.get("exact_below", 0):
            return super().find_many(asked, mask, k, ef)
        found, work = [[] for _ in asked], [Counters() for _ in asked]
        vectors = columns(asked)[0]
        for box in self.boxes(mask):
            tree = self.orient[box.orient]
            for i, (got, w) in enumerate(tree.find_many(vectors, [tree.bounds(box, lq, rq) for _, lq, rq in asked], k, ef, o.get("mode", "layered"))):
                found[i] += got
                for c in vars(w):
                    setattr(work[i], c, getattr(work[i], c) + getattr(w, c))
        return [self.top(f, k, w) for f, w in zip(found, work, strict=True)]

    def graphs(self) -> list[Edges]:
        return [e for t in self.orient.values() for e in (t.edges, *(h.edges for h, _, _ in t.hubs))]


class AtomicUnion(VersionedTree):
    """The same index, one search an atom."""

    name = "atomic_union"

    def boxes(self, mask: int) -> list[Box]:
        return atomic_plan(mask)


# --- baselines ---------------------------------------------------------------------------


class OneGraph(Method):
    """A graph over all objects."""

    degree = 1

    def prepare(self) -> None:
        order = np.argsort(self.shard.ids)
        most = self.m * self.degree
        self.edges = Edges.of(len(self.shard), grown(self.shard, order, most, max(self.ef_con, most), prune=self.degree == 1))
        self.entry = [int(order[0])] if len(order) else []

    def graphs(self) -> list[Edges]:
        return [self.edges]

    def open_many(self, query: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Neighbours for ``walk_many``."""
        first = self.edges.start[rows].astype(np.int64)
        of, place = spread(first, self.edges.start[rows + 1] - first)
        return of, self.edges.dst[place], np.zeros(len(rows), int)

    def walks(self, q: np.ndarray, ef: int) -> tuple[np.ndarray, np.ndarray, list[Counters]]:
        return walk_many(q, self.shard.vectors, [self.entry] * len(q), self.open_many, ef, np.zeros((len(q), len(self.shard)), bool))


class PlainGraph(OneGraph):
    """Unfiltered search: the mask is not looked at."""

    name, filters = "knn_ann", False

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        work = Counters()
        return self.top(walk(q, self.shard.vectors, self.entry, open_neighbours(self.edges), max(k, ef), work), k, work)


class PostFilter(OneGraph):
    """Search, filter, widen until k qualify or the width ends."""

    name = "post_filter"

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        s, (q, lq, rq) = self.shard, columns(asked)
        out: list[Found] = [None] * len(asked)
        work, left, width = [Counters() for _ in asked], np.arange(len(asked)), max(k, ef)
        while len(left):
            row, dist, more = self.walks(q[left], width)
            fine = (row >= 0) & qualifies(mask, s.left[row], s.right[row], lq[left], rq[left])
            last = width >= self.options.get("max_ef", 512)
            done = (fine.sum(axis=1) >= k) | last
            for i, at in enumerate(left.tolist()):
                for c in vars(more[i]):
                    setattr(work[at], c, getattr(work[at], c) + getattr(more[i], c))
                if done[i]:
                    work[at].unqualified += int((row[i] >= 0).sum() - fine[i].sum())
                    out[at] = self.top(zip(dist[i][fine[i]].tolist(), row[i][fine[i]].tolist(), strict=True), k, work[at])
            left, width = left[~done], width * self.options.get("widen", 2)
        return out

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work = self.shard, Counters()
        width = max(k, ef)
        while True:
            best = walk(q, s.vectors, self.entry, open_neighbours(self.edges), width, work)
            rows = np.array([r for _, r in best], np.int64)
            fine = qualifies(mask, s.left[rows], s.right[rows], lq, rq)
            got = [p for p, f in zip(best, fine.tolist(), strict=True) if f]
            if len(got) >= k or width >= self.options.get("max_ef", 512):
                work.unqualified += len(best) - len(got)
                return self.top(got, k, work)
            width *= self.options.get("widen", 2)


class DenseSubgraph(OneGraph):
    """A graph of gamma * m neighbours, of which only qualifying ones are visited, m a hop."""

    name = "dense_subgraph"

    def __init__(self, m: int = 16, ef_con: int = 100, gamma: int = 4, **options):
        super().__init__(m, ef_con, **options)
        self.degree = gamma

    def near(self, u: int, fine) -> list[int]:
        t = self.edges.dst[self.edges.at(u)]
        return t[fine(t)][: self.m].tolist()

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work = self.shard, Counters()
        fine = lambda rows: qualifies(mask, s.left[rows], s.right[rows], lq, rq)
        start = np.array(self.entry, np.int64)
        if not fine(start).any():
            start = np.flatnonzero(fine(slice(None)))[:1]
        return self.top(walk(q, s.vectors, start.tolist(), lambda u: self.near(u, fine), max(k, ef), work), k, work)

    def near_many(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each of some rows (by their places) what a walk may go to."""
        place, to, _ = self.open_many(rows, rows)
        return place, to

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        s, (q, lq, rq) = self.shard, columns(asked)
        fine = qualifies(mask, s.left, s.right, lq, rq)
        seeds = [self.entry if fine[i, self.entry].any() else np.flatnonzero(fine[i])[:1].tolist() for i in range(len(asked))]
        table = np.zeros(fine.shape, np.int32)

        def neighbours(query: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            of, to = self.near_many(rows)
            good = fine[query[of], to]
            of, to = of[good], to[good]
            keep = first_of_each(of, to, table, self.m)
            return of[keep], to[keep], np.zeros(len(rows), int)

        row, dist, work = walk_many(q, s.vectors, seeds, neighbours, max(k, ef), np.zeros(fine.shape, bool))
        return [self.top(pairs_of(row[i], dist[i]), k, w) for i, w in enumerate(work)]


class TwoHop(DenseSubgraph):
    """An ordinary graph whose neighbours' neighbours stand in for those that do not qualify."""

    name = "two_hop"

    def __init__(self, m: int = 16, ef_con: int = 100, **options):
        super().__init__(m, ef_con, gamma=1, **options)

    def near(self, u: int, fine) -> list[int]:
        e = self.edges
        one = e.dst[e.at(u)]
        t = np.concatenate([one, *(e.dst[e.at(v)] for v in one)])
        return [v for v in dict.fromkeys(t[fine(t)].tolist()) if v != u][: self.m]

    def near_many(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        of, one = super().near_many(rows)
        via, two = super().near_many(one)
        of, to = np.concatenate([of, of[via]]), np.concatenate([one, two])
        order = np.argsort(of, kind="stable")
        of, to = of[order], to[order]
        other = to != rows[of]
        return of[other], to[other]


def widened(search, fine, width: int, wanted: int, most: int, work: Counters) -> list[tuple[float, int]]:
    """What of a search's answers is fine, the width doubled until that is enough."""
    while True:
        best = search(width)
        got = [(d, r) for d, r in best if fine(r)]
        if len(got) >= wanted or width >= most:
            work.unqualified += len(best) - len(got)
            return got
        width *= 2


class SegmentedStore(Method):
    """Segments by rising l, a graph each; a segment is scanned if few of it qualify, else walked and filtered."""

    name = "segmented_store"

    def prepare(self) -> None:
        s = self.shard
        order = np.lexsort((s.ids, s.left))
        self.parts = np.array_split(order, max(1, -(-len(order) // self.options.get("seg_rows", 256)))) if len(order) else []
        cuts = np.cumsum([0, *map(len, self.parts)])
        e = grow(s.vectors[order], np.zeros(len(s), np.int64), cuts, self.m, self.ef_con)
        e = e[e[:, 3] == OPEN]
        self.edges = Edges.of(len(s), np.column_stack([np.zeros(len(e), np.int64), order[e[:, 0]], order[e[:, 1]], e[:, 2:]]))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work, found = self.shard, Counters(), []
        fine = qualifies(mask, s.left, s.right, lq, rq)  # the scalar index' bitmap
        for p in self.parts:
            rows = p[fine[p]]
            if len(rows) <= self.options.get("scan_share", 0.2) * len(p):
                work.distances += len(rows)
                found += zip(squared(s.vectors[rows], q).tolist(), rows.tolist(), strict=True)
            else:
                found += widened(lambda w: walk(q, s.vectors, [int(p[0])], open_neighbours(self.edges), w, work), lambda r: fine[r], max(k, 2 * ef), min(k, len(rows)), len(p), work)  # noqa: B023
        return self.top(found, k, work)

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        s, e, (q, lq, rq) = self.shard, self.edges, columns(asked)
        fine = qualifies(mask, s.left, s.right, lq, rq)
        found, work = [[] for _ in asked], [Counters() for _ in asked]

        def neighbours(query: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            first = e.start[rows].astype(np.int64)
            of, place = spread(first, e.start[rows + 1] - first)
            return of, e.dst[place], np.zeros(len(rows), int)

        for p in self.parts:
            count = fine[:, p].sum(axis=1)
            few = count <= self.options.get("scan_share", 0.2) * len(p)
            query, place = np.nonzero(fine[:, p] & few[:, None])
            gap = s.vectors[p[place]] - q[query]
            for i, d, r in zip(query.tolist(), np.einsum("ij,ij->i", gap, gap).tolist(), p[place].tolist(), strict=True):
                work[i].distances += 1
                found[i].append((d, r))
            left, width = np.flatnonzero(~few), max(k, 2 * ef)
            while len(left):
                row, dist, more = walk_many(q[left], s.vectors, [[int(p[0])]] * len(left), neighbours, width, np.zeros((len(left), len(s)), bool))
                good = (row >= 0) & fine[left[:, None], row]
                done = (good.sum(axis=1) >= np.minimum(k, count[left])) | (width >= len(p))
                for i, at in enumerate(left.tolist()):
                    for c in vars(more[i]):
                        setattr(work[at], c, getattr(work[at], c) + getattr(more[i], c))
                    if done[i]:
                        work[at].unqualified += int((row[i] >= 0).sum() - good[i].sum())
                        found[at] += zip(dist[i][good[i]].tolist(), row[i][good[i]].tolist(), strict=True)
                left, width = left[~done], width * 2
        return [self.top(f, k, w) for f, w in zip(found, work, strict=True)]

    def graphs(self) -> list[Edges]:
        return [self.edges]


class PointMethod(Method):
    """Baselines for objects of one point: mask {4}."""

    masks, point_objects = (8,), True

    def prepare(self) -> None:
        s = self.shard
        self.order = np.lexsort((s.ids, s.left))
        self.sorted = s.left[self.order]
        self.grow()

    def place(self, lq, rq) -> tuple[int, int]:
        return int(np.searchsorted(self.sorted, lq, side="left")), int(np.searchsorted(self.sorted, rq, side="right"))

    def grow(self) -> None:
        raise NotImplementedError


class PrefixCompressed(PointMethod):
    """Points enter by attribute; edges keep the span of prefixes they belong to; the left end is a filter on the walk.

    The variant with one pair of labels: prefixes are compressed, left ends are not.
    """

    name = "segment2d"

    def grow(self) -> None:
        o = self.order
        e = grow(self.shard.vectors[o], np.arange(1, len(o) + 1), np.array([0, len(o)]), self.m, self.ef_con)
        self.edges = Edges.of(len(o), np.column_stack([np.zeros(len(e), np.int64), o[e[:, 0]], o[e[:, 1]], e[:, 2:]]))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work, e = self.shard, Counters(), self.edges
        a, b = self.place(lq, rq)
        if a >= b:
            return self.top([], k, work)

        def near(u: int) -> list[int]:
            at = e.at(u)
            return e.dst[at][(e.begin[at] <= b) & (e.end[at] >= b)].tolist()

        seeds = [int(self.order[0]), int(self.order[a])]
        share = (b - a) / b  # of the prefix' members that the walk's answers are filtered to
        got = widened(lambda w: walk(q, s.vectors, seeds, near, w, work), lambda r: lq <= s.left[r] <= rq, int(max(k, ef) / share), min(k, b - a), b, work)
        return self.top(got, k, work)

    def graphs(self) -> list[Edges]:
        return [self.edges]


class SliceInclusive(PointMethod):
    """Slices of equal count; every vertex keeps neighbours in each; a query unites those of the slices it meets."""

    name = "slice_inclusive"

    def grow(self) -> None:
        s = self.shard
        self.slices = np.array_split(self.order, max(1, min(self.options.get("slices", 8), len(self.order) or 1)))
        each, rows = max(2, self.m // 2), []
        square = np.einsum("ij,ij->i", s.vectors, s.vectors)
        for j, part in enumerate(self.slices):
            for a in range(0, len(s) if len(part) else 0, 512):
                u = np.arange(a, min(a + 512, len(s)))
                d = square[u, None] + square[None, part] - 2 * (s.vectors[u] @ s.vectors[part].T)
                d[u[:, None] == part[None, :]] = np.inf
                n = min(each, len(part))
                near = np.argpartition(d, n - 1, axis=1)[:, :n]
                fine = np.isfinite(np.take_along_axis(d, near, axis=1))
                r, c = np.nonzero(fine)
                rows.append(np.column_stack([np.full(len(r), j), u[r], part[near[r, c]], np.zeros(len(r), np.int64), np.full(len(r), OPEN)]))
        self.edges = Edges.of(len(s), np.concatenate(rows) if rows else np.zeros((0, 5), np.int64), len(self.slices))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work, e = self.shard, Counters(), self.edges
        a, b = self.place(lq, rq)
        met = [j for j, p in enumerate(self.slices) if len(p) and s.left[p[0]] <= rq and s.left[p[-1]] >= lq]
        if not met or a >= b:
            return self.top([], k, work)
        near = lambda u: list(dict.fromkeys(e.dst[e.at(u, met[0], met[-1])].tolist()))  # noqa: E731  slices met are neighbours
        best = walk(q, s.vectors, [int(self.slices[j][0]) for j in met], near, max(k, ef), work)
        got = [(d, r) for d, r in best if lq <= s.left[r] <= rq]
        work.unqualified += len(best) - len(got)
        return self.top(got, k, work)

    def graphs(self) -> list[Edges]:
        return [self.edges]


class WindowPostFilter(PointMethod):
    """Half-overlapping windows of each length; the least one around the query is searched and filtered."""

    name = "window_postfilter"

    def grow(self) -> None:
        """For each length the windows one after the other: their objects, where each begins, and one graph of all."""
        n, self.lengths = len(self.order), []
        for j in range(max(1, n).bit_length() + 1):
            width = 1 << j
            if width < self.options.get("least", 16) and width < n:
                continue
            begins = np.arange(0, max(n - width // 2, 1), max(1, width // 2))
            parts = [self.order[a : a + width] for a in begins]
            cuts = np.cumsum([0, *map(len, parts)])
            rows = np.concatenate(parts) if parts else self.order
            e = grow(self.shard.vectors[rows], np.zeros(len(rows), np.int64), cuts, self.m, self.ef_con)
            e = e[e[:, 3] == OPEN]
            self.lengths.append((width, rows, cuts, self.shard.vectors[rows], Edges.of(len(rows), np.column_stack([np.zeros(len(e), np.int64), e]))))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work = self.shard, Counters()
        a, b = self.place(lq, rq)
        if a >= b:
            return self.top([], k, work)
        for width, rows, cuts, vectors, e in self.lengths:  # the shortest window around the query
            w = min(a // max(1, width // 2), len(cuts) - 2)
            if w * max(1, width // 2) <= a and b <= w * max(1, width // 2) + width:
                break
        size, width = cuts[w + 1] - cuts[w], max(k, ef)
        while True:
            best = [(d, int(rows[r])) for d, r in walk(q, vectors, [int(cuts[w])], open_neighbours(e), width, work)]
            got = [(d, r) for d, r in best if lq <= s.left[r] <= rq]
            if len(got) >= min(k, b - a) or width >= size:
                work.unqualified += len(best) - len(got)
                return self.top(got, k, work)
            width *= 2

    def graphs(self) -> list[Edges]:
        return [e for *_, e in self.lengths]


class TreeGraph(PointMethod):
    """The tree of graphs with a single version."""

    name = "tree_graph"

    def grow(self) -> None:
        s = self.shard
        flat = Shard(s.ids, s.vectors, np.zeros_like(s.left), s.right)
        domain, small = Domain(flat, "LU"), self.options.get("small", SMALL)
        self.tree = Oriented(flat, domain, tree_edges(flat, domain, self.m, self.ef_con, small), self.m, small)

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        best, work = self.tree.find(q, *self.tree.bounds(Box("LU", None, "lq", "rq"), lq, rq), k, ef)
        return self.top(best, k, work)

    def graphs(self) -> list[Edges]:
        return [self.tree.edges]


class StabGraph(Method):
    """One graph through time: objects enter at l and leave after r; a query reads the edges of its moment."""

    name, masks, point_queries = "stab_graph", (2,), True

    def prepare(self) -> None:
        s, g = self.shard, GrowingGraph(self.shard.vectors, self.m, self.ef_con, scan=True)
        self.values = np.unique(np.concatenate([s.left, s.right]))
        enter, leave = (np.searchsorted(self.values, x) + 1 for x in (s.left, s.right))
        todo = sorted([(int(v), 1, int(i), r) for r, (v, i) in enumerate(zip(enter, s.ids, strict=True))] + [(int(v) + 1, 0, int(i), r) for r, (v, i) in enumerate(zip(leave, s.ids, strict=True))])
        first: dict[int, int] = {}  # a live object at each value
        for v, enters, _, r in todo:
            g.insert(r, v) if enters else g.remove(r, v)
            first[v] = next(iter(g.rows), -1)
        at = np.searchsorted(list(first), np.arange(1, len(self.values) + 1), side="right") - 1
        self.first = np.array(list(first.values()), np.int64)[at] if first else np.zeros(0, np.int64)
        e = g.edges()
        self.edges = Edges.of(len(s), np.column_stack([np.zeros(len(e), np.int64), e]))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, e, work = self.shard, self.edges, Counters()
        x = int(np.searchsorted(self.values, lq, side="right"))
        seed = int(self.first[x - 1]) if x else -1
        if seed >= 0 and not s.left[seed] <= lq <= s.right[seed]:  # between two values
            live = np.flatnonzero((s.left <= lq) & (s.right >= lq))
            seed = int(live[0]) if len(live) else -1
        if seed < 0:
            return self.top([], k, work)

        def near(u: int) -> list[int]:
            at = e.at(u)
            t = e.dst[at][(e.begin[at] <= x) & (e.end[at] >= x)]
            work.edges += at.stop - at.start
            return t[(s.left[t] <= lq) & (s.right[t] >= lq)].tolist()

        return self.top(walk(q, s.vectors, [seed], near, max(k, ef), work), k, work)

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        s, e, (q, lq, _) = self.shard, self.edges, columns(asked)
        x = np.searchsorted(self.values, lq[:, 0], side="right")
        seeds = []
        for v, at in zip(x.tolist(), lq[:, 0], strict=True):
            seed = int(self.first[v - 1]) if v else -1
            if seed >= 0 and not s.left[seed] <= at <= s.right[seed]:  # between two values
                seed = int(next(iter(np.flatnonzero((s.left <= at) & (s.right >= at))), -1))
            seeds.append([seed] if seed >= 0 else [])

        def neighbours(query: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            first = e.start[rows].astype(np.int64)
            of, place = spread(first, e.start[rows + 1] - first)
            looked = np.bincount(of, minlength=len(rows))
            own = query[of]
            t = e.dst[place]
            fine = (e.begin[place] <= x[own]) & (e.end[place] >= x[own]) & (s.left[t] <= lq[own, 0]) & (s.right[t] >= lq[own, 0])
            return of[fine], t[fine], looked

        row, dist, work = walk_many(q, s.vectors, seeds, neighbours, max(k, ef), np.zeros((len(q), len(s)), bool))
        return [self.top(pairs_of(row[i], dist[i]), k, w) for i, w in enumerate(work)]

    def graphs(self) -> list[Edges]:
        return [self.edges]


class QuadGraph(Method):
    """Intervals as points of a plane in a quadtree, a graph a cell; cells inside the query are searched, leaves at its edge verified."""

    name, masks = "quad_graph", (8,)

    def prepare(self) -> None:
        s = self.shard
        self.values = np.unique(np.concatenate([s.left, s.right]))
        self.at = np.column_stack([np.searchsorted(self.values, s.left), np.searchsorted(self.values, s.right)])
        self.height = height_of(len(self.values))
        self.cells: dict[tuple[int, int, int], tuple[np.ndarray, bool]] = {}
        self.split(0, 0, 0, np.argsort(s.ids))
        rows = [np.zeros((0, 5), np.int64)]
        for level in range(self.height + 1):
            parts = [r for (j, _, _), (r, leaf) in self.cells.items() if j == level]
            if parts:
                order, cuts = np.concatenate(parts), np.cumsum([0, *map(len, parts)])
                e = grow(s.vectors[order], np.zeros(len(order), np.int64), cuts, self.m, self.ef_con)
                e = e[e[:, 3] == OPEN]
                rows.append(np.column_stack([np.full(len(e), level), order[e[:, 0]], order[e[:, 1]], e[:, 2:]]))
        self.edges = Edges.of(len(s), np.concatenate(rows), self.height + 1)

    def split(self, level: int, x: int, y: int, rows: np.ndarray) -> None:
        if not len(rows):
            return
        leaf = len(rows) <= self.options.get("leaf", 32) or level == self.height
        self.cells[level, x, y] = rows, leaf
        if not leaf:
            half = self.at[rows] >> (self.height - level - 1)
            for a in (2 * x, 2 * x + 1):
                for b in (2 * y, 2 * y + 1):
                    self.split(level + 1, a, b, rows[(half[:, 0] == a) & (half[:, 1] == b)])

    def cover(self, lq, rq) -> tuple[list[tuple[int, np.ndarray]], list[np.ndarray]]:
        """The cells inside a query (level and rows), and the leaves at its edge."""
        low, high = int(np.searchsorted(self.values, lq, side="left")), int(np.searchsorted(self.values, rq, side="right")) - 1
        inside, edge, todo = [], [], [(0, 0, 0)]
        while todo:
            level, x, y = todo.pop()
            if (level, x, y) not in self.cells:
                continue
            rows, leaf = self.cells[level, x, y]
            width = 1 << (self.height - level)
            if (x + 1) * width - 1 < low or y * width > high:
                continue
            if x * width >= low and (y + 1) * width - 1 <= high:
                inside.append((level, rows))
            elif leaf:
                edge.append(rows)
            else:
                todo += [(level + 1, a, b) for a in (2 * x, 2 * x + 1) for b in (2 * y, 2 * y + 1)]
        return inside, edge

    def verified(self, q, lq, rq, edge: list[np.ndarray], work: Counters) -> list[tuple[float, int]]:
        """What of the leaves at a query's edge is inside it."""
        if not edge:
            return []
        s, rows = self.shard, np.concatenate(edge)
        fine = (s.left[rows] >= lq) & (s.right[rows] <= rq)
        work.distances += len(rows)
        work.unqualified += int((~fine).sum())
        return list(zip(squared(s.vectors[rows[fine]], q).tolist(), rows[fine].tolist(), strict=True))

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, e, work = self.shard, self.edges, Counters()
        inside, edge = self.cover(lq, rq)
        found = self.verified(q, lq, rq, edge, work)
        for level, rows in inside:
            found += walk(q, s.vectors, [int(rows[0])], lambda u, j=level: e.dst[e.at(u, j, j)].tolist(), max(k, ef), work)
        return self.top(found, k, work)

    def find_many(self, asked, mask, k, ef) -> list[Found]:
        s, e, q = self.shard, self.edges, columns(asked)[0]
        found, work, cells, covers = [], [Counters() for _ in asked], [], {}
        for i, (v, lq, rq) in enumerate(asked):
            if (lq, rq) not in covers:
                covers[lq, rq] = self.cover(lq, rq)
            inside, edge = covers[lq, rq]
            found.append(self.verified(v, lq, rq, edge, work[i]))
            cells += [(i, level, int(rows[0])) for level, rows in inside]
        step = block_of(len(s))
        for a in range(0, len(cells), step):  # a walk for each query and cell
            of, level, first = (np.array(c) for c in zip(*cells[a : a + step], strict=True))

            def neighbours(query: np.ndarray, rows: np.ndarray, level=level) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
                at = rows * e.levels + level[query]
                start = e.start[at].astype(np.int64)
                run, place = spread(start, e.start[at + 1] - start)
                return run, e.dst[place], np.zeros(len(rows), int)

            row, dist, more = walk_many(q[of], s.vectors, first[:, None].tolist(), neighbours, max(k, ef), np.zeros((len(of), len(s)), bool))
            for i, r, d, w in zip(of.tolist(), row, dist, more, strict=True):
                found[i] += zip(d[r >= 0].tolist(), r[r >= 0].tolist(), strict=True)
                for c in vars(w):
                    setattr(work[i], c, getattr(work[i], c) + getattr(w, c))
        return [self.top(f, k, w) for f, w in zip(found, work, strict=True)]

    def graphs(self) -> list[Edges]:
        return [self.edges]


class OracleGraph(Method):
    """A graph made for the very objects that qualify: the best that any graph search could do."""

    name = "subset_graph"

    def prepare(self) -> None:
        self.made: dict = {}

    def find(self, q, lq, rq, mask, k, ef) -> Found:
        s, work = self.shard, Counters()
        rows = np.flatnonzero(qualifies(mask, s.left, s.right, lq, rq))
        rows = rows[np.argsort(s.ids[rows])]
        if not len(rows):
            return self.top([], k, work)
        key = hash(rows.tobytes())
        if key not in self.made:
            self.made[key] = Edges.of(len(s), grown(s, rows, self.m, self.ef_con))
        return self.top(walk(q, s.vectors, [int(rows[0])], open_neighbours(self.made[key]), max(k, ef), work), k, work)

    def graphs(self) -> list[Edges]:
        return list(self.made.values())


METHODS: dict[str, type[Method]] = {c.name: c for c in (Exact, VersionedTree, AtomicUnion, PlainGraph, PostFilter, DenseSubgraph, TwoHop, SegmentedStore, PrefixCompressed, SliceInclusive, WindowPostFilter, TreeGraph, StabGraph, QuadGraph, OracleGraph)}


def edge_bound(n: int, m: int, height: int) -> int:
    """The most directed edges that n insertions can create in all levels of one orientation."""
    return 2 * m * n * (height + 1)


def cover_bound(size: int) -> int:
    return max(1, 2 * math.ceil(math.log2(max(2, size))))


