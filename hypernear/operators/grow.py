"""Ball trees in one process: grown, annotated and walked on numpy arrays.

A shard's tree is a set of parallel arrays, nodes in the order they were opened, points in leaf order. The same code serves the
shard builder and the shard search, and it has no Spark in it.
"""

from __future__ import annotations

import bisect
import heapq
import math
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

MASK = (1 << 64) - 1
P1, P2, P3, P4, P5 = (np.uint64(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def rotl(x, r: int):
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def hash_long(value, seed):
    """The 64-bit xxHash of one long, as Spark chains it over columns."""
    with np.errstate(over="ignore"):
        h = seed + P5 + np.uint64(8)
        h = rotl(h ^ (rotl(value * P2, 31) * P1), 27) * P1 + P4
        h = (h ^ (h >> np.uint64(33))) * P2
        h = (h ^ (h >> np.uint64(29))) * P3
        return h ^ (h >> np.uint64(32))


def random_keys(seed: int, node: int, ids: np.ndarray) -> np.ndarray:
    """xxhash64(seed, node, id) as signed longs: the same numbers that Spark's function gives."""
    start = hash_long(np.uint64(seed), np.uint64(42))
    start = hash_long(np.uint64(node & MASK), start)
    return hash_long(ids.astype(np.int64).view(np.uint64), start).view(np.int64)


@dataclass
class Tree:
    d: int
    node: list[int] = field(default_factory=list)  # heap number: the root is 1, children 2i and 2i + 1, modulo 2 ** 64
    parent: list[int] = field(default_factory=list)  # positions in these arrays, -1 for none
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    depth: list[int] = field(default_factory=list)
    lo: list[int] = field(default_factory=list)
    hi: list[int] = field(default_factory=list)
    flat: list[bool] = field(default_factory=list)  # a leaf larger than allowed, as all its points are equal
    weight: list[int] = field(default_factory=list)  # the points that the centre is the mean of: appends add points and move no centre
    centers: np.ndarray = None
    norms: np.ndarray = None
    radii: np.ndarray = None
    ids: np.ndarray = None
    X: np.ndarray = None
    r_x: np.ndarray = None
    x_par: np.ndarray = None
    x_perp: np.ndarray = None
    a_par: np.ndarray = None  # x_par without its sign
    x_len: np.ndarray = None  # length of each point
    closer: list[float] = None  # r_x negated: rising along a leaf
    across: tuple = None  # X by component; leaves with points, in the order of these, where they start, and their sizes
    plain: tuple = None  # left, right, weight, centres, radii, and the bounds' room for rounding, as lists

    def ready(self) -> Tree:
        """What every walk reads of the annotations, worked out once."""
        if self.plain is None:
            self.a_par, self.x_len, self.closer = np.abs(self.x_par), np.hypot(self.x_par, self.x_perp), (-self.r_x).tolist()
            whole = [np.asarray(v).tolist() for v in (self.left, self.right, self.weight)]
            self.plain = (*whole, list(self.centers), np.asarray(self.radii).tolist(), (1e-9 * np.maximum(1.0, self.norms)).tolist())
        return self

    def n(self, at: int) -> int:
        return self.hi[at] - self.lo[at]

    def is_leaf(self, at: int) -> bool:
        return self.left[at] < 0


def squared(X: np.ndarray, c: np.ndarray) -> np.ndarray:
    diff = X - c
    return np.einsum("ij,ij->i", diff, diff)


def farthest(dist: np.ndarray, ids: np.ndarray) -> int:
    """Position of the greatest distance, ties to the least id."""
    top = np.flatnonzero(dist == dist.max())
    return int(top[ids[top].argmin()])


def pivots(X: np.ndarray, ids: np.ndarray, seed: int, node: int) -> tuple[int, int, np.ndarray]:
    """Two far points, found by two sweeps from a random one, and the distances to the first of them."""
    keys = random_keys(seed, node, ids)
    low = np.flatnonzero(keys == keys.min())
    start = int(low[ids[low].argmin()])
    a = farthest(squared(X, X[start]), ids)
    to_a = squared(X, X[a])
    return a, farthest(to_a, ids), to_a


def grow(ids: np.ndarray, X: np.ndarray, leaf_size: int, seed: int, annotate: bool = True) -> Tree:
    """Split until nodes have at most leaf_size points; then centres from the leaves upwards, radii, annotations."""
    return next(grow_all(ids, X, [leaf_size], seed, annotate))


def grow_all(ids: np.ndarray, X: np.ndarray, leaf_sizes: list[int], seed: int, annotate: bool = True) -> Iterator[Tree]:
    """The trees that grow() gives for each leaf size, from one series of splits: that of larger leaves is the beginning of that of smaller ones."""
    tree, order = Tree(X.shape[1]), np.argsort(ids, kind="stable")
    todo, least = [(0, len(ids), 1, 0, -1, False)], min(leaf_sizes)
    while todo:
        lo, hi, name, depth, parent, right = todo.pop()
        at = len(tree.node)
        for values, value in ((tree.node, name), (tree.parent, parent), (tree.left, -1), (tree.right, -1), (tree.depth, depth), (tree.lo, lo), (tree.hi, hi), (tree.flat, False)):
            values.append(value)
        if parent >= 0:
            (tree.right if right else tree.left)[parent] = at
        if hi - lo <= least:
            continue
        rows = order[lo:hi]
        near = X.take(rows, axis=0)
        a, b, to_a = pivots(near, ids[rows], seed, name)
        if to_a[b] == 0:
            tree.flat[at] = True
            continue
        nearer = to_a <= squared(near, near[b])
        order[lo:hi] = np.concatenate([rows[nearer], rows[~nearer]])
        middle = lo + int(nearer.sum())
        todo.append((middle, hi, (2 * name + 1) & MASK, depth + 1, at, True))
        todo.append((lo, middle, 2 * name & MASK, depth + 1, at, False))
    for leaf_size in leaf_sizes:
        part, rows = cut(tree, order, ids, leaf_size)
        finish(part, ids.take(rows), X.take(rows, axis=0), annotate)
        yield part


def cut(tree: Tree, order: np.ndarray, ids: np.ndarray, leaf_size: int) -> tuple[Tree, np.ndarray]:
    """A tree whose splits end at nodes of at most leaf_size points, and the order of its points: splits keep them by id within a node."""
    part, place, order = Tree(tree.d), {-1: -1}, order.copy()
    for at, parent in enumerate(tree.parent):  # children come after their parent
        if parent not in place or parent >= 0 and tree.n(parent) <= leaf_size:
            continue
        place[at] = len(part.node)
        for name in ("node", "depth", "lo", "hi"):
            getattr(part, name).append(getattr(tree, name)[at])
        part.parent.append(place[parent])
        part.left.append(-1)
        part.right.append(-1)
        part.flat.append(tree.flat[at] and tree.n(at) > leaf_size)
        if parent >= 0:
            (part.left if tree.left[parent] == at else part.right)[place[parent]] = place[at]
        if tree.n(at) <= leaf_size and not tree.is_leaf(at):
            rows = order[tree.lo[at] : tree.hi[at]]
            order[tree.lo[at] : tree.hi[at]] = rows[np.argsort(ids[rows], kind="stable")]
    return part, order


def finish(tree: Tree, ids: np.ndarray, X: np.ndarray, annotate: bool) -> None:
    count = len(tree.node)
    tree.centers = np.zeros((count, tree.d))
    for at in range(count - 1, -1, -1):  # children come after their parent
        if tree.is_leaf(at):
            tree.centers[at] = X[tree.lo[at] : tree.hi[at]].mean(axis=0) if tree.n(at) else 0
        else:
            l, r = tree.left[at], tree.right[at]
            tree.centers[at] = (tree.n(l) * tree.centers[l] + tree.n(r) * tree.centers[r]) / tree.n(at)
    tree.norms = np.linalg.norm(tree.centers, axis=1)
    tree.radii = np.array([np.sqrt(squared(X[tree.lo[at] : tree.hi[at]], tree.centers[at]).max(initial=0)) for at in range(count)])
    tree.r_x, tree.x_par, tree.x_perp = np.zeros(len(ids)), np.zeros(len(ids)), np.zeros(len(ids))
    order = np.arange(len(ids))
    for at in range(count):
        if tree.is_leaf(at) and tree.n(at):
            span = slice(tree.lo[at], tree.hi[at])
            r, along, across = measured(X[span], tree.centers[at], tree.norms[at])
            rank = np.lexsort((ids[span], -r)) if annotate else np.argsort(ids[span])
            order[span] = order[span][rank]
            tree.r_x[span], tree.x_par[span], tree.x_perp[span] = r[rank], along[rank], across[rank]
    tree.ids, tree.X = ids.take(order), X.take(order, axis=0)
    tree.weight = [tree.n(at) for at in range(count)]


def measured(part: np.ndarray, c: np.ndarray, norm: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of a leaf's points: distance from its centre, and the parts along and across it."""
    along = part @ c / norm
    return np.sqrt(squared(part, c)), along, np.linalg.norm(part - np.outer(along / norm, c), axis=1)


WHOLE, REAL = ("parent", "left", "right", "lo", "hi", "weight"), ("norms", "radii", "centers")


def to_bytes(tree: Tree) -> bytes:
    """A tree as one value, to be read back without a row a point: d, counts, then its arrays one after another. The three numbers a point are
    left out, as from_bytes() measures them again."""
    head = np.array([tree.d, len(tree.parent), len(tree.ids)], dtype="<i8")
    whole = [np.asarray(getattr(tree, name), dtype="<i8") for name in WHOLE] + [np.asarray(tree.ids, dtype="<i8")]
    real = [getattr(tree, name) for name in REAL] + [tree.X]
    return b"".join([head.tobytes(), *(w.tobytes() for w in whole), *(np.ascontiguousarray(r, dtype="<f8").tobytes() for r in real)])


def from_bytes(value) -> Tree:
    d, nodes, points = (int(v) for v in np.frombuffer(value, "<i8", 3))
    at, tree = 24, Tree(d)

    def take(kind: str, *shape: int) -> np.ndarray:
        nonlocal at
        size = int(np.prod(shape))
        out = np.frombuffer(value, kind, size, at).reshape(shape)
        at += 8 * size
        return out

    for name in WHOLE:
        setattr(tree, name, take("<i8", nodes).tolist())
    tree.ids = take("<i8", points)
    tree.norms, tree.radii, tree.centers = take("<f8", nodes), take("<f8", nodes), take("<f8", nodes, d)
    tree.X = take("<f8", points, d)
    tree.r_x, tree.x_par, tree.x_perp = np.zeros(points), np.zeros(points), np.zeros(points)
    for at in range(nodes):
        if tree.is_leaf(at) and tree.n(at):
            span = slice(tree.lo[at], tree.hi[at])
            tree.r_x[span], tree.x_par[span], tree.x_perp[span] = measured(tree.X[span], tree.centers[at], tree.norms[at])
    return tree


@dataclass
class Options:
    """How to walk: see search.shard_dfs."""

    k: int = 10
    ball: bool = True
    cone: bool = True
    derive_sibling: bool = True
    preference: str = "center"
    eps: float = 0.0
    rederive: int = 8  # derivations in a row before a product is computed afresh
    clock: bool = False  # fill the counters of nanoseconds


COUNTERS = ("nodes_visited", "center_products", "leaves_scanned", "points_seen", "pruned_ball", "cone_evals", "pruned_cone", "verified", "verify_ns", "walk_ns")


def walk(tree: Tree, q: np.ndarray, q_norm: float, options: Options, lam: float = np.inf, quota: int | None = None) -> tuple[list[tuple[float, int]], dict[str, int]]:
    """The k nearest points of one plane, depth first, and what it cost.

    lam may start at a known upper bound of the k-th margin. A branch is left out only if its bound passes lam by more than
    rounding allows, so ties are decided by (margin, id) alone. With a quota the walk ends once that many points are verified.
    """
    return walks(tree, q, q_norm, options, lam, [quota])[0]


class Met:
    """A plane's margins of all points of a tree, the least of each leaf and the cone's bounds, worked out once for walks with several options. Answers and
    counters are those of walks on their own; seconds are not, so that walks with a clock don't use it."""

    def __init__(self, tree: Tree, q: np.ndarray, q_norm: float):
        if tree.across is None:
            leaves = np.array([at for at in range(len(tree.parent)) if tree.left[at] < 0 and tree.hi[at] > tree.lo[at]], dtype=np.int64)
            leaves = leaves[np.argsort(np.asarray(tree.lo)[leaves])]
            tree.across = np.ascontiguousarray(tree.X.T), leaves, np.asarray(tree.lo)[leaves], (np.asarray(tree.hi) - np.asarray(tree.lo))[leaves]
        self.tree, self.q, self.q_norm, self.ips, self.bounds = tree, q, q_norm, [None] * len(tree.parent), None
        columns, leaves, starts, _ = tree.across
        self.margins = columns[0] * q[0]
        for j in range(1, len(q)):  # left folds in component order
            self.margins += columns[j] * q[j]
        np.abs(self.margins, out=self.margins)
        self.least = dict(zip(leaves.tolist(), np.minimum.reduceat(self.margins, starts).tolist())) if len(leaves) else {}

    def low(self) -> np.ndarray:
        if self.bounds is None:
            tree, (_, leaves, _, sizes) = self.tree.ready(), self.tree.across
            along = (tree.centers[leaves] @ self.q) / tree.norms[leaves]
            across = np.sqrt(np.maximum(self.q_norm * self.q_norm - along * along, 0.0))
            self.bounds = np.repeat(np.abs(along), sizes) * tree.a_par
            self.bounds -= np.repeat(across, sizes) * tree.x_perp
            self.bounds -= 1e-7 * self.q_norm * tree.x_len
        return self.bounds


def walks(tree: Tree, q: np.ndarray, q_norm: float, options: Options, lam: float, quotas: list[int | None], met: Met | None = None) -> list[tuple[list[tuple[float, int]], dict[str, int]]]:
    """What walk() gives for each quota, in one walk: that of a smaller quota is the beginning of that of a larger one. met: for several walks of one plane."""
    done = dict.fromkeys(COUNTERS, 0)
    best: list[tuple[float, int]] = []  # a heap of negated (margin, id)
    if not len(tree.ids):
        return [([], dict(done)) for _ in quotas]
    stops, ended = sorted({n for n in quotas if n is not None}, reverse=True), {}
    quota = None if None in quotas else stops[0]

    def note(stop: int | None) -> None:
        spent = time.perf_counter_ns() - begun if options.clock else 0
        ended[stop] = sorted((-m, -i) for m, i in best), done | {"walk_ns": spent}

    tree.ready()
    left, right, weight, rows, radii, rooms = tree.plain  # lists, as a step reads single numbers
    widen, nearest, derive, rederive, visited, products = 1 + options.eps, options.preference == "center", options.derive_sibling, options.rederive, 0, 1
    ips = [None] * len(left) if met is None else met.ips
    begun = time.perf_counter_ns()
    todo = [(0, float(rows[0].dot(q)), 0)]
    while stops and stops[-1] <= 0:
        done["center_products"] = products
        note(stops.pop())
    while todo and (quota is None or done["verified"] < quota):
        at, ip, since = todo.pop()
        visited += 1
        if max(abs(ip) - q_norm * radii[at], 0.0) * widen - rooms[at] * q_norm > lam:
            continue
        l, r = left[at], right[at]
        if l < 0:
            done["nodes_visited"], done["center_products"] = visited, products
            if met is not None and lam < np.inf and not (stops and done["verified"] + tree.hi[at] - tree.lo[at] >= stops[-1]):
                lam = scan_met(met, at, ip, options, lam, rooms[at] * q_norm, best, done)
            else:
                lam = scan(tree, at, ip, q, q_norm, options, lam, quota, best, done, stops, note)
            continue
        small, big = (l, r) if weight[l] <= weight[r] else (r, l)
        ip_small = ips[small]
        if ip_small is None:
            ip_small = ips[small] = float(rows[small].dot(q))
        derived = derive and since < rederive
        if derived:
            ip_big = (weight[at] * ip - weight[small] * ip_small) / weight[big]
        else:
            ip_big = ips[big]
            if ip_big is None:
                ip_big = ips[big] = float(rows[big].dot(q))
        products += 2 - derived
        one, other = (small, ip_small, 0), (big, ip_big, since + 1 if derived else 0)
        if nearest:
            first, second = abs(ip_small), abs(ip_big)
            ahead = first < second or (first == second and small > big)
        else:
            first, second = (max(abs(v) - q_norm * radii[c], 0.0) * widen - rooms[c] * q_norm for c, v in ((small, ip_small), (big, ip_big)))
            ahead = first < second or (first == second and small < big)
        todo += (other, one) if ahead else (one, other)  # the preferred child is popped first
    done["nodes_visited"], done["center_products"] = visited, products
    note(None)
    return [ended.get(n, ended[None]) for n in quotas]


def scan_met(met: Met, at: int, ip: float, options: Options, lam: float, slack: float, best: list, done: dict, chunk: int = 1024) -> float:
    """scan() of a leaf in which no quota is met, with the margins at hand and a finite lam."""
    tree = met.tree
    start, hi = tree.lo[at], tree.hi[at]
    lo, nearest = start, met.least[at]
    done["leaves_scanned"] += 1
    done["points_seen"] += hi - lo
    while start < hi:
        if options.ball:
            end = max(bisect.bisect_right(tree.closer, -((abs(ip) - lam - slack) / met.q_norm), lo, hi), start)
            done["pruned_ball"] += hi - end
            hi = end
        stop = min(start + chunk, hi)
        count, near = stop - start, None
        if options.cone and count:
            done["cone_evals"] += count
            near = met.low()[start:stop] <= lam
            kept = int(np.count_nonzero(near))
            done["pruned_cone"] += count - kept
            count = kept
        done["verified"] += count
        if count and nearest <= lam:
            margins = met.margins[start:stop]
            some = (margins <= lam if near is None else near & (margins <= lam)).nonzero()[0]
            for value, name in zip(margins[some].tolist(), tree.ids[start:stop][some].tolist()):
                entry = (-value, -name)
                if len(best) < options.k:
                    heapq.heappush(best, entry)
                elif entry > best[0]:
                    heapq.heapreplace(best, entry)
            if len(best) == options.k:
                lam = min(lam, -best[0][0])
        start = stop
    return lam


def scan(tree: Tree, at: int, ip: float, q: np.ndarray, q_norm: float, options: Options, lam: float, quota: int | None, best: list, done: dict, stops: list[int], note, chunk: int = 1024) -> float:
    """Verify a leaf's points that no bound rules out; returns the new lam. stops: the quotas still ahead, the next one last; note is called at each."""
    lo, hi = int(tree.lo[at]), int(tree.hi[at])
    done["leaves_scanned"] += 1
    done["points_seen"] += hi - lo
    norm = float(tree.norms[at])
    slack = 1e-9 * q_norm * max(1.0, norm)
    along = ip / norm if norm else np.float64(ip) / norm
    across = math.sqrt(max(q_norm * q_norm - along * along, 0.0))
    start, cosine, room = lo, abs(along), 1e-7 * q_norm
    while start < hi and (quota is None or done["verified"] < quota):
        if options.ball and lam < np.inf:  # distances fall along the leaf, so survivors are a prefix
            end = bisect.bisect_right(tree.closer, -((abs(ip) - lam - slack) / q_norm), lo, hi)
            if end < hi:
                done["pruned_ball"] += hi - max(end, start)
                hi = max(end, start)
                continue
        stop = min(start + chunk, hi)
        some, count = slice(start, stop), stop - start
        start = stop
        if options.cone:
            done["cone_evals"] += count
            if lam < np.inf:
                low = cosine * tree.a_par[some] - across * tree.x_perp[some] - room * tree.x_len[some]
                kept = (low <= lam).nonzero()[0]
                if len(kept) < count:
                    done["pruned_cone"] += count - len(kept)
                    some, count = kept + some.start, len(kept)
        left = count if quota is None else min(count, quota - done["verified"])
        if left == count and count and not (stops and done["verified"] + count >= stops[-1]):
            lam = verify(tree, some, count, q, options, lam, slack, best, done)
            continue
        some = (np.arange(some.start, some.stop) if isinstance(some, slice) else some)[:left]
        while len(some):  # a quota is met within these points
            more = min(len(some), stops[-1] - done["verified"]) if stops else len(some)
            lam = verify(tree, some[:more], more, q, options, lam, slack, best, done)
            some = some[more:]
            if stops and done["verified"] == stops[-1]:
                note(stops.pop())
    return lam


def verify(tree: Tree, some: slice | np.ndarray, count: int, q: np.ndarray, options: Options, lam: float, slack: float, best: list, done: dict) -> float:
    """Put points to the best, if they are near enough; returns the new lam."""
    done["verified"] += count
    begun = time.perf_counter_ns() if options.clock else 0
    X, ids = (tree.X[some], tree.ids[some]) if isinstance(some, slice) else (tree.X.take(some, axis=0), None)
    rough = np.abs(X.dot(q))
    if lam < np.inf:
        near = (rough <= lam + slack).nonzero()[0]
    elif count > 4 * options.k:
        near = (rough <= np.partition(rough, options.k - 1)[options.k - 1] + slack).nonzero()[0]
    else:
        near = np.arange(count)
    if len(near):
        exact = np.abs(np.add.accumulate(X[near] * q, axis=1)[:, -1])  # left folds in component order
        for value, name in zip(exact.tolist(), (tree.ids[some[near]] if ids is None else ids[near]).tolist()):
            entry = (-value, -name)
            if len(best) < options.k:
                heapq.heappush(best, entry)
            elif entry > best[0]:
                heapq.heapreplace(best, entry)
        if len(best) == options.k:
            lam = min(lam, -best[0][0])
    if options.clock:
        done["verify_ns"] += time.perf_counter_ns() - begun
    return lam
