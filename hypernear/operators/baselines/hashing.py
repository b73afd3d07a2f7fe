"""Hash baselines: near hashing, far hashing and sphere hashing. All verify their candidates with true margins.

An index is one row a point: its vector beside its keys in all tables, made in Arrow batches. A search scores every point by how its keys meet
those of a plane and verifies the best scored points, up to a budget (a share of the points). Two passes do that without moving a row: the first
counts points by score and plane (partial sums by task), which gives each plane the score that its budget reaches; the second verifies
in place, and each task keeps k rows a plane. No bucket is gathered, whatever it holds, and nothing is cut off but by the budget.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...functions import exprs as E
from ...sources.storage import opened, persisted, ship
from ..brute import batches_of, folded, ranked, small_side
from ..build import dimension
from . import lift as L

BINS = 512  # of scores that are not counts
CELLS = 1 << 19  # keys scored at once: enough to hide the cost of a step, few enough for a core's cache
VARIED = "variant int, qid long, id long, margin double, look_ns long, verify_ns long"


@dataclass
class HashIndex:
    """rows: (id, x, part, keys) of all points; setting: what hashing a plane needs; n: the number of points; width: bytes a key. Where keys are not stored,
    points (id, x) and make(), which a search calls in its own tasks, so that keys are never handed from one to another."""

    rows: DataFrame
    setting: dict
    n: int
    width: int
    points: DataFrame | None = None
    make: Callable | None = None

    def read(self, *needed: str) -> DataFrame:
        return self.rows.select(*needed) if self.make is None else self.points.select("id", "x")

    def bytes(self) -> int:
        """Bytes beside the data: all keys, and the random numbers that made them."""
        return self.n * (self.setting["m"] * self.width + 8) + 8 * sum(v.size for v in self.setting.values() if isinstance(v, np.ndarray))


def pair_list(d: int, lam: int | None, seed: int) -> list[tuple[int, int]] | None:
    return None if lam is None else L.random_pairs(d, lam, seed)


def keyed(points: DataFrame, setting: dict, make, kind: str, label: str, stored: bool = True) -> DataFrame:
    """Rows (id, x, part, keys) with make(X, setting) -> (part, keys). Keys that are not stored are made anew by each pass over them."""
    shared = ship(points.sparkSession, setting)
    arrow = pa.int32() if kind == "int" else pa.float64()

    def run(batches):
        s = opened(shared)
        for batch in batches:
            for some in slices(batch, s["m"]):
                part, keys = make(np.asarray(some.column(1).flatten()).reshape(some.num_rows, -1), s)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(some.num_rows + 1, dtype=np.int32) * keys.shape[1]), pa.array(np.ascontiguousarray(keys).ravel(), arrow))
                yield pa.RecordBatch.from_arrays([*some.columns, pa.array(part, pa.int32()), lists], names=["id", "x", "part", "keys"])

    rows = points.select("id", "x").mapInArrow(run, f"id long, x array<double>, part int, keys array<{kind}>")
    return persisted(rows, label) if stored else rows


def indexed(points: DataFrame, setting: dict, make, kind: str, label: str, stored: bool, width: int, n: int) -> HashIndex:
    rows = keyed(points, setting, make, kind, label, stored)
    return HashIndex(rows, setting, n, width) if stored else HashIndex(rows, setting, n, width, points, make)


def verify(points: DataFrame, candidates: DataFrame, planes: DataFrame, k: int, d: int) -> DataFrame:
    met = points.select("id", "x").join(candidates.select("qid", "id"), "id").join(small_side(planes.select("qid", "q")), "qid")
    return ranked(met.select("qid", "id", F.inline(F.array(F.struct(E.absdot(F.col("x"), F.col("q"), d).alias("margin"))))), k)


def slices(batch: pa.RecordBatch, m: int):
    """A batch in equal slices of about CELLS keys, 1,024 rows at least."""
    step = -(-batch.num_rows // max(1, -(-batch.num_rows // max(1024, CELLS // m))))
    for at in range(0, batch.num_rows, max(step, 1)):
        yield batch.slice(at, step)


def matrix(column, n: int) -> np.ndarray:
    return np.asarray(column.flatten()).reshape(n, -1)


def pieces(batches, s: dict, make, vectors: bool = True):
    """(ids, X, parts, keys) of some points at a time, from columns id, x, part, keys; or, without vectors, (None, None, parts, keys) from part, keys. With
    make, always from id, x."""
    for batch in batches:
        for some in slices(batch, s["m"]):
            n, columns = some.num_rows, some.columns
            if make is not None:
                X = matrix(columns[1], n)
                yield np.asarray(columns[0]), X, *make(X, s)
            elif vectors:
                yield np.asarray(columns[0]), matrix(columns[1], n), np.asarray(columns[2]), matrix(columns[3], n)
            else:
                yield None, None, np.asarray(columns[0]), matrix(columns[1], n)


def gathered(batches, most_rows: int = 1 << 16, most_bytes: int = 16 << 20):
    """Arrow batches put together, so that a block is as large as a core's cache allows."""
    held, rows, size = [], 0, 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            rows, size = rows + batch.num_rows, size + batch.nbytes
        if rows >= most_rows or size >= most_bytes:
            yield held[0] if len(held) == 1 else pa.concat_batches(held)
            held, rows, size = [], 0, 0
    if held:
        yield held[0] if len(held) == 1 else pa.concat_batches(held)


def passes(searches: list[tuple], planes: int, most_bytes: int = 64 << 20) -> list[list[int]]:
    """Places of searches that read the same points in one pass, as keys are made on the spot; the counts of their scores fit in most_bytes of a task."""
    out: list[list[int]] = []
    size = 0
    for number, (index, _, score) in enumerate(searches):
        more = 8 * score.kinds * planes * index.setting.get("parts", 1) * (index.setting["bins"] + 1)
        before = searches[out[-1][0]][0] if out else None
        if before and index.make and before.make and index.points is before.points and size + more <= most_bytes:
            out[-1].append(number)
            size += more
        else:
            out.append([number])
            size = more
    return out


def lot(ids: np.ndarray) -> np.ndarray:
    """A number in [0, 1) by id, the same in every run: of points with equal scores the budget takes the least."""
    z = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    z = (z ^ (z >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((z ^ (z >> np.uint64(29))) >> np.uint64(11)).astype(np.float64) / float(1 << 53)


def cuts(searches: list[tuple], shipped: list, groups: list[list[int]], budget: np.ndarray, least: int) -> list[list[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
    """Of each search and each kind of its score, by plane and part: the score from which points are taken, and the share of those with just that score; and
    the nanoseconds of each plane.

    The table lookup of all searches: one job, and one pass over the points of searches that make keys on the spot, else over the keys of each. Points are scored once for each group of equal planes, and for all kinds
    together; each kind is charged what it costs alone, in proportion to a measured sample of each task.
    """
    planes, tallies = len(groups), None
    for some in passes(searches, planes):

        def run(batches, some=some, shared=[shipped[n] for n in some], searches=[(searches[n][2], searches[n][0].make) for n in some]):
            opens, ratios = [opened(one) for one in shared], [None] * len(some)
            counts = [np.zeros((score.kinds, planes, s.get("parts", 1) * (s["bins"] + 1)), dtype=np.int64) for (score, _), (s, *_) in zip(searches, opens)]
            costs = [np.zeros((score.kinds, planes)) for score, _ in searches]
            for batch in gathered(batches):
                for n, ((score, make), (s, _, Q, looked, groups), count, spent) in enumerate(zip(searches, opens, counts, costs)):
                    parts, bins, kinds = s.get("parts", 1), s["bins"], score.kinds
                    for _, _, part, keys in pieces([batch], s, make, False):
                        view, place = score.view(keys, part, s), part * (bins + 1) if parts > 1 else None
                        ratios[n] = ratio = charges(score, view, looked, s) if ratios[n] is None else ratios[n]
                        for q in range(planes):
                            begun = time.perf_counter_ns()
                            levels = score.all(view, looked[groups[q][0]], s)
                            scored = time.perf_counter_ns()
                            for kind, level in enumerate(levels):
                                count[kind, q] += np.bincount(level if place is None else place + level, minlength=parts * (bins + 1))
                            spent[:, q] += (scored - begun) * ratio + (time.perf_counter_ns() - scored) / kinds
            for number, count, spent in zip(some, counts, costs):
                cell = np.flatnonzero(count)
                cells = np.concatenate([cell, -1 - np.arange(spent.size)])
                yield pa.RecordBatch.from_pydict({"search": pa.array(np.full(len(cells), number)), "cell": pa.array(cells), "n": pa.array(np.concatenate([count.ravel()[cell], spent.ravel().astype(np.int64)]))})

        tally = searches[some[0]][0].read("part", "keys").mapInArrow(run, "search long, cell long, n long")
        tallies = tally if tallies is None else tallies.unionByName(tally)
    table = tallies.groupBy("search", "cell").agg(F.sum("n").alias("n")).toArrow()
    search, cells, ns = (table.column(c).to_numpy() for c in ("search", "cell", "n"))
    out = []
    for number, (index, _, score) in enumerate(searches):
        parts, bins, kinds = index.setting.get("parts", 1), index.setting["bins"], score.kinds
        cell, n = cells[search == number], ns[search == number]
        count, spent = np.zeros(kinds * planes * parts * (bins + 1), dtype=np.int64), np.zeros(kinds * planes, dtype=np.int64)
        count[cell[cell >= 0]], spent[-1 - cell[cell < 0]] = n[cell >= 0], n[cell < 0]
        out.append([(*cut_of(c, groups, budget, least), spread(t, groups, len(budget))) for c, t in zip(count.reshape(kinds, planes, parts, bins + 1), spent.reshape(kinds, planes))])
    return out


def charges(score, view, looked: np.ndarray, s: dict, some: int = 4) -> np.ndarray:
    """Seconds of each kind of a score alone, as shares of those of all together, measured on a few planes."""
    if score.kinds == 1:
        return np.ones(1)
    seconds = np.zeros(score.kinds + 1)
    for key in looked[:some]:
        for n, one in enumerate([*score.alone(), score]):
            begun = time.perf_counter_ns()
            one.all(view, key, s)
            seconds[n] += time.perf_counter_ns() - begun
    return seconds[:-1] / max(seconds[-1], 1)


def spread(spent: np.ndarray, groups: list[list[int]], n: int) -> np.ndarray:
    """Of each plane, what its group took."""
    out = np.zeros(n, dtype=np.int64)
    for g, group in enumerate(groups):
        out[group] = spent[g]
    return out


def cut_of(count: np.ndarray, groups: list[list[int]], budget: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """From points by group, part and score: by plane and part, the score that the budget reaches and the share taken of those with it."""
    bins, whole = count.shape[2] - 1, count.sum(axis=2)
    cut, share = np.zeros((len(budget), count.shape[1]), dtype=np.int64), np.zeros((len(budget), count.shape[1]))
    for g, group in enumerate(groups):
        above = np.cumsum(count[g, :, ::-1], axis=1)[:, ::-1] - count[g]  # points of higher scores
        for q in group:
            wanted = np.minimum(np.ceil(np.maximum(budget[q] * whole[g], least * whole[g] / max(whole[g].sum(), 1)) - 1e-9), whole[g])
            cut[q] = bins - np.argmax((above + count[g] >= wanted[:, None])[:, ::-1], axis=1)  # the highest score that reaches the budget
            here, more = (np.take_along_axis(a, cut[q][:, None], axis=1)[:, 0] for a in (count[g], above))
            share[q] = np.where(here > 0, (wanted - more) / np.maximum(here, 1), 0.0)
    return cut, share


def best_scored(index: HashIndex, planes: DataFrame, look, score, k: int, budget: float | dict[int, float], timed: bool = False) -> DataFrame:
    """The k least margins of each plane among its best scored points: see searched(). timed: rows of tasks, and what each plane cost in
    nanoseconds of scoring (the table lookup) and verification, without an id."""
    found = searched([(index, look, score)], planes, k, budget).drop("variant")
    return found if timed else ranked(found.filter("id is not null"), k)


def searched(searches: list[tuple], planes, k: int, budget: float | dict[int, float]) -> DataFrame:
    """Rows VARIED of several searches (index, look, score) as two jobs, one that counts scores and one that verifies; variants number the kinds of
    their scores. look(Q, setting) gives the planes' keys; score.all(score.view(keys, part, setting), key, setting) for each kind whole numbers from 0 to the
    setting's bins. A budget for each qid may be given. Costs have no id.

    The second job needs no point's whole score at first, only whether it reaches the largest budget's cut; the scores of points whose margin may be among the
    best decide. Budgets of equal planes take nested sets of points: the largest is multiplied once, which each is charged in proportion to its budget, and
    only margins that may be among a budget's k least so far are looked at again."""
    spark, found = searches[0][0].rows.sparkSession, None
    for qids, Q in batches_of(planes):
        alike: dict[bytes, list[int]] = {}
        for at in range(len(qids)):
            alike.setdefault(Q[at].tobytes(), []).append(at)
        groups = list(alike.values())
        looks = [look(Q, index.setting) for index, look, _ in searches]
        shipped = [ship(spark, (index.setting | {"furthest": float(np.abs(looked).max(initial=0))}, qids, Q, looked, groups)) for (index, *_), looked in zip(searches, looks)]
        shares = np.array([budget[q] if isinstance(budget, dict) else budget for q in qids.tolist()])
        reached, first, costs = cuts(searches, shipped, groups, shares, k), 0, []
        limits = []
        for kinds in reached:
            limits.append(ship(spark, ([(cut, share) for cut, share, _ in kinds], shares, first)))
            costs += [(first + v, int(q), None, None, int(n), 0) for v, (_, _, looking) in enumerate(kinds) for q, n in zip(qids, looking)]
            first += len(kinds)
        for some in passes(searches, len(groups)):

            def run(batches, shared=[(shipped[n], limits[n]) for n in some], searches=[(searches[n][2], searches[n][0].make) for n in some]):
                todo = []
                for (score, make), (one, limit) in zip(searches, shared):
                    s, qids, Q, looked, groups = opened(one)
                    kinds, shares, first = opened(limit)
                    kept = [Kept(cut, share, len(qids)) for cut, share in kinds]
                    todo.append((score, make, s, qids, Q, looked, [sorted(group, key=lambda q: shares[q]) for group in groups], shares, first, kept))
                for batch in gathered(batches):
                    for score, make, s, qids, Q, looked, groups, shares, _, kept in todo:
                        slack = 1e-9 * (1 + np.abs(Q).sum(axis=1))
                        for ids, X, part, keys in pieces([batch], s, make):
                            chance, view = lot(ids), score.view(keys, part, s)
                            for group in groups:
                                near = score.nearing(view, looked[group[0]], part, s)
                                for kind, one in enumerate(kept):
                                    one.verify(group, near, kind, ids, X, part, chance, Q, shares, slack, k)
                for *_, qids, _, _, _, _, first, kept in todo:
                    for v, one in enumerate(kept):
                        yield from one.rows(first + v, qids)

            part_found = searches[some[0]][0].read("id", "x", "part", "keys").mapInArrow(run, VARIED)
            found = part_found if found is None else found.unionByName(part_found)
        found = found.unionByName(spark.createDataFrame(costs, VARIED))
    return spark.createDataFrame([], VARIED) if found is None else found


class Kept:
    """The best points of a task so far, of each plane, among those that its scores let through."""

    def __init__(self, cut: np.ndarray, share: np.ndarray, planes: int):
        self.cut, self.share = cut, share
        self.best = [(np.empty(0), np.empty(0, dtype=np.int64))] * planes
        self.spent, self.worst = np.zeros(planes), np.full(planes, np.inf)  # worst: the k-th margin so far

    def taken(self, q: int, level: np.ndarray, part: np.ndarray, chance: np.ndarray) -> np.ndarray:
        cut, share = self.cut[q], self.share[q]
        if len(cut) == 1:
            first = int(cut[0])  # scores stay in as few bytes as they have
            return (level > first) | ((level == first) & (chance < share[0]))
        edge = cut.take(part)
        return (level > edge) | ((level == edge) & (chance < share.take(part)))

    def verify(self, group: list[int], near, kind: int, ids: np.ndarray, X: np.ndarray, part: np.ndarray, chance: np.ndarray, Q: np.ndarray, shares: np.ndarray, slack: np.ndarray, k: int) -> None:
        best, worst, spent, last = self.best, self.worst, self.spent, group[-1]
        begun = time.perf_counter_ns()
        at = near.reaching(kind, self.cut[last], lambda level: self.taken(last, level, part, chance))
        rough, limits = np.abs((X if len(at) == len(X) else X.take(at, axis=0)).dot(Q[last])), worst[group] + slack[last]
        least = (~(rough > limits.max())).nonzero()[0]
        at, rough = at.take(least), rough.take(least)
        if len(at):  # of the budgets whose k-th margin a point may be below, the largest has the least cut
            mine = ~(rough > limits[:, None])
            widest, parted = np.asarray(group).take(len(group) - 1 - mine[::-1].argmax(axis=0)), part.take(at)
            some = near.reached(kind, at, self.cut[widest, parted]).nonzero()[0]
            at, rough, mine, parted = at.take(some), rough.take(some), mine[:, some], parted.take(some)
        ended = time.perf_counter_ns()
        spent[group] += (ended - begun) * shares[group] / max(shares[last], 1e-300)
        if not len(at):
            return
        begun = time.perf_counter_ns()
        levels, chances, names, margins = near.levels(kind, at), chance.take(at), ids.take(at), np.abs(folded(X.take(at, axis=0), Q[last]))
        spent[group] += (time.perf_counter_ns() - begun) * shares[group] / max(shares[last], 1e-300)
        for n, q in enumerate(group):
            begun = time.perf_counter_ns()
            if mine[n].any():
                chosen = (mine[n] & self.taken(q, levels, parted, chances)).nonzero()[0]
                if len(chosen) > 4 * k:
                    chosen = chosen[margins[chosen] <= np.partition(margins[chosen], k - 1)[k - 1]]
                if len(chosen):
                    known, some = np.concatenate([best[q][0], margins[chosen]]), np.concatenate([best[q][1], names[chosen]])
                    order = np.lexsort((some, known))[:k]
                    best[q] = known[order], some[order]
                    if len(order) == k:
                        worst[q] = known[order[-1]]
            spent[q] += time.perf_counter_ns() - begun

    def rows(self, variant: int, qids: np.ndarray):
        counts = [len(names) for _, names in self.best]
        total, n = sum(counts), len(qids)
        if total:
            zero = pa.array(np.zeros(total, dtype=np.int64))
            yield pa.RecordBatch.from_pydict({"variant": pa.array(np.full(total, variant, dtype=np.int32)), "qid": pa.array(np.repeat(qids, counts)), "id": pa.array(np.concatenate([b[1] for b in self.best])), "margin": pa.array(np.concatenate([b[0] for b in self.best])), "look_ns": zero, "verify_ns": zero})
        yield pa.RecordBatch.from_pydict({"variant": pa.array(np.full(n, variant, dtype=np.int32)), "qid": pa.array(qids), "id": pa.nulls(n, pa.int64()), "margin": pa.nulls(n, pa.float64()), "look_ns": pa.array(np.zeros(n, dtype=np.int64)), "verify_ns": pa.array(self.spent.astype(np.int64))})


class Scored:
    """A block's scores of one plane, all at hand: which points a cut takes, and their scores."""

    def __init__(self, levels: list[np.ndarray]):
        self.all = levels

    def reaching(self, kind: int, cut: np.ndarray, taken: Callable) -> np.ndarray:
        return taken(self.all[kind]).nonzero()[0]

    def reached(self, kind: int, at: np.ndarray, cuts: np.ndarray) -> np.ndarray:
        return self.all[kind].take(at) >= cuts

    def levels(self, kind: int, at: np.ndarray) -> np.ndarray:
        return self.all[kind].take(at)


class Collisions:
    """In how many tables a point stands in the plane's bucket. Keys are held table by table, in as few bytes as they need."""

    kinds = 1

    def view(self, keys: np.ndarray, part: np.ndarray, s: dict) -> np.ndarray:
        low, high = (int(keys.min()), int(keys.max())) if keys.size else (0, 0)
        kind = next(t for t in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(t).min <= low and high <= np.iinfo(t).max)
        return np.ascontiguousarray(keys.T, dtype=kind)

    def __call__(self, view: np.ndarray, key: np.ndarray, s: dict) -> np.ndarray:
        at = key.astype(view.dtype)
        met = view == at[:, None]
        if (at != key).any():
            met[at != key] = False  # no point has such a key
        return np.add.reduce(met.view(np.uint8), axis=0, dtype=np.uint8 if len(view) < 256 else np.uint16)

    def all(self, view: np.ndarray, key: np.ndarray, s: dict) -> list[np.ndarray]:
        return [self(view, key, s)]

    def nearing(self, view: np.ndarray, key: np.ndarray, part: np.ndarray, s: dict) -> Scored:
        return Scored(self.all(view, key, s))


collisions = Collisions()


def measures(points: DataFrame, lams: list[int | None], seed: int = 42) -> tuple[int, int, dict[int | None, float]]:
    """Dimension and number of the points, and the greatest norm of each of their sampled lifts, for indexes of one seed."""
    d = dimension(points)
    n, norms = L.largest_norms(points, [pair_list(d, lam, seed) for lam in lams])
    return d, n, dict(zip(lams, norms))


# --- near hashing ---


def near_build(points: DataFrame, m: int = 128, lam: int | None = None, width: float | None = None, seed: int = 42, stored: bool = True, known: tuple[int, int, dict[int, float]] | None = None) -> HashIndex:
    """m tables of random projections of the completed lift, in steps of width (a share of their spread, by default). known: see measures()."""
    d, n, norms = known or measures(points, [lam], seed)
    pairs = pair_list(d, lam, seed)
    size = (lam or d * (d + 1) // 2) + 1
    random = np.random.default_rng(seed)
    setting = {"pairs": pairs, "most": norms[lam], "A": random.standard_normal((size, m)), "m": m, "bins": m}
    setting["width"] = width or 0.5 * max(setting["most"], 1e-9)
    setting["b"] = random.uniform(0, setting["width"], m)

    def make(X, s):
        P = L.complete(L.sampled_rows(X, s["pairs"]), s["most"]) @ s["A"]
        return np.zeros(len(X), np.int32), np.floor((P + s["b"]) / s["width"]).astype(np.int32)

    return indexed(points, setting, make, "int", "near-hash", stored, 4, n)


def near_look(Q: np.ndarray, s: dict) -> np.ndarray:
    return np.floor((L.lifted_query(Q, s["pairs"], True) @ s["A"] + s["b"]) / s["width"]).astype(np.int32)


def near_search(index: HashIndex, planes: DataFrame, k: int = 10, budget: float | dict[int, float] = 0.1, timed: bool = False) -> DataFrame:
    """Verify the points that collide most often, up to a share of all points."""
    return best_scored(index, planes, near_look, collisions, k, budget, timed)


# --- far hashing ---


def far_build(points: DataFrame, m: int = 128, lam: int | None = None, ratio: float = 0.9, parts: int = 48, seed: int = 42, stored: bool = True, known: tuple[int, int, dict[int, float]] | None = None) -> HashIndex:
    """m projections of each part of the points, parts by lifted norm in steps of ratio (the last holds all shorter ones). known: see measures()."""
    d, n, norms = known or measures(points, [lam], seed)
    pairs = pair_list(d, lam, seed)
    size = (lam or d * (d + 1) // 2) + 1
    setting = {"pairs": pairs, "most": norms[lam], "ratio": ratio, "A": np.random.default_rng(seed).standard_normal((size, m)), "m": m, "parts": parts, "bins": BINS}

    def make(X, s):
        rows = L.sampled_rows(X, s["pairs"])
        length = np.maximum(np.linalg.norm(rows, axis=1), 1e-300)
        part = np.clip(np.floor(np.log(length / s["most"]) / np.log(s["ratio"]) + 1e-9), 0, s["parts"] - 1).astype(np.int32) if s["most"] else np.zeros(len(X), np.int32)
        return part, L.complete(rows, s["most"] * s["ratio"] ** part.astype(float)) @ s["A"]

    return indexed(points, setting, make, "double", "far-hash", stored, 8, n)


def far_look(Q: np.ndarray, s: dict) -> np.ndarray:
    lifted = L.lifted_query(Q, s["pairs"], False)
    reach = np.linalg.norm(lifted, axis=1, keepdims=True)
    return np.concatenate([lifted @ s["A"], reach], axis=1)


def nth_greatest(rows: np.ndarray, nth: int) -> np.ndarray:
    return greatest(rows, [nth])[0]


def greatest(rows: np.ndarray, wanted: list[int]) -> list[np.ndarray]:
    """The nth greatest numbers of each column of non-negative numbers, for each n wanted, at most the number of rows. Rows are merged by pairs: the r-th of two falling lists is the greatest of the lesser
    ones of their i-th and (r - i)-th, so that all columns take the same steps."""
    size = 1 << max(len(rows) - 1, 0).bit_length()
    lists = [rows if len(rows) == size else np.concatenate([rows, np.zeros((size - len(rows), rows.shape[1]), rows.dtype)])]
    half, most = size // 2, max(wanted)
    while half:
        a, b, merged = [one[:half] for one in lists], [one[half:] for one in lists], []
        for r in range(1, min(most, 2 * len(lists)) + 1):
            if half == 1 and r not in wanted:
                merged.append(None)  # the last merge gives what is wanted
                continue
            best = np.maximum(a[r - 1], b[r - 1]) if r <= len(lists) else None
            for i in range(max(1, r - len(lists)), min(r - 1, len(lists)) + 1):
                lesser = np.minimum(a[i - 1], b[r - i - 1])
                best = lesser if best is None else np.maximum(best, lesser, out=best)
            merged.append(best)
        lists, half = merged, half // 2
    return [lists[n - 1][0] for n in wanted]


class Seen:
    """Score of a point by the gap that ``separation`` projections pass: with the threshold falling from far to near, points become candidates
    in this order, as each must be seen beyond the threshold in that many projections.

    Gaps are taken with 16 bits (24 for planes out of their reach); scores that these can't tell for certain are worked out again with 53. Several separations take one series of gaps."""

    def __init__(self, *separations: int):
        self.separations, self.kinds = separations, len(separations)

    def alone(self) -> list[Seen]:
        return [Seen(n) for n in self.separations]

    def view(self, keys: np.ndarray, part: np.ndarray, s: dict) -> tuple:
        """keys, part, the keys by projection in units, the unit, the reach, and the largest key."""
        largest = float(np.abs(keys).max(initial=0.0))
        reach = max(largest, s.get("furthest", 1.5 * largest))
        if not 1e-290 < reach < 1e290:
            return keys, part, None, 0.0, 0.0, largest
        unit = reach / 16_300  # gaps of up to two reaches
        rows = keys / unit
        return keys, part, np.ascontiguousarray(np.rint(rows, out=rows).astype(np.int16).T), unit, reach, largest

    def __call__(self, view: tuple, key: np.ndarray, s: dict) -> np.ndarray:
        return self.all(view, key, s)[0]

    def gaps(self, view: tuple, key: np.ndarray) -> tuple[np.ndarray, float, float]:
        """The gaps in units, the unit, and by how much they may be wrong."""
        keys, _, rows, unit, reach, largest = view
        look = key[:-1]
        furthest = float(np.abs(look).max(initial=0.0))
        if rows is not None and furthest <= reach:
            gap = rows - np.rint(look / unit).astype(np.int16)[:, None]
            return np.abs(gap, out=gap), unit, 1.01 * unit
        rows = np.ascontiguousarray(keys.T, dtype=np.float32 if largest + furthest < 1e30 else np.float64)
        gap = rows - look.astype(rows.dtype)[:, None]
        return np.abs(gap, out=gap), 1.0, 3e-7 * (largest + furthest)

    @staticmethod
    def most(key: np.ndarray, s: dict) -> np.ndarray:
        """Of each part, five standard errors of the longest possible gap."""
        return np.maximum(5.0 * (s["most"] * s["ratio"] ** np.arange(s["parts"], dtype=float) + key[-1]), 1e-300)

    def all(self, view: tuple, key: np.ndarray, s: dict) -> list[np.ndarray]:
        keys, part, bins, out = view[0], view[1], s["bins"], []
        if not len(keys):
            return [np.zeros(0, dtype=np.int64)] * self.kinds
        (gap, unit, wrong), most = self.gaps(view, key), self.most(key, s)
        share = np.minimum(bins / most, 1e30)
        scale, room = (v.astype(np.float32).take(part) for v in (unit * share, np.minimum(wrong * share, 2.0 * bins) + 1e-3))
        for kind, far in enumerate(greatest(gap, [min(n, len(gap)) for n in self.separations])):
            value = np.minimum(far * scale, np.float32(2 * bins))
            level, highest = (value - room).astype(np.int32), (value + room).astype(np.int32)
            unsure = ((level != highest) & (level < bins)).nonzero()[0]
            level = np.minimum(level, bins, out=level)
            if len(unsure):
                level[unsure] = self.exact(kind, keys.take(unsure, axis=0), key, most.take(part.take(unsure)), bins)
            out.append(level)
        return out

    def exact(self, kind: int, keys: np.ndarray, key: np.ndarray, most: np.ndarray, bins: int) -> np.ndarray:
        gaps = np.abs(keys - key[:-1])
        at = gaps.shape[1] - min(self.separations[kind], gaps.shape[1])
        return np.minimum(np.partition(gaps, at, axis=1)[:, at] / most * bins, bins).astype(np.int64)

    def nearing(self, view: tuple, key: np.ndarray, part: np.ndarray, s: dict) -> Passed:
        return Passed(self, view, key, s)


class Passed:
    """A block's gaps of one plane: a point reaches a cut if as many gaps as the separation says pass the cut's threshold, which is found without putting gaps in
    order. Points that miss it by no more than rounding are among them; levels() gives the whole scores."""

    def __init__(self, seen: Seen, view: tuple, key: np.ndarray, s: dict):
        self.seen, self.view, self.key, self.s = seen, view, key, s
        (self.gap, self.unit, self.wrong), self.most = seen.gaps(view, key), seen.most(key, s)

    def least(self, cuts: np.ndarray, most: np.ndarray) -> np.ndarray:
        """The gaps at which scores begin, with room for what gaps are wrong by."""
        low = (cuts * (most / self.s["bins"]) * (1 - 1e-6) - 1.01 * self.wrong) / self.unit
        return (low if self.gap.dtype.kind == "f" else np.clip(np.floor(low), 0, 32_767)).astype(self.gap.dtype)

    def passing(self, kind: int, gap: np.ndarray, least: np.ndarray) -> np.ndarray:
        return np.add.reduce((gap >= least).view(np.uint8), axis=0, dtype=np.uint8 if len(gap) < 256 else np.uint16) >= min(self.seen.separations[kind], len(gap))

    def reaching(self, kind: int, cut: np.ndarray, taken: Callable) -> np.ndarray:
        return self.passing(kind, self.gap, self.least(cut, self.most).take(self.view[1])).nonzero()[0]

    def reached(self, kind: int, at: np.ndarray, cuts: np.ndarray) -> np.ndarray:
        return self.passing(kind, self.gap.take(at, axis=1), self.least(cuts, self.most.take(self.view[1].take(at))))

    def levels(self, kind: int, at: np.ndarray) -> np.ndarray:
        keys, part, rows, *rest = self.view
        keys, part = keys.take(at, axis=0), part.take(at)
        if len(at) > 256:
            return self.seen.alone()[kind]((keys, part, rows if rows is None else rows[:, at], *rest), self.key, self.s)
        return self.seen.exact(kind, keys, self.key, self.most.take(part), self.s["bins"])


def far_search(index: HashIndex, planes: DataFrame, k: int = 10, separation: int = 4, budget: float | dict[int, float] = 0.1, timed: bool = False) -> DataFrame:
    """Verify the points of each part that are the first to be seen far away in ``separation`` projections, up to a share of the part."""
    return best_scored(index, planes, far_look, Seen(separation), k, budget, timed)


# --- sphere hashing ---


def signs(X: np.ndarray, s: dict, query: bool) -> np.ndarray:
    """Bits of each row: pairs of signs, signs of products, or signs of lifted projections; planes get the opposite of points that lie in them."""
    U, V = X @ s["U"], X @ s["V"]
    if s["kind"] == "pair":
        return np.concatenate([U > 0, (V > 0) ^ query], axis=-1)
    if s["kind"] == "bilinear":
        return ((U * V) > 0) ^ query
    return (L.sampled_rows(X, s["pairs"]) @ s["A"] > 0) ^ query


def sphere_build(points: DataFrame, kind: str = "bilinear", bits: int = 8, m: int = 16, seed: int = 42) -> HashIndex:
    d = dimension(points)
    random = np.random.default_rng(seed)
    setting = {"kind": kind, "bits": bits * (2 if kind == "pair" else 1), "m": m, "bins": m, "U": random.standard_normal((d, m * bits)), "V": random.standard_normal((d, m * bits)), "pairs": L.random_pairs(d, 4 * d, seed), "A": random.standard_normal((4 * d, m * bits))}
    return HashIndex(keyed(points, setting, lambda X, s: (np.zeros(len(X), np.int32), code_rows(signs(X, s, False), s)), "int", "sphere-hash"), setting, points.count(), 4)


def code_rows(bits: np.ndarray, s: dict) -> np.ndarray:
    """One number a table from its bits."""
    return (bits.reshape(len(bits), s["bits"], s["m"]).transpose(0, 2, 1) @ (1 << np.arange(s["bits"], dtype=np.int64))).astype(np.int32)


def sphere_search(index: HashIndex, planes: DataFrame, k: int = 10, budget: float = 0.3) -> DataFrame:
    """Verify the points that share most buckets with the plane, up to a share of all points."""
    return best_scored(index, planes, lambda Q, s: code_rows(signs(Q, s, True), s), collisions, k, budget)
