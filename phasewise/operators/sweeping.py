"""Many settings over one stream.  (M29)

Cells (settings) that differ only in what sets a phase's price and limits read the same points with the same
draws.  As long as a point opens for all of them or for none, they hold the same medians: they are one group
and each phase is done once.  Where a point parts them, the phase starts again for either part.  A limit is a
bound on sums that only grow within a phase, so it has fired where a phase's end passes it; such a cell, and
one whose settings are not in ``SHARED``, is left to ``Miner``.  Every result is that of ``Miner``.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass, field
from hashlib import md5
from operator import sub

import numpy as np
import pyarrow as pa

from ..plans.schedule import grow, log, multiplier
from .engine import Miner, Settings

#: Settings that groups know.
SHARED = {
    "mode": ("chunked",), "runs": (1,), "draws": ("hash",), "opening_rule": ("priced",), "distance": ("euclidean", "manhattan", "chebyshev"), "cost_basis": ("total",), "zero_floor": ("distinct",),
    "candidate_rule": ("stalled",), "absorb_counts": (True,), "rewatch": (True,), "final_policy": ("report", "drop"), "max_phases": (None,), "repass": (False,),
}
#: Settings that are equal within a group.
ALIKE = ("num", "outlier_phases", "seed", "include_first_phase", "warmup_phases", "distance")
#: Coordinates whose gaps neither overflow nor vanish when they are squared.
MOST = 1e150


class Cell:
    """What a cell has of its own: floor, price, limits, and its phases' costs."""

    def __init__(self, place: int, s: Settings, n: int):
        self.place, self.s, self.floor, self.costs = place, s, s.floor, []
        self.by = s.k * (1 + log(s.n_declared or n, s.log_base))
        self.multiplier = multiplier(s.gamma, s.beta)
        self.median_cap = 4 * self.by * self.multiplier if s.median_cap is None else s.median_cap
        self.set_price()

    def set_price(self) -> None:
        self.price = (self.floor or 0.0) / self.by
        self.cost_cap = math.inf if self.floor is None else 4 * self.floor * self.multiplier if self.s.cost_cap is None else self.s.cost_cap

    def close(self, total: float, medians: int) -> bool:
        """Notes a phase; False where one of its limits has fired."""
        if total > self.cost_cap or medians > self.median_cap:
            return False
        self.costs.append(total)
        if self.floor is not None and self.s.floor_growth == "every_phase":
            self.floor = grow(self.floor, self.s.beta, "every_phase", False)
            self.set_price()
        return True


@dataclass
class Group:
    """Cells with the same medians.  ``age``: 0 for a median that is not watched, else one more than its age as a
    candidate, negative once it has gained."""

    cells: list[Cell]
    read: int = 0
    phase: int = 0
    outliers: int = 0
    ids: list[int] = field(default_factory=list)
    x: list[float] = field(default_factory=list)
    w: list[float] = field(default_factory=list)
    age: list[int] = field(default_factory=list)


def _closest(x: list[float], k: int, distance: str) -> float | None:
    """The closest pair of the first k + 1 different places; None where there is one place only."""
    first = sorted(list(dict.fromkeys(x))[: k + 1])
    if len(first) < 2:
        return None
    gap = min(map(sub, first[1:], first))
    return math.sqrt(gap * gap) if distance == "euclidean" else gap


class LineSweep:
    """All groups of one stream on one coordinate."""

    def __init__(self, ids: list[int], x: list[float], w: list[float]):
        self.ids, self.x, self.w, self.least = ids, x, w, min(w)  # a median weighs no less than a point
        self.known: dict[tuple, float] = {}  # draws
        self.firsts: dict[tuple, float | None] = {}

    def draw(self, seed: int, phase: int, ident: int) -> float:
        key = (seed, phase, ident)
        u = self.known.get(key)
        if u is None:
            u = self.known[key] = int.from_bytes(md5(b"%d|0|%d|%d" % key).digest()[:4]) / 4294967296.0
        return u

    def run(self, cells: list[Cell]) -> dict[int, tuple[int, int, float, int]]:
        """{place: (phases, outliers, total cost, medians)}, without the cells that a limit stops."""
        alike: dict[tuple, list[Cell]] = {}
        for c in cells:
            alike.setdefault(tuple(getattr(c.s, name) for name in ALIKE), []).append(c)
        open_groups, done = [Group(group) for group in alike.values()], {}
        while open_groups:
            g = open_groups.pop()
            while g.cells and g.read < len(self.ids):
                parts = self.step(g)
                if parts:
                    open_groups += parts
                    break
            else:
                done |= {c.place: (g.phase, g.outliers, sum(c.costs), len(g.x)) for c in g.cells}
        return done

    def set_floors(self, g: Group, fresh: list[float], s: Settings) -> None:
        for c in g.cells:
            if c.floor is None:
                key = (s.num, c.s.k, s.distance)
                if g.phase:
                    closest = _closest(g.x + fresh, c.s.k, s.distance)
                else:
                    closest = self.firsts[key] if key in self.firsts else self.firsts.setdefault(key, _closest(fresh, c.s.k, s.distance))
                if closest is not None:
                    c.floor = closest / c.s.beta
                    c.set_price()

    def step(self, g: Group) -> list[Group] | None:
        """One phase of a group; where its cells part, the groups that do it instead."""
        s, phase = g.cells[0].s, g.phase + 1
        part = slice(g.read, g.read + s.num)
        ids, xs, ws = self.ids[part], self.x[part], self.w[part]
        fresh = len(ids)
        self.set_floors(g, xs, s)
        prices = [c.price for c in g.cells]
        high, low = max(prices), min(prices)
        zeros, gained, service = [0] * fresh, [], 0.0
        if self._far(sorted(g.x + xs), high):  # every point opens, whatever its draw
            opened, at, weight, age = g.ids + ids, g.x + xs, g.w + ws, g.age + zeros
        else:
            places, held = sorted(g.x), len(g.x)
            if not self._far(places, high):  # carried medians may join one another
                places, held = [], 0
            ids, xs, ws, age = g.ids[held:] + ids, g.x[held:] + xs, g.w[held:] + ws, g.age[held:] + zeros
            which, rows, m = dict(zip(g.x[:held], range(held), strict=True)), [], held
            for row, x in enumerate(xs):
                near = which.get(x)
                if near is not None:
                    gained.append((near, ws[row]))
                    continue
                i = bisect_left(places, x)
                if m:
                    t = places[i] - x if i < m else math.inf
                    if i and x - places[i - 1] < t:
                        t = x - places[i - 1]
                    load = t * ws[row]
                    if not load or load < high:
                        u = self.draw(s.seed, phase, ids[row])
                        if not self.opens(u, load, high):
                            if self.opens(u, load, low):
                                return self.parted(g, u, load)
                            near, j = m, i
                            while j < m and places[j] - x == t:
                                near, j = min(near, which[places[j]]), j + 1
                            j = i - 1
                            while j >= 0 and x - places[j] == t:
                                near, j = min(near, which[places[j]]), j - 1
                            service += load
                            gained.append((near, ws[row]))
                            continue
                places.insert(i, x)
                which[x] = m
                rows.append(row)
                m += 1
            opened, at = g.ids[:held] + [ids[r] for r in rows], g.x[:held] + [xs[r] for r in rows]
            weight, age = g.w[:held] + [ws[r] for r in rows], g.age[:held] + [age[r] for r in rows]
            for near, w in gained:
                weight[near] += w
        m = len(at)
        g.cells = [c for c in g.cells if c.close(service + c.price * m, m)]
        g.phase, g.read = phase, g.read + fresh
        self.settle(g, s, opened, at, weight, {near for near, _ in gained}, age)
        return None

    def _far(self, places: list[float], price: float) -> bool:
        """True where these places in order are so far apart that each opens at this price."""
        load = min(map(sub, places[1:], places), default=math.inf) * self.least
        return load > 0 and load >= price

    @staticmethod
    def opens(u: float, load: float, price: float) -> bool:
        load = load / price if price > 0 else float(load > 0)
        return u < (load if load < 1.0 else 1.0)

    def parted(self, g: Group, u: float, load: float) -> list[Group]:
        apart = ([], [])
        for c in g.cells:
            apart[self.opens(u, load, c.price)].append(c)
        return [Group(cells, g.read, g.phase, g.outliers, g.ids, g.x, g.w, g.age) for cells in apart]

    @staticmethod
    def settle(g: Group, s: Settings, opened: list[int], at: list[float], weight: list[float], gained: set[int], age: list[int]) -> None:
        """Ages the candidates, watches what has not grown, and hands over what is not retired."""
        most = s.outlier_phases
        first = 0 if g.phase <= s.warmup_phases else 2 if s.include_first_phase else 1
        ages = [a + 1 if a > 0 else a - 1 if a else first for a in age]
        for j in gained:
            ages[j] = -abs(age[j]) - 1 if age[j] else 0
        if min(ages) < -most:
            ages = [a if a >= -most else 0 for a in ages]
        if max(ages) > most:
            stay = [j for j, a in enumerate(ages) if a <= most]
            g.outliers += len(ages) - len(stay)
            opened, at, weight, ages = ([v[j] for j in stay] for v in (opened, at, weight, ages))
        g.ids, g.x, g.w, g.age = opened, at, weight, ages


def sweep_stream(cells: list[Settings], ids: np.ndarray, x: np.ndarray, w: np.ndarray) -> list[tuple[int, int, float, int]]:
    """(phases, outliers, total cost, medians) of every cell on a stream in order."""
    done = {}
    if x.shape[1] == 1 and len(np.unique(ids)) == len(ids) and (np.abs(x) < MOST).all() and ((w > 0) & (w < math.inf)).all():
        shared = [Cell(i, s, len(ids)) for i, s in enumerate(cells) if all(getattr(s, name) in values for name, values in SHARED.items())]
        done = LineSweep(ids.tolist(), x[:, 0].tolist(), w.tolist()).run(shared)
    for i, s in enumerate(cells):
        if i not in done:
            log = Miner(s, x.shape[1]).run(ids, x, w)
            done[i] = (len(log.phases), sum(v["verdict"] == "outlier" for v in log.verdicts), sum(float(p["total_cost"]) for p in log.phases), int(log.phases[-1]["medians_out"]))
    return [done[i] for i in range(len(cells))]


def streams(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(point ids, coordinates, weights) of one stream after the other, from rows sorted by stream and ordinal; one
    stream is held at a time."""
    held, key = [], None
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        keys = batch.column("stream_key")
        code = keys.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
        ids, w = batch.column("point_id").to_numpy(zero_copy_only=False), batch.column("weight").to_numpy(zero_copy_only=False)
        x = batch.column("vec").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(n, -1)
        starts = [0, *(np.flatnonzero(np.diff(code)) + 1).tolist(), n]
        for a, b in zip(starts, starts[1:]):
            if held and (a or keys[0].as_py() != key):
                yield tuple(np.concatenate(parts) for parts in zip(*held, strict=True))
                held = []
            held.append((ids[a:b], x[a:b], w[a:b]))
        key = keys[n - 1].as_py()
    if held:
        yield tuple(np.concatenate(parts) for parts in zip(*held, strict=True))
