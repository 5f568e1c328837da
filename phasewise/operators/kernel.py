"""The facility pass: one reading of points in order that opens medians or assigns to them.  (M8, M9)

A point of weight w at distance t from the nearest open median opens a median if its draw is below
min(t * w / price, 1) (rule "priced") or min(t * w, 1) (rule "unpriced"); otherwise its weight goes
to that median.  The first point opens.  A point whose effect would pass a limit is rolled back and
the pass stops before it.

``FacilityScan`` takes the points batch by batch and holds the open medians only, so a pass over any
number of points needs no more memory than its medians; ``facility_pass`` takes them all at once.
"""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass
from functools import cached_property

import numpy as np

from ..functions.distance import block_distances

#: Points whose distances are taken at a time.
BLOCK = 64
RULES = ("priced", "unpriced")


@dataclass(frozen=True)
class StopLimits:
    """``cost_basis``: "total" (facility and service) or "service"."""

    cost_cap: float = float("inf")
    median_cap: float = float("inf")
    cost_basis: str = "total"


def _opens(theta: np.ndarray, w: np.ndarray, u: np.ndarray, price: float, rule: str) -> np.ndarray:
    load = theta * w
    if rule == "priced":
        load = load / price if price > 0 else np.where(load > 0, 1.0, 0.0)
    return u < np.minimum(load, 1.0)


class Pool:
    """The medians that any run of a phase has opened: runs read the same points, so their distances to a block
    are taken once for all of them."""

    def __init__(self, d: int, distance: str):
        self.distance, self._at, self.place = distance, np.empty((64, d)), {}

    def add(self, row: int, x: np.ndarray) -> int:
        i = self.place.get(row)
        if i is None:
            i = self.place[row] = len(self.place)
            if i == len(self._at):
                self._at = np.concatenate([self._at, np.empty_like(self._at)])
            self._at[i] = x
        return i

    def coordinates(self, places: np.ndarray) -> np.ndarray:
        return self._at[places]


class Meeting:
    """A block of points, and its distances to the medians of the pool that were open before it."""

    def __init__(self, x: np.ndarray, pool: Pool):
        self.x, self.distance, self.pool, self.known = x, pool.distance, pool, len(pool.place)

    @cached_property
    def gaps(self) -> np.ndarray:
        return block_distances(self.distance, self.x, self.pool._at[: self.known])

    @cached_property
    def inner(self) -> np.ndarray:
        return block_distances(self.distance, self.x, self.x)


class FacilityScan:
    """What one run has done so far.  ``rows``, ``ids`` and ``at`` are the open medians: their places in the
    input, ids and coordinates; ``stop_reason`` is "end" while no limit has been met."""

    def __init__(self, d: int, price: float, *, rule: str = "priced", distance: str = "euclidean", limits: StopLimits = StopLimits(), carried: int = 0, run: int = 0, keep: bool = False, pool: Pool | None = None):
        """``carried`` leading points are medians of earlier phases (for ``gained_raw``); ``keep`` holds every
        point's median and distance; ``pool`` is shared by the runs of a phase."""
        if rule not in RULES:
            raise ValueError(f"unknown opening rule {rule!r}")
        self.price, self.rule, self.distance, self.limits, self.carried, self.run = price, rule, distance, limits, carried, run
        self.pool = pool or Pool(d, distance)
        self._places, self._weight = np.zeros(64, np.int64), np.zeros(64)
        self._gained, self._raw = np.zeros(64, bool), np.zeros(64, bool)
        self._rows: list[int] = []
        self.ids: list[int] = []
        self.read, self.service, self.ssq, self.max_dist, self.stop_reason = 0, 0.0, 0.0, 0.0, "end"
        self.kept: list[tuple[np.ndarray, np.ndarray]] | None = [] if keep else None

    rows = property(lambda self: np.array(self._rows, np.int64))
    at = property(lambda self: self.pool.coordinates(self._places[: len(self._rows)]))
    weight = property(lambda self: self._weight[: len(self._rows)])
    gained = property(lambda self: self._gained[: len(self._rows)])
    gained_raw = property(lambda self: self._raw[: len(self._rows)])
    facility = property(lambda self: self.price * len(self._rows))
    total = property(lambda self: self.service + self.facility)
    to = property(lambda self: np.concatenate([np.zeros(0, np.int64), *(t for t, _ in self.kept)]))
    dist = property(lambda self: np.concatenate([np.zeros(0), *(t for _, t in self.kept)]))

    def _open(self, row: int, ident: int, x: np.ndarray, w: float) -> int:
        m = len(self._rows)
        if m == len(self._weight):
            self._places, self._weight, self._gained, self._raw = (np.concatenate([v, np.zeros_like(v)]) for v in (self._places, self._weight, self._gained, self._raw))
        self._places[m], self._weight[m] = self.pool.add(row, x), w
        self._rows.append(row), self.ids.append(ident)
        return m

    def feed(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray, u: np.ndarray) -> None:
        for part in blocks(len(x)):
            if self.stop_reason != "end":
                return
            self.block(ids[part], Meeting(x[part], self.pool), w[part], u[part])

    def block(self, ids: np.ndarray, meeting: Meeting, w: np.ndarray, u: np.ndarray) -> None:
        """Reads the next block; all runs that share a pool read a block before any reads the next."""
        x = meeting.x
        limits, price, size, start = self.limits, self.price, len(x), self.read
        counted = limits.cost_basis == "total"
        # distances to the medians opened before this block, then only corrections by new ones
        theta, near = np.full(size, np.inf), np.zeros(size, np.int64)
        if self._rows:
            gaps = meeting.gaps[:, self._places[: len(self._rows)]]
            near = gaps.argmin(1)
            theta = gaps[np.arange(size), near]
        opens = _opens(theta, w, u, price, self.rule)
        if not self._rows:
            opens[0] = True
        taken, to, dist = size, np.zeros(size, np.int64), np.zeros(size)
        j = 0
        while j < size:
            stop = j + int(opens[j:].argmax())
            if not opens[stop]:
                stop = size
            if stop > j:  # points j..stop-1 are assigned
                costs = np.cumsum(np.concatenate([[self.service], theta[j:stop] * w[j:stop]]))[1:]
                over = costs + (price * len(self._rows) if counted else 0.0) > limits.cost_cap
                upto = j + int(over.argmax()) if over.any() else stop
                to[j:upto], dist[j:upto] = near[j:upto], theta[j:upto]
                np.add.at(self._weight, near[j:upto], w[j:upto])
                self._gained[near[j:upto]] = True
                self._raw[near[max(j, min(upto, self.carried - start)) : upto]] = True
                self.service = float(costs[upto - j - 1]) if upto > j else self.service
                if upto < stop:
                    self.stop_reason, taken = "cost", upto
                    break
            if stop < size:  # point ``stop`` opens a median
                m = len(self._rows)
                if self.service + (price * (m + 1) if counted else 0.0) > limits.cost_cap:
                    self.stop_reason, taken = "cost", stop
                    break
                if m + 1 > limits.median_cap:
                    self.stop_reason, taken = "medians", stop
                    break
                to[stop] = self._open(start + stop, int(ids[stop]), x[stop], w[stop])
                if stop + 1 < size:
                    gap = meeting.inner[stop + 1 :, stop]
                    closer = (gap < theta[stop + 1 :]).nonzero()[0]  # ties stay with the earlier median
                    if len(closer):
                        gap, closer = gap[closer], closer + (stop + 1)
                        theta[closer] = gap
                        near[closer] = m
                        opens[closer] = _opens(gap, w[closer], u[closer], price, self.rule)
            j = stop + 1
        self.read += taken
        gone = dist[:taken]
        self.ssq += float((w[:taken] * (gone if self.distance == "sqeuclidean" else gone * gone)).sum())
        self.max_dist = max(self.max_dist, float(gone.max(initial=0.0)))
        if self.kept is not None:
            self.kept.append((to[:taken], gone))


class LineScan(FacilityScan):
    """The same pass on one coordinate: the open medians are kept in the order of their places, so a point looks at
    its neighbours only.  Every decision, sum and tie is that of ``FacilityScan``."""

    def __init__(self, d: int, price: float, **how):
        super().__init__(d, price, **how)
        self._sorted: list[float] = []  # places in order, and which median each is
        self._which: list[int] = []
        self._xs: list[float] = []
        self._weight, self._gained, self._raw = [], [], []

    at = property(lambda self: np.array(self._xs, float).reshape(-1, 1))
    weight = property(lambda self: np.array(self._weight, float))
    gained = property(lambda self: np.array(self._gained, bool))
    gained_raw = property(lambda self: np.array(self._raw, bool))

    def block(self, ids: np.ndarray, meeting: Meeting, w: np.ndarray, u: np.ndarray) -> None:
        limits, price, rows, row = self.limits, self.price, self._rows, self.read
        counted, priced, squared = limits.cost_basis == "total", self.rule == "priced", self.distance == "sqeuclidean"
        places, which, weight, gained, raw, service = self._sorted, self._which, self._weight, self._gained, self._raw, self.service
        to, dist, m = [], [], len(rows)
        for ident, x, wi, ui in zip(ids.tolist(), meeting.x[:, 0].tolist(), w.tolist(), u.tolist(), strict=True):
            i = bisect_left(places, x)
            if m:
                if i < m:
                    t, near = places[i] - x, which[i]
                    j = i + 1
                    while j < m and places[j] - x == t:
                        near, j = min(near, which[j]), j + 1
                else:
                    t, near = float("inf"), m
                if i:
                    left = x - places[i - 1]
                    if left <= t:
                        near = which[i - 1] if left < t else min(near, which[i - 1])
                        t, j = left, i - 2
                        while j >= 0 and x - places[j] == t:
                            near, j = min(near, which[j]), j - 1
                if squared:
                    t *= t
                load = t * wi
                if priced:
                    load = load / price if price > 0 else float(load > 0)
                opens = ui < (load if load < 1.0 else 1.0)
            else:
                t, near, opens = 0.0, 0, True
            if opens:
                if service + (price * (m + 1) if counted else 0.0) > limits.cost_cap:
                    self.stop_reason = "cost"
                    break
                if m + 1 > limits.median_cap:
                    self.stop_reason = "medians"
                    break
                places.insert(i, x), which.insert(i, m)
                rows.append(row), self.ids.append(ident), self._xs.append(x)
                weight.append(wi), gained.append(False), raw.append(False)
                to.append(m), dist.append(0.0)
                m += 1
            else:
                cost = service + t * wi
                if cost + (price * m if counted else 0.0) > limits.cost_cap:
                    self.stop_reason = "cost"
                    break
                service = cost
                weight[near] += wi
                gained[near] = True
                if row >= self.carried:
                    raw[near] = True
                to.append(near), dist.append(t)
            row += 1
        self.service, self.read = service, row
        gone = np.array(dist, float)
        self.ssq += float((w[: len(gone)] * (gone if squared else gone * gone)).sum())
        self.max_dist = max(self.max_dist, float(gone.max(initial=0.0)))
        if self.kept is not None:
            self.kept.append((np.array(to, np.int64), gone))


def scan(d: int, price: float, **how) -> FacilityScan:
    return (LineScan if d == 1 else FacilityScan)(d, price, **how)


def blocks(n: int) -> list[slice]:
    return [slice(start, start + BLOCK) for start in range(0, n, BLOCK)]


def facility_pass(x: np.ndarray, w: np.ndarray, u: np.ndarray, price: float, *, ids: np.ndarray | None = None, **how) -> FacilityScan:
    """One pass over all points; ``how`` goes to ``FacilityScan``."""
    done = scan(x.shape[1], price, keep=True, **how)
    done.feed(np.arange(len(x)) if ids is None else ids, x, w, u)
    return done
