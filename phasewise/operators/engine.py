"""The phased miner on the points of one stream, in one worker.  (M10-M19, M23, M30, M31)

``Miner`` holds the state between phases (weighted medians, candidates, floor); ``step`` runs one
phase: independent facility passes over carried medians and unread points, choice of a winner,
marking, ageing and settlement of candidates, and the hand-over of weighted medians.  A phase may also
be fed batch by batch.  ``StreamMiner`` takes the points of a stream as they come and cuts them into
phases; whole streams, stretches of a stored stream and micro-batches all go through it.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

import numpy as np

from ..functions.draws import draws
from ..plans.schedule import grow, plan_phase
from .kernel import FacilityScan, Meeting, Pool, StopLimits, blocks, facility_pass, scan


@dataclass(frozen=True)
class Settings:
    """All choices that the method leaves open, with the literal reading as default."""

    k: int = 2
    outlier_phases: int = 2
    gamma: float = 34.0
    beta: float = 34.0
    log_base: str = "e"
    mode: str = "chunked"  # or "limit_driven"
    num: int = 500
    n_declared: int | None = None
    runs: int | None = None
    seed: int = 1
    draws: str = "hash"
    constant: float = 0.5
    opening_rule: str = "priced"
    distance: str = "euclidean"
    cost_basis: str = "total"
    cost_cap: float | None = None
    median_cap: float | None = None
    plateau: str | None = None  # None, "runs": stop launching runs once two tie; "repass"
    winner: str = "last_to_stop"  # or "cheapest"
    floor_growth: str = "every_phase"  # or "on_breach", "none"
    zero_floor: str = "distinct"  # or "error"
    floor: float | None = None
    candidate_rule: str = "stalled"  # or "stalled_light"
    max_weight: float = 3.0
    absorb_counts: bool = True
    include_first_phase: bool = True
    warmup_phases: int = 0
    rewatch: bool = True
    final_policy: str = "report"  # or "promote", "drop"
    max_phases: int | None = None
    max_stalled_phases: int = 3
    repass: bool = False

    def __post_init__(self):
        for name, values in CHOICES.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} must be one of {values}, not {getattr(self, name)!r}")
        if self.k < 1 or self.outlier_phases < 1 or self.num < 1:
            raise ValueError("k, outlier_phases and num start at 1")


CHOICES = {
    "log_base": ("e", "2", "10"), "mode": ("chunked", "limit_driven"), "draws": ("hash", "constant", "always_at_price"), "opening_rule": ("priced", "unpriced"),
    "cost_basis": ("total", "service"), "plateau": (None, "runs", "repass"), "winner": ("last_to_stop", "cheapest"), "floor_growth": ("every_phase", "on_breach", "none"),
    "zero_floor": ("distinct", "error"), "candidate_rule": ("stalled", "stalled_light"), "final_policy": ("report", "promote", "drop"),
}


class NoProgress(RuntimeError):
    """Too many phases in a row read no new point."""


@dataclass
class Candidate:
    median_id: int
    first_phase: int
    age: int
    score: int
    weight: float


@dataclass
class Log:
    """Rows of the result tables."""

    phases: list[dict] = field(default_factory=list)
    runs: list[dict] = field(default_factory=list)
    medians: list[dict] = field(default_factory=list)
    verdicts: list[dict] = field(default_factory=list)
    holds_medians: bool = True
    last_only: bool = False  # of the medians, only those of the last phase


def closest_pair(x: np.ndarray, distance: str) -> float:
    from ..functions.distance import distances

    return min((float(distances(distance, x[i + 1 :], x[i]).min()) for i in range(len(x) - 1)), default=0.0)


def first_points(x: np.ndarray, k: int, zero_floor: str) -> np.ndarray:
    if zero_floor == "error":
        return x[: k + 1]
    seen, rows = set(), []
    for i, row in enumerate(map(tuple, x)):
        if row not in seen:
            seen.add(row)
            rows.append(i)
            if len(rows) > k:
                break
    return x[rows]


def pick_winner(passes: list[FacilityScan], rule: str) -> FacilityScan:
    """Most points read (ties: lower cost, then lower run), or lowest cost."""
    if rule == "cheapest":
        return min(passes, key=lambda p: (p.total, -p.read, p.run))
    return min(passes, key=lambda p: (-p.read, p.total, p.run))


class Miner:
    def __init__(self, s: Settings, d: int):
        self.s, self.d = s, d
        self.ids = np.zeros(0, np.int64)
        self.x = np.zeros((0, d))
        self.w = np.zeros(0)
        self.born = np.zeros(0, np.int64)
        self.candidates: dict[int, Candidate] = {}
        self.floor = s.floor
        self.phase = 0
        self.stalled_phases = 0
        self.seen = 0
        self.once: set[int] = set()  # settled inliers, kept where they are not watched again
        self.log = Log()
        self.passes: list[FacilityScan] = []

    # state that a stream keeps between batches ---------------------------------------------

    def state(self) -> dict:
        return {"ids": self.ids.tolist(), "x": self.x.ravel().tolist(), "w": self.w.tolist(), "born": self.born.tolist(), "candidates": [asdict(c) for c in self.candidates.values()], "floor": self.floor, "phase": self.phase, "stalled": self.stalled_phases, "seen": self.seen, "once": sorted(self.once)}

    @classmethod
    def restored(cls, s: Settings, d: int, state: dict) -> Miner:
        m = cls(s, d)
        m.ids, m.w, m.born = np.array(state["ids"], np.int64), np.array(state["w"], float), np.array(state["born"], np.int64)
        m.x = np.array(state["x"], float).reshape(-1, d)
        m.candidates = {c["median_id"]: Candidate(**c) for c in state["candidates"]}
        m.floor, m.phase, m.stalled_phases, m.seen = state["floor"], state["phase"], state["stalled"], state["seen"]
        m.once = set(state["once"])
        return m

    # one phase ------------------------------------------------------------------------------

    def set_floor(self, x: np.ndarray) -> bool:
        """False while the stream has too few different points for a floor."""
        if self.floor is None:
            first = first_points(x, self.s.k, self.s.zero_floor)
            if len(first) < 2:
                return False
            closest = closest_pair(first, self.s.distance)
            if closest <= 0:
                raise ValueError("the first points repeat: zero floor")
            self.floor = closest / self.s.beta
        return True

    def open_phase(self, x: np.ndarray, n: float) -> None:
        """Starts the runs of a phase, whose first points are ``x``, with the carried medians."""
        s = self.s
        self.set_floor(np.concatenate([self.x, x]))
        self.phase += 1
        floor = self.floor if self.floor is not None else 0.0
        self.plan = plan_phase(self.phase, floor, k=s.k, n=n, gamma=s.gamma, beta=s.beta, log_base=s.log_base, runs=s.runs)
        self.limits = StopLimits(self.plan.cost_cap if s.cost_cap is None else s.cost_cap, self.plan.median_cap if s.median_cap is None else s.median_cap, s.cost_basis)
        if self.floor is None:
            self.limits = replace(self.limits, cost_cap=float("inf"))
        self.pool = Pool(self.d, s.distance)
        self.passes = [scan(self.d, self.plan.price, rule=s.opening_rule, distance=s.distance, limits=self.limits, carried=len(self.ids), run=run, pool=self.pool) for run in range(self.plan.runs)]
        self.fed = 0
        self._scan(self.ids, self.x, self.w)

    def _scan(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray) -> None:
        s = self.s
        reading = [(p, draws(s.draws, s.seed, p.run, self.phase, ids, s.constant)) for p in self.passes if p.stop_reason == "end"]
        for part in blocks(len(ids)):
            if not reading:
                break
            meeting = Meeting(x[part], self.pool)
            for p, u in reading:
                p.block(ids[part], meeting, w[part], u[part])
            reading = [(p, u) for p, u in reading if p.stop_reason == "end"]

    def feed(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray) -> bool:
        """Reads points into the open phase; False once all its runs have stopped."""
        self.fed += len(ids)
        self._scan(ids, x, w)
        return any(p.stop_reason == "end" for p in self.passes)

    def step(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray, n: float) -> int:
        """Runs one phase on the carried medians and these points; returns how many were read."""
        self.open_phase(x, n)
        self.feed(ids, x, w)
        return self.close_phase()

    def close_phase(self) -> int:
        """Chooses the winner, settles candidates, hands over the medians; returns how many points were read."""
        s, plan, limits = self.s, self.plan, self.limits
        floor = self.floor if self.floor is not None else 0.0
        passes, totals = [], set()
        for p in self.passes:
            passes.append(p)
            if s.plateau == "runs" and p.total in totals:
                break
            totals.add(p.total)
        carried = len(self.ids)
        won = pick_winner(passes, s.winner)
        for p in passes:
            self.log.runs.append({"phase": self.phase, "run": p.run, "points_read": max(p.read - carried, 0), "medians": len(p.rows), "total_cost": p.total, "stop_reason": p.stop_reason})
        breached = won.stop_reason != "end"
        # a limit-driven phase is offered all the rest; what it looks at is what it reads, and the point it stops at
        looked = self.fed if s.mode == "chunked" else max(won.read - carried, 0) + breached
        read = max(won.read - carried, 0)
        # carried medians that were not read stay as they are
        rest = np.arange(min(won.read, carried), carried)
        new_ids, rows = np.array(won.ids, np.int64), np.array(won.rows, np.int64)
        born = np.where(rows < carried, np.append(self.born, 0)[np.minimum(rows, carried)], self.phase)
        self._settle(set(self.ids[: min(won.read, carried)].tolist()), new_ids, won)
        keep = np.array([i not in self.retired for i in won.ids], bool)
        at, weight = won.at, won.weight
        if self.log.last_only:
            self.log.medians.clear()
        before = {int(i): float(v) for i, v in zip(self.ids, self.w, strict=True)} if self.log.holds_medians else {}
        for j, i in enumerate(won.ids if self.log.holds_medians else ()):
            c = self.candidates.get(i)
            self.log.medians.append({"phase": self.phase, "median_id": i, "vec": at[j].tolist(), "weight_before": before.get(i, 0.0), "weight_after": float(weight[j]), "born_phase": int(born[j]), "is_candidate": c is not None or i in self.retired, "score": c.score if c else 0, "age": c.age if c else 0})
        self.log.phases.append({"phase": self.phase, "floor": floor, "price": plan.price, "runs": len(passes), "winner_run": won.run, "points_in": looked, "points_read": read, "unread": looked - read, "medians_out": int(keep.sum()) + len(rest), "new_medians": int((rows >= carried).sum()), "service_cost": won.service, "facility_cost": won.facility, "total_cost": won.total, "ssq": won.ssq, "max_dist": won.max_dist, "stop_reason": won.stop_reason})
        self.ids, self.x = np.concatenate([new_ids[keep], self.ids[rest]]), np.concatenate([at[keep], self.x[rest]])
        self.w, self.born = np.concatenate([weight[keep], self.w[rest]]), np.concatenate([born[keep], self.born[rest]])
        if s.repass:
            self._compact(plan, limits)
        if self.floor is not None:
            self.floor = grow(self.floor, s.beta, s.floor_growth, breached)
        self.seen += read
        self.stalled_phases = 0 if read or not self.fed else self.stalled_phases + 1
        if self.stalled_phases >= s.max_stalled_phases:
            raise NoProgress(f"{self.stalled_phases} phases read no new point")
        self.passes = []
        return read

    def _settle(self, reread: set[int], new_ids: np.ndarray, won: FacilityScan) -> None:
        """Ages candidates and gives verdicts; ``self.retired`` are the outliers of this phase."""
        s = self.s
        self.retired: set[int] = set()
        gained = won.gained if s.absorb_counts else won.gained_raw
        grew = {int(i): bool(g) for i, g in zip(new_ids, gained, strict=True)}
        weight = {int(i): float(v) for i, v in zip(new_ids, won.weight, strict=True)}
        for i, c in list(self.candidates.items()):
            if i not in reread:
                continue  # a limit fired in the carried prefix: nothing moves
            if i not in grew:
                self._verdict(c, "absorbed")
                del self.candidates[i]
                continue
            c.age += 1
            c.weight = weight[i]
            c.score += not grew[i]
            self._at_age(c)
        fresh = [] if self.phase <= s.warmup_phases else [i for i in weight if not grew[i] and i not in self.candidates and i not in self.retired and i not in self.just_inlier]
        for i in fresh:
            if s.candidate_rule == "stalled_light" and weight[i] > s.max_weight or not s.rewatch and i in self.once:
                continue
            first = 1 if s.include_first_phase else 0
            c = self.candidates[i] = Candidate(i, self.phase, first, first, weight[i])
            self._at_age(c)
        self.just_inlier = set()

    just_inlier: set[int] = set()

    def _at_age(self, c: Candidate) -> None:
        if c.age < self.s.outlier_phases:
            return
        if c.score == self.s.outlier_phases:
            self._verdict(c, "outlier")
            self.retired.add(c.median_id)
        else:
            self._verdict(c, "inlier")
            self.just_inlier = self.just_inlier | {c.median_id}
            if not self.s.rewatch:
                self.once.add(c.median_id)
        self.candidates.pop(c.median_id, None)

    def _verdict(self, c: Candidate, verdict: str) -> None:
        self.log.verdicts.append({"median_id": c.median_id, "first_phase": c.first_phase, "settled_phase": self.phase, "age": c.age, "score": c.score, "weight": c.weight, "verdict": verdict})

    def _compact(self, plan, limits: StopLimits) -> None:
        """Passes over the medians themselves at a price that grows until both limits hold."""
        price, last = plan.price, None
        while len(self.ids) > limits.median_cap or price * len(self.ids) > limits.cost_cap:
            price *= self.s.beta
            p = facility_pass(self.x, self.w, draws(self.s.draws, self.s.seed, -1, self.phase, self.ids, self.s.constant), price, distance=self.s.distance)
            self.ids, self.x, self.w, self.born = self.ids[p.rows], self.x[p.rows], p.weight.copy(), self.born[p.rows]
            if self.s.plateau == "repass" and p.total == last or len(self.ids) <= 1:
                break
            last = p.total
        self.candidates = {i: c for i, c in self.candidates.items() if i in set(self.ids.tolist())}

    # whole streams --------------------------------------------------------------------------

    def run(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray) -> Log:
        """All points of a stream in order."""
        stream = StreamMiner(self.s, self.d, n=self.s.n_declared or len(ids), miner=self)
        stream.add(ids, x, w)
        stream.flush(final=True)
        return self.log

    def finish(self) -> Log:
        """Verdicts of the candidates that are still watched."""
        s = self.s
        for c in self.candidates.values():
            if s.final_policy == "promote" and c.score == c.age:
                self._verdict(c, "outlier")
            elif s.final_policy != "drop":
                self._verdict(c, "pending")
        return self.log


class StreamMiner:
    """A stream's miner and the points that it has not read yet.  A chunk closes when ``num`` points are
    there; what a limit leaves unread heads the next chunk.  In limit-driven mode a phase takes points
    until all its runs have stopped, and what the winner left unread begins the next one; an open phase
    lives as long as the process, so its points are not given away before it ends."""

    def __init__(self, settings: Settings, d: int, state: str | None = None, *, n: float | None = None, miner: Miner | None = None):
        """``n``: the declared length; without one it is the next power of two of the points so far."""
        self.settings, self.d, self.n = settings, d, n or settings.n_declared
        held = json.loads(state) if state else None
        self.miner = miner or (Miner.restored(settings, d, held["miner"]) if held else Miner(settings, d))
        self.ids = np.array(held["ids"] if held else [], np.int64)
        self.x = np.array(held["x"] if held else [], float).reshape(-1, d)
        self.w = np.array(held["w"] if held else [], float)
        self.fed = 0  # points at hand that the open phase has been fed

    def state(self) -> str:
        """What the next batch needs; a phase that is still open starts again from its first point."""
        if self.miner.passes:
            raise RuntimeError("a phase is open")
        return json.dumps({"miner": self.miner.state(), "ids": self.ids.tolist(), "x": self.x.ravel().tolist(), "w": self.w.tolist()})

    def _more_phases(self) -> bool:
        return self.settings.max_phases is None or self.miner.phase < self.settings.max_phases

    def _length(self, here: int) -> float:
        return self.n or 1 << max(int(self.miner.seen + here - 1).bit_length(), 1)

    def _drop(self, read: int) -> None:
        self.ids, self.x, self.w, self.fed = self.ids[read:], self.x[read:], self.w[read:], 0

    def add(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray) -> None:
        """Takes points in stream order and runs the phases that they complete."""
        self.ids, self.x, self.w = np.concatenate([self.ids, ids]), np.concatenate([self.x, x]), np.concatenate([self.w, w])
        if self.settings.mode == "limit_driven":
            while self.fed < len(self.ids) and self._more_phases() and not self._extend():
                pass
            return
        num = self.settings.num
        while len(self.ids) >= num and self._more_phases():
            self._drop(self.miner.step(self.ids[:num], self.x[:num], self.w[:num], self._length(num)))

    def _extend(self) -> bool:
        """Feeds the open phase all points at hand; True while it wants more."""
        if not self.miner.passes:
            self.miner.open_phase(self.x, self._length(len(self.ids)))
        more = self.miner.feed(self.ids[self.fed :], self.x[self.fed :], self.w[self.fed :])
        self.fed = len(self.ids)
        if not more:
            self._drop(self.miner.close_phase())
        return more

    def flush(self, final: bool = False) -> None:
        """Reads all that is left, in shorter phases; ``final`` also ends the watch of candidates."""
        while len(self.ids) and self._more_phases():
            if self.settings.mode == "limit_driven":
                if self._extend():
                    self._drop(self.miner.close_phase())
            else:
                num = self.settings.num
                self._drop(self.miner.step(self.ids[:num], self.x[:num], self.w[:num], self._length(min(num, len(self.ids)))))
        if final:
            self.miner.finish()
