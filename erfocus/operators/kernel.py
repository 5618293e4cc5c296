"""A chain over one canopy: single-mention moves with local rescoring.

The chain is sequential, so it runs in one task on a bounded canopy.  Every random number is a hash of
(seed, run, step, slot); a retried task makes the same chain.  Slots: 0 branch, 1 source entity, 2 mention in
it, 3 target entity, 4 acceptance, 5-6 and 7-8 the two influence draws, 9-16 further draws of the first.

Entities are named by their smallest member and listed in that order while they have members; where a new
entity may be a target it is listed last.  A proposal that moves nothing (the query's own mention where the sampler
holds it in place, the mention's own entity, a single mention to a new entity) counts as a proposal and is not
accepted.  Samplers that do not name the query's entity let the query's own mention move like any other: it joins the
largest fragment of its entity instead of waiting for that to come to it.
"""

from __future__ import annotations

import math
from bisect import bisect_left, insort
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np

from erfocus.functions.rand import SPAN, py_h32
from erfocus.operators import accept as accepting
from erfocus.operators.alias import place
from erfocus.operators.pairs import Rows

SAMPLERS = ("uniform", "pin_target", "influence_both", "influence_to_query", "expel", "expel_both")
NEW = -1
REDRAWS = (5, 9, 11, 13, 15)


@dataclass
class Biased:
    """Draws in proportion to weights: by an alias table, or by integer cumulative weights."""

    prob: np.ndarray | None = None
    alias: np.ndarray | None = None
    whole: np.ndarray | None = None

    def __post_init__(self):
        if self.whole is not None:
            self.cumulative = np.cumsum(self.whole)

    def draw(self, h1: int, h2: int) -> int:
        if self.whole is not None:
            # The first place whose cumulative weight times SPAN is over h1 times the whole, in whole numbers.
            target = h1 * int(self.cumulative[-1]) // SPAN
            return min(int(np.searchsorted(self.cumulative, target, side="right")), len(self.cumulative) - 1)
        return place(h1 / SPAN, h2 / SPAN, self.prob, self.alias)


@dataclass
class Query:
    """A query's own member and its draws."""

    query_id: int
    at: int
    influence: Biased | None = None
    inverse: Biased | None = None


@dataclass
class EntityFeatures:
    """Entity-wide terms: for each member of an entity of several, whether another is similar, and whether one is of its
    document; for each pair of a member with an equal string, matching.  similar(i): which members are similar to i."""

    doc: np.ndarray
    similar: Callable[[int], np.ndarray]
    neighbour: tuple[int, int] = (100, -5)
    document: tuple[int, int] = (350, -15)
    string: np.ndarray | None = None
    matching: int = 0

    def of(self, members: Sequence[int]) -> int:
        if len(members) < 2:
            return 0
        total, rows = 0, np.asarray(members)
        counts = dict(zip(*np.unique(self.doc[rows], return_counts=True), strict=True))
        for x in members:
            total += self.document[0] if counts[self.doc[x]] > 1 else self.document[1]
            total += self.neighbour[0] if (self.similar(x)[rows] & (rows != x)).any() else self.neighbour[1]
        if self.matching:
            k = np.unique(self.string[rows], return_counts=True)[1]
            total += self.matching * int((k * (k - 1) // 2).sum())
        return total


class EntityTotals:
    """Running counts of a chain's entities, so that a move costs no more than a look at the members it meets."""

    def __init__(self, features: EntityFeatures, label: np.ndarray, members: dict[int, list[int]]):
        self.f, self.label, self.members = features, label, members
        self.near = np.zeros(len(label), dtype=np.int64)
        for own in members.values():
            rows = np.asarray(own)
            for x in own if len(own) > 1 else ():
                self.near[x] = int((features.similar(x)[rows] & (rows != x)).sum())

    def _change(self, m: int, e: int, sign: int) -> int:
        """The change of entity e's terms when m, not counted among its members now, joins it; sign -1: when it has left."""
        f, rows = self.f, np.flatnonzero(self.label == e)
        rows = rows[rows != m]
        if not len(rows):
            return 0
        like = f.similar(m)[rows]
        total, same = 0, int((f.doc[rows] == f.doc[m]).sum())
        doc = lambda k: k * f.document[0] if k > 1 else k * f.document[1]
        near = self.near[rows] - (like if sign < 0 else 0)
        flips = int((like & (near == 0)).sum())
        total += doc(same + 1) - doc(same) + flips * (f.neighbour[0] - f.neighbour[1]) + f.neighbour[0 if like.any() else 1]
        if len(rows) == 1:  # an entity of one has no terms
            total += doc(same) + doc(1 - same) + f.neighbour[1]
        if f.matching:
            total += f.matching * int((f.string[rows] == f.string[m]).sum())
        return total * (1 if sign > 0 else -1)

    def delta(self, m: int, source: int, target: int) -> int:
        return self._change(m, source, -1) + (self._change(m, target, 1) if target in self.members else 0)

    def moved(self, m: int, left: np.ndarray, joined: np.ndarray) -> None:
        """m has gone from among the members left to those joined."""
        like = self.f.similar(m)
        self.near[left[like[left]]] -= 1
        self.near[joined[like[joined]]] += 1
        self.near[m] = int(like[joined].sum())


#: Samplers that hold the query's own mention in place: they name its entity as target, or keep it from leaving.
HOLDING = ("pin_target", "influence_to_query", "expel", "expel_both")


@dataclass
class Chain:
    ids: np.ndarray
    edges: Rows
    queries: list[Query]
    sampler: str = "influence_to_query"
    tau: float = 0.9
    seed: int = 1
    run: int = 0
    accept: str = "greedy"
    temperature: float = 1.0
    single: bool | None = None
    start: np.ndarray | None = None
    entity_features: EntityFeatures | None = None
    allow_new_target: bool = False
    hold: bool | None = None
    trace: list = field(default_factory=list)
    #: The step of the last accepted proposal.
    last: int = -1

    def __post_init__(self):
        if self.sampler not in SAMPLERS:
            raise ValueError(f"{self.sampler} is none of {SAMPLERS}")
        n = len(self.ids)
        single = self.sampler in ("expel", "expel_both") if self.single is None else self.single
        groups = self.start if self.start is not None else np.zeros(n, dtype=int) if single else np.arange(n)
        first: dict = {}
        self.entity = np.array([first.setdefault(int(g), i) for i, g in enumerate(groups)], dtype=np.int64)
        self.members: dict[int, list[int]] = {}
        for i, e in enumerate(self.entity.tolist()):
            self.members.setdefault(e, []).append(i)
        self.listed = sorted(self.members)
        hold = self.sampler in HOLDING if self.hold is None else self.hold
        self.pinned = {q.at for q in self.queries} if hold else set()
        self.step = 0
        self.limit = int(self.tau * SPAN)
        self.totals = EntityTotals(self.entity_features, self.entity, self.members) if self.entity_features else None

    # draws

    def h(self, slot: int) -> int:
        return py_h32(f"{self.seed}|{self.run}|{self.step}|{slot}")

    def pick(self, options: Sequence[int], slot: int):
        return options[self.h(slot) * len(options) >> 32] if len(options) else None

    def pick_entity(self, slot: int, but: int = NEW, new: bool = False):
        """A listed entity other than one; a new one counts as the last."""
        leave = but != NEW
        size = len(self.listed) - leave + new
        if not size:
            return None
        k = self.h(slot) * size >> 32
        if new and k == size - 1:
            return NEW
        return self.listed[k + (leave and k >= bisect_left(self.listed, but))]

    def propose(self, q: Query):
        """(kind, mention, source, target); None where there is nothing to choose from."""
        own = int(self.entity[q.at])
        guided = self.h(0) < self.limit
        s = self.sampler
        if s == "influence_both":
            m, t = q.influence.draw(self.h(5), self.h(6)), q.influence.draw(self.h(7), self.h(8))
            return "guided", m, int(self.entity[m]), int(self.entity[t])
        if s == "uniform" or (s == "influence_to_query" and not guided):
            source = self.pick_entity(1)
            return "uniform", self.pick(self.members[source], 2), source, self.pick_entity(3, new=self.allow_new_target)
        if s == "influence_to_query":
            for slot in REDRAWS:
                m = q.influence.draw(self.h(slot), self.h(slot + 1))
                if self.entity[m] != own:
                    break
            return "guided", m, int(self.entity[m]), own
        if s == "pin_target":
            if guided:
                source = self.pick_entity(1, own)
                return "guided", None if source is None else self.pick(self.members[source], 2), source, own
            target = self.pick_entity(3, own, True)
            source = self.pick_entity(1, target)
            return "back", None if source is None else self.pick(self.members[source], 2), source, target
        if guided:  # expel, expel_both
            m = q.inverse.draw(self.h(5), self.h(6))
            if s == "expel_both":
                t = int(self.entity[q.inverse.draw(self.h(7), self.h(8))])
                return "guided", m, int(self.entity[m]), NEW if t == own else t
            return "guided", m, int(self.entity[m]), self.pick_entity(3, own, True)
        target = self.pick_entity(3, new=True)
        source = self.pick_entity(1, target)
        return "back", None if source is None else self.pick(self.members[source], 2), source, target

    # moves

    def pull(self, row: np.ndarray, e: int) -> int:
        """The sum of a mention's weights with an entity's members; its weight with itself is zero."""
        own = self.members.get(e, ())
        if len(own) < 32:
            return sum(int(row[x]) for x in own)
        return int(row[self.entity == e].sum())

    def delta(self, m: int, source: int, target: int) -> int:
        row = self.edges.row(m)
        d = self.pull(row, target) - self.pull(row, source)
        return d + self.totals.delta(m, source, target) if self.totals else d

    def move(self, m: int, source: int, target: int) -> None:
        src = self.members[source]
        del src[bisect_left(src, m)]
        if self.totals:
            self.totals.moved(m, np.array(src, dtype=np.int64), np.array(self.members.get(target, ()), dtype=np.int64))
        if not src:
            del self.members[source]
            del self.listed[bisect_left(self.listed, source)]
        elif source == m:
            self._rename(source, src[0])
        if target == NEW:
            self.members[m] = [m]
            insort(self.listed, m)
            self.entity[m] = m
            return
        if m < target:
            self._rename(target, m)
            target = m
        insort(self.members[target], m)
        self.entity[m] = target

    def _rename(self, old: int, new: int) -> None:
        own = self.members.pop(old)
        self.members[new] = own
        del self.listed[bisect_left(self.listed, old)]
        insort(self.listed, new)
        self.entity[own] = new

    def advance(self, q: Query, steps: int) -> int:
        """Proposals for a query; returns how many were accepted."""
        hits = 0
        for _ in range(steps):
            kind, m, source, target = self.propose(q)
            nothing = m is None or target is None or m in self.pinned or source == target or (target == NEW and len(self.members[source]) == 1)
            d, ok = 0, False
            if not nothing:
                d = self.delta(m, source, target)
                ok = accepting.greedy(d) if self.accept == "greedy" else self._mh(q, m, source, target, d)
            name = lambda e: None if e is None else NEW if e == NEW else int(self.ids[e])
            self.trace.append((self.run, self.step, q.query_id, kind, None if m is None else int(self.ids[m]), name(source), name(target), d, ok))
            if ok:
                self.move(m, source, target)
                hits, self.last = hits + 1, self.step
            self.step += 1
        return hits

    # Metropolis-Hastings

    def _share(self, b: Biased, i) -> float:
        """The chance that a draw gives i, or one of several."""
        if not hasattr(b, "mass"):
            if b.whole is not None:
                b.mass = b.whole / b.cumulative[-1]
            else:
                n = len(b.prob)
                b.mass = b.prob / n
                np.add.at(b.mass, b.alias, (1 - b.prob) / n)
        return float(b.mass[i].sum())

    def log_proposal(self, q: Query, m: int, source: int, target: int) -> float:
        """Log chance that the sampler, in the present state, proposes m from source to target."""
        own, n, k = int(self.entity[q.at]), len(self.listed), len(self.members[source])
        s = self.sampler
        uniform = 1 / n / k / (n + self.allow_new_target) if target != NEW or self.allow_new_target else 0.0
        if s == "uniform":
            p = uniform
        elif s == "influence_both":
            p = 0.0 if target == NEW else self._share(q.influence, m) * self._share(q.influence, self.members[target])
        elif s == "influence_to_query":
            # Redraws are of mentions outside the query's entity, so that shares are taken among those.
            outside = 1 - self._share(q.influence, self.members[own])
            p = self.tau * (self._share(q.influence, m) / max(outside, 1e-300) if target == own else 0.0) + (1 - self.tau) * uniform
        elif s == "pin_target":
            back = (1 / n if target != own else 0.0) * (1 / max(n - (target != NEW), 1)) / k
            p = self.tau * (1 / max(n - 1, 1) / k if target == own and source != own else 0.0) + (1 - self.tau) * back
        else:
            if s == "expel":
                guided = self._share(q.inverse, m) / n if target != own else 0.0
            else:
                where = self.members[own] if target == NEW else self.members[target] if target != own else []
                guided = self._share(q.inverse, m) * (self._share(q.inverse, where) if where else 0.0)
            p = self.tau * guided + (1 - self.tau) / (n + 1) / max(n - (target != NEW), 1) / k
        return math.log(p) if p > 0 else -math.inf

    def _mh(self, q: Query, m: int, source: int, target: int, d: int) -> bool:
        forward = self.log_proposal(q, m, source, target)
        was_alone = len(self.members[source]) == 1
        back_to = NEW if was_alone else source if source != m else self.members[source][1]
        self.move(m, source, target)
        reverse = self.log_proposal(q, m, int(self.entity[m]), back_to)
        if accepting.mh(d, forward, reverse, self.temperature, self.h(4) / SPAN):
            self.move(m, int(self.entity[m]), back_to)
            return True
        self.move(m, int(self.entity[m]), back_to)
        return False

    def score(self) -> int:
        total = sum(self.pull(self.edges.row(m), e) for e, own in self.members.items() for m in own if len(own) > 1) // 2
        return total + sum(map(self.entity_features.of, self.members.values())) if self.entity_features else total

    def labels(self) -> np.ndarray:
        return self.ids[self.entity]


#: Steps whose hashes a worker keeps.
KEPT_STEPS = 1 << 17
_kept: dict[tuple[int, int, int], list[int]] = {}


def hashes(seed: int, run: int, slot: int, first: int, many: int) -> list[int]:
    """A slot's hashes of some steps; the early ones are kept, as all components of a run have the same."""
    make = lambda a, b: [py_h32(f"{seed}|{run}|{t}|{slot}") for t in range(a, b)]
    if first + many > KEPT_STEPS:
        return make(first, first + many)
    if (seed, run, slot) not in _kept and len(_kept) >= 12:
        _kept.clear()
    known = _kept.setdefault((seed, run, slot), [])
    if len(known) < first + many:
        known.extend(make(len(known), first + many))
    return known[first : first + many]


@dataclass
class ClassChain(Chain):
    """The chain of uniform proposals and greedy acceptance without entity-wide terms, kept without a trace.

    Mentions are of classes that no feature tells apart; an entity holds its summed weights with each class, so that
    a proposal costs two look-ups.  Proposals and results are those of Chain.  between: weights of classes.
    """

    of: list[int] = field(default_factory=list)
    between: np.ndarray | None = None

    def __post_init__(self):
        super().__post_init__()
        if self.sampler != "uniform" or self.accept != "greedy" or self.totals or self.allow_new_target:
            raise ValueError("classes carry uniform proposals and greedy acceptance only")
        self.own = np.diagonal(self.between).tolist()
        self.columns = self.between.T.tolist()
        self.sums = {}
        for e, own in self.members.items():
            self.sums[e] = self.columns[self.of[own[0]]] if len(own) == 1 else self.between[:, [self.of[x] for x in own]].sum(axis=1).tolist()

    def move(self, m: int, source: int, target: int) -> None:
        row, left, joined, rest = self.columns[self.of[m]], self.sums.pop(source), self.sums.pop(target), self.members[source]
        super().move(m, source, target)
        if rest:
            self.sums[rest[0]] = [x - y for x, y in zip(left, row, strict=True)]
        self.sums[int(self.entity[m])] = [x + y for x, y in zip(joined, row, strict=True)]

    def advance(self, q: Query, steps: int) -> int:
        hits, listed, members, sums, of, own, pinned = 0, self.listed, self.members, self.sums, self.of, self.own, self.pinned
        draws = [hashes(self.seed, self.run, slot, self.step, steps) for slot in (1, 2, 3)]
        for a, b, c in zip(*draws, strict=True):
            n = len(listed)
            source, target = listed[a * n >> 32], listed[c * n >> 32]
            if source != target:
                inside = members[source]
                m = inside[b * len(inside) >> 32]
                k = of[m]
                if sums[target][k] - sums[source][k] + own[k] > 0 and m not in pinned:
                    self.move(m, source, target)
                    hits, self.last = hits + 1, self.step
            self.step += 1
        return hits


@dataclass
class Budget:
    """When a chain ends: after samples, or when a function of the last accepts says so, asked after every some.

    A schedule's turns are spent whole, however often the function is asked.
    """

    samples: int = 1000
    fn: Callable[[list], bool] | None = None
    every: int = 100
    idle: int | None = None

    def spend(self, chain: Chain, choose: Callable[[Chain], tuple[Query, int]]) -> None:
        while chain.step < self.samples:
            q, turn = choose(chain)
            turn = min(turn, self.samples - chain.step)
            while turn > 0:
                steps = min(turn, self.every) if self.fn or self.idle else turn
                chain.advance(q, steps)
                turn -= steps
                if self.fn and self.fn(chain.trace[-self.every :]):
                    return
                if self.idle and chain.step >= self.idle and chain.last < chain.step - self.idle:
                    return
