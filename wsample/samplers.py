"""Reservoir samplers: one pass over items in order, a valid sample after every item.

``offer`` takes arrays of ids and weights; ``snapshot`` gives the reservoir; ``to_state`` and ``from_state`` move it
between tasks and streaming batches.  Randomness comes from a numpy generator keyed by the caller, or from uniforms
that the caller passes along with the items.  ``draws``, ``insertions`` and ``heap_steps`` count the work.
"""

from __future__ import annotations

import abc
import heapq
import itertools
from dataclasses import dataclass

import numpy as np


#: Items that are compared with the worst kept one at once.
BLOCK = 4096


def keyed_rng(seed: int, *key: int) -> np.random.Generator:
    """A generator that depends on the seed and a group, bucket or partition number only."""
    return np.random.Generator(np.random.Philox(np.random.SeedSequence([seed & (2**63 - 1), *(k & (2**63 - 1) for k in key)])))


@dataclass(frozen=True)
class SampleEntry:
    """An item of a sample: its id, weight, and key or adjusted weight."""

    item: object
    weight: float
    key: float


class ReservoirSampler(abc.ABC):
    """A sample of at most ``m`` items of the stream so far."""

    def __init__(self, m: int, rng: np.random.Generator | None = None):
        if m < 0:
            raise ValueError("sample size is negative")
        self.m, self.rng = m, rng or keyed_rng(0)
        self.seen = self.draws = self.insertions = self.heap_steps = 0

    @abc.abstractmethod
    def offer(self, items, weights, uniforms=None) -> None:
        """Feed items in order."""

    @abc.abstractmethod
    def snapshot(self) -> list[SampleEntry]:
        """The sample of all items fed so far."""

    def feed(self, item, weight: float) -> None:
        """Feed one item."""
        self.offer([item], np.array([weight], float))

    def _uniforms(self, n: int) -> np.ndarray:
        self.draws += n
        return (self.rng.integers(0, 2**52, n) + 0.5) / 2**52

    @staticmethod
    def _weights(weights) -> np.ndarray:
        w = np.asarray(weights, float)
        if len(w) and not (np.isfinite(w).all() and (w > 0).all()):
            raise ValueError("weight is not a positive real")
        return w


class RaceSampler(ReservoirSampler):
    """Draw role: the m earliest finishers of an exponential race, in a heap of their times."""

    def __init__(self, m: int, rng=None):
        super().__init__(m, rng)
        self.heap: list[tuple[float, int, object, float]] = []  # (-time, -order, item, weight)
        self.scale = 1.0

    def offer(self, items, weights, uniforms=None) -> None:
        w = self._weights(weights)
        u = self._uniforms(len(w)) if uniforms is None else np.asarray(uniforms, float)
        e = -np.log(u) / w
        self._enter(items, w, e)

    def _enter(self, items, w, e) -> None:
        base, at = self.seen, np.arange(len(w))
        self.seen += len(w)
        if not self.m:
            return
        free = min(self.m - len(self.heap), len(w))
        self._push(items, w, e, at[:free], base)
        for lo in range(free, len(w), BLOCK):  # most items of a block lose against the worst kept time at once
            rows = at[lo : lo + BLOCK]
            self._push(items, w, e, rows[e[rows] / self.scale <= -self.heap[0][0]], base)

    def _push(self, items, w, e, at, base: int) -> None:
        for i in at.tolist():
            entry = (-float(e[i]) / self.scale, -(base + i), items[i], float(w[i]))
            if len(self.heap) < self.m:
                heapq.heappush(self.heap, entry)
            elif entry > self.heap[0]:
                heapq.heapreplace(self.heap, entry)
            else:
                continue
            self.insertions += 1
            self.heap_steps += max(1, len(self.heap).bit_length())

    def snapshot(self) -> list[SampleEntry]:
        return [SampleEntry(i, w, -t * self.scale) for t, _, i, w in sorted(self.heap, reverse=True)]

    def age(self, c: float) -> None:
        """Multiply the weights of all items so far by c < 1: their times grow by 1 / c, through one shared factor."""
        self.scale /= c

    def merge(self, other: RaceSampler) -> None:
        """Join the reservoir of another, disjoint population."""
        kept = other.snapshot()
        if kept:
            self._enter([x.item for x in kept], np.array([x.weight for x in kept]), np.array([x.key for x in kept]))
            self.seen += other.seen - len(kept)

    def to_state(self) -> dict:
        return {"m": self.m, "seen": self.seen, "entries": [(x.item, x.weight, x.key) for x in self.snapshot()]}

    @classmethod
    def from_state(cls, state: dict, rng=None) -> RaceSampler:
        out = cls(state["m"], rng)
        if state["entries"]:
            items, w, e = zip(*state["entries"], strict=True)
            out._enter(list(items), np.array(w), np.array(e))
        out.seen, out.insertions = state["seen"], 0
        return out


class RaceJumpSampler(RaceSampler):
    """The race with jumps: once full, one exponential draw says how much weight to pass over."""

    def __init__(self, m: int, rng=None):
        super().__init__(m, rng)
        self.skip: float | None = None  # weight still to be passed over

    @property
    def worst(self) -> float:
        """The latest kept time; kept times are stored without the common factor."""
        return -self.heap[0][0] * self.scale

    def _next(self) -> float:
        return -np.log(self._uniforms(1)[0]) / self.worst

    def age(self, c: float) -> None:
        """Kept times grow by 1 / c, so the weight still to be passed over shrinks by c: what is left of it stays exponential."""
        super().age(c)
        if self.skip is not None:
            self.skip *= c

    def offer(self, items, weights, uniforms=None) -> None:
        w = self._weights(weights)
        start = min(len(w), self.m - len(self.heap))
        if start:
            u = self._uniforms(start)
            self._enter(items[:start], w[:start], -np.log(u) / w[:start])
        if len(self.heap) < self.m or start == len(w) or not self.m:
            return
        total = np.cumsum(w[start:])
        base = self.seen
        self.seen += len(total)
        done = 0.0
        if self.skip is None:
            self.skip = self._next()
        while total[-1] - done >= self.skip:
            i = int(np.searchsorted(total, done + self.skip))
            i = min(i, len(total) - 1)
            weight = float(w[start + i])
            e = -np.log1p(-self._uniforms(1)[0] * -np.expm1(-weight * self.worst)) / weight
            heapq.heapreplace(self.heap, (-float(e) / self.scale, -(base + i), items[start + i], weight))
            self.insertions += 1
            self.heap_steps += max(1, self.m.bit_length())
            done, self.skip = float(total[i]), self._next()
            if i == len(total) - 1:
                return
        self.skip -= float(total[-1]) - done

    def to_state(self) -> dict:
        return super().to_state() | {"skip": self.skip}

    @classmethod
    def from_state(cls, state: dict, rng=None) -> RaceJumpSampler:
        out = super().from_state(state, rng)
        out.skip = state.get("skip")
        return out


class SlotRaces:
    """m races of one winner each with jumps, all slots at once: O(n) for the running weights and a few draws a slot, not n * m."""

    def __init__(self, m: int, rng: np.random.Generator):
        self.m, self.rng = m, rng
        self.seen = self.draws = self.insertions = 0
        self.item, self.time, self.skip = np.full(m, -1), np.full(m, np.inf), np.zeros(m)

    def _exponentials(self, n: int) -> np.ndarray:
        self.draws += n
        return -np.log((self.rng.integers(0, 2**52, n) + 0.5) / 2**52)

    def offer(self, weights: np.ndarray) -> None:
        """Items in order; ``item`` holds their numbers from 0."""
        if not self.m or not len(weights):
            return
        total, base = np.cumsum(weights), self.seen
        done, live = np.zeros(self.m), np.arange(self.m)
        if not base:
            self.item[:] = 0
            self.time = self._exponentials(self.m) / weights[0]
            self.skip = self._exponentials(self.m) / self.time
            self.insertions += self.m
            done[:] = total[0]
        self.seen += len(weights)
        while True:
            live = live[total[-1] - done[live] >= self.skip[live]]
            live = live[done[live] < total[-1]]
            if not len(live):
                break
            # the item after the weight passed over; at least the one after what is done
            at = np.maximum(np.searchsorted(total, done[live] + self.skip[live]), np.searchsorted(total, done[live], side="right"))
            at = np.minimum(at, len(total) - 1)
            w = weights[at]
            self.draws += len(live)
            u = (self.rng.integers(0, 2**52, len(live)) + 0.5) / 2**52
            self.time[live] = -np.log1p(u * np.expm1(-w * self.time[live])) / w
            self.item[live] = base + at
            self.insertions += len(live)
            done[live] = total[at]
            self.skip[live] = self._exponentials(len(live)) / self.time[live]
        self.skip -= np.where(done < total[-1], total[-1] - done, 0)


class ProportionalSampler(ReservoirSampler):
    """Inclusion role: an item's chance to be in the sample is min(1, weight / threshold) after every item.

    Items too heavy for a share (``pinned``) are kept for certain until later arrivals make them feasible again.
    Which are pinned depends on weights alone; only acceptance and the choice of the victim are random.
    """

    def __init__(self, m: int, rng=None):
        super().__init__(m, rng)
        self.slots: list[tuple[object, float]] = []
        self.pins: list[tuple[float, int]] = []  # heap of (weight, slot)
        self.total = self.pinned = 0.0

    @property
    def threshold(self) -> float:
        free = self.m - len(self.pins)
        return (self.total - self.pinned) / free if free > 0 and self.seen > self.m else 0.0

    def offer(self, items, weights, uniforms=None) -> None:
        """``uniforms``: pairs of columns, for acceptance and for the victim."""
        w = self._weights(weights)
        u = v = None
        if uniforms is not None:
            u, v = (np.asarray(x, float) for x in uniforms)
        i = 0
        while i < len(w):
            if not self.pins and len(self.slots) == self.m and self.m:
                run = np.cumsum(w[i:]) + self.total
                heavy = np.flatnonzero(self.m * w[i:] >= run)
                stop = i + (int(heavy[0]) if len(heavy) else len(run))
                if stop > i:
                    self._plain(items, w, run, u, v, i, stop)
                    i = stop
                    continue
            self._one(items[i], float(w[i]), None if u is None else u[i], None if v is None else v[i])
            i += 1

    def _plain(self, items, w, run, u, v, lo: int, hi: int) -> None:
        """Items without any pinned one: acceptance by prefix sums, the last writer of a slot stays."""
        run = run[: hi - lo]
        first = self._uniforms(hi - lo) if u is None else u[lo:hi]
        taken = np.flatnonzero(first * run < self.m * w[lo:hi])
        second = self._uniforms(len(taken)) if v is None else v[lo:hi][taken]
        for k, s in zip(taken.tolist(), np.floor(second * self.m).astype(int).tolist(), strict=True):
            self.slots[s] = (items[lo + k], float(w[lo + k]))
        self.insertions += len(taken)
        self.seen += hi - lo
        self.total = float(run[-1])

    def _settle(self, weight: float) -> tuple[list[tuple[float, int]], bool]:
        """Take the weight in; the pins it frees, and whether the newcomer is pinned itself."""
        self.total += weight
        self.seen += 1
        heapq.heappush(self.pins, (weight, -1))
        self.pinned += weight
        freed = []
        while self.pins:
            lightest = self.pins[0][0]
            if (self.m - len(self.pins) + 1) * lightest >= self.total - self.pinned + lightest:
                break
            freed.append(heapq.heappop(self.pins))
            self.pinned -= lightest
            self.heap_steps += 1
        if not self.pins:
            self.pinned = 0.0
        self.heap_steps += 1
        own = any(s == -1 for _, s in self.pins)
        return [x for x in freed if x[1] != -1], own

    def _one(self, item, weight: float, u=None, v=None) -> None:
        if not self.m:
            self.seen += 1
            return
        if len(self.slots) < self.m:
            self.slots.append((item, weight))
            self.total += weight
            self.pinned += weight
            self.seen += 1
            heapq.heappush(self.pins, (weight, len(self.slots) - 1))
            self.insertions += 1
            return
        before = {s for _, s in self.pins}
        freed, own = self._settle(weight)
        tau = self.threshold
        chance = 1.0 if own else min(1.0, weight / tau)
        if not own and (self._uniforms(1)[0] if u is None else u) >= chance:
            return
        slot = self._victim(freed, before, tau, chance, self._uniforms(1)[0] if v is None else v)
        self.slots[slot] = (item, weight)
        self.insertions += 1
        self.pins = [(w, slot if s == -1 else s) for w, s in self.pins]
        heapq.heapify(self.pins)

    def _victim(self, freed, before: set[int], tau: float, chance: float, v: float) -> int:
        """A freed item with the chance it loses over the newcomer's; else any item that was feasible before."""
        left = v
        for w, s in sorted(freed, key=lambda x: x[1]):
            share = (1 - min(1.0, w / tau)) / chance if tau else 0.0
            if left < share:
                return s
            left -= share
        rest = [s for s in range(self.m) if s not in before]
        if not rest:  # rounding at the end of the unit interval
            return max(freed, key=lambda x: x[1])[1]
        shares = sum((1 - min(1.0, w / tau)) / chance for w, _ in freed) if tau else 0.0
        return rest[min(int(left / max(1 - shares, 1e-300) * len(rest)), len(rest) - 1)]

    def snapshot(self) -> list[SampleEntry]:
        tau = self.threshold
        return [SampleEntry(i, w, max(w, tau)) for i, w in self.slots]

    def merge(self, other: ProportionalSampler) -> None:
        """Join the reservoir of another, disjoint population: its items come with their adjusted weights."""
        mine = self.snapshot()
        joined = type(self)(self.m, self.rng)
        both = [*mine, *other.snapshot()]
        joined.offer([x.item for x in both], np.array([x.key for x in both], float))
        self.slots, self.pins, self.total, self.pinned = joined.slots, joined.pins, joined.total, joined.pinned
        self.draws, self.insertions = joined.draws + self.draws, self.insertions + joined.insertions
        self.seen += other.seen

    def to_state(self) -> dict:
        return {"m": self.m, "seen": self.seen, "total": self.total, "pinned": self.pinned, "slots": list(self.slots), "pins": list(self.pins)}

    @classmethod
    def from_state(cls, state: dict, rng=None) -> ProportionalSampler:
        out = cls(state["m"], rng)
        out.seen, out.total, out.pinned = state["seen"], state["total"], state["pinned"]
        out.slots, out.pins = [tuple(x) for x in state["slots"]], [tuple(x) for x in state["pins"]]
        heapq.heapify(out.pins)
        return out


class ProportionalJumpSampler(ProportionalSampler):
    """The inclusion role with jumps: chances add up until they pass one draw, which names the next accepted item."""

    def __init__(self, m: int, rng=None):
        super().__init__(m, rng)
        self.left: float | None = None  # log survival still to be used up

    def _plain(self, items, w, run, u, v, lo: int, hi: int) -> None:
        run = run[: hi - lo]
        p = self.m * w[lo:hi] / run
        gone = np.cumsum(-np.log1p(-p))
        done = 0.0
        if self.left is None:
            self.left = -np.log(self._uniforms(1)[0])
        while gone[-1] - done >= self.left:
            i = min(int(np.searchsorted(gone, done + self.left)), len(gone) - 1)
            self.slots[int(self._uniforms(1)[0] * self.m)] = (items[lo + i], float(w[lo + i]))
            self.insertions += 1
            done, self.left = float(gone[i]), -np.log(self._uniforms(1)[0])
        self.left -= float(gone[-1]) - done
        self.seen += hi - lo
        self.total = float(run[-1])

    def _one(self, item, weight: float, u=None, v=None) -> None:
        if len(self.slots) < self.m or not self.m:
            super()._one(item, weight)
            return
        before = {s for _, s in self.pins}
        freed, own = self._settle(weight)
        tau = self.threshold
        chance = 1.0 if own else min(1.0, weight / tau)
        if self.left is None:
            self.left = -np.log(self._uniforms(1)[0])
        gone = np.inf if chance >= 1 else -np.log1p(-chance)
        if gone < self.left:
            self.left -= gone
            return
        slot = self._victim(freed, before, tau, chance, self._uniforms(1)[0])
        self.slots[slot] = (item, weight)
        self.insertions += 1
        self.pins = [(w, slot if s == -1 else s) for w, s in self.pins]
        heapq.heapify(self.pins)
        self.left = -np.log(self._uniforms(1)[0])


class ReplacementSampler(ReservoirSampler):
    """With replacement: m slots, each a sample of one by itself."""

    def __init__(self, m: int, rng=None, *, jumps: bool = True, engine: str = "proportional"):
        super().__init__(m, rng)
        kinds = {("proportional", True): ProportionalJumpSampler, ("proportional", False): ProportionalSampler, ("race", True): RaceJumpSampler, ("race", False): RaceSampler}
        self.parts = [kinds[engine, jumps](1, self.rng) for _ in range(m)]

    def offer(self, items, weights, uniforms=None) -> None:
        self.seen += len(weights)
        for p in self.parts:
            p.offer(items, weights)
        self.draws = sum(p.draws for p in self.parts)
        self.insertions = sum(p.insertions for p in self.parts)

    def snapshot(self) -> list[SampleEntry]:
        return list(itertools.chain.from_iterable(p.snapshot() for p in self.parts))


class BoundedSampler(ReservoirSampler):
    """Draw role with at most k slots an item (or its own): samplers of one in a chain.

    An item goes from sampler to sampler until it holds its share of slots; when it loses a slot it goes on from the
    first sampler it has not seen.  ``engine``: the samplers of one are races, or proportional reservoirs; the law is the same.
    """

    def __init__(self, m: int, k: int = 2, rng=None, *, engine: str = "race"):
        if engine not in ("race", "proportional"):
            raise ValueError(f"unknown engine: {engine!r}")
        super().__init__(m, rng)
        self.k, self.engine, self.weight_seen = k, engine, [0.0] * m
        self.slot: list[tuple[float, int] | None] = [None] * m  # (time, number of the item)
        self.item: dict[int, list] = {}  # number -> [item, weight, share, next sampler, slots held]

    def offer(self, items, weights, uniforms=None, shares=None) -> None:
        """``uniforms``: one row an item, one column a slot."""
        w = self._weights(weights)
        for i in range(len(w)):
            u = None if uniforms is None else np.asarray(uniforms[i], float)
            number = self.seen
            self.seen += 1
            self.item[number] = [items[i], float(w[i]), self.k if shares is None else int(shares[i]), 0, 0, u]
            self._pass_on(number)

    def _pass_on(self, number: int) -> None:
        waiting = [number]
        while waiting:
            x = waiting.pop()
            entry = self.item.get(x)
            while entry is not None and entry[3] < self.m and entry[4] < entry[2]:
                j = entry[3]
                entry[3] += 1
                u = self._uniforms(1)[0] if entry[5] is None else entry[5][j]
                if self.engine == "race":
                    time = -np.log(u) / entry[1]
                    taken = self.slot[j] is None or (time, x) < self.slot[j]
                else:
                    self.weight_seen[j] += entry[1]
                    time, taken = self.weight_seen[j], u * self.weight_seen[j] < entry[1]
                if taken:
                    lost = self.slot[j]
                    self.slot[j] = (time, x)
                    entry[4] += 1
                    self.insertions += 1
                    if lost is not None:
                        self.item[lost[1]][4] -= 1
                        waiting.append(lost[1])
            if entry is not None and entry[3] >= self.m and entry[4] == 0:
                self.item.pop(x, None)

    def snapshot(self) -> list[SampleEntry]:
        return [SampleEntry(self.item[s[1]][0], self.item[s[1]][1], s[0]) for s in self.slot if s is not None]
