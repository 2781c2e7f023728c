"""The bounded table of counters that one stream walks through.

Each entry is one of four events. Hit: the label has a counter, which takes the item. Fill: it has none and there is room. Pass-by: it has none,
the table is full, and the entry's draw does not beat the cached floor; nothing happens. Challenge: the smallest counter is looked up; if the gate lets the newcomer
in, it takes over that counter. The four kinds of walk differ in two switches only:

    kind          gate                              take-over
    offset        none                              the counter starts empty, and its old value becomes the offset
    recycled      none                              the counter keeps its contents
    gated_eager   draw above the smallest value     keeps its contents
    gated         as eager, behind the cached floor keeps its contents

Hits commute, and a passed-by entry changes nothing. Where events are rare, a batch is handled in stretches between fills and challenges: all hits of a stretch at once, by
arrays. Where they are frequent (the offset and the recycled walk have one at nearly every strange label), entries are walked one by one over plain lists. Both ways take the same steps.
The floor never falls, so a floor that is out of date only lets through entries that the exact test then refuses. Values hardly ever fall either (those of histogram and exact counters
never do), so the heap of the smallest one holds an entry for each slot that may be too low, and is brought up to date when it comes to the top.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass, field

import numpy as np

from tallywalk.functions.registers import HALVES, alpha, estimate_sums, linear_table, sigma_table

KINDS = ("offset", "recycled", "gated_eager", "gated")
COUNTERS = ("registers", "exact")
DENSE = 32  # entries an event, below which they are walked one by one
CHUNK = 4096  # entries that are walked one by one before the next look at their events
HALF = HALVES.tolist()


@dataclass
class CounterTable:
    kind: str = "gated"
    s: int = 1000
    m: int = 1024
    counter: str = "registers"
    estimator: str = "histogram"
    min_search: str = "heap"
    labels: list[str] = field(default_factory=list)
    threshold: float = 0.0
    entries: int = 0
    hits: int = 0
    admissions: int = 0
    min_scans: int = 0
    rejected: int = 0
    evicted: bool = False
    dense: bool = True

    def __post_init__(self) -> None:
        if self.kind not in KINDS or self.counter not in COUNTERS or self.min_search not in ("argmin", "heap"):
            raise ValueError(f"kind must be one of {KINDS}, counter one of {COUNTERS}, min_search argmin or heap")
        if self.s < 1:
            raise ValueError("a table needs at least one counter")
        room = min(self.s, 1024)
        self.slot_of: dict[str, int] = {}
        self.offsets: list[float] = []
        self.values: list[float] = []
        self.dirty = np.zeros(room, bool)
        self.registers = np.zeros((room, self.m), np.uint8) if self.counter == "registers" else None
        self.empty: list[int] = []  # of a slot's registers
        self.powers: list[float] = []  # the sum of 2**-value over a slot's registers
        self.items: list[set] = []
        self.heap: list[tuple[float, int]] = []
        self.level = 0.0  # consume_keys: the smallest value, and its slots, the first one last
        self.low: list[int] = []

    def _grow(self) -> None:
        more = min(self.s, 2 * len(self.dirty)) - len(self.dirty)
        self.dirty = np.concatenate([self.dirty, np.zeros(more, bool)])
        if self.registers is not None:
            self.registers = np.concatenate([self.registers, np.zeros((more, self.m), np.uint8)])

    @property
    def full(self) -> bool:
        return len(self.labels) == self.s

    def refresh(self) -> list[float]:
        """The counters' values, offsets included, after bringing the touched ones up to date."""
        touched = np.flatnonzero(self.dirty[: len(self.labels)])
        if len(touched):
            slots = touched.tolist()
            if self.registers is not None:
                rows = self.registers[touched]
                empty, powers = (rows == 0).sum(axis=1), HALVES[rows].sum(axis=1)
                for i, e, p, v in zip(slots, empty.tolist(), powers.tolist(), estimate_sums(self.m, empty, powers, self.estimator).tolist()):
                    self.empty[i], self.powers[i] = e, p
                    self._value(i, v + self.offsets[i])
            else:
                for i in slots:
                    self._value(i, len(self.items[i]) + self.offsets[i])
            self.dirty[touched] = False
        return self.values

    def _value(self, slot: int, value: float) -> None:
        fell = value < self.values[slot]
        self.values[slot] = value
        if fell:  # the classic estimator where it changes formulas: the heap's entry must not be too high
            heapq.heappush(self.heap, (value, slot))
            if len(self.heap) > 2 * max(len(self.labels), 32):
                self.heap = [(v, i) for i, v in enumerate(self.values)]
                heapq.heapify(self.heap)

    def _least(self) -> int:
        """The slot of the smallest value, the first of equals; values are up to date."""
        if self.min_search == "argmin":
            return self.values.index(min(self.values))
        while self.heap[0][0] != self.values[self.heap[0][1]]:  # too low
            slot = self.heap[0][1]
            heapq.heapreplace(self.heap, (self.values[slot], slot))
        return self.heap[0][1]

    def smallest(self) -> int:
        self.min_scans += 1
        self.refresh()
        return self._least()

    def floor(self) -> float:
        """The smallest value of a full table, else 0: what an unknown label may have lost."""
        return float(min(self.refresh())) if self.full else 0.0

    def _touch(self, slots: np.ndarray, what: np.ndarray, rank: np.ndarray | None) -> None:
        if self.registers is not None:
            np.maximum.at(self.registers.reshape(-1), slots * self.m + what, rank)
            self.dirty[slots] = True
        else:
            for i, x in zip(slots.tolist(), what.tolist()):
                if x not in self.items[i]:
                    self.items[i].add(x)
                    self.dirty[i] = True

    def _fill(self, label: str) -> int:
        slot = len(self.labels)
        if slot == len(self.dirty):
            self._grow()
        self.labels.append(label)
        self.offsets.append(0.0)
        self.values.append(0.0)
        if self.registers is None:
            self.items.append(set())
        else:
            self.empty.append(self.m)
            self.powers.append(float(self.m))
        self.slot_of[label] = slot
        heapq.heappush(self.heap, (0.0, slot))
        return slot

    def _take_over(self, slot: int, label: str) -> str:
        old = self.labels[slot]
        del self.slot_of[old]
        self.labels[slot] = label
        self.slot_of[label] = slot
        if self.kind == "offset":
            self.offsets[slot] = self.values[slot]
            if self.registers is None:
                self.items[slot] = set()
            else:
                self.registers[slot] = 0
                self.empty[slot], self.powers[slot] = self.m, float(self.m)
        return old

    def consume(self, labels: list[str], codes: np.ndarray, what: np.ndarray, rank: np.ndarray | None, draws: np.ndarray) -> None:
        """A batch of entries: labels[codes[i]] gets what[i] (a register with its rank, or an item), and draws[i] is its draw."""
        self.entries += len(codes)
        slot = [self.slot_of.get(x, -1) for x in labels]
        code_of = {x: i for i, x in enumerate(labels)}
        at = 0
        while at < len(codes):
            at = (self._one_by_one if self.dense else self._in_stretches)(labels, code_of, slot, codes, what, rank, draws, at)

    def _one_by_one(self, labels: list[str], code_of: dict[str, int], slot: list[int], codes: np.ndarray, what: np.ndarray, rank: np.ndarray | None, draws: np.ndarray, at: int) -> int:
        """A chunk of a batch from `at` on; slot: the slot of each code, or -1. Where it ends."""
        stop = min(len(codes), at + CHUNK)
        values, offsets, items, empty, powers = self.refresh(), self.offsets, self.items, self.empty, self.powers
        own, slot_of, kind, m, exact, full = self.labels, self.slot_of, self.kind, self.m, self.registers is None, self.full
        gated, cached, anew, by_heap = kind.startswith("gated"), kind == "gated", kind == "offset", self.min_search == "heap"
        threshold, fills, scans, admitted, rejected, hits = self.threshold, 0, 0, 0, 0, 0
        if exact:
            ranks = cells = None
        else:
            ranks, cells = rank[at:stop].tolist(), memoryview(self.registers.reshape(-1))
            histogram, linear = self.estimator == "histogram", linear_table(m).tolist()
            sigmas, top, raw = (m * sigma_table(m)).tolist(), m * m / (2 * math.log(2)), alpha(m) * m * m
        drawn = draws[at:stop].tolist() if gated else None
        for k, (c, x) in enumerate(zip(codes[at:stop].tolist(), what[at:stop].tolist())):
            i = slot[c]
            if i >= 0:
                hits += 1
            elif not full:
                slot[c] = i = self._fill(labels[c])
                full, fills = self.full, fills + 1
                if not exact:
                    cells = memoryview(self.registers.reshape(-1))
            else:
                if cached and not drawn[k] > threshold:
                    rejected += 1
                    continue
                scans += 1
                least, i = self.heap[0]
                if not by_heap or values[i] != least:
                    i = self._least()
                    least = values[i]
                if gated:
                    if least > threshold:
                        threshold = least
                    if not drawn[k] > least:
                        rejected += 1
                        continue
                admitted += 1
                # as _take_over does
                old, new = own[i], labels[c]
                del slot_of[old]
                own[i] = new
                slot_of[new] = slot[c] = i
                if old in code_of:
                    slot[code_of[old]] = -1
                if anew:
                    offsets[i] = least
                    if exact:
                        items[i] = {x}
                        values[i] = least + 1.0
                        continue
                    cells[i * m : i * m + m] = bytes(m)
                    empty[i], powers[i] = m, float(m)
            if exact:
                held = items[i]
                if x not in held:
                    held.add(x)
                    values[i] += 1.0
            else:
                cell, r = i * m + x, ranks[k]
                was = cells[cell]
                if r > was:
                    cells[cell] = r
                    if not was:
                        empty[i] -= 1
                    e = empty[i]
                    powers[i] = p = powers[i] + (HALF[r] - HALF[was])
                    if histogram:
                        value = top / (sigmas[e] + p - e) + offsets[i]
                    else:
                        value = raw / p
                        value = (linear[e] if e and value <= 2.5 * m else value) + offsets[i]
                    if value >= values[i]:
                        values[i] = value
                    else:
                        self._value(i, value)
        self.threshold = threshold
        self.hits += hits
        self.min_scans += scans
        self.admissions += admitted
        self.rejected += rejected
        self.evicted |= admitted > 0
        self.dense = DENSE * (fills + scans) >= stop - at
        return stop

    def consume_keys(self, labels: list, items: list) -> None:
        """Entries of a walk without a gate and with exact counters: labels[k] gets items[k]. Labels and items are taken as they are, numbers or strings. Values never fall here, so the slots of the
        smallest one are listed once for each value that it takes, and leave the list by growing."""
        if self.kind.startswith("gated") or self.registers is not None:
            raise ValueError("only walks without a gate and with exact counters take keys")
        values, held, own, slot_of, offsets = self.refresh(), self.items, self.labels, self.slot_of, self.offsets
        anew, full, get, level, low, hits, admitted = self.kind == "offset", self.full, slot_of.get, self.level, self.low, 0, 0
        for label, x in zip(labels, items):
            i = get(label)
            if i is not None:
                hits += 1
            elif not full:
                i, full = self._fill(label), self.full
            else:
                while low and values[low[-1]] != level:
                    low.pop()
                if not low:
                    level = min(values)
                    low = [j for j in range(self.s - 1, -1, -1) if values[j] == level]
                i = low[-1]
                admitted += 1
                # as _take_over does
                del slot_of[own[i]]
                own[i] = label
                slot_of[label] = i
                if anew:
                    offsets[i] = level
                    held[i] = {x}
                    values[i] = level + 1.0
                    continue
            mine = held[i]
            if x not in mine:
                mine.add(x)
                values[i] += 1.0
        self.level, self.low = level, low
        self.entries += len(labels)
        self.hits += hits
        self.min_scans += admitted
        self.admissions += admitted
        self.evicted |= admitted > 0

    def _in_stretches(self, labels: list[str], code_of: dict[str, int], slot: list[int], codes: np.ndarray, what: np.ndarray, rank: np.ndarray | None, draws: np.ndarray, at: int) -> int:
        """A batch from `at` to its end, or to where events are frequent. Where that is."""
        n, began, events, width = len(codes), at, 0, 64
        where = np.array(slot, np.int64)
        gated = self.kind in ("gated", "gated_eager")
        cached = self.kind == "gated"
        while at < n and not self.dense:
            stop = min(n, at + width)
            slots = where[codes[at:stop]]
            strange = slots < 0
            if cached and self.full:
                strange &= draws[at:stop] > self.threshold
            first = int(strange.argmax()) if strange.any() else -1
            end = stop if first < 0 else at + first
            members = slots[: end - at] >= 0
            if members.any():
                rows = np.flatnonzero(members) + at
                self.hits += len(rows)
                self._touch(slots[: end - at][members], what[rows], None if rank is None else rank[rows])
            if cached and self.full:
                self.rejected += int((~members).sum())
            if first < 0:
                at, width = stop, min(width * 2, 1 << 16)
                continue
            events += 1
            self.dense = events >= 16 and DENSE * events > end + 1 - began
            label = labels[codes[end]]
            if not self.full:
                here = self._fill(label)
            else:
                here = self.smallest()
                value = self.values[here]
                if gated:
                    self.threshold = max(self.threshold, value)
                if gated and not draws[end] > value:
                    self.rejected += 1
                    at = end + 1
                    continue
                self.admissions += 1
                self.evicted = True
                old = code_of.get(self._take_over(here, label))
                if old is not None:
                    where[old] = -1
            where[codes[end]] = here
            self._touch(np.array([here]), what[end : end + 1], None if rank is None else rank[end : end + 1])
            at, width = end + 1, max(64, width // 2)
        slot[:] = where.tolist()
        return at

    def counters(self, contents: bool = True) -> list[dict]:
        """A row for each slot; contents: with what the counters hold."""
        values = self.refresh()
        return [
            {
                "slot": i,
                "label_key": str(x),
                "offset": float(self.offsets[i]),
                "registers": self.registers[i].tobytes() if contents and self.registers is not None else None,
                "items": sorted(map(str, self.items[i])) if contents and self.registers is None else None,
                "estimate": float(values[i]),
            }
            for i, x in enumerate(self.labels)
        ]

    def meta(self) -> dict:
        return {
            "entries": self.entries,
            "threshold": self.threshold,
            "floor": self.floor() if self.labels else 0.0,
            "is_full": self.full,
            "evicted": self.evicted,
            "hits": self.hits,
            "admissions": self.admissions,
            "min_scans": self.min_scans,
            "rejected": self.rejected,
        }


@dataclass
class EntryTable:
    """The ancestor of the walks: s counters of entries, where a newcomer takes over the smallest count and adds one."""

    s: int

    def __post_init__(self) -> None:
        self.counts: dict[str, list[int]] = {}
        self.heap: list[list] = []

    def consume(self, labels: list[str]) -> None:
        for x in labels:
            cell = self.counts.get(x)
            if cell:
                cell[0] += 1
                continue
            if len(self.counts) < self.s:
                self.counts[x] = [1]
                heapq.heappush(self.heap, (1, len(self.heap), x))
                continue
            while True:  # bring the top up to date until it is the smallest
                count, place, old = self.heap[0]
                now = self.counts[old][0]
                if now == count:
                    break
                heapq.heapreplace(self.heap, (now, place, old))
            del self.counts[old]
            self.counts[x] = [count + 1]
            heapq.heapreplace(self.heap, (count + 1, place, x))
