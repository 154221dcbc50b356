"""Planning balanced batches: the exact interval planner, the item-by-item reference, comparators and the optimum.

Items are taken largest first (equal sizes by id). Bins are opened for the total size, their number rounded up to a
multiple of the workers. Laps go over the bins, emptiest first, and give each the next item; the bins from the first
that has no room on are full. Full bins come back as soon as the fullest open bin has less room than the emptiest full
one. What is left when all bins are full starts over with new bins.

As sizes never rise along the items and room never rises along a lap, a lap fills a prefix of the bins. Runs of bins
with equal room and runs of items with equal size are dealt at once, so planning depends on the number of distinct
sizes and laps, not on items or bins.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field


class OversizeError(ValueError):
    """An item is larger than the capacity."""


def bin_count(total: int, capacity: int, ranks: int, items: int | None = None) -> int:
    """ceil(total / capacity), raised to a multiple of ranks; at least ranks where there are items."""
    if capacity <= 0 or ranks <= 0:
        raise ValueError("capacity and ranks must be positive")
    least = -(-total // capacity)
    if items and not least:
        least = 1
    return -(-least // ranks) * ranks


@dataclass(frozen=True)
class Piece:
    """Items of places first..first+count-1 go to the bins bin_lo, bin_lo + 1, ... one each."""

    level: int
    lap: int
    first: int
    count: int
    bin_lo: int
    size: int


@dataclass
class Plan:
    pieces: list[Piece] = field(default_factory=list)
    n_bins: int = 0
    unassigned: int = 0
    trace: list[dict] = field(default_factory=list)


def plan_intervals(histogram: list[tuple[int, int]], capacity: int, ranks: int, reactivate: bool = True, recursive: bool = True) -> Plan:
    """The plan for (size, count) runs."""
    runs = [[s, c] for s, c in sorted(histogram, reverse=True) if c]
    if any(s < 0 for s, _ in runs):
        raise ValueError("sizes must not be negative")
    if runs and runs[0][0] > capacity:
        raise OversizeError(f"size {runs[0][0]} exceeds the capacity {capacity}")
    plan, at, level = Plan(), 0, 0
    i = 0
    while i < len(runs):
        total = sum(s * c for s, c in runs[i:])
        opened = bin_count(total, capacity, ranks, len(runs) - i)
        active = [(plan.n_bins, plan.n_bins + opened, capacity)]
        plan.n_bins += opened
        full: list[tuple[int, int, int]] = []
        lap = 0
        while i < len(runs) and active:
            active.sort(key=lambda r: -r[2])
            kept: list[tuple[int, int, int]] = []
            placed = marked = 0
            stuck = False
            for lo, hi, room in active:
                while lo < hi and not stuck and i < len(runs):
                    size, left = runs[i]
                    if room < size:
                        stuck = True
                        break
                    n = min(hi - lo, left)
                    plan.pieces.append(Piece(level, lap, at, n, lo, size))
                    kept.append((lo, lo + n, room - size))
                    at, lo, placed = at + n, lo + n, placed + n
                    runs[i][1] -= n
                    i += runs[i][1] == 0
                if lo < hi:
                    (full if stuck else kept).append((lo, hi, room))
                    marked += (hi - lo) * stuck
            back = bool(reactivate and kept and full and min(r[2] for r in kept) < max(r[2] for r in full))
            plan.trace.append({"level": level, "lap": lap, "placed": placed, "marked": marked, "reactivated": back, "active": sum(h - l for l, h, _ in active)})
            active = kept + full if back else kept
            full = [] if back else full
            lap += 1
        if i < len(runs) and not recursive:
            plan.unassigned = sum(c for _, c in runs[i:])
            break
        level += 1
    return plan


def pack_local(sizes: list[int], capacity: int, ranks: int, reactivate: bool = True, recursive: bool = True, emptiest_first: bool = True) -> tuple[list[int], int]:
    """The bin of each item (-1: none), item by item, and the number of bins. sizes in any order; equal sizes by place."""
    if any(s < 0 for s in sizes):
        raise ValueError("sizes must not be negative")
    if sizes and max(sizes) > capacity:
        raise OversizeError(f"size {max(sizes)} exceeds the capacity {capacity}")
    order = sorted(range(len(sizes)), key=lambda i: -sizes[i])
    bins_of, opened, at = [-1] * len(sizes), 0, 0
    while at < len(order):
        n = bin_count(sum(sizes[i] for i in order[at:]), capacity, ranks, len(order) - at)
        room = {b: capacity for b in range(opened, opened + n)}
        active, full = list(room), []
        opened += n
        while at < len(order) and active:
            active.sort(key=lambda b: -room[b] if emptiest_first else room[b])
            kept, refused = [], []
            for b in active:
                if at < len(order) and room[b] >= sizes[order[at]]:
                    bins_of[order[at]] = b
                    room[b] -= sizes[order[at]]
                    at += 1
                    kept.append(b)
                elif at < len(order):
                    refused.append(b)
                else:
                    kept.append(b)
            full += refused
            if reactivate and kept and full and min(room[b] for b in kept) < max(room[b] for b in full):
                kept, full = kept + full, []
            active = kept
        if not recursive:
            break
    return bins_of, opened


def pack_greedy(sizes: list[int], capacity: int, rule: str, decreasing: bool = False) -> list[int]:
    """first (lowest bin with room), best (fullest bin with room) or next (the last bin or a new one) fit."""
    order = sorted(range(len(sizes)), key=lambda i: -sizes[i]) if decreasing else range(len(sizes))
    room: list[int] = []
    out = [0] * len(sizes)
    tree = _FirstFit(len(sizes)) if rule == "first" else None
    by_room: list[tuple[int, int]] = []
    from bisect import bisect_left, insort

    for i in order:
        s = sizes[i]
        if rule == "first":
            b = tree.place(s, capacity)
        elif rule == "best":
            k = bisect_left(by_room, (s, -1))
            if k < len(by_room):
                left, b = by_room.pop(k)
            else:
                left, b = capacity, len(room)
                room.append(capacity)
            insort(by_room, (left - s, b))
        elif rule == "next":
            if not room or room[-1] < s:
                room.append(capacity)
            b = len(room) - 1
            room[b] -= s
        else:
            raise ValueError(rule)
        out[i] = b
    return out


class _FirstFit:
    """A tree of rooms that finds the lowest bin with room."""

    def __init__(self, n: int):
        self.n = 1 << max(0, (n - 1).bit_length())
        self.room = [-1] * (2 * self.n)
        self.used = 0

    def _set(self, b: int, room: int) -> None:
        i = b + self.n
        self.room[i] = room
        while i > 1:
            i >>= 1
            self.room[i] = max(self.room[2 * i], self.room[2 * i + 1])

    def place(self, size: int, capacity: int) -> int:
        if self.room[1] < size:
            self._set(self.used, capacity)
            self.used += 1
        i = 1
        while i < self.n:
            i = 2 * i if self.room[2 * i] >= size else 2 * i + 1
        self._set(i - self.n, self.room[i] - size)
        return i - self.n


def pack_fixed_bins(sizes: list[int], bins: int, capacity: int | None = None) -> list[int]:
    """Largest items first, each to the emptiest of a fixed number of bins (-1: no bin has room)."""
    heap = [(0, b) for b in range(bins)]
    out = [-1] * len(sizes)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        load, b = heap[0]
        if capacity is None or load + sizes[i] <= capacity:
            heapq.heapreplace(heap, (load + sizes[i], b))
            out[i] = b
    return out


def pack_exact(sizes: list[int], capacity: int, ranks: int) -> tuple[int, int, int]:
    """(bins, padding, spread of squares) of the best packing, in this order of weight, by trying all. Nine items at most."""
    if len(sizes) > 9:
        raise ValueError("too many items")
    best = None

    def go(i: int, bins: list[list[int]]) -> None:
        nonlocal best
        if i == len(sizes):
            n = -(-len(bins) // ranks) * ranks
            squares = [sum(x * x for x in b) for b in bins] + [0] * (n - len(bins))
            got = (n, n * capacity - sum(sizes), max(squares) - min(squares))
            best = got if best is None or got < best else best
            return
        for b in bins:
            if sum(b) + sizes[i] <= capacity:
                b.append(sizes[i])
                go(i + 1, bins)
                b.pop()
        if best is None or -(-(len(bins) + 1) // ranks) * ranks <= best[0]:
            bins.append([sizes[i]])
            go(i + 1, bins)
            bins.pop()

    go(0, [])
    return best or (0, 0, 0)


__all__ = ["OversizeError", "Piece", "Plan", "bin_count", "pack_exact", "pack_fixed_bins", "pack_greedy", "pack_local", "plan_intervals"]
