"""Ring summaries: each counter also counts arrivals by distance band around its cell.

Bands end at a geometric row of radii in cell units, smallest first; what lies beyond the
largest goes to the last band (`overflow='last'`) or nowhere (`'drop'`).

When a new cell takes a counter, its bands start by policy: `transfer` shares out the
victim's bands by overlapping area, `reset` starts at zero, `freeze` stops new cells after
a part of the stream, `nearby_skip` refuses new cells within the first band of a kept one.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.functions.scratch import materialize
from termatlas.operators import counters
from termatlas.operators.counters import SUMMARY, Counters

DISC_MEAN_RATIO, OUTER, CAP, WORDS = 2 / 3, 98.0, 10, 648
KEPT, WIDE = 65_536, 4096  # distances that a state remembers, cells of which it keeps a table of bands
WAITING, ROOM = 65_536, 1 << 19  # arrivals that bands lag behind at most, pairs that are looked up at once
FEW = 32  # arrivals that are taken one by one
PARTS = 4096  # transfers whose shares are looked up at once
DIGITS = 12  # of distances of centres
POLICIES = ("transfer", "reset", "freeze", "nearby_skip")


def count_for(ratio: float, outer: float = OUTER, cap: int = CAP) -> int:
    """Bands from the outer radius down to one cell, at most cap."""
    return min(cap, 1 + math.ceil(math.log(outer) / math.log(1 / ratio) - 1e-9))


def count_for_column(ratio: Column | str, outer: Column | str, cap: int = CAP) -> Column:
    """count_for of columns; outer radii below a cell count as one."""
    ratio, outer = (F.col(x) if isinstance(x, str) else x for x in (ratio, outer))
    return F.least(F.lit(cap), 1 + F.ceil(F.log(F.greatest(outer, F.lit(1.0))) / F.log(1 / ratio) - 1e-9)).cast("int")


def edges(outer: float = OUTER, ratio: float = 0.6, n: int | None = None, cap: int = CAP) -> list[float]:
    n = count_for(ratio, outer, cap) if n is None else n
    return [outer * ratio**k for k in range(n - 1, -1, -1)]


def capacity_for_budget(words: int = WORDS, n_rings: int = CAP) -> int:
    """Counters of 3 + n_rings words each in a budget of words."""
    return round(words / (3 + n_rings))


def space_words(capacity: int, n_rings: int) -> int:
    return capacity * (3 + n_rings)


def band(distance: Column | str, radii: list[float], mode: str | None = None, overflow: str = "last") -> Column:
    """Band of a distance, from 0; null for distance 0 (the centre) and, with 'drop', beyond the last.

    Modes: 'linear' tests radius by radius, 'binary' halves the row of radii in a tree of
    conditions, 'closed' takes the logarithm that geometric radii allow and corrects it by one step.
    By default few radii are halved and many, whose tree would outgrow compiled code, taken closed.
    """
    mode = mode or ("binary" if len(radii) <= 16 else "closed")
    d = F.col(distance) if isinstance(distance, str) else distance
    n = len(radii)
    if mode == "linear":
        out = F.lit(n)
        for k in range(n - 1, -1, -1):
            out = F.when(d <= radii[k], F.lit(k)).otherwise(out)
    elif mode == "closed":
        if n == 1:
            out = F.when(d <= radii[0], F.lit(0)).otherwise(F.lit(1))
        else:
            step = math.log(radii[1] / radii[0])
            guess = F.greatest(F.lit(0), F.least(F.lit(n), F.ceil(F.log(F.greatest(d, F.lit(1e-12)) / radii[0]) / step).cast("int")))
            ends = F.array(F.lit(0.0), *(F.lit(float(r)) for r in radii), F.lit(float("inf")))
            # the guess is off by one step at most; band k reaches from ends[k] to ends[k + 1]
            out = guess + (d > F.element_at(ends, guess + 2)).cast("int") - ((guess > 0) & (d <= F.element_at(ends, guess + 1))).cast("int")
    else:

        def tree(lo: int, hi: int) -> Column:
            if lo == hi:
                return F.lit(lo)
            mid = (lo + hi) // 2
            return F.when(d <= radii[mid], tree(lo, mid)).otherwise(tree(mid + 1, hi))

        out = tree(0, n)
    last = F.least(out, F.lit(n - 1)) if overflow == "last" else F.when(out < n, out)
    return F.when(d > 0, last).cast("int")


def lens(p: np.ndarray, q: np.ndarray, d: float | np.ndarray) -> np.ndarray:
    """Area common to discs of radii p and q whose centres are d apart."""
    p, q, d = np.broadcast_arrays(*(np.asarray(x, float) for x in (p, q, d)))
    small, large = np.minimum(p, q), np.maximum(p, q)
    out = np.where(d <= large - small, np.pi * small**2, 0.0)
    cut = (d > large - small) & (d < p + q) & (small > 0)
    a, b, d = p[cut], q[cut], d[cut]
    x = np.clip((d**2 + a**2 - b**2) / (2 * d * a), -1, 1)
    y = np.clip((d**2 + b**2 - a**2) / (2 * d * b), -1, 1)
    root = np.sqrt(np.maximum((a + b - d) * (d + a - b) * (d - a + b) * (d + a + b), 0))
    out[cut] = a**2 * np.arccos(x) + b**2 * np.arccos(y) - root / 2
    return out


def planar_overlap(radii: np.ndarray, d: float | np.ndarray) -> np.ndarray:
    """Area of new band i and old band k, centres d apart, by inclusion and exclusion of discs; for several d a matrix each."""
    r = np.concatenate([[0.0], radii])
    discs = lens(r[:, None], r[None, :], np.asarray(d, float)[..., None, None])
    return np.maximum(discs[..., 1:, 1:] - discs[..., :-1, 1:] - discs[..., 1:, :-1] + discs[..., :-1, :-1], 0.0)


class Sphere:
    """Distances of cells in cell units, with a cache of centres' coordinates."""

    def __init__(self, size_e6: int = geo.SIZE, metric: str = "arc"):
        self.n, self.step, self.metric = geo.columns(size_e6), size_e6 / geo.DEGREE, metric

    def place(self, cell) -> tuple:
        row, col = np.asarray(cell) // self.n, np.asarray(cell) % self.n
        return ((row, col) if self.metric == "grid" else (np.radians((row + 0.5) * self.step - 90), np.radians((col + 0.5) * self.step)))

    def between(self, a: tuple, b: tuple) -> np.ndarray:
        if self.metric == "grid":
            return np.sqrt((a[0] - b[0]) ** 2 + (a[1] - b[1]) ** 2.0)
        h = np.sin((b[0] - a[0]) / 2) ** 2 + np.cos(a[0]) * np.cos(b[0]) * np.sin((b[1] - a[1]) / 2) ** 2
        return np.degrees(2 * np.arcsin(np.sqrt(np.minimum(h, 1.0)))) / self.step


class CellOverlap:
    """Exact shares on the grid: of the cells in old band k, the part in new band i; masked cells don't count."""

    def __init__(self, radii: np.ndarray, sphere: Sphere, n_rows: int, mask: np.ndarray | None = None):
        self.radii, self.sphere = radii, sphere
        cells = np.arange(n_rows * sphere.n)
        self.cells = cells if mask is None else cells[~mask]
        self.places = sphere.place(self.cells)

    def bands(self, cell: int) -> np.ndarray:
        d = self.sphere.between(self.sphere.place(cell), self.places)
        b = np.minimum(np.searchsorted(self.radii, d), len(self.radii) - 1)
        return np.where(d > 0, b, len(self.radii))

    def shares(self, new: int, old: int) -> np.ndarray:
        r = len(self.radii)
        both = np.bincount(self.bands(new) * (r + 1) + self.bands(old), minlength=(r + 1) ** 2).reshape(r + 1, r + 1)
        return both[:r, :r] / np.maximum(both[:, :r].sum(axis=0), 1)


def transfer(old: np.ndarray, radii: np.ndarray, d: float) -> np.ndarray:
    """Starting bands of a centre at distance d from one with bands old, each spread evenly over its band's area."""
    return band_shares(radii, d) @ old


def moved(radii: list[float]):
    """For mapInPandas: term, band, n of rows (term, d, old), whose bands old go to a centre at distance d."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for t, d, old in zip(frame.term, frame.d, frame.old, strict=True):
                yield pd.DataFrame({"term": t, "band": range(len(radii)), "n": transfer(np.asarray(old, float), np.asarray(radii), float(d))})

    return run


def band_shares(radii: np.ndarray, d: float | np.ndarray) -> np.ndarray:
    """Of the area of old band k, the part in new band i, centres d apart."""
    r = np.concatenate([[0.0], radii])
    return planar_overlap(radii, d) / (np.pi * (r[1:] ** 2 - r[:-1] ** 2))


class RingState:
    """The core of a term's ring summary.

    Arrivals wait in a buffer; a centre's bands are brought up to date only when they are asked for or the centre loses its
    counter, so an arrival costs no look at each centre. radii may be several lists: counters don't depend on them,
    and bands of all lists are kept at once (not for nearby_skip without a skip_radius).
    """

    def __init__(self, capacity: int, radii: list[float] | list[list[float]], policy: str = "transfer", freeze_after: float | None = None, skip_radius: float | None = None, transfer_from: str = "victim", transfer_center: bool = False, geometry: str = "planar", backfill: bool = False, overflow: str = "last", skip_to: str = "rings", size_e6: int = geo.SIZE, metric: str = "arc", mask: np.ndarray | None = None):
        if policy not in POLICIES:
            raise ValueError(f"policy {policy!r} is none of {POLICIES}")
        self.lists = [np.asarray(x, float) for x in (radii if np.ndim(radii[0]) else [radii])]
        if len(self.lists) > 1 and policy == "nearby_skip" and skip_radius is None:
            raise ValueError("nearby_skip of several lists of radii needs a skip_radius")
        self.capacity, self.radii, self.policy, self.freeze_after = capacity, self.lists[0], policy, freeze_after
        self.skip_radius = float(self.radii[0]) if skip_radius is None else skip_radius
        self.transfer_from, self.transfer_center, self.backfill, self.overflow, self.skip_to = transfer_from, transfer_center, backfill, overflow, skip_to
        self.sphere, self.n_rows = Sphere(size_e6, metric), geo.rows(size_e6)
        self.cells_overlap = [CellOverlap(x, self.sphere, self.n_rows, mask) for x in self.lists] if geometry == "cells" else None
        self.total = self.replaced = 0
        self.slot: dict[int, int] = {}
        m, width = capacity, max(map(len, self.lists))
        self.cell, self.f, self.err, self.born = (np.zeros(m, np.int64) for _ in range(4))
        self.heap: list[tuple[int, int]] = []  # (f, cell) of each counter, which may lag behind
        self.counted, self.at = np.zeros((m, len(self.lists), width)), (np.zeros(m), np.zeros(m))
        # distances are told apart by the radii of all lists; spread: from there to each list's bands
        self.ends = np.unique(np.concatenate(self.lists))
        self.spread = np.zeros((len(self.ends) + 1, len(self.lists), width))
        for i, x in enumerate(self.lists):
            k = np.searchsorted(x, np.append(self.ends, np.inf))
            k = np.minimum(k, len(x) - 1) if overflow == "last" else k
            here = np.flatnonzero(k < len(x))
            self.spread[here, i, k[here]] = 1
        self.spread = self.spread.reshape(len(self.ends) + 1, -1)
        # all cells seen, by number, and the arrivals (cell's number, size) that bands don't have yet, from since on
        self.number: dict[int, int] = {}
        self.places = np.zeros((2, 64))
        self.waiting, self.sizes, self.fill, self.since = np.zeros(WAITING, np.int32), np.zeros(WAITING), 0, [0] * m
        self.near, self.overlaps = {}, {}
        # places of the distances of numbered cells among all radii, and up to which number each row is filled
        self.table, self.filled = np.zeros((0, 0), np.int16), np.zeros(0, np.int64)
        # transfers of one victim's bands don't change counters, so they are done many at a time
        self.later = policy != "reset" and transfer_from == "victim" and skip_to == "rings" and not transfer_center and not self.cells_overlap
        self.log: list[np.ndarray] = []  # rows (slot, since, to, old cell's number, new cell's)
        # bands that start at zero or later
        self.plain = self.later or (policy == "reset" and skip_to == "rings")

    @property
    def rings(self) -> np.ndarray:
        self._settle_all()
        return self.counted[:, 0, : len(self.radii)]

    def __getstate__(self) -> dict:
        return self.__dict__ | {"near": {}, "overlaps": {}, "table": np.zeros((0, 0), np.int16), "filled": np.zeros(0, np.int64)}

    @property
    def frozen(self) -> bool:
        return self.policy == "freeze" and self.freeze_after is not None and self.total >= self.freeze_after

    def _numbered(self, cells: np.ndarray) -> np.ndarray:
        """Numbers of cells; new ones get the next."""
        number = self.number
        used, which = np.unique(cells, return_inverse=True)
        used = used.tolist()
        fresh = [cell for cell in used if cell not in number]
        if fresh:
            n = len(number)
            number.update(zip(fresh, range(n, n + len(fresh)), strict=True))
            while self.places.shape[1] < len(number):
                self.places = np.concatenate([self.places, np.zeros_like(self.places)], axis=1)
            self.places[:, n : len(number)] = self.sphere.place(np.array(fresh, np.int64))
        return np.fromiter(map(number.__getitem__, used), np.int32, len(used))[which]

    def _told(self, centres: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """Place of the distances of numbered cells among all radii; one more than there are for a cell and itself."""
        d = self.sphere.between(tuple(self.places[:, centres]), tuple(self.places[:, cells]))
        b = np.searchsorted(self.ends, d)
        b[d <= 0] = len(self.ends) + 1
        return b

    def _bands(self, centres: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """The same, by a table while cells are few."""
        n = len(self.number)
        if n > WIDE:
            return self._told(centres, cells)
        if len(self.table) < n:
            size = min(WIDE, max(64, 2 * n))
            table, filled = np.zeros((size, size), np.int16), np.zeros(size, np.int64)
            table[: len(self.table), : len(self.table)], filled[: len(self.filled)] = self.table, self.filled
            self.table, self.filled = table, filled
        used = np.unique(centres)
        for rows in np.array_split(short := used[self.filled[used] < n], -(-len(short) * n // ROOM) or 1):
            if len(rows):
                low = int(self.filled[rows].min())
                self.table[rows, low:n], self.filled[rows] = self._told(rows[:, None], np.arange(low, n)[None, :]), n
        return self.table[centres, cells]

    def _found(self, centres: np.ndarray, since: np.ndarray, to: np.ndarray) -> np.ndarray:
        """What waits from since to `to`, by list and band around each of some centres (numbers)."""
        sizes, width = to - since, len(self.ends) + 2
        out = np.zeros((len(centres), *self.counted.shape[1:]))
        ends = np.cumsum(sizes)
        a = 0
        while a < len(centres):
            b = max(a + 1, int(np.searchsorted(ends, ends[a] + ROOM)))
            which = np.repeat(np.arange(b - a), sizes[a:b])
            at = np.arange(len(which)) + (since[a:b] - (ends[a:b] - sizes[a:b]) + (ends[a] - sizes[a]))[which]
            key = which * width + self._bands(centres[a:b][which], self.waiting[at])
            sums = np.bincount(key, self.sizes[at], (b - a) * width).reshape(b - a, width)
            out[a:b] = (sums[:, :-1] @ self.spread).reshape(out[a:b].shape)
            a = b
        return out

    def _settle(self, slots: list[int], to: int) -> None:
        """Count what waits before `to` in the bands of centres."""
        if slots:
            since = np.array([self.since[k] for k in slots])
            centres = np.array([self.number[int(self.cell[k])] for k in slots])
            self.counted[slots] += self._found(centres, since, np.full(len(slots), to))
            for k in slots:
                self.since[k] = to

    def _settle_all(self) -> None:
        self._settle(list(self.slot.values()), self.fill)
        self.fill, self.since = 0, [0] * self.capacity

    def _put(self, k: int, cell: int, place: tuple, f: int, err: int, seq: int, rings: np.ndarray | None) -> None:
        if cell not in self.number:
            self._numbered(np.array([cell]))
        self.slot[cell] = k
        self.cell[k], self.f[k], self.err[k], self.born[k] = cell, f, err, seq
        self.at[0][k], self.at[1][k] = place
        if rings is not None:
            self.counted[k] = rings
        heapq.heappush(self.heap, (f, cell))

    def _lowest(self) -> int:
        """The slot of the counter lowest by (f, cell)."""
        heap, f, slot = self.heap, self.f, self.slot
        while heap[0][0] != (now := int(f[slot[heap[0][1]]])):
            heapq.heapreplace(heap, (now, heap[0][1]))
        return slot[heap[0][1]]

    def _start(self, cell: int, place: tuple, victim: int, at: int) -> np.ndarray:
        """Bands of a cell that takes the victim's counter by the arrival `at` of those that wait."""
        if self.policy == "reset":
            return np.zeros(self.counted.shape[1:])
        if self.transfer_from == "victim":
            sources = [victim]
        elif self.transfer_from == "nearest":
            sources = [int(np.argmin(self.sphere.between(self.at, place)))]
        else:  # mean_all
            sources = list(range(self.capacity))
        got = []
        for k in sources:
            self._settle([k], at)
            old = int(self.cell[k])
            shares = np.stack([x.shares(cell, old) for x in self.cells_overlap]) if self.cells_overlap else self._shares(np.array([self._apart(old, cell)]))[0]
            got.append((shares @ self.counted[k][:, :, None])[:, :, 0])
        rings = got[0] if len(got) == 1 else np.mean(got, axis=0)
        if self.transfer_center and (d := self._apart(int(self.cell[victim]), cell)) > 0:
            for i, x in enumerate(self.lists):
                rings[i, min(int(np.searchsorted(x, d)), len(x) - 1)] += self.f[victim]
        return rings

    def _apart(self, a: int, b: int) -> float:
        return round(float(self.sphere.between(self.sphere.place(a), self.sphere.place(b))), DIGITS)

    def _shares(self, apart: np.ndarray) -> list[np.ndarray]:
        """Of each list the part of each old band that a new one takes, by the centres' distances; few distances make up most."""
        known, width = self.overlaps, self.counted.shape[2]
        if len(known) > KEPT // 16:
            known.clear()
        fresh = np.array([d for d in apart.tolist() if d not in known])
        for at in range(0, len(fresh), 256):
            part = fresh[at : at + 256]
            out = np.zeros((len(part), len(self.lists), width, width))
            for i, x in enumerate(self.lists):
                out[:, i, : len(x), : len(x)] = band_shares(x, part)
            known.update(zip(part.tolist(), out, strict=True))
        return [known[d] for d in apart.tolist()]

    def _skipped(self, cell: int) -> bool:
        """Whether a kept centre is within the skip radius of a cell."""
        near = self.near.get(cell)
        if near is None:
            if len(self.near) >= KEPT:
                self.near.clear()
            n, row, reach = self.sphere.n, cell // self.sphere.n, math.floor(self.skip_radius + 1e-9)
            # a row's step is a cell unit at least
            around = np.arange(max(0, row - reach) * n, min(self.n_rows, row + reach + 1) * n)
            d = self.sphere.between(self.sphere.place(around), self.sphere.place(cell))
            near = self.near[cell] = around[d <= self.skip_radius].tolist()
        return any(c in self.slot for c in near)

    def observe(self, cell: int, n: int = 1, seq: int = 0) -> None:
        """Count n arrivals in a row at a cell."""
        while n:
            # a freeze may fall inside a run
            part = n if self.policy != "freeze" or self.freeze_after is None or self.total >= self.freeze_after else max(1, min(n, math.ceil(self.freeze_after - self.total)))
            self._observe_part(np.array([cell]), np.array([part]), np.array([seq]))
            transfer_logged([self])
            n -= part

    def observe_all(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray) -> None:
        """observe() of each of several runs, in order."""
        if self.policy == "freeze" and self.freeze_after is not None:
            left = math.ceil(self.freeze_after - self.total)
            if self.total >= self.freeze_after:
                # no order counts any more
                cells, which = np.unique(cells, return_inverse=True)
                sizes, seqs = np.bincount(which, sizes).astype(np.int64), np.zeros(len(cells), np.int64)
            elif (ends := np.cumsum(sizes))[-1] > left:
                # the freeze falls inside: at most one run is cut in two
                k = int(np.searchsorted(ends, left))
                cut = left - (int(ends[k]) - int(sizes[k]))
                self.observe_all(cells[: k + 1], np.append(sizes[:k], cut), seqs[: k + 1])
                rest = sizes[k:].copy()
                rest[0] -= cut
                k, rest = (k, rest) if rest[0] else (k + 1, rest[1:])
                self.observe_all(cells[k:], rest, seqs[k:])
                return
        for at in range(0, len(cells), WAITING):
            self._observe_part(*(x[at : at + WAITING] for x in (cells, sizes, seqs)))
            transfer_logged([self])

    def _observe_part(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray) -> None:
        if self.fill + len(cells) > WAITING:
            self._settle_all()
        at, self.fill = self.fill, self.fill + len(cells)
        self.waiting[at : self.fill], self.sizes[at : self.fill] = self._numbered(cells), sizes
        slot, f, done = self.slot, self.f, 0
        for i, (cell, n, seq) in enumerate(zip(cells.tolist(), sizes.tolist(), seqs.tolist(), strict=True), at):
            if self.plain and not self.frozen and len(slot) == self.capacity and len(cells) - done > FEW:
                self._arrive_all(cells[done:], sizes[done:], seqs[done:], i)
                break
            done += 1
            k = slot.get(cell)
            if k is not None:
                f[k] += n
            elif not self.frozen:
                self._arrive(cell, n, seq, i)
            self.total += n

    def _arrive_all(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray, at: int) -> None:
        """Arrivals, `at` the first of those that wait and all before a freeze, when every counter is taken: what `_arrive` does, with lists of plain numbers."""
        slot, m, skips = self.slot, self.capacity, self.policy == "nearby_skip"
        unit = self.n_rows * self.sphere.n * m
        # a counter is f * unit + its cell * m + its slot, so the least of them is the lowest by (f, cell)
        key = [f * unit + cell * m + k for k, (f, cell) in enumerate(zip(self.f.tolist(), self.cell.tolist(), strict=True))]
        heap = sorted(key)
        err, own, taken, when = self.err.tolist(), self.cell.tolist(), [], []
        before = [self.number[cell] for cell in own]
        for i, (cell, n) in enumerate(zip(cells.tolist(), sizes.tolist(), strict=True)):
            k = slot.get(cell)
            if k is not None:
                key[k] += n * unit
                continue
            if skips and self._skipped(cell):
                continue
            low = heap[0]
            k = low % m
            while low != key[k]:
                heapq.heapreplace(heap, key[k])
                low = heap[0]
                k = low % m
            del slot[own[k]]
            slot[cell], own[k] = k, cell
            taken.append(k)
            when.append(i)
            err[k] = f = low // unit
            key[k] = low = (f + n) * unit + cell * m + k
            heapq.heapreplace(heap, low)
        self.total += int(sizes.sum())
        self.replaced += len(taken)
        self.f[:], self.cell[:], self.err[:] = [x // unit for x in key], own, err
        self.heap = sorted(zip(self.f.tolist(), own, strict=True))
        if not taken:
            return
        slots, when = np.array(taken), np.array(when)
        new = self.waiting[at + when]
        # a slot's rows, one after the other: each begins where the one before ended
        order = np.argsort(slots, kind="stable")
        first = np.concatenate([[True], np.diff(slots[order]) > 0])
        since, old = np.concatenate([[0], at + when[order][:-1]]), np.concatenate([[0], new[order][:-1]])
        lead = slots[order][first]
        since[first], old[first] = np.array(self.since)[lead], np.array(before)[lead]
        last = order[np.append(first[1:], True)]
        self.born[lead] = seqs[when[last]]
        self.at[0][lead], self.at[1][lead] = self.places[:, new[last]]
        for k, i in zip(lead.tolist(), (at + when[last]).tolist(), strict=True):
            self.since[k] = i
        if self.policy == "reset":
            self.counted[lead] = 0
        else:
            self.log.append(np.stack([slots[order], since, at + when[order], old, new[order]], axis=1))

    def _arrive(self, cell: int, n: int, seq: int, at: int) -> None:
        """Arrivals at a cell without a counter, `at` of those that wait."""
        used, number = len(self.slot), self.number[cell]
        place = tuple(self.places[:, number].tolist())
        if used < self.capacity:
            rings = np.zeros(self.counted.shape[1:])
            if self.backfill and used:
                d = self.sphere.between((self.at[0][:used], self.at[1][:used]), place)
                for i, x in enumerate(self.lists):
                    np.add.at(rings[i], np.minimum(np.searchsorted(x, d), len(x) - 1), self.f[:used])
            self._put(used, cell, place, n, 0, seq, rings)
            self.since[used] = at
            return
        if self.policy == "nearby_skip" and self._skipped(cell):
            if self.skip_to == "nearest":
                k = int(np.argmin(self.sphere.between(self.at, place)))
                self.f[k] += n
                # counted in its counter, so not in its bands
                b = int(self._told(np.array([self.number[int(self.cell[k])]]), np.array([number]))[0])
                self.counted[k] -= n * self.spread[b].reshape(self.counted.shape[1:])
            return
        victim = self._lowest()
        old, err = int(self.cell[victim]), int(self.f[victim])
        if self.later:
            rings = None
            self.log.append(np.array([[victim, self.since[victim], at, self.number[old], number]]))
        else:
            rings = self._start(cell, place, victim, at)
        del self.slot[old]
        heapq.heappop(self.heap)
        self.replaced += 1
        self._put(victim, cell, place, err + n, err, seq, rings)
        self.since[victim] = at

    def row(self, term: str, which: int = 0) -> dict:
        """The SUMMARY row of a term, with the bands of one list of radii."""
        self._settle_all()
        used, width = len(self.slot), len(self.lists[which])
        order = np.lexsort((self.cell[:used], self.err[:used], -self.f[:used]))
        centres = [{"cell": int(self.cell[k]), "f": int(self.f[k]), "err": int(self.err[k]), "rings": self.counted[k, which, :width].tolist(), "born_seq": int(self.born[k])} for k in order]
        return {"term": term, "total": int(self.total), "capacity": self.capacity, "policy": self.policy, "n_replaced": int(self.replaced), "frozen": self.frozen, "centers": centres}


def transfer_logged(states: list[RingState]) -> None:
    """The transfers of all counters that were taken since, of states side by side: one's do not depend on another's."""
    states = [s for s in states if s.log]
    if not states:
        return
    lists, width = (max(s.counted.shape[k] for s in states) for k in (1, 2))
    parts, shares, begin, known = [], [], 0, 0
    rings = np.zeros((sum(s.capacity for s in states), lists, width))
    for s in states:
        slots, since, to, old, new = np.concatenate(s.log).T
        if len(s.log) > 1:
            order = np.lexsort((to, slots))
            slots, since, to, old, new = (x[order] for x in (slots, since, to, old, new))
        found = np.zeros((len(slots), lists, width))
        found[:, : s.counted.shape[1], : s.counted.shape[2]] = s._found(old, since, to)
        rings[begin : begin + s.capacity, : s.counted.shape[1], : s.counted.shape[2]] = s.counted
        # rounded, so that equal steps of columns share a distance; pairs of cells are fewer than transfers
        pairs, which = np.unique(old * len(s.number) + new, return_inverse=True)
        d = s.sphere.between(tuple(s.places[:, pairs // len(s.number)]), tuple(s.places[:, pairs % len(s.number)]))
        apart, place = np.unique(np.round(d, DIGITS), return_inverse=True)
        parts.append((begin + slots, known + place[which], found))
        shares.append((s, apart))
        begin, known = begin + s.capacity, known + len(apart)
    slots, which, found = (np.concatenate(x) for x in zip(*parts, strict=True))
    first_of = np.cumsum([0, *(len(apart) for _, apart in shares)])
    # a counter's transfers follow each other, those of different counters go together: first the first of each, and so on
    turn = np.arange(len(slots)) - np.searchsorted(slots, slots)
    times = np.bincount(slots, minlength=begin)
    first = np.argsort(-times, kind="stable")  # counters of the most transfers lead, so a turn takes the first of them
    lead = np.empty(begin, np.int64)
    lead[first] = np.arange(begin)
    order = np.lexsort((lead[slots], turn))
    which, found, rings = which[order], found[order], rings[first]
    ends = np.cumsum(np.bincount(turn)).tolist()
    step = max(1, PARTS // begin)
    for a in range(0, len(ends), step):
        part = ends[a : a + step]
        low = ends[a - 1] if a else 0
        used, where = np.unique(which[low : part[-1]], return_inverse=True)
        table, cuts = np.zeros((len(used), lists, width, width)), np.searchsorted(used, first_of)
        for (s, apart), i, j, k in zip(shares, cuts[:-1], cuts[1:], first_of[:-1], strict=True):
            if j > i:
                got = np.array(s._shares(apart[used[i:j] - k]))
                table[i:j, : got.shape[1], : got.shape[2], : got.shape[3]] = got
        for i, j in zip([low, *part[:-1]], part, strict=True):
            rings[: j - i] = np.einsum("nlij,nlj->nli", table.take(where[i - low : j - low], axis=0), rings[: j - i] + found[i:j])
    out = rings[lead]
    begin = 0
    for s in states:
        s.counted[:] = out[begin : begin + s.capacity, : s.counted.shape[1], : s.counted.shape[2]]
        s.log, begin = [], begin + s.capacity


class Together:
    """States of one stream side by side: what each would be by itself, with their transfers done together."""

    def __init__(self, states: list):
        self.states, self.rings = states, [s for s in states if isinstance(s, RingState)]

    def observe_all(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray) -> None:
        for s in self.states:
            if s not in self.rings or s.policy == "freeze":
                s.observe_all(cells, sizes, seqs)
        rings = [s for s in self.rings if s.policy != "freeze"]
        for at in range(0, len(cells), WAITING):
            for s in rings:
                s._observe_part(*(x[at : at + WAITING] for x in (cells, sizes, seqs)))
            transfer_logged(rings)

    def rows(self, term: str) -> list[dict]:
        return [s.row(term) | {"list": i} for i, s in enumerate(self.states)]


def build(
    occ: DataFrame, capacity: int, radii: list[float] | None = None, policy: str = "transfer", freeze_fraction: float | None = None,
    freeze_after_rows: int | None = None, panes: int = 1, **options
) -> DataFrame:
    """SUMMARY with bands of each term, by replay in arrival order.

    With `freeze`, only arrivals up to the freeze are replayed; what follows has no order any more and is
    counted by (term, cell) and added; gathered arrivals, which are in order already, are all taken by the replay. panes cut each term into parts that are replayed apart and merged.
    """
    radii = edges() if radii is None else list(radii)
    freezes = policy == "freeze" and not (freeze_fraction is None and freeze_after_rows is None)
    if freezes and "cells" in occ.columns:
        totals = occ.groupBy("term").agg(F.sum(F.size("cells")).alias("pane"))

        def run_frozen(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            after = (lambda n: freeze_after_rows) if freeze_fraction is None else (lambda n: int(n) * freeze_fraction)
            yield from counters.replay(frames, lambda _t, n: RingState(capacity, radii, policy, freeze_after=after(n), **options), lambda s, t: s.row(t))

        return counters.arrivals(occ.join(totals, "term"), panes).mapInPandas(run_frozen, SUMMARY)
    if freezes:
        first, rest = _at_freeze(occ.where(F.col("term").isNotNull() & F.col("cell").isNotNull()), freeze_fraction, freeze_after_rows)
        occ = first

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield from counters.replay(frames, lambda *_: RingState(capacity, radii, policy, **options), lambda s, t: s.row(t))

    out = counters.arrivals(occ, panes).mapInPandas(run, SUMMARY)
    if panes > 1:
        out = counters.merge(out, capacity).withColumn("policy", F.lit(policy))
    if not freezes:
        return out
    reached = F.lit(True) if freeze_fraction is not None else F.col("total") >= freeze_after_rows
    return _with_rest(out, rest, radii, options).withColumn("frozen", reached)


def build_each(occ: DataFrame, capacity: int, lists: list[list[float]], policy: str = "transfer", **options) -> DataFrame:
    """SUMMARY with a column `list` (from 0): the summaries that `build` makes for each list of radii, by one replay for all."""

    def finish(s: RingState, term: str) -> list[dict]:
        return [s.row(term, i) | {"list": i} for i in range(len(lists))]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in counters.replay(frames, lambda *_: RingState(capacity, lists, policy, **options), lambda s, t: {"rows": finish(s, t)}):
            yield pd.DataFrame([r for rows in frame["rows"] for r in rows])

    return counters.arrivals(occ).mapInPandas(run, f"{SUMMARY}, list int")


def build_every(occ: DataFrame, settings: list[tuple[int, list[float] | None]], policy: str = "transfer", **options) -> DataFrame:
    """SUMMARY with a column `list` (from 0): for each (capacity, radii) the summary that `build` makes, or that of counters alone
    for radii None; one replay for all."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        new = lambda *_: Together([Counters(m) if radii is None else RingState(m, radii, policy, **options) for m, radii in settings])
        for frame in counters.replay(frames, new, lambda s, t: {"rows": s.rows(t)}):
            yield pd.DataFrame([r for rows in frame["rows"] for r in rows])

    return counters.arrivals(occ).mapInPandas(run, f"{SUMMARY}, list int")


SLICES = 256


def _at_freeze(occ: DataFrame, fraction: float | None, rows: int | None) -> tuple[DataFrame, DataFrame]:
    """The arrivals before each term's freeze, and counts (term, cell, n) of those after it.

    Each term's time is cut into SLICES; only the slice in which its freeze falls is sorted.
    """
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    by = occ.groupBy("term").agg(F.count("*").alias("_n"), F.min(t).alias("_lo"), F.max(t).alias("_hi"))
    after = F.col("_n") * fraction if fraction is not None else F.lit(rows)
    by = by.select("term", "_lo", "_hi", F.least(F.ceil(after.cast("double")), F.col("_n")).alias("_after"))
    part = F.floor((t - F.col("_lo")) * SLICES / (F.col("_hi") - F.col("_lo") + 1)).cast("int")
    cut = occ.join(by, "term").withColumn("_part", part)
    sizes = cut.groupBy("term", "_part", "_after").agg(F.count("*").alias("_rows"))
    before = F.coalesce(F.sum("_rows").over(Window.partitionBy("term").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    plan = materialize(sizes.withColumn("_left", F.col("_after") - before).select("term", "_part", "_left", (F.col("_left") < F.col("_rows")).alias("_split")), "freeze")
    rows_ = cut.drop("_after").join(plan, ["term", "_part"])
    names = occ.columns
    order = Window.partitionBy("term", "_part").orderBy("ts", "seq", "msg_id", "cell")
    numbered = rows_.where("_split and _left > 0").withColumn("_k", F.row_number().over(order))
    first = rows_.where("not _split").select(*names).unionByName(numbered.where("_k <= _left").select(*names))
    late = rows_.where("_left <= 0").select("term", "cell").unionByName(numbered.where("_k > _left").select("term", "cell"))
    return first, materialize(late.groupBy("term", "cell").agg(F.count("*").alias("n")), "rest")


def _with_rest(summary: DataFrame, rest: DataFrame, radii: list[float], options: dict) -> DataFrame:
    """Frozen summaries with the counts of later arrivals added."""
    summary = materialize(summary, "frozen")
    centres = summary.select("term", F.explode("centers").alias("c")).select("term", "c.cell")
    geometry = {k: options[k] for k in ("overflow", "size_e6", "metric") if k in options}
    bands = exact(rest, centres, radii, **geometry).groupBy("term", "center_cell").agg(F.map_from_entries(F.collect_list(F.struct("band", F.col("n").cast("double")))).alias("m"))
    own = centres.join(rest, ["term", "cell"]).select("term", F.col("cell").alias("center_cell"), "n")
    more = bands.join(own, ["term", "center_cell"], "full_outer").groupBy("term").agg(F.map_from_entries(F.collect_list(F.struct("center_cell", F.struct("m", F.coalesce("n", F.lit(0)).alias("n"))))).alias("more"))
    totals = rest.groupBy("term").agg(F.sum("n").alias("late"))

    def grown(c: Column) -> Column:
        late = F.element_at(F.col("more"), c["cell"])
        rings = F.transform(c["rings"], lambda x, k: x + F.coalesce(F.element_at(late["m"], k), F.lit(0.0)))
        return F.struct(c["cell"].alias("cell"), (c["f"] + F.coalesce(late["n"], F.lit(0))).alias("f"), c["err"].alias("err"), rings.alias("rings"), c["born_seq"].alias("born_seq"))

    rows = summary.join(more, "term", "left").join(totals, "term", "left")
    ranked = F.sort_array(F.transform(F.transform("centers", grown), lambda c: F.struct((-c["f"]).alias("a"), c["err"].alias("b"), c["cell"].alias("c"), c.alias("x"))))
    centers = F.transform(ranked, lambda r: r["x"]).cast(f"array<{counters.CENTRE}>").alias("centers")
    return rows.select("term", (F.col("total") + F.coalesce("late", F.lit(0))).alias("total"), "capacity", "policy", "n_replaced", F.lit(True).alias("frozen"), centers)


def snapshots(occ: DataFrame, capacity: int, slices: int = 20) -> DataFrame:
    """term, part (1..slices), replaced, top1, top3 (cells), centers (cells): counters at equal parts of each term's stream."""
    length = occ.where(F.col("cell").isNotNull()).groupBy("term").agg(F.count("*").alias("length"))
    rows = occ.where(F.col("cell").isNotNull()).join(length, "term").select("term", F.col("length").alias("pane"), "cell", "ts", "seq", "msg_id")
    tasks = int(occ.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(tasks, "term", "pane").sortWithinPartitions("term", "pane", "ts", "seq", "msg_id", "cell")
    schema = "term string, part int, replaced long, top array<int>, centers array<int>"

    class Slices:
        def __init__(self, length: int):
            self.core, self.length, self.out = Counters(capacity), length, []

        def observe_all(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray) -> None:
            for cell, n, seq in zip(cells.tolist(), sizes.tolist(), seqs.tolist(), strict=True):
                for _ in range(n):
                    self._observe(cell, seq)

        def _observe(self, cell: int, seq: int) -> None:
            self.core.observe(cell, 1, seq)
            while len(self.out) < slices and self.core.total >= self.length * (len(self.out) + 1) / slices:
                order = [c["cell"] for c in self.core.row("")["centers"]]
                self.out.append((self.core.replaced, order[:3], order))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def finish(s: Slices, term: str) -> dict:
            return {"term": term, "out": s.out}

        for frame in counters.replay(frames, lambda _t, n: Slices(int(n)), finish):
            yield pd.DataFrame([(t, i + 1, a, b, c) for t, out in zip(frame.term, frame.out, strict=True) for i, (a, b, c) in enumerate(out)], columns=["term", "part", "replaced", "top", "centers"])

    return rows.mapInPandas(run, schema)


def exact(counts: DataFrame, centres: DataFrame, radii: list[float], overflow: str = "last", size_e6: int = geo.SIZE, metric: str = "arc", with_cells: bool = False) -> DataFrame:
    """term, center_cell, band, n (and occ_cells): exact bands around given centres, in two passes without order.

    counts: term, cell, n; centres: term, cell. An equi-join on term of counted cells with a few centres; sums combine on the map side.
    """
    c = centres.select("term", F.col("cell").alias("center_cell"))
    d = geo.cell_distance("center_cell", "cell", size_e6, metric)
    # the distance is a column of its own: a band's conditions use it several times
    rows = counts.join(c, "term").withColumn("distance", d).withColumn("band", band("distance", radii, overflow=overflow)).where(F.col("band").isNotNull())
    sums = [F.sum("n").alias("n")] + ([F.count("*").alias("occ_cells")] if with_cells else [])
    return rows.groupBy("term", "center_cell", "band").agg(*sums)


def empty_cells(bands: DataFrame, table: DataFrame, size_e6: int = geo.SIZE) -> DataFrame:
    """bands (term, center_cell, band, n) with cells of the band and cells less arrivals, which may be negative."""
    rows = bands.withColumn("row", geo.cell_row("center_cell", size_e6)).join(F.broadcast(table.select("row", "band", "cells")), ["row", "band"])
    return rows.select("term", "center_cell", "band", "n", "cells", (F.col("cells") - F.col("n")).alias("empty"))


def cells(spark: SparkSession, size_e6: int = geo.SIZE, mask: Column | None = None) -> DataFrame:
    """cell, row, col, lat, lon of the grid; mask: uninhabitable cells to leave out."""
    grid = spark.range(geo.rows(size_e6) * geo.columns(size_e6)).select(F.col("id").cast("int").alias("cell"))
    grid = grid.select("cell", geo.cell_row("cell", size_e6).alias("row"), geo.cell_col("cell", size_e6).alias("col"), geo.centre_lat("cell", size_e6).alias("lat"), geo.centre_lon("cell", size_e6).alias("lon"))
    return grid if mask is None else grid.where(~mask)


def band_table(spark: SparkSession, radii: list[float], size_e6: int = geo.SIZE, metric: str = "arc", overflow: str = "last") -> DataFrame:
    """row, band, cells, mean_dist for a centre in each row of the grid: on an unmasked sphere its column doesn't matter.

    By rows and column steps, O(rows**2 * columns), not by pairs of cells. For `grid` the centre stands in the middle column.
    """
    n_rows, n_cols = geo.rows(size_e6), geo.columns(size_e6)
    centre = spark.range(n_rows).select(F.col("id").cast("int").alias("row"))
    pairs = centre.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n_rows - 1)))).withColumn("col", F.explode(F.sequence(F.lit(0), F.lit(n_cols - 1))))
    a, b = F.col("row") * n_cols + n_cols // 2, F.col("other") * n_cols + F.col("col")
    d = geo.cell_distance(a, b, size_e6, metric)
    rows = pairs.withColumn("d", d).withColumn("band", band("d", radii, overflow=overflow)).where(F.col("band").isNotNull())
    return rows.groupBy("row", "band").agg(F.count("*").alias("cells"), F.avg("d").alias("mean_dist"))


def band_tables(spark: SparkSession, lists: list[list[float]], size_e6: int = geo.SIZE, metric: str = "arc", overflow: str = "last") -> DataFrame:
    """list (from 0), row, band, cells, mean_dist: the band_table of each list of radii, by one computation of the distances."""
    n_rows, n_cols = geo.rows(size_e6), geo.columns(size_e6)
    centre = spark.range(n_rows).select(F.col("id").cast("int").alias("row"))
    # where columns go round evenly, those to the west are as far as those to the east, and are counted with them
    even, mid = metric == "arc" and 360 * geo.DEGREE % size_e6 == 0, n_cols // 2
    away = F.explode(F.sequence(F.lit(0), F.lit(mid if even else n_cols - 1)))
    pairs = centre.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n_rows - 1)))).withColumn("away", away)
    a, b = F.col("row") * n_cols + (0 if even else mid), F.col("other") * n_cols + F.col("away")
    times = F.when((F.col("away") > 0) & (2 * F.col("away") < n_cols), F.lit(2)).otherwise(F.lit(1)) if even else F.lit(1)
    ends = [np.asarray(x, float) for x in lists]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        # a band more than there are, for what is beyond the last
        sums = [np.zeros((2, n_rows * (len(x) + 1))) for x in ends]
        for frame in frames:
            there = (d := frame.d.to_numpy()) > 0
            row, d, n = frame.row.to_numpy()[there], d[there], frame.times.to_numpy(float)[there]
            for x, out in zip(ends, sums, strict=True):
                k = np.searchsorted(x, d)
                key = row * (len(x) + 1) + (np.minimum(k, len(x) - 1) if overflow == "last" else k)
                low = int(key.min()) if len(key) else 0
                for j, part in enumerate((np.bincount(key - low, n), np.bincount(key - low, n * d))):
                    out[j, low : low + len(part)] += part
        for i, (x, out) in enumerate(zip(ends, sums, strict=True)):
            at = np.flatnonzero(out[0])
            at = at[at % (len(x) + 1) < len(x)]
            yield pd.DataFrame({"list": i, "row": at // (len(x) + 1), "band": at % (len(x) + 1), "cells": out[0, at].astype(np.int64), "dist": out[1, at]})

    parts = pairs.select("row", geo.cell_distance(a, b, size_e6, metric).alias("d"), times.alias("times")).mapInPandas(run, "list int, row int, band int, cells long, dist double")
    return parts.groupBy("list", "row", "band").agg(F.sum("cells").alias("cells"), (F.sum("dist") / F.sum("cells")).alias("mean_dist"))


def masked_band_table(grid: DataFrame, centres: DataFrame, radii: list[float], size_e6: int = geo.SIZE, overflow: str = "last") -> DataFrame:
    """center_cell, band, cells, mean_dist with only the cells of a (masked) grid, for given centres."""
    d = geo.cell_distance("center_cell", "cell", size_e6)
    c = centres.select(F.col("cell").alias("center_cell")).distinct()
    rows = geo.on_every_cell(grid, c).withColumn("d", d).withColumn("band", band("d", radii, overflow=overflow)).where(F.col("band").isNotNull())
    return rows.groupBy("center_cell", "band").agg(F.count("*").alias("cells"), F.avg("d").alias("mean_dist"))


def mean_distance(radii: list[float], mode: str = "mid") -> list[float] | None:
    """Middles of the bands; with 'cells' None: take mean_dist of the band table."""
    return [(a + b) / 2 for a, b in zip([0.0, *radii], radii, strict=False)] if mode == "mid" else None
