"""Orders in which buckets are trained, on one machine and on many; all of it is small driver work.

A bucket is (source part, destination part). A unit is what one task trains: the buckets between two
parts, or those of one part with itself, so the two directions share one load of both parts.
"""

from __future__ import annotations

import random

from ..functions.hashing import py_h32

Bucket = tuple[int, int]
Unit = tuple[int, int]


def inside_out(p: int) -> list[Bucket]:
    """Shell k keeps part k and walks its partners downwards, both directions together, then (k, k)."""
    out: list[Bucket] = []
    for k in range(p):
        for j in range(k - 1, -1, -1):
            out += [(k, j), (j, k)]
        out.append((k, k))
    return out


def order(kind: str, p: int, seed: int = 1) -> list[Bucket]:
    grid = [(i, j) for i in range(p) for j in range(p)]
    if kind == "inside_out":
        return inside_out(p)
    if kind == "outside_in":
        return inside_out(p)[::-1]
    if kind == "row_major":
        return grid
    if kind == "column_major":
        return [(i, j) for j in range(p) for i in range(p)]
    mixed = sorted(grid, key=lambda b: py_h32(seed, "order", *b))
    if kind == "random":
        return mixed
    if kind == "random_aligned":
        out, seen = [mixed.pop(0)], set()
        seen.update(out[0])
        while mixed:
            nxt = next(b for b in mixed if b[0] in seen or b[1] in seen)
            mixed.remove(nxt)
            out.append(nxt)
            seen.update(nxt)
        return out
    raise ValueError(f"unknown order {kind!r}")


def aligned_by_part(seq: list[Bucket]) -> int | None:
    """Place of the first bucket, after the first, of which neither part was trained before; None if there is none."""
    seen: set[int] = set()
    for k, (i, j) in enumerate(seq):
        if k and i not in seen and j not in seen:
            return k
        seen |= {i, j}
    return None


def aligned_by_side(seq: list[Bucket]) -> int | None:
    """The same where a part must have been trained on the same side."""
    src: set[int] = set()
    dst: set[int] = set()
    for k, (i, j) in enumerate(seq):
        if k and i not in src and j not in dst:
            return k
        src.add(i)
        dst.add(j)
    return None


def simulate_swaps(seq: list[Bucket], slots: int = 2) -> dict[str, int]:
    """Loads and stores of parts with a buffer of some slots; the longest unused part leaves first."""
    held: list[int] = []
    loads = stores = 0
    for i, j in seq:
        need = [i] if i == j else [i, j]
        for part in need:
            if part in held:
                held.remove(part)
            else:
                loads += 1
                while len(held) >= slots:
                    gone = next(h for h in held if h not in need)
                    held.remove(gone)
                    stores += 1
            held.append(part)
    return {"loads": loads, "stores": stores + len(held)}


def unit_of(b: Bucket) -> Unit:
    return (min(b), max(b))


def buckets_of(unit: Unit) -> list[Bucket]:
    a, b = unit
    return [(a, a)] if a == b else [(a, b), (b, a)]


def units_in_order(seq: list[Bucket]) -> list[Unit]:
    """Units of a bucket order, each at its first bucket."""
    return list(dict.fromkeys(unit_of(b) for b in seq))


class LockTable:
    """The lock server: hands out units on free parts, prefers those that reuse the worker's part.

    In the first epoch only the first unit may touch two parts that were never trained.
    """

    def __init__(self, p: int, policy: str = "affinity", initialised: set[int] | None = None, first: list[Unit] | None = None):
        self.left = first or units_in_order(inside_out(p))
        self.policy, self.known, self.held, self.started = policy, set(initialised or ()), {}, bool(initialised)
        self.last: dict[int, Unit] = {}

    def acquire(self, worker: int) -> Unit | None:
        busy = {part for u in self.held.values() for part in u}
        free = [u for u in self.left if u[0] not in busy and u[1] not in busy and (not self.started or u[0] in self.known or u[1] in self.known)]
        if not free:
            return None
        if self.policy == "affinity" and worker in self.last:
            free.sort(key=lambda u: -len({*u} & {*self.last[worker]}))
        unit = free[0]
        self.left.remove(unit)
        self.held[worker], self.started = unit, True
        return unit

    def release(self, worker: int) -> None:
        unit = self.held.pop(worker)
        self.known |= {*unit}
        self.last[worker] = unit


def tournament(p: int) -> list[list[Unit]]:
    """Rounds of disjoint pairs that meet every pair once (a circle rotates around one fixed part)."""
    parts = list(range(p)) + ([-1] if p % 2 else [])
    n, out = len(parts), []
    for _ in range(n - 1):
        pairs = [(parts[i], parts[n - 1 - i]) for i in range(n // 2)]
        out.append([(min(a, b), max(a, b)) for a, b in pairs if -1 not in (a, b)])
        parts = [parts[0], parts[-1], *parts[1:-1]]
    return out


def rounds(p: int, m: int, policy: str = "affinity", first_epoch: bool = True) -> list[list[Unit]]:
    """Rounds of at most m units on disjoint parts that cover all units once.

    ``tournament`` has full rounds once all parts are trained; in a first epoch the lock table is used.
    """
    if policy == "tournament" and not first_epoch:
        out = []
        for r in tournament(p):
            out += [r[i : i + m] for i in range(0, len(r), m)]
        own = [(a, a) for a in range(p)]
        return out + [own[i : i + m] for i in range(0, p, m)]
    locks = LockTable(p, "affinity" if policy == "tournament" else policy, None if first_epoch else set(range(p)))
    out = []
    while locks.left:
        now: list[Unit] = []
        for worker in range(m):
            unit = locks.acquire(worker)
            if unit is None:
                continue
            now.append(unit)
            if first_epoch and not locks.known:
                break
        for worker in list(locks.held):
            locks.release(worker)
        if not now:
            raise RuntimeError("no unit is free")
        out.append(now)
    return out


def chains(p: int, m: int, policy: str = "affinity", first_epoch: bool = True) -> list[list[list[Unit]]]:
    """Rounds of at most m chains on disjoint parts that cover all units once.

    A chain is a pair of parts and the units of either part alone that are still to be trained: a worker
    that holds both trains them without another load. Parts that no pair takes along come last.
    """
    own, out = set(range(p)), []
    for units in rounds(p, m, policy, first_epoch):
        now = []
        for a, b in units:
            if a == b:
                continue
            line = [(a, b)]
            for part in (a, b):
                if part in own:
                    own.discard(part)
                    line.append((part, part))
            now.append(line)
        if now:
            out.append(now)
    left = [[(a, a)] for a in sorted(own)]
    return out + [left[i : i + m] for i in range(0, len(left), m)]


def occupancy(plan: list[list[Unit]], m: int) -> float:
    return sum(map(len, plan)) / (m * len(plan)) if plan else 0.0


def schedule_rows(p: int, m: int, epochs: int, policy: str = "affinity", sub_epochs: int = 1) -> list[tuple]:
    """(epoch, sub_epoch, round, slot, unit, p_a, p_b) of a whole training."""
    out = []
    for e in range(epochs):
        for sub in range(sub_epochs):
            for r, units in enumerate(rounds(p, m, policy, e == 0 and sub == 0)):
                out += [(e, sub, r, slot, slot, a, b) for slot, (a, b) in enumerate(units)]
    return out


def shuffled(seq: list, seed: int) -> list:
    out = list(seq)
    random.Random(seed).shuffle(out)
    return out
