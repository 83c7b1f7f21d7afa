"""Array and loop kernels for what columns can't express: early stops and running estimates."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

MASK = (1 << 64) - 1
U64 = np.uint64


def mix(x: int) -> int:
    """A 64-bit finaliser of an int."""
    x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & MASK
    x = (x ^ x >> 27) * 0x94D049BB133111EB & MASK
    return x ^ x >> 31


def mix_array(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


_STEP = 0x9E3779B97F4A7C15
_PLACE = 0xD1B54A32D192ED03


def draw(key: int, k: int) -> float:
    """The k-th uniform number, in (0, 1), of an element."""
    return ((mix(key + k * _STEP & MASK) >> 12) + 0.5) / (1 << 52)


def rand_between(key: int, k: int, m: int) -> int:
    """An integer from k to m that the element fixes."""
    return k + mix((key ^ _PLACE) + k * _STEP & MASK) % (m - k + 1)


def ascending_exponentials(key: int, w: float, m: int) -> np.ndarray:
    """All m exponential variables of an element of weight w, smallest first, from their spacings."""
    k = np.arange(1, m + 1)
    u = ((mix_array(U64(key) + k.astype(U64) * U64(_STEP)) >> U64(12)).astype(float) + 0.5) / (1 << 52)
    return np.cumsum(-np.log(u) / (w * (m - k + 1)))


def shuffle_step(slots: dict[int, int], key: int, k: int, m: int) -> int:
    """The register of the k-th smallest variable: one swap of a random permutation, of which only touched slots are kept."""
    j = rand_between(key, k, m)
    here, there = slots.get(k, k), slots.get(j, j)
    slots[k], slots[j] = there, here
    return there


def permutation(key: int, m: int) -> list[int]:
    """The registers 1..m in the order in which the element reaches them."""
    slots: dict[int, int] = {}
    return [shuffle_step(slots, key, k, m) for k in range(1, m + 1)]


@dataclass
class OrderedSketch:
    """Registers filled by ascending variables, with an early stop.

    ``bits`` None: float registers, which keep the minimum. Otherwise integers,
    which keep the maximum of the truncated bucket. The worst register bounds
    what can still change; "eager" keeps it exact, "lazy" looks for it again
    only at each batch's begin. Registers are the same either way.
    """

    m: int
    low: int = 0
    high: int = 0
    floats: bool = True
    early_stop: bool = True
    tracking: str = "eager"
    registers: np.ndarray = field(init=False)
    draws: int = 0
    arrivals: int = 0
    refreshes: int = 0

    def __post_init__(self):
        self.registers = np.full(self.m, np.inf) if self.floats else np.full(self.m, self.low, np.int64)
        self._refresh()

    def _refresh(self) -> None:
        self.worst = self.registers.max() if self.floats else self.registers.min()
        self.at_worst = int((self.registers == self.worst).sum())
        self.refreshes += 1

    def add(self, keys: np.ndarray, weights: np.ndarray, first: np.ndarray | None = None) -> None:
        """A batch of elements, known by 64-bit keys, with positive weights.

        ``first``: their smallest variables, if these are known already.
        """
        if self.tracking == "lazy":
            self._refresh()
        self.arrivals += len(keys)
        if first is None:
            u = ((mix_array(keys + U64(_STEP)) >> U64(12)).astype(float) + 0.5) / (1 << 52)
            first = -np.log(u) / (weights * self.m)
        if self.early_stop and len(keys):
            # most elements stop at their first variable, which is looked at for the whole batch at once
            self.draws += len(keys)
            # the bound only falls during the batch, so what fails now fails later
            go = first < self.worst if self.floats else self._bucket(first) > self.worst
            keys, weights, first = keys[go], weights[go], first[go]
            self.draws -= len(keys)
        for key, w, r in zip(keys.tolist(), weights.tolist(), first.tolist(), strict=True):
            self._one(key, w, r)

    def _bucket(self, r: np.ndarray) -> np.ndarray:
        return np.clip(np.floor(-np.log2(r)), self.low, self.high)

    def _one(self, key: int, w: float, r: float) -> None:
        slots: dict[int, int] = {}
        m = self.m
        for k in range(1, m + 1):
            if k > 1:
                r -= math.log(draw(key, k)) / (w * (m - k + 1))
            self.draws += 1
            value = r if self.floats else min(max(math.floor(-math.log2(r)), self.low), self.high)
            if self.early_stop and (value >= self.worst if self.floats else value <= self.worst):
                return
            j = shuffle_step(slots, key, k, m) - 1
            old = self.registers[j]
            if (value < old) if self.floats else (value > old):
                self.registers[j] = value
                if self.tracking == "eager" and old == self.worst:
                    self.at_worst -= 1
                    if self.at_worst == 0:
                        self._refresh()


@dataclass
class LiveSketch:
    """One register for each arrival, a histogram of register values, and the running estimate.

    ``timing``: the chance of a rise by the state before ("pre") or after ("post")
    it; ``begin``: whether the histogram starts with all registers at the lowest
    value ("full") or empty ("zero"). The defaults are unbiased; the others show why.
    """

    m: int
    low: int
    high: int
    timing: str = "pre"
    begin: str = "full"
    est: float = 0.0
    var: float = 0.0
    rises: int = 0

    def __post_init__(self):
        self.registers: dict[int, int] = {}
        self.count: dict[int, int] = {self.low: self.m} if self.begin == "full" else {}

    def chance(self, w: float) -> float:
        """Probability that an element of weight w raises some register."""
        stuck, rising = 0, 0.0
        for y, n in self.count.items():
            if y >= self.high:
                stuck += n
            else:
                rising += n * -math.expm1(-w * 2.0 ** -(y + 1))
        missing = self.m - stuck - sum(n for y, n in self.count.items() if y < self.high)
        return (rising + missing) / self.m  # registers that an empty histogram lacks count as sure to rise

    def histogram(self) -> list[tuple[int, int]]:
        """(value, registers) in order of value."""
        return sorted(self.count.items())

    def add(self, j: int, y: int, w: float) -> bool:
        """An arrival at register j with truncated bucket y; whether it rises."""
        old = self.registers.get(j, self.low)
        if y <= old:
            return False
        q = self.chance(w) if self.timing == "pre" else 0.0
        self.registers[j] = y
        if self.count.get(old, 0) > 0:
            self.count[old] -= 1
            if not self.count[old]:
                del self.count[old]
        self.count[y] = self.count.get(y, 0) + 1
        if self.timing == "post":
            q = self.chance(w)
        self.last_q = q
        self.est += w / q
        self.var += w * w * (1 - q) / (q * q)
        self.rises += 1
        return True


def newton_rows(row: np.ndarray, y: np.ndarray, n: np.ndarray, c: np.ndarray, low: int | None, high: int | None, tol: float = 1e-12, max_iter: int = 40) -> np.ndarray:
    """``estimators.newton`` from starts ``c`` for many histograms side by side; their entries (y, n) belong to rows ``row`` of ``c``."""
    a = np.power(2.0, -(y + 1.0))
    at_low, at_high = (y <= low, y >= high) if low is not None else (np.zeros(len(y), bool),) * 2
    end = np.where(at_high, 2 * a, a)
    total = lambda term: np.bincount(row, n * term, len(c))
    done = np.zeros(len(c), bool)
    with np.errstate(all="ignore"):
        for _ in range(max_iter):
            x = c[row] * end
            grown = np.expm1(x)
            score = total(np.where(at_low, -a, np.where(at_high, end / grown, a * (1 / grown - 1))))
            curve = total(np.where(at_low, 0.0, -end * end / (grown * -np.expm1(-x))))
            new = c - score / curve
            moved = np.abs(new - c) > tol * np.abs(new)
            c = np.where(done, c, new)
            done |= ~moved
            if done.all():
                break
    return c


def fold_rises(size: np.ndarray, y: np.ndarray, before: np.ndarray, w: np.ndarray, m: int, low: int, high: int, timing: str = "pre", begin: str = "full", histograms: bool = False) -> dict[str, list | np.ndarray]:
    """What ``LiveSketch`` tells after each rise (q, est, var, rise[, hist]), for many streams side by side.

    ``size``: rises of each stream, which follow each other in ``y``, ``before``
    (the register's value until then) and ``w``. The k-th rises of all streams
    are one step.
    """
    values = np.unique(np.concatenate([y, before, [low]]))
    up, old = np.searchsorted(values, y), np.searchsorted(values, before)
    with np.errstate(over="ignore"):
        rate = np.where(values < high, np.power(2.0, -(values + 1.0)), 0.0)
    streams = np.argsort(-size, kind="stable")
    first, left = (np.cumsum(size) - size)[streams], -size[streams]
    count = np.zeros((len(size), len(values)))
    if begin == "full":
        count[:, np.searchsorted(values, low)] = m
    out: dict[str, list | np.ndarray] = {"q": np.empty(len(y)), "est": np.empty(len(y)), "var": np.empty(len(y)), "rise": np.empty(len(y), np.int64)}
    hist: list = [None] * len(y)
    est, var = np.zeros(len(size)), np.zeros(len(size))

    def chance(held: np.ndarray, weight: np.ndarray) -> np.ndarray:
        rising = (held * -np.expm1(-weight[:, None] * rate)).sum(1)
        return (rising if begin == "full" else rising + m - held.sum(1)) / m  # registers that an empty histogram lacks count as sure to rise

    for k in range(int(size.max(initial=0))):
        n = int(np.searchsorted(left, -k))  # streams of more than k rises
        at, held = first[:n] + k, count[:n]
        weight, each = w[at], np.arange(n)
        q = chance(held, weight) if timing == "pre" else None
        known = slice(None) if begin == "full" else before[at] > low
        held[each[known], old[at][known]] -= 1
        held[each, up[at]] += 1
        if q is None:
            q = chance(held, weight)
        est[:n] += weight / q
        var[:n] += weight * weight * (1 - q) / (q * q)
        out["q"][at], out["est"][at], out["var"][at], out["rise"][at] = q, est[:n], var[:n], k + 1
        if histograms:
            for i, row in zip(at.tolist(), held, strict=True):
                some = np.flatnonzero(row)
                hist[i] = [{"y": a, "n": int(b)} for a, b in zip(values[some].tolist(), row[some].tolist(), strict=True)]
    return out | ({"hist": hist} if histograms else {})
