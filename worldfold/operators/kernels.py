"""NumPy kernels of the world aggregates: what the engine's built-in aggregation can't do by expressions.

A kernel takes the masks and values of one group's batch and keeps a state that merges by addition (or by extremes).
Bits are unpacked to a rows x 64 matrix of 0 and 1 where a kernel is predicated.
"""

from __future__ import annotations

import numpy as np

WORLDS = 64
#: Levels of the approximate sum, bits of a counter, and bits between levels.
LEVELS, COUNTER, STAGGER = 25, 16, 4


def bits(masks: np.ndarray) -> np.ndarray:
    """rows x 64, world j in column j."""
    return np.unpackbits(np.ascontiguousarray(masks, "<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")


def branch_sum(masks: np.ndarray, values: np.ndarray) -> np.ndarray:
    """The slow reference: a test for each row and world."""
    out = np.zeros(WORLDS, values.dtype if values.dtype.kind == "f" else np.int64)
    for m, v in zip(masks.tolist(), values.tolist(), strict=True):
        for j in range(WORLDS):
            if m >> j & 1:
                out[j] += v
    return out


def matrix_sum(masks: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Values times the bit matrix. Whole numbers are added exactly, in halves of 26 bits as floats hold them."""
    real = values.dtype.kind == "f"
    out = np.zeros(WORLDS, np.float64 if real else object)
    for a in range(0, len(masks), 1 << 16):  # sums of 2**16 halves stay far below 2**53
        b = bits(masks[a : a + (1 << 16)]).astype(np.float64)
        if real:
            out += values[a : a + (1 << 16)] @ b
            continue
        v = values[a : a + (1 << 16)].astype(np.int64)
        out += ((v & ((1 << 26) - 1)).astype(np.float64) @ b).astype(np.int64).astype(object)
        out += ((v >> 26).astype(np.float64) @ b).astype(np.int64).astype(object) * (1 << 26)
    return out


def matrix_count(masks: np.ndarray) -> np.ndarray:
    return bits(masks).sum(0, dtype=np.int64)


class ExactLevels:
    """Sums in levels of 8, 16, 32, 64 bits and one without bound. A value is added to the first level that holds it;
    each level keeps the exact sum of magnitudes and is emptied into the next before that sum could overflow."""

    SIZES = (np.int8, np.int16, np.int32, np.int64)

    def __init__(self):
        self.levels = [np.zeros(WORLDS, t) for t in self.SIZES]
        self.sure = [0] * len(self.SIZES)
        self.wide = [0] * WORLDS
        self.updates = self.flushes = 0

    def add(self, mask: int, value: int) -> None:
        self.updates += 1
        self._put(np.array([mask >> j & 1 for j in range(WORLDS)], np.int64) * 1, value, 0)

    def add_many(self, masks: np.ndarray, values: np.ndarray) -> ExactLevels:
        """Many values at once: runs that surely fit are summed in their level's own type, and the sums go one level up."""
        self.updates += len(values)
        v = values.astype(np.int64)
        huge = v == np.iinfo(np.int64).min  # has no magnitude in 64 bits
        for m in masks[huge].tolist():
            self.wide = [w + (int(np.iinfo(np.int64).min) if m >> j & 1 else 0) for j, w in enumerate(self.wide)]
        b, below = bits(masks).astype(np.int8), -1
        for k, size in enumerate(self.SIZES):
            top = int(np.iinfo(size).max)
            at = np.flatnonzero((np.abs(v) > below) & (np.abs(v) <= top) & ~huge)
            if len(at):
                self._cascade(b[at] * v[at, None].astype(size), k, max(1, int(np.abs(v[at]).max())))
            below = top
        return self

    def _cascade(self, block: np.ndarray, k: int, most: int) -> None:
        """Adds rows of world values, none over ``most``, to level ``k``."""
        while True:
            top = int(np.iinfo(self.SIZES[k]).max)
            if self.sure[k] + len(block) * most <= top:
                self.levels[k] += block.sum(0, dtype=self.SIZES[k])
                self.sure[k] += len(block) * most
                return
            run = max(1, top // most)
            up = np.add.reduceat(block, np.arange(0, len(block), run), axis=0, dtype=self.SIZES[k])
            up, most = np.concatenate((up, self.levels[k][None])), max(run * most, self.sure[k])
            self.flushes += len(up)
            self.levels[k][:] = 0
            self.sure[k] = 0
            if k + 1 == len(self.SIZES):
                self.wide = [w + int(x) for w, x in zip(self.wide, up.astype(object).sum(0), strict=True)]
                return
            k += 1
            block = up.astype(self.SIZES[k])

    def _put(self, which: np.ndarray, value: int, level: int) -> None:
        for k in range(level, len(self.SIZES)):
            top = int(np.iinfo(self.SIZES[k]).max)
            if abs(value) <= top:
                if self.sure[k] + abs(value) > top:
                    self.flush(k)
                self.sure[k] += abs(value)
                self.levels[k] += (which * value).astype(self.SIZES[k])
                return
        self.wide = [w + int(b) * value for w, b in zip(self.wide, which, strict=True)]

    def flush(self, k: int) -> None:
        self.flushes += 1
        top = self.sure[k]
        if k + 1 < len(self.SIZES):
            if self.sure[k + 1] + top > int(np.iinfo(self.SIZES[k + 1]).max):
                self.flush(k + 1)
            self.levels[k + 1] += self.levels[k].astype(self.SIZES[k + 1])
            self.sure[k + 1] += top
        else:
            self.wide = [w + int(x) for w, x in zip(self.wide, self.levels[k], strict=True)]
        self.levels[k][:] = 0
        self.sure[k] = 0

    def total(self) -> list[int]:
        return [w + sum(int(lv[j]) for lv in self.levels) for j, w in enumerate(self.wide)]

    @staticmethod
    def state_bytes() -> int:
        return WORLDS * (1 + 2 + 4 + 8 + 16)


class ApproxLevels:
    """Approximate sums of values that are not negative: 16-bit counters on up to 25 levels, four bits apart.

    A value goes to the level of its highest bit, without the bits below that level. When a counter might overflow, the
    level's upper 12 bits go one level up. Levels exist only once they are used.
    """

    def __init__(self):
        self.levels: dict[int, np.ndarray] = {}
        self.sure: dict[int, int] = {}

    @staticmethod
    def level_of(values: np.ndarray) -> np.ndarray:
        high = np.zeros(len(values), np.int64)
        v = values.astype(np.uint64)
        for s in (32, 16, 8, 4, 2, 1):
            big = v >= np.uint64(1) << np.uint64(s)
            high += big * s
            v = np.where(big, v >> np.uint64(s), v)
        return np.maximum(0, (high - 8) // STAGGER)

    def add(self, masks: np.ndarray, values: np.ndarray) -> None:
        level = self.level_of(values)
        b = bits(masks)
        for k in np.unique(level).tolist():
            at = np.flatnonzero(level == k)
            small = (values[at].astype(np.uint64) >> np.uint64(STAGGER * k)).astype(np.int64)
            lo = 0
            room = (1 << COUNTER) - 1
            ends = np.cumsum(small)
            while lo < len(at):  # as many values as surely fit, then the level is emptied
                used = self.sure.get(k, 0)
                base = int(ends[lo - 1]) if lo else 0
                hi = int(np.searchsorted(ends, base + room - used, side="right"))
                if hi == lo:
                    self.cascade(k)
                    continue
                part = at[lo:hi]
                self._level(k)[:] += (small[lo:hi] @ b[part].astype(np.int64)).astype(np.uint16)
                self.sure[k] = used + int(ends[hi - 1]) - base
                lo = hi

    def _level(self, k: int) -> np.ndarray:
        if k not in self.levels:
            self.levels[k] = np.zeros(WORLDS, np.uint16)
            self.sure[k] = 0
        return self.levels[k]

    def cascade(self, k: int) -> None:
        if k + 1 >= LEVELS:
            raise OverflowError("an approximate sum is over 2**112")
        up = self._level(k) >> STAGGER
        top = int(up.max())
        if self.sure.get(k + 1, 0) + top > (1 << COUNTER) - 1:
            self.cascade(k + 1)
        self._level(k + 1)[:] += up
        self.sure[k + 1] += top
        self.levels[k][:] = 0
        self.sure[k] = 0

    def merge(self, other: ApproxLevels) -> None:
        for k, v in sorted(other.levels.items()):
            if self.sure.get(k, 0) + int(v.max()) > (1 << COUNTER) - 1:
                self.cascade(k)
            self._level(k)[:] += v
            self.sure[k] += int(v.max())

    def total(self) -> np.ndarray:
        out = np.zeros(WORLDS)
        for k, v in self.levels.items():
            out += v.astype(np.float64) * 2.0 ** (STAGGER * k)
        return out

    def state_bytes(self) -> int:
        """25 pointers, in whose free back part the first level has its place, and 128 bytes for each other level."""
        return 200 + 128 * max(0, len(self.levels) - 1)


def approx_sum(masks: np.ndarray, values: np.ndarray, two_sided: bool = True) -> np.ndarray:
    """Approximate world sums; two-sided keeps the negative values in a state of their own.

    One state for both signs has to take a value off counters that only grow: it is added as its complement in the
    level's counter and the borrow is lost with the bits that are cut, which is the weakness this variant shows.
    """
    v = values.astype(np.int64)
    positive, negative = ApproxLevels(), ApproxLevels()
    if two_sided:
        positive.add(masks[v >= 0], v[v >= 0])
        negative.add(masks[v < 0], -v[v < 0])
        return positive.total() - negative.total()
    return SignedLevels().add(masks, v).total()


class SignedLevels:
    """One state for both signs: 16-bit signed counters. Cutting bits rounds down, so errors of both signs pile up."""

    def __init__(self):
        self.levels = np.zeros((LEVELS, WORLDS), np.int64)
        self.sure = np.zeros(LEVELS, np.int64)

    def add(self, masks: np.ndarray, values: np.ndarray) -> SignedLevels:
        top = (1 << (COUNTER - 1)) - 1
        for a in range(0, len(masks), 1 << 16):
            v = values[a : a + (1 << 16)]
            level = ApproxLevels.level_of(np.abs(v))
            b = bits(masks[a : a + (1 << 16)]).astype(np.int64)
            small = v >> (STAGGER * level)
            for k, s, row in zip(level.tolist(), small.tolist(), b, strict=True):
                if self.sure[k] + abs(s) > top:
                    self.cascade(k)
                self.levels[k] += row * s
                self.sure[k] += abs(s)
        return self

    def cascade(self, k: int) -> None:
        up = self.levels[k] >> STAGGER
        top = int(np.abs(up).max())
        if self.sure[k + 1] + top > (1 << (COUNTER - 1)) - 1:
            self.cascade(k + 1)
        self.levels[k + 1] += up
        self.sure[k + 1] += top
        self.levels[k] = 0
        self.sure[k] = 0

    def total(self) -> np.ndarray:
        return (self.levels * 2.0 ** (STAGGER * np.arange(LEVELS))[:, None]).sum(0)


def float_sum(masks: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Sums in single precision, as approximate state for doubles."""
    return (values.astype(np.float32) @ bits(masks).astype(np.float32)).astype(np.float64)


class Pruned:
    """Extremes of each world, skipping values that are no better than the worst world's; the bound is renewed every so many rows."""

    def __init__(self, largest: bool = True, every: int = 2048):
        self.sign = 1.0 if largest else -1.0
        self.every = every
        self.best = np.full(WORLDS, -np.inf)
        self.seen = self.updated = 0

    def add(self, masks: np.ndarray, values: np.ndarray) -> Pruned:
        v = values.astype(np.float64) * self.sign
        for a in range(0, len(v), self.every):
            part, m = v[a : a + self.every], masks[a : a + self.every]
            at = np.flatnonzero(part > self.best.min())
            self.seen += len(part)
            self.updated += len(at)
            if len(at):
                self.best = np.maximum(self.best, np.where(bits(m[at]) == 1, part[at][:, None], -np.inf).max(0))
        return self

    def total(self) -> np.ndarray:
        return np.where(np.isinf(self.best), np.nan, self.best * self.sign)


class Buffered:
    """Three (value, mask) pairs at first; the fourth makes the full state, which takes all four at once."""

    def __init__(self):
        self.pairs: list[tuple[int, int]] = []
        self.state: ExactLevels | None = None

    def add(self, mask: int, value: int) -> None:
        if self.state is None and len(self.pairs) < 3:
            self.pairs.append((mask, value))
            return
        if self.state is None:
            self.state = ExactLevels()
            for p in self.pairs:
                self.state.add(*p)
            self.pairs = []
        self.state.add(mask, value)

    def add_many(self, masks: np.ndarray, values: np.ndarray) -> Buffered:
        some = 0
        if self.state is None:
            some = min(len(masks), 4 - len(self.pairs))
            for m, v in zip(masks[:some].tolist(), values[:some].tolist(), strict=True):
                self.add(m, v)
        if some < len(masks):
            self.state.add_many(masks[some:], values[some:])
        return self

    def total(self) -> list[int]:
        if self.state is not None:
            return self.state.total()
        return [sum(v for m, v in self.pairs if m >> j & 1) for j in range(WORLDS)]

    def state_bytes(self) -> int:
        return 40 if self.state is None else 40 + ExactLevels.state_bytes()


class Running:
    """A state that batches are added to: the kernel's own where it has one, else sums of its batches."""

    def __init__(self, fn: str, strategy: str, whole: bool):
        self.fn, self.strategy, self.whole = fn, strategy, whole
        self.sum = np.zeros(WORLDS, object if whole or fn == "count" else np.float32 if strategy == "float32" else np.float64)
        if fn in ("max", "min"):
            self.own = Pruned(fn == "max", 2048 if strategy == "pruned" else 1 << 62)
        elif fn not in ("sum", "count"):
            raise ValueError(f"{strategy} has no {fn}")
        else:
            self.own = {"levels": ExactLevels, "buffered": Buffered, "approx": lambda: (ApproxLevels(), ApproxLevels()), "approx_single": SignedLevels}.get(strategy, lambda: None)() if fn == "sum" else None
        if fn == "sum" and strategy in ("levels", "buffered", "approx", "approx_single") and not whole:
            raise ValueError(f"{strategy} adds whole numbers")

    def add(self, masks: np.ndarray, values: np.ndarray | None) -> None:
        if self.fn == "count":
            self.sum = self.sum + matrix_count(masks)
        elif self.fn in ("max", "min"):
            self.own.add(masks, values)
        elif self.strategy in ("levels", "buffered"):
            self.own.add_many(masks, values)
        elif self.strategy == "approx":
            v = values.astype(np.int64)
            self.own[0].add(masks[v >= 0], v[v >= 0])
            self.own[1].add(masks[v < 0], -v[v < 0])
        elif self.strategy == "approx_single":
            self.own.add(masks, values.astype(np.int64))
        elif self.strategy == "float32":
            self.sum += values.astype(np.float32) @ bits(masks).astype(np.float32)
        else:
            self.sum = self.sum + matrix_sum(masks, values if self.whole else values.astype(float))

    def total(self) -> list:
        if self.strategy == "approx" and self.fn == "sum":
            return (self.own[0].total() - self.own[1].total()).tolist()
        return list(self.sum if self.own is None else self.own.total())


def state_bytes(strategy: str, levels: int = 2) -> int:
    """Bytes of one group's state."""
    full = {"wide": 64 * 8 + 16, "levels": ExactLevels.state_bytes(), "buffered": 40, "approx": 200 + 128 * max(0, levels - 1), "approx_single": LEVELS * WORLDS * 2, "late": 24, "preagg": 24, "float32": 64 * 4}
    if strategy.startswith("lanes"):
        return int(strategy[5:]) * 8 + 64 * 8
    return full[{"multiply": "wide", "arrow": "wide", "branch": "wide", "pruned": "wide"}.get(strategy, strategy)]
