"""What a private query is drawn with, and what it costs."""

from __future__ import annotations

import math
import secrets as entropy
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class QueryContext:
    """Key of the membership hash, secret world, and budget of one query.

    ``key`` makes the worlds, ``secret_world`` is the one that is answered from, ``mi`` the mutual information spent on a
    released cell. A fresh key a query makes the budget one of the query; a session that keeps its key adds up.
    ``query`` numbers the queries under one key: worlds depend on the key alone, noise, null draws and coins on both, so
    two answers never share a draw.
    """

    key: str
    secret_world: int
    mi: float = 1 / 128
    worlds: int = 64
    hash: str = "xxhash64"  # or "md5", which other engines can repeat
    balance: str = "complement"  # "none", "complement", "repair", "exact"
    posterior: str = "uniform"  # or "sequential"
    scale: str = "estimate"  # counts and sums doubled before variance is measured; or "sample"
    noise: bool = True
    query: int = 0

    @staticmethod
    def new(seed: int | None = None, **options) -> QueryContext:
        worlds = options.get("worlds", 64)
        if worlds not in (64, 128):
            raise ValueError("64 or 128 worlds")
        if seed is None:
            return QueryContext(entropy.token_hex(16), entropy.randbelow(worlds), **options)
        return QueryContext(f"seed-{seed}", (seed * 7919 + 13) % worlds, **options)

    @property
    def draws(self) -> str:
        """The key of this query's draws."""
        return f"{self.key}+{self.query}" if self.query else self.key

    @property
    def adaptive(self) -> bool:
        """Whether noise follows the running posterior, which is what budgets add up under."""
        return self.posterior == "sequential"

    @property
    def factor(self) -> int:
        return 2 if self.scale == "estimate" else 1

    def but(self, **changes) -> QueryContext:
        return replace(self, **changes)

    def __repr__(self) -> str:
        return f"QueryContext(worlds={self.worlds}, mi={self.mi:g}, balance={self.balance}, posterior={self.posterior})"


@dataclass(frozen=True)
class Charge:
    """One release: its cells and their price each.

    ``tosses`` counts rows that a coin let through or not. A coin's chance is the share of worlds that keep the row, the same
    whichever world is secret, so tosses tell nothing about it and cost nothing; they are listed to be seen.
    """

    what: str
    cells: int
    mi: float
    tosses: int = 0
    adaptive: bool = False


@dataclass
class BudgetLedger:
    """Mutual information spent: it adds up over cells where they are released, below limits, filters and outer aggregates."""

    limit: float | None = None
    entries: list[Charge] = field(default_factory=list)

    @property
    def spent(self) -> float:
        return sum(e.cells * e.mi for e in self.entries)

    @property
    def composes(self) -> bool:
        """Whether ``spent`` bounds the information of all releases together: each cell took the running posterior into account.

        Without it the bound holds for each cell on its own, not for the sum of many cells.
        """
        return all(e.adaptive for e in self.entries if e.cells) or sum(e.cells for e in self.entries) <= 1

    def charge(self, what: str, cells: int, mi: float, tosses: int = 0, adaptive: bool = False) -> float:
        if self.limit is not None and self.spent + cells * mi > self.limit + 1e-12:
            raise PermissionError(f"budget exceeded: {self.spent + cells * mi:g} of {self.limit:g}")
        self.entries.append(Charge(what, cells, mi, tosses, adaptive))
        return self.spent

    def success_bound(self, prior: float = 0.5) -> float:
        """The best success of an attack on all releases. Only adaptive releases have one."""
        if not self.composes:
            raise ValueError("releases without a running posterior have no joint bound: use posterior='sequential'")
        return attack_bound(self.spent, prior)


def divergence(p: float, q: float) -> float:
    """Kullback-Leibler divergence of two coins, in nats."""
    part = lambda a, b: 0.0 if a == 0 else math.inf if b == 0 else a * math.log(a / b)
    return part(p, q) + part(1 - p, 1 - q)


def attack_bound(mi: float, prior: float = 0.5) -> float:
    """The best success of any attack whose success was ``prior`` before ``mi`` nats were released."""
    if mi < 0 or not 0 < prior < 1:
        raise ValueError("mi must not be negative and prior must be a probability")
    if divergence(1.0, prior) <= mi:
        return 1.0
    low, high = prior, 1.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if divergence(mid, prior) <= mi else (low, mid)
    return low


def budget_for(success: float, prior: float = 0.5) -> float:
    """The mutual information that holds attacks to ``success``."""
    if not prior <= success <= 1:
        raise ValueError("success must be between the prior and 1")
    return divergence(success, prior)
