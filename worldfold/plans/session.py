"""Private sessions: SQL in, released rows out, budget kept."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from worldfold.context import BudgetLedger, QueryContext
from worldfold.functions.release import FED_ALONE
from worldfold.plans import ir
from worldfold.plans.frontend import parse
from worldfold.plans.rewrite import Rejected, Rewriter
from worldfold.sources.catalog import UnitCatalog


@dataclass(frozen=True)
class Verdict:
    """kind: "pass" (no unit data), "rewrite" or "reject"; ``formal``: within the class that the theorems cover, or
    ``outside`` of it for these reasons. ``warnings``: what noise may change besides values (order, limit, offset)."""

    kind: str
    reason: str = ""
    node: str = ""
    formal: bool = True
    joins_added: int = 0
    releases: int = 0
    outside: tuple[str, ...] = ()
    warnings: tuple[str, ...] = ()


class PrivateSession:
    def __init__(self, spark: SparkSession, catalog: UnitCatalog, mi: float = 1 / 128, worlds: int = 64, seed: int | None = None, mode: str = "query", null_draw: bool = True, limit: float | None = None, boundary: str = "release", strategy: str = "kernel", diversity: bool = True, **context):
        """``mode`` "query" draws a key for each query; "session" keeps one, so budgets add up over the session.

        Every query has draws of its own in both. With ``posterior="sequential"`` releases are calibrated to what all
        releases under the key have told so far, one after the other; only then the ledger's sum bounds them together.
        ``null_draw``, ``strategy``, ``diversity`` and ``boundary`` are the rewriter's; other options the context's.
        """
        self.spark, self.catalog, self.mode = spark, catalog, mode
        self.seed, self.queries = seed, 0
        self.rules = {"null_draw": null_draw, "boundary": boundary, "strategy": strategy, "diversity": diversity}
        self.options = {"mi": mi, "worlds": worlds, **context}
        self.kept = QueryContext.new(seed, **self.options) if mode == "session" else None
        self.posterior: list[float] | None = None
        self.ledger = BudgetLedger(limit)
        self.held: list[DataFrame] = []

    def context(self) -> QueryContext:
        """The next query's: a key of its own, or the session's with the next number."""
        self.queries += 1
        if self.kept:
            return self.kept.but(query=self.queries)
        return QueryContext.new(None if self.seed is None else self.seed + self.queries - 1, **self.options)

    def rewriter(self, ctx: QueryContext, mode: str = "release", charge=None) -> Rewriter:
        return Rewriter(self.spark, self.catalog, ctx, mode, charge=charge, posterior=self.posterior if self.kept and ctx.key == self.kept.key else None, **self.rules)

    def close(self) -> None:
        """Lets go of the results that were kept; they are computed again, with equal values, if they are read again."""
        while self.held:
            self.held.pop().unpersist()

    def classify(self, sql: str) -> Verdict:
        try:
            plan, _ = parse(self.spark, sql)
        except Rejected as x:
            return Verdict("reject", x.reason, x.node)
        return self._classify(plan)

    def tried(self, sql: str) -> Verdict:
        """What becomes of a query on the tables as they are: its class, and whether its run is refused, as one is that
        meets an aggregate of a single unit. Runs are not charged and give no rows out (for studies)."""
        v = self.classify(sql)
        if v.kind == "reject":
            return v
        try:
            self.rewrite(sql, QueryContext.new(0, **{**self.options, "posterior": "uniform"})).write.format("noop").mode("overwrite").save()
        except Exception as x:  # the guard's error comes wrapped in the job's
            if FED_ALONE not in str(x):
                raise
            return Verdict("reject", "SINGLE_UNIT")
        return v

    def all_tried(self, queries: list[str]) -> list[Verdict]:
        """Each different query is run once, four at a time."""
        once = list(dict.fromkeys(queries))
        with ThreadPoolExecutor(4) as pool:
            got = dict(zip(once, pool.map(self.tried, once), strict=True))
        return [got[q] for q in queries]

    def passes(self, plan: ir.Node) -> bool:
        """No unit data is read."""
        return not any(isinstance(n, ir.Scan) and self.catalog.sensitive(n.table) or isinstance(n, ir.Unsupported) and n.what == "RECURSION" for n in ir.walk(plan))

    def _classify(self, plan: ir.Node) -> Verdict:
        if self.passes(plan):
            return Verdict("pass")
        r = self.rewriter(QueryContext.new(0, **{**self.options, "posterior": "uniform"}))
        try:
            r.finish(r.node(plan))
        except Rejected as x:
            return Verdict("reject", x.reason, x.node)
        return Verdict("rewrite", formal=r.formal, joins_added=r.joins_added, releases=r.releases, outside=tuple(r.outside), warnings=tuple(r.warnings))

    def rewrite(self, sql: str, ctx: QueryContext | None = None, mode: str = "release") -> DataFrame:
        """The rewritten query, lazily and uncharged (for tests and measurements). Pass-through queries come back as they are;
        others raise ``Rejected``. Under a running posterior releases are computed at once, since each needs the one before.

        A context that is passed in is used as it is: two queries under one key and number share their draws.
        """
        plan, df = parse(self.spark, sql)
        if self.passes(plan):
            return df
        return self._run(plan, ctx or self.context(), mode)

    def _run(self, plan: ir.Node, ctx: QueryContext, mode: str = "release", charge=None) -> DataFrame:
        r = self.rewriter(ctx, mode, charge)
        try:
            return r.finish(r.node(plan))
        finally:
            self.held += r.held
            if self.kept and ctx.key == self.kept.key:
                self.posterior = r.posterior

    def sql(self, text: str, ctx: QueryContext | None = None) -> DataFrame:
        """Released rows. What is released is computed once and kept until ``close``, its cells are counted and charged where
        they are released (a limit, a filter or an outer aggregate above makes them no cheaper), and only then given out."""
        plan, df = parse(self.spark, text)
        if self.passes(plan):
            return df
        ctx = ctx or self.context()
        return self._run(plan, ctx, charge=lambda cells, tosses: self.ledger.charge(text.strip()[:80], cells, ctx.mi, tosses, ctx.adaptive))

    def with_unit_joins(self, sql: str) -> DataFrame:
        """The baseline that only adds the joins to the unit: plain aggregates."""
        return self.rewrite(sql, QueryContext.new(0, **self.options), "plain")

    def explain(self, sql: str) -> str:
        """What would be done, without keys or secrets."""
        plan, _ = parse(self.spark, sql)
        v = self._classify(plan)
        lines = [f"verdict: {v.kind} {v.reason}".strip(), f"joins added: {v.joins_added}, columns released: {v.releases}, formal: {v.formal}"]
        lines += [f"outside of the formal class: {x}" for x in v.outside] + [f"warning: {x}" for x in v.warnings]

        def show(n: ir.Node, depth: int) -> None:
            what = getattr(n, "table", None) or getattr(n, "kind", None) or getattr(n, "what", "") or ""
            mark = " [unit data]" if isinstance(n, ir.Scan) and self.catalog.sensitive(n.table) else ""
            lines.append("  " * depth + f"{type(n).__name__} {what}".rstrip() + mark)
            for c in n.children:
                show(c, depth + 1)

        show(plan, 1)
        return "\n".join(lines)
