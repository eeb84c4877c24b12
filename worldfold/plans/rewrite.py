"""The privacy rewriter: from the IR to a DataFrame whose aggregates hold a value for each world.

The walk goes down the plan once and builds DataFrames on the way up; no job runs. A relation is sensitive while its
rows belong to units. The mask column is made late, when something needs it: from a join of the query that already leads
to the unit if there is one, else by joining pruned tables along the links; the last link holds the unit's key itself
and is not joined.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from itertools import count

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.context import QueryContext
from worldfold.functions import aggregates as A
from worldfold.functions import lift as L
from worldfold.functions.masks import world_mask
from worldfold.functions.release import FED_ALONE, release, release_sequential, single_unit
from worldfold.operators import vectorized as V
from worldfold.plans import ir
from worldfold.plans.expressions import COMPARE, FLIPPED, NotExpressible, to_column
from worldfold.sources.catalog import UnitCatalog

MASK = "__mask"
#: Rows from which on a group that one unit alone feeds is refused.
MIN_UPDATES = 64

#: What takes a query out of the class that the theorems cover, and what is only worth a warning.
COIN, NESTED = "FILTER_AFTER_AGGREGATE", "COMPUTED_FROM_RELEASED"
LIMITED, SKIPPED, ORDERED = "LIMIT_ON_NOISED_ORDER", "OFFSET_ON_NOISED_ORDER", "ORDER_BY_NOISED"


class Rejected(Exception):
    """The query can't be answered privately; ``reason`` is one of a fixed list, ``node`` says where."""

    def __init__(self, reason: str, node: str = ""):
        super().__init__(f"{reason} {node}".strip())
        self.reason, self.node = reason, node


@dataclass
class Vector:
    name: str
    touched: str | None


@dataclass
class Rel:
    df: DataFrame
    attrs: list[ir.Attr]
    origin: dict[int, tuple[str, str]] = field(default_factory=dict)
    protected: set[int] = field(default_factory=set)
    sensitive: bool = False
    masked: bool = False
    narrowed: bool = False
    vectors: dict[int, Vector] = field(default_factory=dict)
    coins: list[str] = field(default_factory=list)
    noised: set[int] = field(default_factory=set)  # released values
    single: bool = False  # an aggregate without keys: one row
    cut: bool = False  # filtered
    roots: dict[int, tuple[DataFrame, bool]] | None = None  # of a join: what each attribute came from, and if that was filtered

    def root(self, i: int) -> tuple[DataFrame, bool] | None:
        """A relation that holds all values attribute ``i`` has here, and whether it is filtered."""
        if self.sensitive and self.masked or self.vectors:
            return None
        return (self.df, self.cut) if self.roots is None else self.roots.get(i)


def name(i: int) -> str:
    return f"c{i}" if i >= 0 else f"cm{-i}"


class Rewriter:
    def __init__(self, spark: SparkSession, catalog: UnitCatalog, ctx: QueryContext, mode: str = "release", null_draw: bool = True, share_sums: bool = True, strategy: str = "kernel", diversity: bool = True, boundary: str = "release", charge: Callable[[int, int], None] | None = None, posterior: list[float] | None = None):
        """``mode``: "release", "vectors" (for tests; shows what must stay hidden) or "plain" (unit joins, plain aggregates).

        ``boundary``: an aggregate of aggregates reads released cells, or ("lift") is taken world by world and released
        once. ``diversity``: groups that many rows of one unit alone have fed are a runtime error. ``charge`` is called
        with the cells and the coin tosses of every release, which is computed and kept for that (``held``); so it is
        under a running posterior, which goes on from ``posterior``, since each release needs the one before.
        """
        self.spark, self.catalog, self.ctx, self.mode = spark, catalog, ctx, mode
        self.null_draw, self.share_sums, self.strategy = null_draw, share_sums, strategy
        self.diversity, self.boundary = diversity, boundary
        self.fresh = count(1_000_000_000)
        self.joins_added = self.releases = self.nodes = 0
        self.charge, self.posterior = charge, posterior
        self.held: list[DataFrame] = []
        self.outside: list[str] = []
        self.warnings: list[str] = []

    # ---- helpers

    @property
    def formal(self) -> bool:
        """Within the class that the theorems cover; ``outside`` says what is not.

        The walk itself keeps the other rules of that class or refuses: unit relations are joined on links only, rows of
        different units are merged by the outermost aggregate only, inner aggregates meet unit rows by inner or left joins or
        as one row, and what filters on them narrows masks.
        """
        return not self.outside

    def note(self, where: list[str], what: str) -> None:
        if what not in where:
            where.append(what)

    def new(self) -> int:
        return next(self.fresh)

    def col(self, e, rel: Rel) -> Column:
        try:
            return to_column(e, lambda i: F.col(name(i)))
        except NotExpressible as x:
            raise Rejected("UNSUPPORTED_EXPRESSION", str(x)) from x

    def lifted(self, e, rel: Rel) -> tuple[Column, list[str]]:
        """A vector column for an expression over vectors and scalars, and the touched columns that it rests on."""
        ids = sorted(i for i in ir.attrs_of(e) if i in rel.vectors)
        touched = [rel.vectors[i].touched for i in ids if rel.vectors[i].touched]
        if isinstance(e, ir.Attr):
            return F.col(name(e.id)), touched

        def f(*parts: Column) -> Column:
            env = dict(zip(ids, parts, strict=True))
            return to_column(e, lambda i: env[i] if i in env else F.col(name(i)), lifted=True)

        try:
            return L.lift(f, *[name(i) for i in ids]), touched
        except NotExpressible as x:
            raise Rejected("UNSUPPORTED_EXPRESSION", str(x)) from x

    def has_vector(self, e, rel: Rel) -> bool:
        return bool(ir.attrs_of(e) & set(rel.vectors))

    # ---- the unit's mask

    def need_mask(self, rel: Rel) -> Rel:
        if rel.masked or not rel.sensitive:
            return rel
        at: dict[tuple[str, str], list[int]] = {}
        for i, o in rel.origin.items():
            at.setdefault(o, []).append(i)
        best = None
        for table in {t for t, _ in at}:
            path = self.catalog.path(table)
            if path is None:
                continue
            cols = self.catalog.key if not path else path[0].cols
            if all((table, c) in at for c in cols) and (best is None or len(path) < len(best[0])):
                best = (path, [name(min(at[(table, c)])) for c in cols])
        if best is None:
            raise Rejected("NO_UNIT_PATH", "the columns that lead to the unit are gone")
        path, cols = best
        df = rel.df
        for k, link in enumerate(path):
            if link.ref == self.catalog.unit and link.ref_cols == self.catalog.key:
                break
            nxt = path[k + 1].cols if k + 1 < len(path) else self.catalog.key
            tag = f"__j{self.new()}_"
            ref = self.spark.table(link.ref).select(*[F.col(c).alias(f"{tag}k{n}") for n, c in enumerate(link.ref_cols)], *[F.col(c).alias(f"{tag}f{n}") for n, c in enumerate(nxt)])
            on = [F.col(c) == F.col(f"{tag}k{n}") for n, c in enumerate(cols)]
            df = df.join(ref, _all(on), "inner")
            cols = [f"{tag}f{n}" for n in range(len(nxt))]
            self.joins_added += 1
        df = df.where(_all([F.col(c).isNotNull() for c in cols])).withColumn(MASK, world_mask(*cols, ctx=self.ctx))
        return replace(rel, df=df.select(*rel.df.columns, MASK), masked=True)

    def class_of(self, rel: Rel, ids: set[int]) -> list[set]:
        """Key classes that the attributes cover as a whole."""
        have = {rel.origin[i] for i in ids if i in rel.origin}
        return [c for c in self.catalog.key_classes() if any(all((t, x) in have for x in cols) for t, cols in c)]

    # ---- nodes

    def node(self, n: ir.Node) -> Rel:
        if isinstance(n, ir.Scan):
            df = self.spark.table(n.table).select(*[F.col(f"`{a.name}`").alias(name(a.id)) for a in n.attrs])
            hidden = {a.id for a in n.attrs if self.catalog.protected(n.table, a.name)}
            return Rel(df, n.attrs, {a.id: (n.table, a.name) for a in n.attrs}, hidden, self.catalog.sensitive(n.table))
        if isinstance(n, ir.Unsupported):
            touch = n.what == "RECURSION" or any(isinstance(x, ir.Scan) and self.catalog.sensitive(x.table) for x in ir.walk(n))
            raise Rejected(f"UNSUPPORTED_{n.what.split()[0]}" if touch else "UNSUPPORTED", n.what)
        return getattr(self, "on_" + type(n).__name__.lower())(n)

    def on_project(self, n: ir.Project) -> Rel:
        return self.project(self.subqueries_of(self.node(n.children[0]), n), n.items)

    def subqueries_of(self, rel: Rel, n) -> Rel:
        if any(ir.subqueries(i) for i in n.items):
            done = {}
            for i in n.items:
                for s in ir.subqueries(i):
                    rel, done[id(s)] = self.scalar(rel, s)
            n.items = [ir.replace(i, lambda e: done.get(id(e)) if isinstance(e, ir.Sub) else None) for i in n.items]
        return rel

    def project(self, rel: Rel, items: list[ir.Item]) -> Rel:
        if any("?Window" in str(i.expr) for i in items) and rel.sensitive:
            raise Rejected("UNSUPPORTED_WINDOW")
        cols, vectors, protected, origin, noised = {}, {}, set(), {}, set()
        for i in items:
            e = i.expr
            if self.has_vector(e, rel):
                v, touched = self.lifted(e, rel)
                cols[name(i.id)] = v
                t = None
                if touched:
                    t = f"__t{self.new()}"
                    both = F.col(touched[0])
                    for x in touched[1:]:
                        both = A.touched_both(both, F.col(x), self.ctx.worlds)
                    cols[t] = both
                vectors[i.id] = Vector(i.name, t)
                continue
            cols[name(i.id)] = self.col(e, rel)
            if ir.attrs_of(e) & rel.noised:
                noised.add(i.id)
            if ir.attrs_of(e) & rel.protected:
                protected.add(i.id)
            if isinstance(e, ir.Attr) and e.id in rel.origin:
                origin[i.id] = rel.origin[e.id]
        # columns that lead to the unit go along, unseen
        keep = [] if not rel.sensitive else [i for i, o in rel.origin.items() if name(i) not in cols and self.catalog.protected(*o)]
        for i in keep:
            origin[i] = rel.origin[i]
        extra = [name(i) for i in keep] + ([MASK] if rel.masked else []) + rel.coins
        df = rel.df.select(*[c.alias(k) for k, c in cols.items()], *dict.fromkeys(extra))
        return replace(rel, df=df, attrs=[ir.Attr(i.id, i.name) for i in items], origin=origin, protected=protected, vectors=vectors, noised=noised)

    def on_filter(self, n: ir.Filter) -> Rel:
        child = n.children[0]
        parts = ir.conjuncts(n.condition)
        if isinstance(child, ir.Join) and child.kind == "inner":  # conditions written below go to the join they belong to
            stay, on = [], ir.conjuncts(child.condition)
            sides = [list(c) for c in ([], [])]
            outs = [{a.id for a in ir.output(c)} for c in child.children]
            for p in parts:
                used = ir.attrs_of(p)
                if ir.subqueries(p):
                    stay.append(p)
                elif used <= outs[0]:
                    sides[0].append(p)
                elif used <= outs[1]:
                    sides[1].append(p)
                elif used <= outs[0] | outs[1]:
                    on.append(p)
                else:
                    stay.append(p)
            kids = [ir.Filter([c], ir.conjunction(s)) if s else c for c, s in zip(child.children, sides, strict=True)]
            child, parts = ir.Join(kids, "inner", ir.conjunction(on)), stay
        rel = self.node(child)
        return self.filter(rel, parts)

    def filter(self, rel: Rel, parts: list) -> Rel:
        later = []
        for p in parts:
            if ir.subqueries(p) or self.has_vector(p, rel):
                later.append(p)
            else:
                rel = replace(rel, df=rel.df.where(self.col(p, rel)), cut=True)
        for p in later:
            e = p
            negated = isinstance(e, ir.Call) and e.op == "Not" and isinstance(e.args[0], ir.Sub)
            inner = e.args[0] if negated else e
            if isinstance(inner, ir.Sub) and inner.kind in ("exists", "in"):
                rel = self.exists(rel, inner, negated)
                continue
            done = {}
            for s in ir.subqueries(p):
                if s.kind != "scalar":
                    raise Rejected("UNSUPPORTED_SUBQUERY", "EXISTS inside an expression")
                rel, done[id(s)] = self.scalar(rel, s)
            p = ir.replace(p, lambda x: done.get(id(x)) if isinstance(x, ir.Sub) else None)
            rel = self.by_worlds(rel, p) if self.has_vector(p, rel) else replace(rel, df=rel.df.where(self.col(p, rel)))
        return rel

    def by_worlds(self, rel: Rel, p) -> Rel:
        """A condition that differs between worlds: narrows the mask of rows, or tosses a coin for released groups."""
        if self.mode == "plain":
            return replace(rel, df=rel.df.where(self.col(p, rel)))
        if rel.sensitive:
            rel = self.need_mask(rel)
            two = isinstance(p, ir.Call) and p.op in COMPARE and [self.has_vector(a, rel) for a in p.args]
            if two and sum(two) == 1:
                v, _ = self.lifted(p.args[two.index(True)], rel)
                op = COMPARE[p.op] if two[1] else FLIPPED[COMPARE[p.op]]
                tmp = f"__v{self.new()}"
                df = rel.df.withColumn(tmp, v).withColumn(MASK, L.mask_cmp(MASK, self.col(p.args[two.index(False)], rel), op, tmp, self.ctx.worlds)).drop(tmp)
            else:
                df = rel.df.withColumn(MASK, L.mask_and(MASK, self.lifted(p, rel)[0], self.ctx.worlds))
            return replace(rel, df=df.where(L.any_world(MASK, self.ctx.worlds)), narrowed=True)
        coin = f"__coin{self.new()}"
        self.note(self.outside, COIN)
        return replace(rel, df=rel.df.withColumn(coin, self.lifted(p, rel)[0]), coins=[*rel.coins, coin])

    # ---- joins

    def on_join(self, n: ir.Join) -> Rel:
        left, right = self.node(n.children[0]), self.node(n.children[1])
        if n.kind == "right":
            return self.join(right, left, ir.conjuncts(n.condition), "left", [*left.attrs, *right.attrs])
        return self.join(left, right, ir.conjuncts(n.condition), n.kind)

    def join(self, left: Rel, right: Rel, parts: list, kind: str, attrs: list | None = None) -> Rel:
        both = Rel(left.df, [], {**left.origin, **right.origin}, vectors={**left.vectors, **right.vectors})
        vec = [p for p in parts if self.has_vector(p, both)]
        plain = [p for p in parts if p not in vec]
        if vec and kind != "inner":
            raise Rejected("UNSUPPORTED_JOIN", "outer join on an aggregate")
        if left.sensitive and right.sensitive:
            if kind == "full" or not self.linked(left, right, plain):
                raise Rejected("BAD_JOIN", "sensitive tables are joined other than by a link")
        elif right.sensitive and kind in ("left", "full", "semi", "anti") or left.sensitive and kind == "full":
            raise Rejected("BAD_JOIN", f"{kind} join makes rows of others depend on units")
        if kind in ("semi", "anti", "left") and right.narrowed:
            raise Rejected("UNSUPPORTED_JOIN", f"{kind} join with rows that differ between worlds")
        if kind == "left" and left.sensitive:
            left = self.need_mask(left)
        r = right.df
        seen = {name(a.id) for a in right.attrs}
        r = r.drop(*[c for c in r.columns if c in left.df.columns and c not in seen and c != MASK])  # unseen keys of a table read twice
        if right.masked:
            r = r.withColumnRenamed(MASK, "__right") if left.masked else r
            if kind in ("semi", "anti", "left"):
                r = r.drop("__right", MASK)
        on = _all([self.col(p, both) for p in plain]) if plain else None
        how = {"inner": "inner", "left": "left", "full": "full", "semi": "left_semi", "anti": "left_anti"}[kind]
        if on is None and kind in ("inner", "left"):  # one row by construction is broadcast; else the engine's statistics decide
            df = left.df.crossJoin(F.broadcast(r) if right.single and not right.sensitive else r)
        else:
            df = left.df.join(r, F.lit(True) if on is None else on, how)
        if kind in ("semi", "anti"):
            return replace(left, df=df)
        masked = left.masked or (right.masked and kind == "inner")
        narrowed = left.narrowed or right.narrowed
        if left.masked and right.masked and kind == "inner":
            if narrowed:
                word = F.col(MASK).bitwiseAND(F.col("__right")) if self.ctx.worlds == 64 else F.zip_with(MASK, "__right", lambda a, b: a.bitwiseAND(b))
                df = df.withColumn(MASK, word).where(L.any_world(MASK, self.ctx.worlds))
            df = df.drop("__right")
        out = Rel(df, attrs or [*left.attrs, *right.attrs], both.origin, left.protected | right.protected, left.sensitive or right.sensitive, masked, narrowed, both.vectors, [*left.coins, *right.coins], left.noised | right.noised)
        roots = lambda side: side.roots or {a.id: side.root(a.id) for a in side.attrs if side.root(a.id)}
        out.roots = {**roots(left), **roots(right)}
        for p in vec:
            out = self.by_worlds(out, p)
        return out

    def linked(self, left: Rel, right: Rel, parts: list) -> bool:
        pairs = set()
        for p in parts:
            if isinstance(p, ir.Call) and p.op in ("EqualTo", "EqualNullSafe") and all(isinstance(a, ir.Attr) for a in p.args):
                a, b = (left.origin.get(p.args[0].id), right.origin.get(p.args[1].id))
                if a is None or b is None:
                    a, b = (left.origin.get(p.args[1].id), right.origin.get(p.args[0].id))
                if a and b:
                    pairs.add((a, b))
        for c in self.catalog.key_classes():
            for t, cols in c:
                for u, others in c:
                    if all(((t, x), (u, y)) in pairs for x, y in zip(cols, others, strict=True)):
                        return True
        return False

    # ---- subqueries

    def decorrelate(self, n: ir.Node, grouped: bool) -> tuple[ir.Node, list]:
        """The plan without conditions on outer attributes, and those conditions; their inner sides become outputs."""
        if isinstance(n, ir.Filter):
            child, taken = self.decorrelate(n.children[0], grouped)
            inside = {a.id for a in ir.output(child)}
            stay = []
            for p in ir.conjuncts(n.condition):
                (stay if ir.attrs_of(p) <= inside else taken).append(p)
            return (ir.Filter([child], ir.conjunction(stay)) if stay else child), taken
        if isinstance(n, (ir.Project, ir.Aggregate)):
            child, taken = self.decorrelate(n.children[0], grouped)
            if not taken:
                return replace(n, children=[child]), taken
            inside = {a.id: a for a in ir.output(child)}
            need = sorted({i for p in taken for i in ir.attrs_of(p) if i in inside} - {i.id for i in n.items})
            more = [ir.Item(i, inside[i].name, inside[i]) for i in need]
            if isinstance(n, ir.Project):
                return ir.Project([child], [*n.items, *more]), taken
            if any(not (isinstance(p, ir.Call) and p.op == "EqualTo") for p in taken):
                raise Rejected("UNSUPPORTED_SUBQUERY", "correlated by other than equality")
            return ir.Aggregate([child], [*n.keys, *[m.expr for m in more]], [*n.items, *more]), taken
        if isinstance(n, ir.Join):
            kids, taken = [], []
            for c in n.children:
                k, t = self.decorrelate(c, grouped)
                kids.append(k)
                taken += t
            inside = {a.id for k in kids for a in ir.output(k)}
            stay = []
            for p in ir.conjuncts(n.condition):
                (stay if ir.attrs_of(p) <= inside else taken).append(p)
            return ir.Join(kids, n.kind, ir.conjunction(stay)), taken
        return n, []

    def scalar(self, rel: Rel, s: ir.Sub) -> tuple[Rel, ir.Attr]:
        plan, taken = self.decorrelate(s.plan, True)
        value = ir.output(s.plan)[0]
        inner = self.node(self.only_asked(rel, plan, taken))
        if inner.sensitive:
            raise Rejected("NO_AGGREGATE", "a subquery returns unit rows")
        zero = isinstance(s.plan, ir.Aggregate) and any(a.fn == "count" for a in ir.aggregates(s.plan.items[0])) and not inner.vectors
        out = self.join(rel, inner, taken, "left" if taken else "inner", [*rel.attrs])
        if zero and taken:
            out = replace(out, df=out.df.withColumn(name(value.id), F.coalesce(name(value.id), F.lit(0))))
        return out, value

    def only_asked(self, rel: Rel, plan: ir.Node, taken: list) -> ir.Node:
        """The subquery's plan, its aggregate fed only with the groups that the outer rows may ask for.

        The outer key's values come from the filtered relation that it was read from, not from all of the outer query.
        """
        if isinstance(plan, ir.Project):
            return replace(plan, children=[self.only_asked(rel, plan.children[0], taken)])
        if not isinstance(plan, ir.Aggregate):
            return plan
        inside = {a.id for a in ir.output(plan.children[0])}
        among = []
        for p in taken:
            if isinstance(p, ir.Call) and p.op == "EqualTo" and all(isinstance(a, ir.Attr) for a in p.args):
                a, b = (x.id for x in p.args)
                a, b = (a, b) if a in inside else (b, a)
                root = rel.root(b) if a in inside and b not in inside else None
                if root and root[1] and name(b) in root[0].columns:
                    among.append((a, root[0], name(b)))
        return replace(plan, children=[ir.Matching(plan.children, among)]) if among else plan

    def on_matching(self, n: ir.Matching) -> Rel:
        rel = self.node(n.children[0])
        for i, df, c in n.among:
            key = f"__m{self.new()}"
            rel = replace(rel, df=rel.df.join(df.select(F.col(c).alias(key)).distinct(), F.col(name(i)) == F.col(key), "left_semi"))
        return rel

    def exists(self, rel: Rel, s: ir.Sub, negated: bool) -> Rel:
        plan, taken = self.decorrelate(s.plan, False)
        if s.kind == "in":
            taken = [*taken, *[ir.Call("EqualTo", (v, ir.Attr(a.id, a.name))) for v, a in zip(s.values, ir.output(s.plan), strict=False)]]
            if negated:
                raise Rejected("UNSUPPORTED_SUBQUERY", "NOT IN")
        inner = self.node(plan)
        if inner.vectors:
            inner = self.released(inner)
        if not taken:
            raise Rejected("UNSUPPORTED_SUBQUERY", "EXISTS without a condition")
        if inner.sensitive and rel.sensitive and not self.linked(rel, inner, taken):
            raise Rejected("UNSUPPORTED_NOT_EXISTS" if negated else "BAD_JOIN", "EXISTS other than on a link")
        return self.join(rel, inner, taken, "anti" if negated else "semi")

    # ---- aggregation

    def on_aggregate(self, n: ir.Aggregate) -> Rel:
        rel = self.subqueries_of(self.node(n.children[0]), n)
        if rel.sensitive and self.share_sums:
            n = replace(n, items=[ir.replace(i, _apart) for i in n.items])
        aggs: list[ir.Agg] = []
        for i in n.items:
            aggs += [a for a in ir.aggregates(i) if a not in aggs]
        lifted = self.boundary == "lift" and rel.vectors and not rel.sensitive and not rel.coins and all(isinstance(x, ir.Attr) and x.id in rel.vectors and a.fn in ("sum", "min", "max", "avg") for a in aggs for x in a.args if self.has_vector(x, rel))
        if rel.vectors and not rel.sensitive and not lifted:
            rel = self.released(rel)
        if set().union(*map(ir.attrs_of, [*n.keys, *aggs]), set()) & rel.noised:
            self.note(self.outside, NESTED)
        if any(self.has_vector(k, rel) for k in n.keys) or not lifted and any(self.has_vector(e, rel) for e in [*n.keys, *aggs]):
            raise Rejected("UNSUPPORTED_AGG", "an aggregate of an aggregate that differs between worlds")
        ids = {a: self.new() for a in aggs}
        keys = [(self.new(), k) if not isinstance(k, ir.Attr) else (k.id, k) for k in n.keys]
        named = {k if not isinstance(k, ir.Item) else k.expr: i for i, k in keys}
        swap = lambda e: ir.Attr(ids[e], "agg") if isinstance(e, ir.Agg) else ir.Attr(named[e], "key") if _hashable(e) and e in named and not isinstance(e, ir.Attr) else None
        items = [ir.replace(i, swap) for i in n.items]
        key_cols = [self.col(k, rel).alias(name(i)) for i, k in keys]
        attrs = [ir.Attr(i, "key") for i, _ in keys] + [ir.Attr(i, "agg") for i in ids.values()]
        key_protected = {i for i, k in keys if ir.attrs_of(k) & rel.protected}
        origin = {i: rel.origin[k.id] for i, k in keys if isinstance(k, ir.Attr) and k.id in rel.origin}
        if rel.sensitive:
            for a in aggs:
                if a.fn.startswith("?"):
                    raise Rejected("UNSUPPORTED_AGG", a.fn[1:])
            by_unit = self.class_of(rel, {k.id for _, k in keys if isinstance(k, ir.Attr)})
            if by_unit:
                rel = self.need_mask(rel)
                df = rel.df.groupBy(*key_cols, MASK).agg(*self.plain(aggs, ids, rel)) if aggs else rel.df.select(*key_cols, MASK).distinct()
                told = {ids[a] for a in aggs if a.fn != "count" and ir.attrs_of(a) & rel.protected}  # a unit's own protected values
                return self.project(Rel(df, attrs, origin, key_protected | told, True, True, rel.narrowed), items)
            if key_protected:
                raise Rejected("PROTECTED_GROUP")
            if not aggs:
                raise Rejected("NO_AGGREGATE", "distinct values of units")
            rel = self.need_mask(rel)
            if self.mode == "plain":
                return self.project(Rel(rel.df.groupBy(*key_cols).agg(*self.plain(aggs, ids, rel)), attrs, origin), items)
            return self.project(replace(self.worlds(rel, keys, key_cols, aggs, ids, attrs, origin), single=not keys), items)
        if lifted:
            return self.project(replace(self.of_worlds(rel, key_cols, aggs, ids, attrs, origin), single=not keys), items)
        df = rel.df.groupBy(*key_cols).agg(*self.plain(aggs, ids, rel)) if aggs else rel.df.select(*key_cols).distinct()
        noised = {i for i, e in [*keys, *((i, a) for a, i in ids.items())] if ir.attrs_of(e) & rel.noised}
        return self.project(Rel(df, attrs, origin, key_protected, noised=noised, single=not keys), items)

    def of_worlds(self, rel: Rel, key_cols: list, aggs: list[ir.Agg], ids: dict, attrs: list, origin: dict) -> Rel:
        """Aggregates of vectors, world by world."""
        cols, vectors = [], {}
        for a in aggs:
            out = name(ids[a])
            if a.args and self.has_vector(a.args[0], rel):
                v = rel.vectors[a.args[0].id]
                cols.append(F.array(*[getattr(F, a.fn)(F.element_at(name(a.args[0].id), j + 1)) for j in range(self.ctx.worlds)]).alias(out))
                t = f"__t{self.new()}" if v.touched else None
                if t:
                    cols.append(A.touched(v.touched, None, self.ctx.worlds).alias(t))
                vectors[ids[a]] = Vector(a.fn, t)
            else:
                cols += self.plain([a], ids, rel)
        return Rel(rel.df.groupBy(*key_cols).agg(*cols), attrs, origin, vectors=vectors)

    def argument(self, a: ir.Agg, rel: Rel) -> Column | None:
        if a.fn == "count" and (not a.args or isinstance(a.args[0], ir.Lit)):
            return None if a.where is None else F.when(self.col(a.where, rel), 1)
        e = self.col(a.args[0], rel)
        return e if a.where is None else F.when(self.col(a.where, rel), e)

    def plain(self, aggs: list[ir.Agg], ids: dict, rel: Rel) -> list[Column]:
        out = []
        for a in aggs:
            if a.fn.startswith("?"):
                raise Rejected("UNSUPPORTED_AGG", a.fn[1:])
            e = self.argument(a, rel)
            f = F.count(F.lit(1)) if e is None else F.count_distinct(e) if a.distinct and a.fn == "count" else getattr(F, a.fn)(e)
            out.append(f.alias(name(ids[a])))
        return out

    def worlds(self, rel: Rel, keys: list, key_cols: list, aggs: list[ir.Agg], ids: dict, attrs: list, origin: dict) -> Rel:
        """World aggregates of a sensitive relation by unprotected keys. Sums and counts that averages need are shared."""
        w, vectors = self.ctx.worlds, {}
        distinct = [a for a in aggs if a.distinct and a.fn in ("count", "sum", "avg")]
        df = rel.df.withColumns({name(i): c for (i, _), c in zip(keys, key_cols, strict=True)}) if keys else rel.df
        read: dict[str, str] = {}  # arguments become columns, each once
        new, wanted = {}, []
        for a in aggs:
            if a in distinct:
                continue
            e = self.argument(a, rel)
            if e is not None and str(e) not in read:
                read[str(e)] = f"__a{len(read)}"
                new[read[str(e)]] = e
            wanted.append((a, None if e is None else read[str(e)]))
        df = df.withColumns(new) if new else df
        types = dict(df.dtypes)
        for a, c in wanted:
            if c and a.fn in ("min", "max") and types[c] in ("string", "binary", "boolean"):
                raise Rejected("UNSUPPORTED_AGG", f"{a.fn} of {types[c]}")
            if c and types[c].startswith(("timestamp", "date")) and a.fn != "count":
                df = df.withColumn(c, F.unix_micros(F.col(c).cast("timestamp")) / 1e6 if types[c].startswith("timestamp") else F.unix_date(c).cast("double"))
                types = dict(df.dtypes)
        by = [name(i) for i, _ in keys]
        specs = V.specs_of(df, [(name(ids[a]), a.fn, c) for a, c in wanted]) if self.strategy == "kernel" and w == 64 else None
        out_df = None
        if wanted and specs is not None:
            out_df, touched, updates = V.aggregate(df, by, MASK, specs)
            out_df = self.guarded(rel, out_df, {touched[s.out]: updates[s.out] for s in specs})
            vectors = {ids[a]: Vector(a.fn, touched[name(ids[a])]) for a, _ in wanted}
        elif wanted:
            cols, shared = [], {}
            for a, c in wanted:
                if c not in shared:
                    shared[c] = f"__t{self.new()}"
                    cols += [A.touched(MASK, c, w).alias(shared[c]), F.count(F.lit(1) if c is None else F.col(c)).alias("__n" + shared[c])]
                cols.append(A.by_name(a.fn, MASK, c, w).alias(name(ids[a])))
                vectors[ids[a]] = Vector(a.fn, shared[c])
            out_df = self.guarded(rel, df.groupBy(*by).agg(*cols), {t: "__n" + t for t in shared.values()})
        doubled = {name(ids[a]): A.scaled(F.col(name(ids[a])), self.ctx) for a, _ in wanted if a.fn in ("sum", "count")}
        out_df = out_df.withColumns(doubled) if doubled else out_df
        for a in distinct:  # a value counts once in each world that has it
            if a.fn != "count":
                raise Rejected("UNSUPPORTED_AGG", f"{a.fn} of distinct values")
            each = df.groupBy(*by, self.col(a.args[0], rel).alias("__value")).agg(A.touched(MASK, None, w).alias(MASK), F.count(F.lit(1)).alias("__n")).where(F.col("__value").isNotNull())
            t = f"__t{self.new()}"
            part = each.groupBy(*by).agg(A.world_count(MASK, None, w).alias(name(ids[a])), A.touched(MASK, None, w).alias(t), F.sum("__n").alias("__n" + t))
            part = self.guarded(rel, part, {t: "__n" + t}).drop("__n" + t)
            vectors[ids[a]] = Vector("count_distinct", t)
            if out_df is None:
                out_df = part
            elif not by:
                out_df = out_df.crossJoin(part)
            else:
                p = part.select(*[F.col(b).alias(f"__{b}") for b in by], name(ids[a]), t)
                out_df = out_df.join(p, _all([F.col(b).eqNullSafe(F.col(f"__{b}")) for b in by]), "left").drop(*[f"__{b}" for b in by])
        return Rel(out_df, attrs, origin, vectors=vectors)

    def guarded(self, rel: Rel, df: DataFrame, columns: dict[str, str]) -> DataFrame:
        """A runtime error where an aggregate (touched column: its number of rows) was fed by one unit alone.

        Masks that a condition has narrowed say nothing about the number of units: there the inner aggregates, which were
        made before, have been looked at.
        """
        if not self.diversity or self.mode != "release" or self.ctx.balance == "none" or rel.narrowed:
            return df
        alone = F.lit(False)
        for t, n in columns.items():
            alone = alone | single_unit(t, n, self.ctx.worlds, MIN_UPDATES)
        return df.where(F.when(alone, F.raise_error(F.lit(FED_ALONE)).cast("boolean")).otherwise(True))

    # ---- the rest

    def on_sort(self, n: ir.Sort) -> Rel:
        rel = self.node(n.children[0])
        if self.mode == "vectors" and (rel.vectors or rel.coins):
            return rel
        rel = self.released(rel)
        if any(ir.attrs_of(e) & rel.noised for e, _, _ in n.orders):
            self.note(self.warnings, ORDERED)
        orders = []
        for e, down, first in n.orders:
            c = self.col(e, rel)
            orders.append((c.desc_nulls_first() if first else c.desc_nulls_last()) if down else (c.asc_nulls_first() if first else c.asc_nulls_last()))
        return replace(rel, df=rel.df.orderBy(*orders))

    def on_limit(self, n: ir.Limit) -> Rel:
        rel = self.node(n.children[0])
        if self.mode == "vectors" and (rel.vectors or rel.coins):
            return rel
        if rel.sensitive:
            self.finish(rel)
        rel = self.released(rel)
        if rel.noised and ORDERED in self.warnings:
            self.note(self.warnings, SKIPPED if n.offset else LIMITED)
        return replace(rel, df=rel.df.offset(n.n) if n.offset else rel.df.limit(n.n))

    def on_distinct(self, n: ir.Distinct) -> Rel:
        rel = self.released(self.node(n.children[0]))
        if rel.noised:
            self.note(self.outside, NESTED)
        if rel.sensitive:
            if set(a.id for a in rel.attrs) & rel.protected and not self.class_of(rel, {a.id for a in rel.attrs}):
                raise Rejected("PROTECTED_OUTPUT")
            rel = self.need_mask(rel)
            if not self.class_of(rel, {a.id for a in rel.attrs}):
                raise Rejected("NO_AGGREGATE", "distinct values of units")
            return replace(rel, df=rel.df.select(*[name(a.id) for a in rel.attrs], MASK).distinct(), origin={a.id: rel.origin[a.id] for a in rel.attrs if a.id in rel.origin})
        return replace(rel, df=rel.df.select(*[name(a.id) for a in rel.attrs]).distinct())

    def on_union(self, n: ir.Union) -> Rel:
        parts = [self.node(c) for c in n.children]
        if len({p.sensitive for p in parts}) > 1:
            raise Rejected("BAD_JOIN", "a union of unit rows with others")
        if any(p.vectors for p in parts):
            parts = [self.released(p) for p in parts]
        if parts[0].sensitive:
            parts = [self.need_mask(p) for p in parts]
        frames, protected = [], set()
        for p in parts:
            frames.append(p.df.select(*[F.col(name(a.id)).alias(name(o.id)) for a, o in zip(p.attrs, n.out, strict=True)], *([MASK] if p.masked else [])))
            protected |= {o.id for a, o in zip(p.attrs, n.out, strict=True) if a.id in p.protected}
        df = frames[0]
        for f in frames[1:]:
            df = df.unionByName(f)
        return Rel(df, n.out, {}, protected, parts[0].sensitive, parts[0].masked, any(p.narrowed for p in parts))

    def released(self, rel: Rel) -> Rel:
        """Vectors become noised values, coins are tossed. What stands above is post-processing.

        Cells and tosses are counted here, below whatever limits, filters or sums up the released rows.
        """
        if not rel.vectors and not rel.coins:
            return rel
        group = [name(a.id) for a in rel.attrs if a.id not in rel.vectors]
        df, tosses = rel.df, 0
        eager = self.mode == "release" and (self.charge is not None or self.ctx.adaptive)
        if rel.coins:
            if self.charge:
                df = self.hold(df)
                tosses = df.count()
            for i, c in enumerate(rel.coins):
                df = df.where(L.coin_filter(c, self.ctx, *group, tag=f"coin{self.nodes}.{i}"))
        self.nodes += 1
        tags, touched = {}, {}
        for a in rel.attrs:
            if a.id in rel.vectors:
                tags[name(a.id)] = f"{self.releases}:{a.name}"
                self.releases += 1
                if self.null_draw and rel.vectors[a.id].touched:
                    touched[name(a.id)] = rel.vectors[a.id].touched
        if tags and self.ctx.adaptive and self.mode == "release":
            df = self.hold(release_sequential(df, group, list(tags), self.ctx, tags, touched, self.posterior, carry=True))
            last = df.where("__posterior IS NOT NULL").orderBy(F.desc("__place")).select("__posterior").first()
            self.posterior = list(last[0]) if last else self.posterior
            df = df.select(*[name(a.id) for a in rel.attrs])
        else:
            df = df.select(*[release(c, self.ctx, tags[c], *group, touched=touched.get(c)).alias(c) if (c := name(a.id)) in tags else F.col(c) for a in rel.attrs])
            df = self.hold(df) if eager else df
        if self.charge:
            self.charge(df.count() * len(tags) if tags else 0, tosses)
        return replace(rel, df=df, vectors={}, coins=[], noised=rel.noised | set(rel.vectors), roots=None)

    def hold(self, df: DataFrame) -> DataFrame:
        df = df.persist()
        self.held.append(df)
        return df

    def finish(self, rel: Rel) -> DataFrame:
        if rel.sensitive:
            raise Rejected("PROTECTED_OUTPUT" if {a.id for a in rel.attrs} & rel.protected else "NO_AGGREGATE")
        if {a.id for a in rel.attrs} & rel.protected:
            raise Rejected("PROTECTED_OUTPUT")
        if self.mode == "vectors" and (rel.vectors or rel.coins):
            keep = [L.fraction_true(c).alias("keep_chance") for c in rel.coins]
            return rel.df.select(*[F.col(name(a.id)).alias(a.name) for a in rel.attrs], *keep)
        rel = self.released(rel)
        return rel.df.select(*[F.col(name(a.id)).alias(a.name) for a in rel.attrs])


def _apart(e):
    """sum(x + constant) is sum(x) + constant * count(x) in every world: many such sums share two vectors."""
    if isinstance(e, ir.Agg) and e.fn == "sum" and not e.distinct and isinstance(e.args[0], ir.Call) and e.args[0].op == "Add" and isinstance(e.args[0].args[1], ir.Lit) and isinstance(e.args[0].args[0], ir.Attr):
        x, c = e.args[0].args[0], e.args[0].args[1]
        return ir.Call("Add", (ir.Agg("sum", (x,), False, e.where), ir.Call("Multiply", (c, ir.Agg("count", (x,), False, e.where)))))
    if isinstance(e, ir.Agg) and e.fn == "avg" and not e.distinct:
        x = e.args[0]
        return ir.Call("Divide", (ir.Call("Cast", (ir.Agg("sum", (x,), False, e.where),), ("double",)), ir.Call("Cast", (ir.Agg("count", (x,), False, e.where),), ("double",))))
    return None


def _all(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out & p
    return out


def _hashable(e) -> bool:
    try:
        hash(e)
    except TypeError:
        return False
    return True
