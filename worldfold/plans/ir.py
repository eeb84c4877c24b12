"""A small closed set of plan nodes and expressions, read from Spark's analyzed plan."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Attr:
    id: int
    name: str
    type: str = ""


@dataclass(frozen=True)
class Lit:
    value: str | None
    type: str


@dataclass(frozen=True)
class Call:
    op: str
    args: tuple
    extra: tuple = ()


@dataclass(frozen=True)
class Agg:
    fn: str
    args: tuple
    distinct: bool = False
    where: object = None


@dataclass(frozen=True)
class Sub:
    """A subquery in an expression: ``scalar``, ``exists`` or ``in`` (with the values that are looked up)."""

    kind: str
    plan: object
    outer: frozenset = frozenset()
    values: tuple = ()


@dataclass(frozen=True)
class Item:
    id: int
    name: str
    expr: object


@dataclass
class Node:
    children: list = field(default_factory=list)


@dataclass
class Scan(Node):
    table: str = ""
    attrs: list[Attr] = field(default_factory=list)


@dataclass
class Project(Node):
    items: list[Item] = field(default_factory=list)


@dataclass
class Filter(Node):
    condition: object = None


@dataclass
class Join(Node):
    kind: str = "inner"
    condition: object = None


@dataclass
class Aggregate(Node):
    keys: list = field(default_factory=list)
    items: list[Item] = field(default_factory=list)


@dataclass
class Sort(Node):
    orders: list = field(default_factory=list)  # (expression, descending, nulls first)


@dataclass
class Limit(Node):
    n: int = 0
    offset: bool = False


@dataclass
class Distinct(Node):
    pass


@dataclass
class Union(Node):
    out: list[Attr] = field(default_factory=list)


@dataclass
class Matching(Node):
    """Rows of the child whose attributes are among given values: (attribute, DataFrame, its column) triples."""

    among: list = field(default_factory=list)


@dataclass
class Unsupported(Node):
    what: str = ""


def attrs_of(e) -> set[int]:
    """Attributes an expression reads; of a subquery only those it takes from outside."""
    if isinstance(e, Attr):
        return {e.id}
    if isinstance(e, Call):
        return set().union(*map(attrs_of, e.args), set())
    if isinstance(e, Agg):
        return set().union(*map(attrs_of, e.args), attrs_of(e.where) if e.where is not None else set(), set())
    if isinstance(e, Sub):
        return set(e.outer) | set().union(*map(attrs_of, e.values), set())
    if isinstance(e, Item):
        return attrs_of(e.expr)
    return set()


def subqueries(e) -> list[Sub]:
    if isinstance(e, Sub):
        return [e]
    if isinstance(e, Item):
        return subqueries(e.expr)
    if isinstance(e, (Call, Agg)):
        return [s for a in e.args for s in subqueries(a)]
    return []


def aggregates(e) -> list[Agg]:
    if isinstance(e, Agg):
        return [e]
    if isinstance(e, Item):
        return aggregates(e.expr)
    return [x for a in e.args for x in aggregates(a)] if isinstance(e, Call) else []


def replace(e, change):
    """The expression with ``change`` (None: leave) tried on every part, outermost first."""
    new = change(e)
    if new is not None:
        return new
    if isinstance(e, Call):
        return Call(e.op, tuple(replace(a, change) for a in e.args), e.extra)
    if isinstance(e, Agg):
        return Agg(e.fn, tuple(replace(a, change) for a in e.args), e.distinct, None if e.where is None else replace(e.where, change))
    if isinstance(e, Item):
        return Item(e.id, e.name, replace(e.expr, change))
    return e


def conjuncts(e) -> list:
    if e is None:
        return []
    return [x for a in e.args for x in conjuncts(a)] if isinstance(e, Call) and e.op == "And" else [e]


def conjunction(parts: list):
    out = None
    for p in parts:
        out = p if out is None else Call("And", (out, p))
    return out


def output(n: Node) -> list[Attr]:
    if isinstance(n, Scan):
        return n.attrs
    if isinstance(n, (Project, Aggregate)):
        return [Attr(i.id, i.name) for i in n.items]
    if isinstance(n, Join):
        left = output(n.children[0])
        return left if n.kind in ("semi", "anti") else left + output(n.children[1])
    if isinstance(n, Union):
        return n.out
    return output(n.children[0]) if n.children else []


def walk(n: Node):
    yield n
    for c in n.children:
        yield from walk(c)
    exprs = getattr(n, "items", None) or []
    exprs = [*exprs, *(x for x in (getattr(n, "condition", None),) if x is not None), *(getattr(n, "keys", None) or [])]
    for e in exprs:
        for s in subqueries(e):
            yield from walk(s.plan)
