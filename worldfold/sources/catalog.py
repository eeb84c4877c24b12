"""Which table is the privacy unit, how others belong to it, and what must not come out."""

from __future__ import annotations

import json
import re
from dataclasses import asdict, dataclass, field
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class UnitLink:
    """Columns of ``table`` that name a row of ``ref``; metadata only, not enforced."""

    table: str
    cols: tuple[str, ...]
    ref: str
    ref_cols: tuple[str, ...]


@dataclass
class UnitCatalog:
    """The unit table with its key, protected columns, and links. Checked on declaration, kept apart from schemas."""

    unit: str | None = None
    key: tuple[str, ...] = ()
    protected_: tuple[str, ...] | None = None
    links: list[UnitLink] = field(default_factory=list)
    schemas: dict[str, dict[str, str]] = field(default_factory=dict)

    # ---- declarations

    def learn(self, spark: SparkSession, *tables: str) -> UnitCatalog:
        """Column names and types of tables, against which declarations are checked."""
        for t in tables:
            self.schemas[t] = dict(spark.table(t).dtypes)
        return self

    def _columns(self, table: str, cols: tuple[str, ...]) -> None:
        if table in self.schemas:
            for c in cols:
                if c not in self.schemas[table]:
                    raise ValueError(f"{table} has no column {c}")

    def declare_unit(self, table: str, key, protected=None) -> UnitCatalog:
        if self.unit not in (None, table):
            raise ValueError("only one table can be the privacy unit")
        key = (key,) if isinstance(key, str) else tuple(key)
        self._columns(table, key + tuple(protected or ()))
        self.unit, self.key = table, key
        self.protected_ = None if protected is None else tuple(protected)
        return self

    alter_unit = declare_unit

    def drop_unit(self) -> UnitCatalog:
        self.unit, self.key, self.protected_ = None, (), None
        return self

    def declare_link(self, table: str, cols, ref: str, ref_cols) -> UnitCatalog:
        one = lambda c: (c,) if isinstance(c, str) else tuple(c)
        link = UnitLink(table, one(cols), ref, one(ref_cols))
        if len(link.cols) != len(link.ref_cols) or not link.cols:
            raise ValueError("a link names as many columns on both sides")
        self._columns(table, link.cols)
        self._columns(ref, link.ref_cols)
        for a, b in zip(link.cols, link.ref_cols, strict=True):
            x, y = self.schemas.get(table, {}).get(a), self.schemas.get(ref, {}).get(b)
            if x and y and x != y:
                raise ValueError(f"{table}.{a} is {x}, {ref}.{b} is {y}")
        if table == ref or self._reaches(ref, table):
            raise ValueError("links must not form a cycle")
        self.links.append(link)
        return self

    def drop_link(self, table: str, ref: str) -> UnitCatalog:
        self.links = [x for x in self.links if (x.table, x.ref) != (table, ref)]
        return self

    def _reaches(self, a: str, b: str) -> bool:
        return a == b or any(self._reaches(x.ref, b) for x in self.links if x.table == a)

    def execute(self, text: str) -> UnitCatalog:
        """Small statements: ``DECLARE UNIT t KEY (a) [PROTECT (b, c)]``, ``DECLARE LINK t (a) TO u (b)``, ``DROP UNIT``, ``DROP LINK t TO u``."""
        names = lambda s: tuple(x.strip() for x in s.split(","))
        for s in filter(None, (x.strip() for x in text.split(";"))):
            if m := re.fullmatch(r"(?:DECLARE|ALTER)\s+UNIT\s+(\w+)\s+KEY\s*\(([^)]*)\)(?:\s+PROTECT\s*\(([^)]*)\))?", s, re.I):
                self.declare_unit(m[1], names(m[2]), names(m[3]) if m[3] else None)
            elif m := re.fullmatch(r"DECLARE\s+LINK\s+(\w+)\s*\(([^)]*)\)\s+TO\s+(\w+)\s*\(([^)]*)\)", s, re.I):
                self.declare_link(m[1], names(m[2]), m[3], names(m[4]))
            elif re.fullmatch(r"DROP\s+UNIT", s, re.I):
                self.drop_unit()
            elif m := re.fullmatch(r"DROP\s+LINK\s+(\w+)\s+TO\s+(\w+)", s, re.I):
                self.drop_link(m[1], m[2])
            else:
                raise ValueError(f"not understood: {s}")
        return self

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> UnitCatalog:
        d = json.loads(text)
        c = UnitCatalog(d["unit"], tuple(d["key"]), None if d["protected_"] is None else tuple(d["protected_"]), schemas=d["schemas"])
        c.links = [UnitLink(x["table"], tuple(x["cols"]), x["ref"], tuple(x["ref_cols"])) for x in d["links"]]
        return c

    # ---- questions

    def path(self, table: str) -> list[UnitLink] | None:
        """The shortest chain of links from a table to the unit; none for other tables. Two equally short ones are refused."""
        if table == self.unit:
            return []
        found = [[x, *rest] for x in self.links if x.table == table and (rest := self.path(x.ref)) is not None]
        if not found:
            return None
        found.sort(key=len)
        if len(found) > 1 and len(found[0]) == len(found[1]):
            raise ValueError(f"{table} has two equally short paths to the unit")
        return found[0]

    def owned(self, spark: SparkSession, table: str) -> DataFrame | None:
        """The rows of a table that belong to a unit: those whose links, followed one by one, end at a row of it."""
        path = self.path(table)
        if path is None:
            return None
        rows = spark.table(table)
        if not path:
            return rows.dropna(subset=list(self.key))
        ref = self.owned(spark, path[0].ref).select(*[F.col(c).alias(f"__{i}") for i, c in enumerate(path[0].ref_cols)])
        return rows.join(ref, reduce(and_, [F.col(c) == F.col(f"__{i}") for i, c in enumerate(path[0].cols)]), "left_semi")

    def sensitive(self, table: str) -> bool:
        return self.unit is not None and self.path(table) is not None

    def protected(self, table: str, column: str) -> bool:
        """Unit columns by declaration (all of them without one); link columns and unit keys always."""
        if not self.sensitive(table):
            return False
        if any(column in x.cols for x in self.links if x.table == table) or any(column in x.ref_cols for x in self.links if x.ref == table):
            return True
        if table != self.unit:
            return False
        return column in self.key or self.protected_ is None or column in self.protected_

    def key_classes(self) -> list[set[tuple[str, tuple[str, ...]]]]:
        """Column lists that name the same thing: equal values mean rows of the same unit."""
        classes: list[set] = [{(self.unit, self.key)}] if self.unit else []
        for x in self.links:
            a, b = (x.table, x.cols), (x.ref, x.ref_cols)
            hit = [c for c in classes if a in c or b in c]
            merged = set().union({a, b}, *hit)
            classes = [c for c in classes if c not in hit] + [merged]
        return classes
