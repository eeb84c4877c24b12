"""From SQL or a DataFrame to the IR, by way of Spark's analyzed plan.

Every attribute of an analyzed plan has an id, so names never have to be resolved here. What has no place in the IR
becomes ``Unsupported`` and is refused later if it touches unit data: the door is closed unless it is known to be safe.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession

from worldfold.plans import ir

AGGREGATES = {"Sum": "sum", "Count": "count", "Average": "avg", "Min": "min", "Max": "max", "StddevSamp": "stddev_samp", "StddevPop": "stddev_pop", "VarianceSamp": "var_samp", "VariancePop": "var_pop"}
JOINS = {"Inner": "inner", "Cross": "inner", "LeftOuter": "left", "RightOuter": "right", "FullOuter": "full", "LeftSemi": "semi", "LeftAnti": "anti"}


def _short(name: str) -> str:
    return name.split(".")[-1].rstrip("$")


def _tree(flat: list[dict]) -> dict:
    """Flat pre-order lists of the plan's JSON as trees with ``kids``."""
    at = 0

    def take() -> dict:
        nonlocal at
        n = dict(flat[at])
        at += 1
        n["kids"] = [take() for _ in range(n["num-children"])]
        return n

    return take()


class Reader:
    def __init__(self):
        self.ctes: dict[int, ir.Node] = {}
        self.common: dict[str, object] = {}
        self.fresh = -1

    def new_id(self) -> int:
        self.fresh -= 1
        return self.fresh

    # ---- expressions

    def expr(self, flat: list[dict]):
        return self._expr(_tree(flat))

    def _id(self, e: dict) -> int:
        return e["exprId"]["id"]

    def _expr(self, e: dict):
        c = _short(e["class"])
        kids = e["kids"]
        if c == "AttributeReference":
            return ir.Attr(self._id(e), e["name"], e["dataType"] if isinstance(e["dataType"], str) else "complex")
        if c == "OuterReference":
            return self._expr(_tree(e["e"])) if not kids else self._expr(kids[0])
        if c == "Literal":
            return ir.Lit(e["value"], e["dataType"] if isinstance(e["dataType"], str) else "complex")
        if c == "Alias":
            return ir.Item(self._id(e), e["name"], self._expr(kids[0]))
        if c == "AggregateExpression":
            f, fn = kids[0], _short(kids[0]["class"])
            where = self._expr(kids[1]) if len(kids) > 1 else None
            if fn not in AGGREGATES:
                return ir.Agg(f"?{fn}", tuple(self._expr(k) for k in f["kids"]), bool(e["isDistinct"]), where)
            return ir.Agg(AGGREGATES[fn], tuple(self._expr(k) for k in f["kids"]), bool(e["isDistinct"]), where)
        if c in ("ScalarSubquery", "Exists", "ListQuery"):
            plan = self.node(_tree(e["plan"]))
            outer = frozenset(i for k in kids for i in ir.attrs_of(self._expr(k)))
            return ir.Sub({"ScalarSubquery": "scalar", "Exists": "exists", "ListQuery": "in"}[c], plan, outer)
        if c == "InSubquery":
            parts = [self._expr(k) for k in kids]
            sub = parts[-1]
            return ir.Sub("in", sub.plan, sub.outer, tuple(parts[:-1]))
        if c in ("Cast", "AnsiCast"):
            return ir.Call("Cast", (self._expr(kids[0]),), (e["dataType"] if isinstance(e["dataType"], str) else "complex",))
        if c == "With":  # a value that is used more than once, such as the middle of BETWEEN
            for d in kids[1:]:
                self.common[str(d["id"])] = self._expr(d["kids"][0])
            return self._expr(kids[0])
        if c == "CommonExpressionRef":
            return self.common[str(e["id"])]
        if c in ("WindowExpression",):
            return ir.Call("?Window", tuple(self._expr(k) for k in kids))
        if c in ("Murmur3Hash", "Rand", "Randn", "PythonUDF", "ScalaUDF"):
            return ir.Call(f"?{c}", tuple(self._expr(k) for k in kids))
        extra = ("branches",) if c == "CaseWhen" else (e.get("pattern"),) if "pattern" in e else ()
        if c == "Extract" or "replacement" in e and len(kids) == 1:
            return self._expr(kids[0])
        return ir.Call(c, tuple(self._expr(k) for k in kids), extra)

    def items(self, flats: list[list[dict]]) -> list[ir.Item]:
        out = []
        for f in flats:
            e = self.expr(f)
            out.append(e if isinstance(e, ir.Item) else ir.Item(e.id, e.name, e) if isinstance(e, ir.Attr) else ir.Item(self.new_id(), "expr", e))
        return out

    # ---- plans

    def node(self, n: dict) -> ir.Node:
        c = _short(n["class"])
        kids = n["kids"]
        if c == "WithCTE":
            for d in kids[:-1]:
                if any(_short(x["class"]) in ("UnionLoop", "UnionLoopRef") for x in self._all(d)):
                    self.ctes[self._cte(d)] = ir.Unsupported([], "RECURSION")
                else:
                    self.ctes[self._cte(d)] = self.node(d["kids"][0])
            return self.node(kids[-1])
        if c == "CTERelationRef":
            plan = self.ctes[n["cteId"]]
            if isinstance(plan, ir.Unsupported):
                return plan
            new = [self.expr(f) for f in n["output"]]
            return ir.Project([plan], [ir.Item(a.id, a.name, o) for a, o in zip(new, ir.output(plan), strict=True)])
        if c == "SubqueryAlias":
            inner = kids[0]
            if _short(inner["class"]) in ("LogicalRelation", "LocalRelation", "LogicalRDD"):
                return ir.Scan([], n["identifier"]["name"], [self.expr(f) for f in inner["output"]])
            return self.node(inner)
        if c == "View":
            return ir.Scan([], n["desc"]["identifier"]["table"], self._out(kids[0]))
        if c == "Project":
            items = self.items(n["projectList"])
            return ir.Project([self.node(kids[0])], items)
        if c == "Filter":
            return ir.Filter([self.node(kids[0])], self.expr(n["condition"]))
        if c == "Join":
            kind = n["joinType"]
            kind = _short(kind["object"] if "object" in kind else kind.get("product-class", "?"))
            if kind not in JOINS:
                return ir.Unsupported([self.node(k) for k in kids], f"JOIN {kind}")
            return ir.Join([self.node(k) for k in kids], JOINS[kind], self.expr(n["condition"]) if n.get("condition") else None)
        if c == "Aggregate":
            return ir.Aggregate([self.node(kids[0])], [self.expr(f) for f in n["groupingExpressions"]], self.items(n["aggregateExpressions"]))
        if c == "Sort":
            orders = []
            for f in n["order"]:
                t = _tree(f)
                orders.append((self._expr(t["kids"][0]), "Descending" in str(t["direction"]), "NullsFirst" in str(t["nullOrdering"])))
            return ir.Sort([self.node(kids[0])], orders)
        if c in ("GlobalLimit", "Offset"):
            e = self.expr(n["limitExpr" if c == "GlobalLimit" else "offsetExpr"])
            return ir.Limit([self.node(kids[0])], int(e.value), c == "Offset")
        if c == "LocalLimit":
            return self.node(kids[0])
        if c == "Distinct":
            return ir.Distinct([self.node(kids[0])])
        if c == "Union":
            parts = [self.node(k) for k in kids]
            return ir.Union(parts, ir.output(parts[0]))
        if c in ("LogicalRelation", "LocalRelation", "LogicalRDD", "OneRowRelation", "Range"):
            return ir.Unsupported([], f"UNNAMED {c}")
        what = {"Window": "WINDOW", "UnionLoop": "RECURSION", "UnionLoopRef": "RECURSION"}.get(c, c.upper())
        return ir.Unsupported([self.node(k) for k in kids], what)

    def _cte(self, d: dict) -> int:
        return d["id"]

    def _all(self, n: dict):
        yield n
        for k in n["kids"]:
            yield from self._all(k)

    def _out(self, n: dict) -> list[ir.Attr]:
        """Output of a view's plan, whose inside is of no interest."""
        c = _short(n["class"])
        if "output" in n and n["output"] and isinstance(n["output"], list):
            return [self.expr(f) for f in n["output"]]
        if c == "Project":
            return [ir.Attr(i.id, i.name) for i in self.items(n["projectList"])]
        if c == "Aggregate":
            return [ir.Attr(i.id, i.name) for i in self.items(n["aggregateExpressions"])]
        return self._out(n["kids"][0])


def to_ir(df: DataFrame) -> ir.Node:
    return Reader().node(_tree(json.loads(df._jdf.queryExecution().analyzed().toJSON())))


def parse(spark: SparkSession, sql: str) -> tuple[ir.Node, DataFrame]:
    df = spark.sql(sql)
    return to_ir(df), df
