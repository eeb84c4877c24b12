"""Studies that once made their data up read given tables."""

import pytest

from worldfold.workloads import distributions, registry


def reads(spark, name, sf, table):
    """Runs a query and tells how many of its executed plans scan the table."""
    seen = []
    real = spark.read.parquet
    reader = type(spark.read)
    with pytest.MonkeyPatch.context() as m:
        m.setattr(reader, "parquet", lambda self, *p, **o: (seen.append(p[0]), real(*p, **o))[1])
        rows = registry.QUERIES[name](spark, sf).collect()
    assert any(p.endswith(f"/{table}.parquet") for p in seen), seen
    return rows


@pytest.mark.parametrize("name,rows", [("ablation_count", 14), ("ablation_max", 6), ("ablation_sum", 20), ("type_costs", 7)])
def test_costs_are_of_events(spark, sf, name, rows):
    assert len(reads(spark, name, sf, "events")) == rows


def test_given_rows_are_all_events(spark, sf):
    e = spark.read.parquet(f"{sf}/events.parquet")
    for order in ("uniform", "increasing"):
        df = distributions.given(spark, sf, 10, order)
        assert df.count() == e.count() == df.where("pk is not null and v is not null").count() and df.select("g").distinct().count() == 10
    v = [r["v"] for r in distributions.given(spark, sf, 0, "increasing").collect()]
    assert v == sorted(v)


@pytest.mark.parametrize("name", ["attack_bounds", "success_budgets"])
def test_bounds_are_of_customers_priors(spark, sf, name):
    from worldfold.context import attack_bound, budget_for

    rows = reads(spark, name, sf, "customer")
    units = {r["prior"]: r["units"] for r in rows}
    assert name == "success_budgets" or sum(units.values()) == spark.read.parquet(f"{sf}/customer.parquet").count()
    for r in rows:
        if name == "attack_bounds":
            assert r["success"] == pytest.approx(attack_bound(1 / r["one_over_mi"], r["prior"]), abs=6e-5)
        else:
            assert r["mi"] == pytest.approx(budget_for(r["success"], r["prior"]), abs=1e-9)


def test_approximate_sums_are_of_events(spark, sf):
    rows = {r["distribution"]: r for r in reads(spark, "approx_sum_study", sf, "events")}
    assert set(rows) == set(distributions.NAMES)
    for k, r in rows.items():
        if k == "negative_mixed":
            assert r["single_percent"] > r["two_percent"]
        else:
            assert r["two_percent"] < 100 * (2**-8 + 8 * 2**-12)
    df = distributions.shaped(spark, sf)
    n = spark.read.parquet(f"{sf}/events.parquet").count()
    assert {r["distribution"]: r["count"] for r in df.where("v is not null and mask is not null").groupBy("distribution").count().collect()} == dict.fromkeys(distributions.NAMES, n)


def test_ways_to_the_unit_are_followed_by_rows(spark, sf):
    got = {r["name"]: (r["hops"], r["n"], r["owned"]) for r in reads(spark, "unit_paths", sf, "lineitem")}
    n = {t: spark.read.parquet(f"{sf}/{t}.parquet").count() for t in got}
    assert got == {"customer": (0, n["customer"], n["customer"]), "orders": (1, n["orders"], n["orders"]), "lineitem": (2, n["lineitem"], n["lineitem"]), "part": (None, n["part"], 0)}


def test_rows_without_a_unit_are_not_owned(spark):
    from worldfold.sources.catalog import UnitCatalog

    for t, rows in {"u": [(1,), (2,), (None,)], "a": [(10, 1), (11, 1), (12, None), (13, 9)], "b": [(10,), (10,), (13,), (14,), (None,)]}.items():
        spark.createDataFrame(rows, {"u": "id int", "a": "k int, u int", "b": "a int"}[t]).createOrReplaceTempView(f"owned_{t}")
    c = UnitCatalog().execute("DECLARE UNIT owned_u KEY (id); DECLARE LINK owned_a (u) TO owned_u (id); DECLARE LINK owned_b (a) TO owned_a (k)")
    assert [c.owned(spark, f"owned_{t}").count() for t in "uab"] == [2, 2, 2]
    assert c.owned(spark, "other") is None


def test_a_run_that_is_refused_is_a_verdict(spark):
    from worldfold.plans.session import PrivateSession
    from worldfold.sources.catalog import UnitCatalog

    spark.range(300).selectExpr("id % 50 AS u", "CASE WHEN id % 50 = 7 THEN 'own' ELSE 'shared' END AS g", "id AS v").createOrReplaceTempView("tried_few")
    spark.sql("SELECT * FROM tried_few UNION ALL SELECT 7, 'own', id FROM range(100)").createOrReplaceTempView("tried")
    s = PrivateSession(spark, UnitCatalog().declare_unit("tried", "u", ["u"]))
    sql = "SELECT g, sum(v) AS s FROM tried GROUP BY g"
    few = PrivateSession(spark, UnitCatalog().declare_unit("tried_few", "u", ["u"]))
    assert s.classify(sql).kind == few.classify(sql.replace("tried", "tried_few")).kind == few.tried(sql.replace("tried", "tried_few")).kind == "rewrite"
    assert (s.tried(sql).kind, s.tried(sql).reason) == ("reject", "SINGLE_UNIT")
    got = s.all_tried([sql, "SELECT u FROM tried", "SELECT sum(v) AS s FROM tried", sql])
    assert [v.kind for v in got] == ["reject", "reject", "rewrite", "reject"] and s.ledger.spent == 0
    with pytest.raises(Exception, match="DIVIDE_BY_ZERO"):
        PrivateSession(spark, UnitCatalog()).tried("SELECT 1 / (v - v) AS x FROM tried")


@pytest.mark.parametrize("name", ["hits_verdicts", "tpch_verdicts"])
def test_verdicts_come_of_runs(spark, sf, name, monkeypatch):
    from worldfold.plans.session import PrivateSession

    seen, real = [], PrivateSession.rewrite
    monkeypatch.setattr(PrivateSession, "rewrite", lambda self, sql, *a: (seen.append(sql), real(self, sql, *a))[1])
    rows = registry.QUERIES[name](spark, sf).collect()
    assert len(seen) == len(set(seen)) == sum(r["verdict"] != "reject" for r in rows) > 15


def test_generated_queries_are_run(spark, sf, monkeypatch):
    from worldfold.plans.session import PrivateSession
    from worldfold.workloads import storm

    seen, real = [], PrivateSession.rewrite
    monkeypatch.setattr(PrivateSession, "rewrite", lambda self, sql, *a: (seen.append(sql), real(self, sql, *a))[1])
    rows = registry.QUERIES["storm_coverage"](spark, sf).collect()
    assert sum(r["queries"] for r in rows) == 120
    assert sorted(seen) == sorted({q for k, q in storm.generate(120) if k in ("rewrite", "pass")})
