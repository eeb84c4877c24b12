import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from worldfold.functions import aggregates as A
from worldfold.operators import kernels as K
from worldfold.operators import vectorized as V
from worldfold.operators.strategies import Shape, choose_strategy, world_aggregate
from worldfold.workloads.distributions import NAMES, approx_study, draw, masks_of


def _rows(n=500, groups=5, seed=0, nulls=True):
    r = random.Random(seed)
    m = masks_of(60, seed)
    return [(f"g{r.randrange(groups)}", int(m[r.randrange(60)]), None if nulls and r.random() < 0.1 else r.randint(-1000, 1000)) for _ in range(n)]


def _brute(rows, fn):
    out = {}
    for g in {r[0] for r in rows}:
        for j in range(64):
            v = [x for k, m, x in rows if k == g and m >> j & 1 and (x is not None or fn == "rows")]
            f = {"rows": len, "count": len, "sum": lambda v: sum(v) if v else None, "min": lambda v: min(v, default=None), "max": lambda v: max(v, default=None), "avg": lambda v: sum(v) / len(v) if v else None}[fn]
            out[g, j] = f(v)
    return out


@pytest.fixture(scope="module")
def data(spark):
    rows = _rows()
    return rows, spark.createDataFrame(rows, "g string, mask long, v long").repartition(3).cache()


def _got(df):
    return {(r["g"], j): x for r in df.collect() for j, x in enumerate(r["v"])}


@pytest.mark.parametrize("strategy", ["wide", "late", "preagg", "arrow", "branch", "levels", "auto"])
def test_sums_equal_brute_force(data, strategy):
    rows, df = data
    got = _got(world_aggregate(df, ["g"], "mask", "sum", "v", strategy))
    for k, want in _brute(rows, "sum").items():
        assert (got[k] or 0) == (want or 0), k


@pytest.mark.parametrize("strategy", ["wide", "lanes8", "lanes16", "lanes32", "preagg", "late", "arrow", "branch"])
def test_counts_equal_brute_force(data, strategy):
    rows, df = data
    assert {k: int(x) for k, x in _got(world_aggregate(df, ["g"], "mask", "count", None, strategy)).items()} == _brute(rows, "rows")


@pytest.mark.parametrize("fn", ["min", "max", "avg"])
@pytest.mark.parametrize("strategy", ["wide", "preagg"])
def test_others_equal_brute_force(data, fn, strategy):
    rows, df = data
    got = _got(world_aggregate(df, ["g"], "mask", fn, "v", strategy))
    for k, want in _brute(rows, fn).items():
        assert got[k] == pytest.approx(want)


def test_kernel_engine_equals_brute_force(data):
    rows, df = data
    specs = V.specs_of(df, [("s", "sum", "v"), ("n", "count", "v"), ("r", "count", None), ("lo", "min", "v"), ("hi", "max", "v")])
    out, touched, _ = V.aggregate(df, ["g"], "mask", specs)
    got = {r["g"]: r for r in out.collect()}
    for name, fn in (("s", "sum"), ("n", "count"), ("r", "rows"), ("lo", "min"), ("hi", "max")):
        for (g, j), want in _brute(rows, fn).items():
            assert got[g][name][j] == want, (name, g, j)
    assert set(touched) == {"s", "n", "r", "lo", "hi"}


def test_kernel_engine_with_many_groups_nulls_and_no_rows(spark):
    rows = [(i % 300, (i % 7) or None, int(m), None if i % 5 == 0 else i * 1.5) for i, m in enumerate(masks_of(2000))]
    df = spark.createDataFrame(rows, "a long, b long, mask long, v double")
    specs = V.specs_of(df, [("s", "sum", "v"), ("n", "count", "v")])
    kernel, _, _ = V.aggregate(df, ["a", "b"], "mask", specs)
    wide = df.groupBy("a", "b").agg(A.world_sum("mask", "v").alias("s"), A.world_count("mask", "v").alias("n"))
    key = lambda r: (r["a"], r["b"] is None, r["b"])
    for x, y in zip(sorted(kernel.collect(), key=key), sorted(wide.collect(), key=key), strict=True):
        assert (x["a"], x["b"], x["n"]) == (y["a"], y["b"], y["n"])
        assert x["s"] == pytest.approx(y["s"]) if None not in x["s"] else [p is None for p in x["s"]] == [p is None for p in y["s"]]
    none, _, _ = V.aggregate(df.where("a < 0"), [], "mask", specs)
    r = none.collect()
    assert len(r) == 1 and set(r[0]["n"]) == {0} and set(r[0]["s"]) == {None}
    assert V.aggregate(df.where("a < 0"), ["a"], "mask", specs)[0].count() == 0


def test_kernel_engine_keeps_nan_to_its_worlds_and_big_numbers_exact(spark):
    m = [0b0101, 0b0010]
    df = spark.createDataFrame([(m[0], float("nan"), 2**60), (m[1], 1.0, 3)], "mask long, v double, w long")
    out, _, _ = V.aggregate(df, [], "mask", V.specs_of(df, [("s", "sum", "v"), ("t", "sum", "w")]))
    r = out.collect()[0]
    assert np.isnan(r["s"][0]) and r["s"][1] == 1.0 and r["s"][3] is None
    assert r["t"][:4] == [2**60, 3, 2**60, None]


def test_mean_over_balanced_worlds_is_the_exact_total(spark):
    m = masks_of(300)
    df = spark.createDataFrame([(int(x), i) for i, x in enumerate(m)], "mask long, v long")
    v = df.agg(A.world_sum("mask", "v").alias("v")).collect()[0]["v"]
    assert sum(2 * x for x in v) / 64 == sum(range(300))


def test_lane_edges(spark):
    for width, n in ((8, 127), (8, 128), (8, 1000), (16, 40_000)):
        df = spark.range(n).select(F.lit(-1).cast("long").alias("mask")).coalesce(1)
        assert set(world_aggregate(df, [], "mask", "count", None, f"lanes{width}").collect()[0]["v"]) == {n}


def test_level_kernels():
    m, v = masks_of(400), draw("negative_mixed", 400) * 10**13
    exact = K.ExactLevels()
    for a, b in zip(m.tolist(), v.tolist(), strict=True):
        exact.add(a, b)
    want = [sum(int(y) for x, y in zip(m.tolist(), v.tolist(), strict=True) if x >> j & 1) for j in range(64)]
    assert exact.total() == want and exact.flushes > 0
    assert [int(x) for x in K.matrix_sum(m, v)] == want
    buffered = K.Buffered()
    for i in range(5):
        buffered.add(int(m[i]), int(v[i]))
        assert buffered.total() == [sum(int(v[k]) for k in range(i + 1) if int(m[k]) >> j & 1) for j in range(64)]
        assert (buffered.state_bytes() == 40) == (i < 3)


def test_big_values_go_wide():
    s = K.ExactLevels()
    for _ in range(10):
        s.add(-1, 2**62)
    assert set(s.total()) == {10 * 2**62}


@pytest.mark.parametrize("name", NAMES)
def test_approximate_sums_stay_within_their_bound(name):
    e = approx_study(name, 20_000)
    if name == "negative_mixed":
        assert e["z2"] < 0.1 and 0.9 < e["variance_ratio"] < 1.1
        assert approx_study(name, 20_000, two_sided=False)["percent"] > 3 * e["percent"]
    else:
        assert e["percent"] < 100 * (2**-8 + 8 * 2**-12)
        assert 0.95 < e["variance_ratio"] < 1.05


def test_approximate_states_merge():
    m, v = masks_of(3000), draw("exponential", 3000)
    a, b = K.ApproxLevels(), K.ApproxLevels()
    a.add(m[:1500], v[:1500])
    b.add(m[1500:], v[1500:])
    a.merge(b)
    assert np.abs(a.total() / K.matrix_sum(m, v).astype(float) - 1).max() < 0.01
    assert a.state_bytes() < K.ExactLevels.state_bytes()


@pytest.mark.parametrize("order", [1, -1, 0])
def test_pruned_extremes(order):
    v = np.arange(10_000) * order if order else np.random.default_rng(0).integers(0, 10**6, 10_000)
    m = masks_of(len(v))
    p = K.Pruned().add(m, v)
    assert p.total().tolist() == np.where(K.bits(m) == 1, v[:, None], -(10**9)).max(0).tolist()
    if order == 0:
        assert p.updated < 0.5 * p.seen
    if order == 1:
        assert p.updated == p.seen


def test_chooser():
    assert choose_strategy("sum", Shape(10**9, 10**7, 10**9, 1000)) == "late"
    assert choose_strategy("sum", Shape(10**9, 10, 10**6)) == "preagg"
    assert choose_strategy("count", Shape(10**9, 10, 10**9)) == "wide"


def test_intervals_hold_the_exact_answer(spark):
    m = masks_of(500)
    df = spark.createDataFrame([(int(x), 1.0) for x in m], "mask long, v double")
    r = df.agg(A.half_sample_interval(F.transform(A.world_sum("mask", "v"), lambda x: x * 2)).alias("i")).collect()[0]["i"]
    assert r["low"] <= 500 <= r["high"]


def test_a_hot_group_among_many_rare_ones(spark):
    """Rare groups travel as rows and the hot one as states; both kinds meet in the same groups."""
    m = masks_of(30_000)
    rows = [(0 if i % 3 == 0 else i // 5, int(x), i % 100) for i, x in enumerate(m)]
    df = spark.createDataFrame(rows, "g long, mask long, v long").repartition(3)
    out, _, _ = V.aggregate(df, ["g"], "mask", V.specs_of(df, [("s", "sum", "v"), ("hi", "max", "v")]))
    want = df.groupBy("g").agg(A.world_sum("mask", "v").alias("s"), A.world_max("mask", "v").alias("hi"))
    assert {r["g"]: (r["s"], r["hi"]) for r in out.collect()} == {r["g"]: (r["s"], r["hi"]) for r in want.collect()}


def test_cascades_of_batches_are_exact():
    r = np.random.default_rng(2)
    m = masks_of(3000)
    for scale in (1, 100, 30_000, 2**31, 2**55):
        v = r.integers(-100, 101, 3000) * scale
        want = [sum(int(y) for x, y in zip(m.tolist(), v.tolist(), strict=True) if x >> j & 1) for j in range(64)]
        s, t = K.ExactLevels(), K.Buffered()
        for a in range(0, 3000, 700):
            s.add_many(m[a : a + 700], v[a : a + 700])
            t.add_many(m[a : a + 700], v[a : a + 700])
        assert s.total() == want == t.total() and (s.flushes > 0 or scale == 2**31)
    edge = K.ExactLevels().add_many(np.array([-1, 1]), np.array([-(2**63), 2**63 - 1]))
    assert edge.total() == [-1] + [-(2**63)] * 63


@pytest.mark.parametrize("strategy", ["arrow", "levels", "buffered"])
def test_exact_strategies_beyond_doubles(spark, strategy):
    m = masks_of(4000)
    df = spark.createDataFrame([(i % 3, int(x), 2**53 + i) for i, x in enumerate(m)], "g long, mask long, v long").repartition(5)
    got = {r["g"]: r["v"] for r in world_aggregate(df, ["g"], "mask", "sum", "v", strategy).collect()}
    for g in range(3):
        want = [sum(2**53 + i for i in range(g, 4000, 3) if int(m[i]) >> j & 1) for j in range(64)]
        assert [int(x) for x in got[g]] == want


def test_approximate_states_go_on_over_batches():
    m, v = masks_of(50_000), draw("uniform_int", 50_000)
    s = K.Running("sum", "approx", True)
    for a in range(0, 50_000, 10_000):
        s.add(m[a : a + 10_000], v[a : a + 10_000])
    exact = K.matrix_sum(m, v).astype(float)
    off = (np.array(s.total()) - exact) / exact
    assert (off <= 0).all() and off.min() > -(2**-8 + 2**-11) and len(s.own[0].levels) > 3
    with pytest.raises(ValueError):
        K.Running("sum", "levels", False)
    assert all(K.state_bytes(x) > 0 for x in ("levels", "lanes32", "approx_single", "buffered", "pruned"))
