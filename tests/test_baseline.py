import pytest
from pyspark.sql import functions as F

from worldfold.operators import baseline as B
from worldfold.operators import utility as U
from worldfold.workloads import distributions, ratios, registry, tpch
from worldfold.workloads.tpch import CONTEXT


def test_many_runs_equal_one_pass_for_the_same_worlds(spark, sf):
    """Vectors and released values of the baseline and of the engine, draw by draw."""
    runs = registry.multi_run(spark, sf, "explode")
    loop = registry.multi_run(spark, sf, "loop", worlds=4)
    key = lambda r: (r["l_returnflag"], r["world"])
    some = sorted((tuple(r) for r in runs.where("world < 4").collect()))
    assert some == sorted(tuple(r) for r in loop.collect())
    one = {key(r): r["v"] for r in registry.vec(spark, sf, "count", "flag").groupBy("l_returnflag", "world").agg(F.sum("v").alias("v")).collect()}
    assert {key(r): r["n"] for r in runs.collect()} == one
    base = {r[0]: r[1] for r in B.released_runs(runs, ["l_returnflag"], ["n"], CONTEXT, {"n": 2}).collect()}
    engine = {r[0]: r[1] for r in tpch.session(spark, sf).rewrite("SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY l_returnflag", CONTEXT).collect()}
    assert base == pytest.approx(engine)


@pytest.mark.parametrize("sampler", ["mask", "balanced", "bernoulli"])
def test_samplers(spark, sampler):
    units = spark.range(300).withColumnRenamed("id", "u")
    n = [r["count"] for r in B.sample_units(units, "u", CONTEXT, sampler).groupBy("unit").count().collect()]
    assert len(n) == 300
    assert set(n) == {32} if sampler != "bernoulli" else 28 < sum(n) / 300 < 36


@pytest.mark.parametrize("query", ["multi_run_explode", "multi_run_released", "multi_run_resampled"])
def test_one_job_repeats_rows_behind_the_join(spark, sf, query):
    """Repeated samples below a join are broadcast by the size of the table they come from, which the driver does not hold."""
    plan = registry.QUERIES[query](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert 0 <= plan.index("Generate explode") < plan.index("Join Inner")
    assert "rightHint=(strategy=merge)" in plan


def test_samples_as_masks_are_the_samples(spark):
    units = spark.range(50).withColumnRenamed("id", "u")
    rows = units.select(F.col("u").alias("k"), (F.col("u") % 3).alias("g"))
    each = lambda d: d.groupBy("g", "world").count()
    got = [sorted(tuple(r) for r in B.multi_run(rows, "k", each, s, mode="explode", keys=k).collect()) for s, k in ((B.sample_units(units, "u", CONTEXT), ()), (B.sample_masks(units, "u", CONTEXT), ("g",)))]
    assert got[0] == got[1] and sum(n for *_, n in got[0]) == 50 * 32


def test_loop_leaves_the_driver_no_plan_of_all_runs(spark, sf):
    """64 runs in one plan, or a broadcast sample for each, is more than the driver holds beside the queries that follow."""
    runs = registry.QUERIES["multi_run_loop"](spark, sf)
    plan = runs._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan
    assert sorted(tuple(r) for r in runs.collect()) == sorted(tuple(r) for r in registry.QUERIES["multi_run_explode"](spark, sf).collect())


def test_loop_takes_both_forms_of_samples(spark):
    units = spark.range(50).withColumnRenamed("id", "u")
    rows = units.select(F.col("u").alias("k"), (F.col("u") % 3).alias("g"))
    count = lambda d: d.groupBy("g").count()
    got = [sorted(tuple(r) for r in B.multi_run(rows, "k", count, s, worlds=8).collect()) for s in (B.sample_units(units, "u", CONTEXT), B.sample_masks(units, "u", CONTEXT))]
    assert got[0] == got[1] and len(got[0]) == 3 * 8


def test_absent_worlds_keep_their_place(spark):
    rows = spark.createDataFrame([("a", 1, 5), ("a", 3, 7)], "g string, world int, v int")
    v = B.collect_worlds(rows, ["g"], ["v"], 4).collect()[0]["v"]
    assert v == [None, 5, None, 7]


def test_utility_of_crafted_answers(spark, sf):
    n = spark.read.parquet(f"{sf}/customer.parquet").count()
    assert n % 6 == 0  # so that shares are what they are of each six
    r = registry.utility_crafted(spark, sf).collect()[0]
    assert tuple(r) == (30.0, 0.75, 0.6, n // 6)


def test_released_errors_match_their_prediction(spark, sf):
    s = tpch.session(spark, sf)
    sql = "SELECT l_returnflag, sum(l_quantity) AS q FROM lineitem GROUP BY l_returnflag"
    exact = {r[0]: r[1] for r in spark.sql(sql).collect()}
    errors, predicted = [], []
    for seed in range(6):
        ctx = CONTEXT.but(key=f"s{seed}", secret_world=seed * 7 % 64)
        v = {r[0]: r[1] for r in s.rewrite(sql, ctx, "vectors").collect()}
        got = {r[0]: r[1] for r in s.rewrite(sql, ctx).collect()}
        errors += [abs(got[k] - exact[k]) / exact[k] * 100 for k in exact]
        predicted += [U.predicted_mape(v[k], ctx.mi) for k in exact]
    mean, want = sum(errors) / len(errors), sum(predicted) / len(predicted)
    assert 0.4 * want < mean < 2 * want


def test_lifting_beats_noise_on_each(spark, sf):
    r = ratios.lift_against_each(spark, sf, n=3, seeds=3).agg(F.avg("lifted_percent"), F.avg("combined_percent")).collect()[0]
    assert r[0] < r[1]


def test_measures():
    assert U.slowdown({"a": 2.0, "b": 6.0}, {"a": 1.0, "b": 2.0})["within_2.5"] == 0.5
    assert U.breakdown(1.0, 2.0, 5.0) == {"joins": 0.25, "aggregates": 0.75}
    assert U.approx_error([100.0, 200.0], [100.0, 202.0])["percent"] == pytest.approx(0.5)


def test_generated_frames(spark):
    for order in ("uniform", "increasing", "decreasing"):
        df = distributions.frame(spark, 1000, 10, order, scattered=order == "uniform")
        assert df.count() == 1000 and df.select("g").distinct().count() == 10


def test_resampled_rows_follow_their_share(spark):
    from worldfold.functions.masks import worlds_of

    runs = spark.range(3000).select("id", F.explode(F.sequence(F.lit(0), F.lit(15))).alias("world"))
    n = B.resample_rows(runs, ["id"], CONTEXT).count()
    assert n == pytest.approx(3000 * 16 / 64, rel=0.12)
    df = spark.createDataFrame([(0b1011,)], "m long")
    assert df.select(worlds_of("m")).first()[0] == [0, 1, 3]


def test_experiments_give_their_tables(spark, sf):
    from worldfold.workloads import experiments as X

    assert X.run_times(spark, sf, ("h06",)).count() == 1
    assert X.ablation(spark, "count", 2000, (0, 5)).count() == 14
    assert X.ablation(spark, "max", 2000, (3,), "increasing").count() == 3
    r = X.attacks(spark, sf, 150).collect()
    assert all(x["measured"] <= x["bound"] + 0.1 for x in r)
    w = {x["worlds"]: x["predicted_percent"] for x in X.worlds_compared(spark, sf).collect()}
    assert w[64] > 0 and w[128] > 0
    u = X.utility_runs(spark, sf, "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY l_returnflag", ["l_returnflag"], 3)
    assert u.where("recall = 1 AND precision = 1").count() == 3


def test_laplace_clips_a_units_part(spark):
    """Without noise to speak of the clipped parts are what is summed; null values add nothing, null groups are a group."""
    rows = [("a", 1, 30.0), ("a", 1, 30.0), ("a", 2, -90.0), ("a", 3, None), (None, 4, 5.0)]
    df = spark.createDataFrame(rows, "g string, u int, v double")
    got = {r["g"]: r["total"] for r in B.laplace_sums(df, ["g"], "u", "v", 40, 1e9, CONTEXT).collect()}
    assert got == {"a": pytest.approx(0.0, abs=1e-3), None: pytest.approx(5.0, abs=1e-3)}
    many = spark.range(4000).select("id", F.lit(1).alias("u"), F.lit(0.0).alias("v"))
    noise = [r["total"] for r in B.laplace_sums(many, ["id"], "u", "v", 10, 0.5, CONTEXT).collect()]
    assert sum(abs(x) for x in noise) / 4000 == pytest.approx(20, rel=0.08)  # the scale is the mean deviation
    assert abs(sum(noise) / 4000) < 2
    assert B.laplace_sums(df.where("false"), ["g"], "u", "v", 40, 1.0, CONTEXT).count() == 0


def test_predicted_errors_as_numpy_gives_them(spark):
    import numpy as np

    v = [float(x % 7 + 20) for x in range(64)]
    df = spark.createDataFrame([(v,), ([0.0] * 64,)], "v array<double>")
    got = [r[0] for r in df.select(U.predicted_percent("v", 1 / 128)).collect()]
    assert got == [pytest.approx(U.predicted_mape(np.array(v), 1 / 128)), None]
