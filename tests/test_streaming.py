import datetime as dt

import pytest
from pyspark.sql import functions as F

from worldfold.context import BudgetLedger
from worldfold.functions.release import release_sequential
from worldfold.streaming import windows as W
from worldfold.workloads.tpch import CONTEXT

SCHEMA = "ts timestamp, user_id long, kind string, value double"


def _events(spark, path, days, late=False):
    rows = [(dt.datetime(2024, 1, d, h), u, "ab"[u % 2], float(u)) for d in days for h in (1, 13) for u in range(40)]
    if late:
        rows += [(dt.datetime(2024, 1, 1, 3), 7, "a", 1000.0)]
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(path)


def _run(spark, path, check, ledger):
    got = {}
    s = W.source(spark, path, spark.createDataFrame([], SCHEMA).schema)
    w = W.windowed(s, "user_id", CONTEXT, value="value")
    q = W.run(w, CONTEXT, lambda df, i: got.update({(r["start"]): (r["count"], r["total"]) for r in df.collect()}), check, ledger=ledger)
    q.awaitTermination(120)
    return got


def test_closed_windows_are_released_once_and_like_a_table(spark, tmp_path):
    path = str(tmp_path / "in")
    _events(spark, path, [1])
    _events(spark, path, [2, 3])
    _events(spark, path, [5])
    _events(spark, path, [7], late=True)
    ledger = BudgetLedger()
    got = _run(spark, path, str(tmp_path / "check"), ledger)
    assert {k.day for k in got} >= {1, 2, 3}
    assert ledger.spent == pytest.approx(len(got) * 2 / 128)
    table = spark.read.parquet(path).where("value < 1000")
    want = {r["start"]: (r["count"], r["total"]) for r in W.released(W.windowed(table, "user_id", CONTEXT, value="value"), CONTEXT).collect()}
    for k, v in got.items():
        assert v == pytest.approx(want[k])
    again = _run(spark, path, str(tmp_path / "other"), BudgetLedger())
    assert again == got  # a replay gives the same values


def test_updating_modes_and_unit_groups_are_refused(spark, tmp_path):
    df = spark.createDataFrame([], SCHEMA)
    w = W.windowed(df, "user_id", CONTEXT)
    with pytest.raises(PermissionError):
        W.run(w, CONTEXT, lambda d, i: None, str(tmp_path), mode="update")
    with pytest.raises(PermissionError):
        W.windowed(df, "user_id", CONTEXT, group=("user_id",))


def test_sliding_windows_are_cells_of_their_own(spark, tmp_path):
    path = str(tmp_path / "in")
    _events(spark, path, [1])
    one = W.windowed(spark.read.parquet(path), "user_id", CONTEXT).count()
    many = W.windowed(spark.read.parquet(path), "user_id", CONTEXT, slide="6 hours").count()
    assert one == 1 and many > 3


def test_charges_and_posterior_outlive_a_restart(spark, tmp_path):
    """A second run on the checkpoint goes on where the first stopped: nothing is charged twice or forgotten, and the
    posterior is that of one run over everything."""
    ctx = CONTEXT.but(posterior="sequential")
    path, check = str(tmp_path / "in"), str(tmp_path / "check")

    def run(folder, ledger):
        got = {}
        w = W.windowed(W.source(spark, path, spark.createDataFrame([], SCHEMA).schema), "user_id", ctx, value="value")
        W.run(w, ctx, lambda df, i: got.update({r["start"]: (r["count"], r["total"]) for r in df.collect()}), folder, ledger=ledger).awaitTermination(120)
        return got

    _events(spark, path, [1, 2])
    _events(spark, path, [3])
    first, ledger = {}, BudgetLedger()
    first = run(check, ledger)
    assert first and ledger.spent == pytest.approx(len(first) * 2 / 128) and ledger.composes
    _events(spark, path, [5])
    _events(spark, path, [7])
    restarted = BudgetLedger()
    second = run(check, restarted)
    assert second and not set(first) & set(second)
    assert restarted.spent == pytest.approx((len(first) + len(second)) * 2 / 128)
    run(check, restarted)
    assert restarted.spent == pytest.approx((len(first) + len(second)) * 2 / 128)
    whole = W.windowed(spark.read.parquet(path), "user_id", ctx, value="value").where(F.col("start").isin([*first, *second]))
    want = {r["start"]: (r["count"], r["total"]) for r in release_sequential(whole, ["start", "end"], ["count", "total"], ctx).collect()}
    for k, v in (first | second).items():
        assert v == pytest.approx(want[k])


def test_a_replayed_batch_starts_from_its_own_posterior(spark, tmp_path):
    c = W.Charges(spark, str(tmp_path / "charges"))
    c.write(0, 4, [0.0, -1.0])
    c.write(2, 6, [0.0, -2.0])
    again = W.Charges(spark, str(tmp_path / "charges"))
    assert again.rows == {0: (4, [0.0, -1.0]), 2: (6, [0.0, -2.0])}
    assert again.before(0) is None and again.before(2) == [0.0, -1.0] and again.before(3) == [0.0, -2.0]
