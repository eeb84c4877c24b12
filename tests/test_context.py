import math

import pytest

from worldfold.context import BudgetLedger, QueryContext, attack_bound, budget_for, divergence


def test_attack_bound_of_known_budgets():
    assert attack_bound(1 / 4) == pytest.approx(0.838, abs=0.002)
    assert attack_bound(1 / 128) == pytest.approx(0.562, abs=0.002)
    assert attack_bound(0) == pytest.approx(0.5)
    assert attack_bound(1.0) == 1.0


def test_budget_is_the_inverse():
    for s in (0.5, 0.6, 0.8, 0.99):
        assert attack_bound(budget_for(s)) == pytest.approx(s, abs=1e-9)
    assert divergence(1.0, 0.5) == pytest.approx(math.log(2))


def test_ledger_adds_up_and_refuses():
    ledger = BudgetLedger(limit=0.1)
    ledger.charge("a", 4, 1 / 128)
    assert ledger.spent == pytest.approx(4 / 128)
    with pytest.raises(PermissionError):
        ledger.charge("b", 100, 1 / 128)
    assert len(ledger.entries) == 1


def test_context_hides_its_key_and_is_fresh():
    a, b = QueryContext.new(), QueryContext.new()
    assert a.key != b.key and a.key not in repr(a)
    with pytest.raises(ValueError):
        QueryContext.new(worlds=32)
