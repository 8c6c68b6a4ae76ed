"""The experiment runner on small facts."""

from __future__ import annotations

import pytest

from matkeep import experiments, measures
from matkeep.materialise import load, materialise
from matkeep.programs import trace_example


@pytest.fixture(scope="module")
def toy(spark):
    program, facts, _ = trace_example(spark)
    return {n: materialise(spark, program, load(facts), n) for n in (0, 1, 2)}


def test_ratios():
    got = experiments.speed_ups({"odr": 6.0, "odr_2c": 2.0, "pbd": 5.0, "pbd_1c": 2.5, "remat": 8.0})
    assert got == {"odr/odr_2c": 3.0, "pbd/pbd_1c": 2.0, "remat/best": 4.0}
    assert experiments.speed_ups({"remat": 1.0, "odr": 2.0}) == {"remat/best": 0.5}
    assert experiments.speed_ups({"pbd": 1.0}) == {}


def test_small_and_large_deletions(toy):
    got = experiments.small(toy, "edge", 2, range(2), ("odr_2c",))
    assert set(got["seconds"]) == {"odr_2c", "remat"}
    assert all(0 < v["best"] <= v["mean"] <= v["worst"] for v in got["seconds"].values())
    assert got["ratios"]["remat/best"] == pytest.approx(got["seconds"]["remat"]["mean"] / got["seconds"]["odr_2c"]["mean"])
    found = experiments.large(toy, "edge", (0.5,), ("pbd_1c",))
    assert set(found[0.5]) == {"pbd_1c", "remat", "remat_1c", "remat_2c"}


@pytest.mark.parametrize("strategy", experiments.STRATEGIES)
def test_updates_leave_what_a_build_gives(toy, strategy):
    assert experiments.exact(toy, "edge", strategy, 2, 1)


def test_break_even_is_found_by_bisection(monkeypatch):
    def priced(mats, pred, share, strategies, seed=0):
        return {s: 1.0 if s == "remat" else 4 * share for s in strategies}

    monkeypatch.setattr(measures, "large_deletion", priced)
    assert measures.break_even({}, "edge", tolerance=1.0) == pytest.approx(0.25, abs=0.01)


def test_every_workload_has_a_predicate_to_change():
    assert set(experiments.CHANGED) == set(experiments.WORKLOADS)
    assert all(p in experiments.WORKLOADS[w].facts for w, p in experiments.CHANGED.items())
