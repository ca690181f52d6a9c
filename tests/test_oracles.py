import importlib

import pytest

from fixtrace.plans import oracles, workloads
from tests.compare import normal


@pytest.mark.parametrize("name", sorted(oracles.SQL))
def test_same_rows_as_sql(spark, duck, small, name):
    got, want = workloads.queries()[name](spark, small).toPandas(), duck.execute(oracles.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert normal(got) == normal(want)


def rows(spark, sf, name):
    return [r.asDict() for r in workloads.queries()[name](spark, sf).collect()]


def test_every_method_is_scored(spark, small):
    got = {r["method"]: r for r in rows(spark, small, "w03_method_scores")}
    assert set(got) == set(workloads.METHODS)
    assert all(0 <= r[c] <= 1 for r in got.values() for c in ("precision", "recall", "f1") if r[c] is not None) and got["two_level"]["f1"] is not None


def test_slices_and_judges(spark, small):
    got = {r["mode"]: r for r in rows(spark, small, "w06_extraction_ablation")}
    assert set(got) == {"slice", "judge", "both"} and all(1 <= r["mean_statements"] <= 7 for r in got.values())
    grid = rows(spark, small, "w07_prompt_grid")
    by = {(r["noise"], r["strategy"]): r["agreement"] for r in grid}
    assert len(by) == 9 and by[0.1, "few_shot_reason"] >= by[0.3, "zero_shot"]  # less noise, more agreement


def test_thresholds_are_chosen_from_the_data(spark, small):
    got = rows(spark, small, "w13_threshold_sweep")
    steps = {s: [r for r in got if r["step"] == s] for s in ("theta_a", "theta_b", "theta_s")}
    fixed = {"theta_b": 800, "theta_s": 800}
    for name, step in steps.items():
        assert len(step) == 10 and sorted(r[name] for r in step) == [k * 100 for k in range(1, 11)]
        chosen = [r for r in step if r["chosen"]]
        assert len(chosen) == 1 and chosen[0]["f1"] == max(r["f1"] or 0 for r in step)
        assert all(r[k] == v for r in step for k, v in fixed.items() if k != name)
        fixed[name] = chosen[0][name]
    full = {(r["theta_a"], r["theta_b"], r["theta_s"]): r["f1"] for r in rows(spark, small, "w13_full_grid")}
    assert len(full) == 64


def test_each_part_of_the_tree_level_finds_refactorings(spark, small):
    got = {r["without"]: r for r in rows(spark, small, "w12_ablations")}
    assert got["full"]["n_found"] == got["full"]["n_refactorings"] > 0 and got["full"]["n_mistaken"] == 0
    assert all(r["n_found"] < got["full"]["n_found"] for k, r in got.items() if k != "full") and len(got) == 7


def test_detectors(spark, small):
    got = rows(spark, small, "w11_detectors")
    best = {r["detector"]: r for r in got if r["best"]}
    assert len(got) == 60 and set(best) == {"edit", "md5", "vector", "tree", "two_level", "function_model"}
    assert best["two_level"]["f1"] >= best["edit"]["f1"] >= best["md5"]["f1"]


def test_stages_are_timed(spark, small):
    got = rows(spark, small, "w15_stage_seconds")
    assert [r["stage"] for r in got] == ["cases and texts", "slices", "similarity", "backtracking", "versions"] and all(r["seconds"] > 0 and r["dynamic_ratio"] > 1 for r in got)


def test_page_trees(spark, small):
    got = rows(spark, small, "w19_page_trees")
    assert got and all(0 <= r["similarity"] <= 1 for r in got) and len({(r["page_a"], r["page_b"]) for r in got}) == len(got)


def test_entry(spark):
    entry = importlib.import_module("__spark_entry__")
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
