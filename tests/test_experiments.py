"""Experiments train the full model over the survey's values."""

from dataclasses import replace

import pytest

from crowdrank.plans import training_queries as t

VALUES = {"dim": ("d", (4, 8, 16, 32, 64, 128)), "heads": ("heads", (1, 2, 4, 8, 16, 32)), "steps": ("rounds", range(1, 7)), "negatives": ("m", range(2, 8)), "neighbours": ("neighbours", (1, 2, 4, 6, 8, 10))}


@pytest.mark.parametrize("name", VALUES)
def test_sweep_changes_one_setting_of_the_full_model(name):
    field, want = VALUES[name]
    values, change = t.SWEEPS[name]
    assert tuple(values) == tuple(want)
    base = replace(t.FULL, d=32) if name == "heads" else t.FULL
    assert all(change(v) == replace(base, **{field: v}) for v in values)


@pytest.mark.parametrize("name", ["w2", "w3", "w4"])
def test_overall_trains_every_setting_in_full(monkeypatch, name):
    seen = {}
    monkeypatch.setattr(t, "compare", lambda w, methods, floors=False: seen.update(methods))
    monkeypatch.setattr(t, "planted", lambda spark, d: None)
    monkeypatch.setattr(t, "WORKLOADS", {k: lambda spark, d: None for k in ("w2", "w3")})
    t.QUERIES[f"exp_overall_{name}"](None, None)
    want = {k: t.METHODS[k] for k in t.OVERALL}
    assert {k: seen[k] for k in t.OVERALL} == (t.short(want) if name == "w2" else want)
