"""The run-time experiments are registered whole."""

from __future__ import annotations

import inspect

import pytest

from logsketch import registry, workloads


@pytest.mark.parametrize("name", ["bench_phase_1_3", "bench_phase_2_4"])
def test_all_cuts_and_trials(name):
    given = inspect.signature(registry.queries()[name]).parameters
    assert given["cuts"].default == workloads.CUTS and len(workloads.CUTS) == 8 and given["trials"].default == 10


def test_only_the_asked_phases_are_repeated(spark, sf, monkeypatch):
    calls = []
    for module, name in ((workloads.audit, "skeletons"), (workloads.audit, "vectorise"), (workloads.audit, "cluster"), (workloads.fptree, "fp_tree")):
        monkeypatch.setattr(module, name, lambda *a, f=getattr(module, name), name=name, **kw: calls.append(name) or f(*a, **kw))
    rows = workloads.bench_phase_2_4(spark, sf, trials=2, cuts=(2,)).collect()
    assert calls == ["skeletons", "vectorise", "cluster", "fp_tree", "vectorise", "fp_tree"]
    assert [(r["phase"], r["trials"]) for r in rows] == [(2, 2), (4, 2)] and all(r["mean_s"] > 0 and r["n_skel"] > 0 for r in rows)
    calls.clear()
    workloads.bench_phase_1_3(spark, sf, trials=2, cuts=(2,))
    assert calls == ["skeletons", "vectorise", "cluster", "skeletons", "cluster"]
