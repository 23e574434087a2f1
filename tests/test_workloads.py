"""Sweeps report on all held-out rows, however few rows runs are fitted on."""

import numpy as np
import pytest

from tierdraw.plans import kernels, workloads

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("load", [workloads.image_data, workloads.text_data])
def test_sweep_reports_on_all_held_out_rows(spark, monkeypatch, load):
    monkeypatch.setattr(workloads, "MAX_ROWS", 60)
    data = load(spark, SF)
    held = data["rows"].select("f", "y").toArrow().combine_chunks()
    a = np.concatenate([data["dense"](b) for b in held.to_batches()])
    assert 10 < len(data["ty"]) + len(data["y"]) < 60 and len(a) > 0
    # nothing is fitted or chosen by a test row
    told = {x.tobytes() for x in a}
    assert sum(x.tobytes() in told for x in np.concatenate([data["a"], data["ta"]])) <= (0 if load is workloads.image_data else 20)  # texts have copies
    r = workloads.sweep(spark, data, [("uncompressed", 1.0, 4, 16, 0)], 5).collect()
    x: list = []
    kernels.train(data, "uncompressed", 1.0, 4, 16, 0, r[0]["eta"], 5, models=x)
    loss, hits = kernels.judged(x[-1], a, held["y"].to_numpy().astype(int), data["classes"], data["model"])
    assert [len(r), r[0]["step"]] == [1, 5]
    assert r[0]["acc"] == pytest.approx(hits.mean()) and r[0]["loss"] == pytest.approx(float(np.mean(loss)))


def test_registered_sweeps_are_whole(monkeypatch):
    """Workers, fractions and five seeds of the published settings."""
    seen = {}
    for name in ("image_data", "text_data"):
        monkeypatch.setattr(workloads, name, lambda *a: None)
    monkeypatch.setattr(workloads.accuracy, "seed_summary", lambda log: log)
    monkeypatch.setattr(workloads.accuracy, "speedup", lambda log: log)
    monkeypatch.setattr(workloads.cost, "first_to_reach", lambda log, *a: log)
    for name, query in workloads.QUERIES.items():
        monkeypatch.setattr(workloads, "sweep", lambda spark, data, configs, steps, name=name: seen.update({name: configs}))
        if name != "divergence_fixture":
            query(None, SF)
    assert len(seen) == 7
    for configs in seen.values():
        assert {c[2] for c in configs} == {4, 32} and {c[4] for c in configs} == set(range(5)) and len(set(configs)) == len(configs)
    fractions = {name: {c[1] for c in seen[name] if c[0] != "uncompressed"} for name in ("curve_text_sparse", "curve_image_sparse")}
    assert fractions == {"curve_text_sparse": {0.01, 0.05, 0.1, 0.5}, "curve_image_sparse": {0.001, 0.005, 0.01, 0.05}}
    assert [len(seen[n]) for n in ("curve_text_sparse", "curve_image_sparse", "curve_text_rounding")] == [170, 170, 60]
