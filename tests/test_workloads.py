from types import SimpleNamespace

import numpy as np

from shardgraph.plans import workloads
from shardgraph.plans.workloads import BUILT, METHODS


def test_build_matrix_builds_every_set_by_every_method(spark, monkeypatch):
    monkeypatch.setattr(workloads, "dataset", lambda spark, sf_dir, name: name)
    monkeypatch.setattr(workloads, "run", lambda method, vecs, cfg: SimpleNamespace(seconds={"overall": 1.0, "shard_build_sum": 1.0}))
    rows = workloads.exp_build_matrix(spark, "").collect()
    assert {(r.dataset, r.method) for r in rows} == {(n, m) for n in BUILT for m in METHODS}


def test_low_dimensional_sweep_takes_every_low_dimensional_set(spark, monkeypatch):
    monkeypatch.setattr(workloads, "search_rows", lambda spark, sf_dir, name, beams: [("search", name, "", f"beam={b}", "recall", 1.0) for b in beams])
    assert {r.dataset for r in workloads.exp_search_lowdim(spark, "").collect()} == {"e64q", "e64", "d96", "l4"}
