"""Grids of sizes, budgets, costs and candidates over data sets of the given tables, against the kernels."""

from __future__ import annotations

import pytest

from vtask.kernels import selection as sel
from vtask.kernels.table import PROFILES, card_threshold
from vtask.kernels.tasks import axes, instantiations
from vtask.plans.cost import counters
from vtask.plans.queries import QUERIES

D = "/root/testdata/sf0.01"


@pytest.mark.parametrize("name", ["candidate_grid", "card_threshold_grid", "cost_counters", "holdout_size_grid", "probe_budget"])
def test_reads_given_tables(spark, name):
    assert any(f.startswith("file:///root/testdata/") for f in QUERIES[name](spark, D).inputFiles())


def test_sizes_equal_the_kernels(spark):
    rows = QUERIES["card_threshold_grid"](spark, D).collect()
    assert min(r.n for r in rows) < 4 and max(r.n for r in rows) > 20_480 and {r.source for r in rows} == {"buyer", "user", "seller", "status"}
    assert all(r.threshold == card_threshold(r.n) for r in rows)
    held = QUERIES["holdout_size_grid"](spark, D).collect()
    assert len(held) == 2 * sum(r.n >= 2 for r in rows) and max(r.h for r in held) == 2048
    assert all(r.h == sel.holdout_size(r.n, r.splits) for r in held)
    budget = {}
    for r in QUERIES["probe_budget"](spark, D).collect():
        budget.setdefault((r.source, r.id, r.h), {})[r.op] = r.probes
    assert set(budget) == {(r.source, r.id, r.h) for r in held if r.splits == 3}
    assert all(v == sel.probe_budget(h, ["shuffle", "replace", "jitter"]) for (_, _, h), v in budget.items())


def test_costs_equal_the_counters(spark):
    n = {(r.source, r.id): r.n for r in QUERIES["card_threshold_grid"](spark, D).collect()}
    rows = QUERIES["cost_counters"](spark, D).collect()
    assert len(rows) == 16 * sum(k[0] in ("seller", "status") and v >= 2 for k, v in n.items())
    assert all(tuple(r)[2:] == counters(r.m, r.g, r.s, sel.holdout_size(n[r.source, r.id], r.s), n[r.source, r.id], r.d) for r in rows)


def test_candidates_of_every_profile(spark):
    rows = [tuple(r) for r in QUERIES["candidate_grid"](spark, D).collect()]
    assert {r[1] for r in rows} == set(PROFILES) and len({r[0] for r in rows}) == 5
    want = {(p, t, k, *(x.get(c) for c in ("clusters", "bins", "transform", "token_bins", "draw"))) for p in PROFILES for t, k in instantiations(p) if t != "S" for x in axes(t, k)}
    assert {r[1:] for r in rows} == want and len(rows) == len(want)
