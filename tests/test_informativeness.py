"""Informativeness of many instances and join sets in one pass."""

import pytest

from purchase_planner.functions.measures import informativeness_df, informativeness_of_samples, informativeness_of_sets
from purchase_planner.operators.sampling import unit_hash
from purchase_planner.plans import joingraph as G
from purchase_planner.sources.marketplace import Marketplace


@pytest.fixture(scope="module")
def frames(spark):
    a = [(i % 7, i % 3, f"v{i % 5}") for i in range(40)] + [(None, 1, "v1"), (2, None, "v9")]
    b = [(i % 11, i % 4) for i in range(30)] + [(None, None)]
    c = [(i % 5, f"v{i % 6}") for i in range(20)] + [(3, None)]
    return {
        "a": spark.createDataFrame(a, "x long, y long, z string"),
        "b": spark.createDataFrame(b, "x int, y long"),  # x is narrower here
        "c": spark.createDataFrame(c, "x long, z string"),
    }


SETS = [("x",), ("y",), ("z",), ("x", "y"), ("x", "z")]


def test_shuffles_do_not_grow_with_instances(frames):
    plan = informativeness_of_sets(frames, SETS)._jdf.queryExecution().executedPlan().toString()
    more = informativeness_of_sets(frames | {f"{n}2": df for n, df in frames.items()}, SETS)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == more.count("Exchange hashpartitioning") <= 5


def test_equals_pairwise_measure_and_samples(frames):
    kept = lambda j, count: unit_hash(j) < 0.5
    half = lambda j, count: kept(j, count).cast("long") * count
    got = {(r["sample"], r["src"], r["dst"], tuple(r["j"])): (r["ji"], r["join_rows"]) for r in informativeness_of_samples(frames, SETS, [None, half]).collect()}
    assert len(got) == 2 * (3 + 3 + 1)  # a-b: x, y, xy; a-c: x, z, xz; b-c: x
    for (sample, src, dst, j), (ji, rows) in got.items():
        left, right = frames[src], frames[dst]
        if sample:
            left, right = left.where(kept(j, None)), right.where(kept(j, None))
        want = informativeness_df(left, right, j).first()
        assert ji == pytest.approx(want["ji"], abs=1e-9) and rows == want["join_rows"], (sample, src, dst, j)


def test_graphs_at_several_rates_from_one_pass(frames):
    market = Marketplace.of(frames)
    for together, rate in zip(G.build_at(market, [1.0, 0.5]), (1.0, 0.5), strict=True):
        alone = G.build(market, rate)
        assert together.rate == rate and together.join_rows == alone.join_rows and together.weights == pytest.approx(alone.weights)
