"""Large joins scored from their tables, against the same scores on the whole join."""

import random

import pytest
from pyspark.sql import functions as F

from purchase_planner import workloads
from purchase_planner.functions import measures as M
from purchase_planner.plans import factored, report
from purchase_planner.plans import joingraph as G
from purchase_planner.plans import request as Q
from purchase_planner.plans.evaluate import TargetGraph, score_row
from purchase_planner.sources.marketplace import Marketplace, star_marketplace
from tests.conftest import SMALL


def test_conditional_entropy_in_cells(spark, monkeypatch):
    for name, value in {"FORMED": 0, "GAIN": 0, "GROUPS": 7, "VALUES": 100}.items():
        monkeypatch.setattr(factored, name, value)
    rng = random.Random(1)
    left = [(rng.choice([None, float("nan"), *[round(rng.gauss(0, 5), 1) for _ in range(9)]]), rng.choice([None, *range(9)]), rng.randint(1, 5)) for _ in range(300)]
    right = [(rng.choice([None, *range(2, 12)]), rng.choice([None, *"abcdefghijkl"]), rng.randint(0, 2), rng.randint(1, 4)) for _ in range(200)]
    left = spark.createDataFrame(left, "x double, k int, w long").groupBy("x", "k").agg(F.sum("w").alias(M.W))
    right = spark.createDataFrame(right, "l int, y string, z int, w long").groupBy("l", "y", "z").agg(F.sum("w").alias(M.W))
    whole = left.join(right.withColumnRenamed(M.W, "v"), F.col("k") == F.col("l")).withColumn(M.W, F.col(M.W) * F.col("v"))
    got = factored.conditional(left, right, "x", [("k", "l")], ["y", "z"])
    assert got == pytest.approx(M.scalar(M.cond_cum_entropy_df(whole, "x", ["y", "z"], M.W)))
    assert factored.conditional(left.where("k = 0"), right, "x", [("k", "l")], ["y", "z"]) is None  # no key in common


@pytest.mark.parametrize("x", ["x1", "x2", "x3"])
def test_scores_from_tables_equal_those_of_the_join(spark, monkeypatch, x):
    monkeypatch.setattr(factored, "FORMED", 0)
    monkeypatch.setattr(factored, "GAIN", 0)
    request, most, _ = workloads.DIRTY[x]
    market = star_marketplace(spark, SMALL, planted=True, dirty=True)
    plan = max(Q.all_plans(workloads._schema_graph(), request, most), key=lambda p: ("xj" in p.label(), "custkey" not in p.label() and "suppkey" not in p.label()))
    a, b = (score_row(market, plan, *request.sides, large=large, rate=0.8) for large in (False, True))
    assert a["join_rows"] == b["join_rows"] > 0
    assert b["quality"] == pytest.approx(a["quality"]) and b["corr"] == pytest.approx(a["corr"])


def test_a_join_of_many_pairs_is_not_formed(spark):
    """Two unrelated attributes over one key: 200 million pairs of a value and a group."""
    market = Marketplace.of({"a": spark.range(20_000).select(F.lit(1).cast("long").alias("k"), F.col("id").cast("double").alias("x")), "b": spark.range(10_000).select(F.lit(1).cast("long").alias("k"), F.col("id").alias("y"))})
    plan = TargetGraph.of({("a", "b"): ["k"]}, {"x": "a", "y": "b"})
    got = score_row(market, plan, ("x",), ("y",), large=True)
    assert got["join_rows"] == 200_000_000 and got["quality"] == 1.0 and got["corr"] == pytest.approx(0, abs=1e-6)


def test_comparisons_build_the_sampled_graph_once(spark, monkeypatch):
    built = []
    real = workloads.G.build
    monkeypatch.setattr(workloads.G, "build", lambda *a, **k: built.append(a[1:]) or real(*a, **k))
    monkeypatch.setattr(workloads.report, "build", workloads.G.build)
    assert len(workloads._three(spark, SMALL, "x1").collect()) == 6
    assert built == [(), (0.5,)]


def test_sampling_sweep_scores_a_plan_once(spark, monkeypatch):
    seen, row = [], Q.Evaluator.row
    monkeypatch.setattr(Q.Evaluator, "row", lambda self, plan: (seen.append((self.rate, plan)), row(self, plan))[1])
    request = workloads.DIRTY["x1"][0]
    market = star_marketplace(spark, SMALL, planted=True, dirty=True).restricted(["customer", "orders"])
    rows = report.sampling_sweep(market, request, (0.5, 1.0), 2, iterations=3)
    assert len(seen) == len(set(seen)) and {r for r, _ in seen} == {0.5, 1.0}
    best = Q.exhaustive(G.build(market), request, 2)
    assert [r["corr"] for r in rows if r["approach"] == "exhaustive_full"] == pytest.approx([best.score.corr] * 2)
    assert all(r["cd"] == 0 for r in rows if r["rate"] == 1.0 and r["approach"] != "heuristic")


def test_fragments_are_searched_whatever_the_size_of_their_joins(spark, monkeypatch):
    """F1 acquire_m29_x6: a join of 1.21e12 rows was beyond a limit of the query and never scored."""
    n = 1_100_000
    brand = F.when(F.col("id") % 2 == 0, "odd").otherwise("even").alias("p_brand")
    frames = {"region": spark.range(n).select(F.lit(1).alias("k"), F.lit("EUROPE").alias("r_name")), "part_core": spark.range(n).select(F.lit(1).alias("k"), brand, (F.col("id") % 3).alias("ev_k"))}
    monkeypatch.setattr(workloads, "fragment_marketplace", lambda *_: Marketplace.of(frames))
    (row,) = workloads._searched(spark, SMALL, "x6").collect()
    assert (row["status"], row["plan"], row["join_rows"], row["evaluated"]) == ("found", "part_core-region(k)", n * n, 1)


def test_the_walk_over_fragments_tries_all_join_sets(spark, monkeypatch):
    """F1 acquire_m29_x6: four steps left most of the 49 states of two edges with three join attributes unseen."""
    rows = spark.range(40).select(*[(F.col("id") % m).alias(f"k{m}") for m in (2, 3, 5)], *[(F.col("id") % m).alias(f"l{m}") for m in (2, 3, 7)], "id")
    frames = {
        "region": rows.select("k2", "k3", "k5", F.concat(F.lit("r"), F.col("id") % 4).alias("r_name")),
        "middle": rows.drop("id"),
        "part_core": rows.select("l2", "l3", "l7", F.concat(F.lit("b"), F.col("id") % 6).alias("p_brand"), (F.col("id") % 5).alias("ev_k")),
    }
    monkeypatch.setattr(workloads, "fragment_marketplace", lambda *_: Marketplace.of(frames))
    (row,) = workloads._searched(spark, SMALL, "x6").collect()
    assert row["status"] == "found" and row["evaluated"] > 5


@pytest.mark.parametrize("x", ["x", "c"])
def test_a_join_of_more_rows_than_a_long_holds(spark, x):
    """Three tables over one key: 2.7e19 rows. The score is that of the same tables with a hundredth of the rows."""
    def scored(n: int, large: bool = True):
        a = spark.range(n).select(F.lit(1).alias("k"), (F.col("id") % 2).alias("j"), (F.col("id") % 4).cast("double").alias("x"), (F.col("id") % 4).alias("c"))
        b = spark.range(n).select(F.lit(1).alias("k"), (F.col("id") % 3).alias("l"), F.when(F.col("id") % 10 == 0, 7).otherwise(F.col("id") % 3).alias("m"), (F.col("id") % 2).alias("j"))
        c = spark.range(n).select((F.col("id") % 3).alias("l"), (F.col("id") % 5).alias("y"))
        market = Marketplace.of({"a": a, "b": b, "c": c}, {"b": [M.FD(("l",), "j")]})
        plan = TargetGraph.of({("a", "b"): ["k"], ("b", "c"): ["l"]}, {x: "a", "j": "b", "y": "c"})
        return score_row(market, plan, (x,), ("j", "y"), large=large)

    small, whole, formed = scored(30_000), scored(9_000_000), scored(9_000_000, large=False)
    assert whole["join_rows"] == formed["join_rows"] == small["join_rows"] * 300**3 > 2**63 > 0
    for got in (whole, formed):
        assert got["quality"] == pytest.approx(small["quality"], abs=1e-9) and got["quality"] < 1
        assert got["corr"] == pytest.approx(small["corr"], rel=1e-9)


def test_a_subtree_is_collapsed_between_its_joins(spark):
    """F1 acquire_m29_x6: the rows of one branch met those of the next before their key fell away."""
    a = spark.range(6).select((F.col("id") % 3).alias("a__k"), (F.col("id") % 2).alias("a__l"), F.lit(1).cast("long").alias(M.W))
    b = spark.range(6).select((F.col("id") % 3).alias("b__k"), (F.col("id") % 4).alias("b__y"), F.lit(2).cast("long").alias(M.W))
    c = spark.range(4).select((F.col("id") % 2).alias("c__l"), F.col("id").alias("c__z"), F.lit(3).cast("long").alias(M.W))
    plan = TargetGraph.of({("a", "b"): ["k"], ("a", "c"): ["l"]}, {"y": "b", "z": "c"})
    out = factored.subtree(plan, {"a": a, "b": b, "c": c}, "a", None, ["b__y", "c__z"])
    whole = a.withColumnRenamed(M.W, "u").join(b.withColumnRenamed(M.W, "v"), F.col("a__k") == F.col("b__k")).join(c, F.col("a__l") == F.col("c__l"))
    assert sorted(out.collect()) == sorted(whole.groupBy("b__y", "c__z").agg(F.sum(F.col("u") * F.col("v") * F.col(M.W))).collect())
    logical = out._jdf.queryExecution().optimizedPlan().toString()
    assert logical.count("Aggregate [") == 4  # each leaf, between the joins, at the end
