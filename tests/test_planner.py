import math
from dataclasses import replace

import pytest

from purchase_planner.operators import sampling as S
from purchase_planner.plans import joingraph as G
from purchase_planner.plans import report, steiner
from purchase_planner.plans import request as Q
from purchase_planner.plans.evaluate import TargetGraph, plan_to_df, plan_weight
from purchase_planner.sources.marketplace import Instance, Marketplace, star_marketplace
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def graph(spark):
    m = star_marketplace(spark, SMALL).restricted(["customer", "orders", "nation"])
    return G.build(m)


REQUEST = Q.Request(("c_acctbal",), ("o_orderpriority",))
TREE = frozenset({("customer", "orders")})


def test_walk_ends_where_exhaustive_search_does(graph):
    evaluator = Q.Evaluator(graph, REQUEST)
    best = Q.exhaustive(graph, REQUEST, 2, evaluator, TREE)
    start = Q.initial(graph, TREE, {"c_acctbal": "customer", "o_orderpriority": "orders"})
    walk = Q.refine(evaluator, start, 50, seed=5)
    assert walk == best.graph
    assert Q.refine(evaluator, start, 50, seed=5, batch=True) == walk
    assert Q.refine(evaluator, start, 0, paper_start=True) is None


def test_limits(graph):
    assert Q.acquire(graph, replace(REQUEST, budget=1.0)).status == "unaffordable"
    assert Q.acquire(graph, replace(REQUEST, alpha=-1.0)).status == "no_igraph"
    assert Q.acquire(graph, replace(REQUEST, beta=1.1), 10).status == "low_quality"
    plan = Q.acquire(graph, replace(REQUEST, alpha=0.5), 30)
    assert plan.status == "found" and plan.score.weight <= 0.5
    low, high = report.budget_range(graph, REQUEST, 2, TREE)
    assert 0 < low <= high


def test_compressed_join_is_the_join(graph):
    plan = TargetGraph.of({("customer", "orders"): ["custkey"], ("customer", "nation"): ["nationkey"]}, {"c_mktsegment": "customer", "o_orderstatus": "orders", "n_name": "nation"})
    m = graph.market
    got = {(r[0], r[1]): r[2] for r in plan_to_df(m, plan, ["customer__c_mktsegment", "orders__o_orderstatus"]).select("customer__c_mktsegment", "orders__o_orderstatus", "__w").collect()}
    direct = m["customer"].df.select("custkey", "nationkey", "c_mktsegment").join(m["orders"].df.select("custkey", "o_orderstatus"), "custkey").join(m["nation"].df.select("nationkey"), "nationkey")
    assert got == {(r[0], r[1]): r[2] for r in direct.groupBy("c_mktsegment", "o_orderstatus").count().collect()}
    assert plan_weight(graph, plan) == pytest.approx(graph.weight("customer", "orders", ["custkey"]) + graph.weight("customer", "nation", ["nationkey"]))


def test_owned_instances_are_free(graph):
    owned = G.JoinGraph(graph.market.with_owned(["customer"]), graph.weights, graph.join_rows)
    assert owned.price("customer", ["custkey"]) == 0 < owned.price("orders", ["custkey"])
    plan = TargetGraph.of({("customer", "orders"): ["custkey"]}, {"c_acctbal": "customer", "o_orderpriority": "orders"})
    assert Q.emit_sql(plan, owned.market) == ["SELECT custkey, o_orderpriority FROM orders"]


def test_samples_are_nested_and_agree(spark, graph):
    a, b = graph.market["customer"].df, graph.market["orders"].df
    small, large = S.keyed_sample(b, ["custkey"], 0.2), S.keyed_sample(b, ["custkey"], 0.6)
    assert small.exceptAll(large).count() == 0
    keys = {r[0] for r in S.keyed_sample(a, ["custkey"], 0.6).select("custkey").collect()}
    assert {r[0] for r in large.select("custkey").collect()} <= keys


def test_bounded_join(graph):
    o, c, n = (graph.market[x].df for x in ("orders", "customer", "nation"))
    frames = [(o.select("orderkey", "custkey"), []), (c.select("custkey", "nationkey"), ["custkey"]), (n.select("nationkey"), ["nationkey"])]
    whole = S.bounded_join(frames, None).count()
    assert S.bounded_join(frames, 10**9).count() == whole
    assert 0 < S.bounded_join(frames, 10, 0.5).count() < whole
    assert S.bounded_join(frames, 10, 1.0).count() == whole


def test_landmarks_against_the_exact_tree(graph):
    sketch = steiner.landmark_sketch(graph, graph.market.names)
    weight = {e: w for e, (w, _) in graph.edges().items()}
    tree = steiner.minimal_igraphs(graph, ["orders", "nation"], sketch)[0]
    assert sum(weight[e] for e in tree) == pytest.approx(steiner.steiner_exact(graph, ["orders", "nation"]))
    assert steiner.minimal_igraphs(graph, ["orders", "nation"], sketch, alpha=-1) == []
    assert steiner.minimal_igraphs(graph, ["orders"], sketch) == [frozenset()]


def test_graph_survives_storage(spark, graph, tmp_path):
    graph.price("orders", ["custkey"])
    G.save_graph(graph, spark, f"file://{tmp_path}/g")
    back = G.load_graph(spark, graph.market, f"file://{tmp_path}/g")
    assert back.weights == graph.weights and back.prices == graph.prices


def test_escalation_bills_nested_samples(graph):
    plan, history = Q.escalate(graph.market, REQUEST, (0.5, 1.0), iterations=10)
    assert history[-1][1] == plan.status == "found" and plan.bill > 0
    assert Q.sample_bill([0.1, 0.4], 100.0) == pytest.approx(40.0)


def test_small_measures():
    assert report.correlation_difference(4.0, 3.0) == 0.25 and report.correlation_difference(0.0, 1.0) is None
    p = TargetGraph.of({("a", "b"): ["x"]}, {"y": "a"})
    assert report.plan_overlap(p, p) == 1.0 and not math.isnan(report.plan_overlap(p, p))
    assert Marketplace({}).names == []


def test_what_the_shopper_owns_supplies_what_they_have(graph):
    both = Marketplace({**graph.market.instances, "other": replace(graph.market["customer"], name="other", owned=True)})
    request = Q.Request(("c_acctbal",), ("o_orderpriority",))
    assert {s["c_acctbal"] for s in Q.supplies(graph.market, request)} == {"customer"}
    assert {s["c_acctbal"] for s in Q.supplies(both, request)} == {"other"}


def test_equal_rows_are_thinned_one_by_one(spark):
    """Over 60 seeds the kept share of each group is near the rate, with a spread like that of independent rows, at small counts and large ones."""
    from pyspark.sql import functions as F

    frame = spark.createDataFrame([("a", 1), ("b", 40), ("c", 200), ("d", 5000), ("e", 2_000_000)], "g string, n long")
    kept = [S.thinned(F.col("n"), 0.3, ["g"], seed=s).alias(f"s{s}") for s in range(60)]
    rows = {r["g"]: r for r in frame.select("g", "n", *kept).collect()}
    for g, r in rows.items():
        got, n = [r[f"s{s}"] for s in range(60)], r["n"]
        spread = math.sqrt(n * 0.3 * 0.7)
        assert all(0 <= x <= n for x in got)
        assert abs(sum(got) / 60 - 0.3 * n) < 4 * spread / math.sqrt(60), g
        if n > 1:
            assert 0.6 < math.sqrt(sum((x - 0.3 * n) ** 2 for x in got) / 60) / spread < 1.5, g


def test_estimates_on_thinned_counts_are_unbiased(spark):
    """Correlation and quality of one joined frame, over 50 seeds, against the truth."""
    from pyspark.sql import functions as F

    from purchase_planner.functions import measures as M

    rows = [(f"x{i % 3}", f"y{(i % 3 if i % 5 else i % 2)}", 40 + i) for i in range(30)]
    frame = spark.createDataFrame(rows, "x string, y string, w long").groupBy("x", "y").agg(F.sum("w").alias(M.W))
    fd = M.FD(("x",), "y")
    truth, quality = M.correlation(frame, ["x"], ["y"], weight=M.W), M.fd_quality(frame, fd, M.W)
    per = frame.crossJoin(spark.range(50).toDF("seed"))  # 50 seeds
    kept = per.select("seed", "x", "y", S.thinned(F.col(M.W), 0.5, ["x", "y", "seed"]).alias("c")).toPandas()
    corrs, shares = [], []
    for _, g in kept.groupby("seed"):
        n = g["c"].sum()
        h = lambda k, g=g, n=n: -sum(c / n * math.log2(c / n) for c in g.groupby(k)["c"].sum() if c)
        corrs.append(h("x") + h("y") - h(["x", "y"]))
        shares.append(g.groupby("x")["c"].max().sum() / n)
    assert abs(sum(corrs) / 50 - truth) < 0.02 and abs(sum(shares) / 50 - quality) < 0.01


def test_resampled_plans_keep_about_the_share(graph):
    plan = TargetGraph.of({("customer", "orders"): ["custkey"], ("customer", "nation"): ["nationkey"]}, {"o_orderstatus": "orders", "n_name": "nation"})
    request = Q.Request(("o_orderstatus",), ("n_name",))
    whole = Q.Evaluator(graph, request).score(plan).join_rows
    got = [Q.Evaluator(graph, request, eta=10, resample=0.5, seed=s).score(plan).join_rows for s in range(3)]
    assert all(abs(x / whole - 0.5) < 0.06 for x in got) and Q.Evaluator(graph, request, eta=10 * whole).score(plan).join_rows == whole


def test_weights_of_samples_and_restricted_graphs(graph):
    sampled = G.build(graph.market, 0.5)
    assert sampled.weights.keys() == graph.weights.keys()
    for (a, b), j in graph.weights:
        assert sampled.weights[(a, b), j] == pytest.approx(S.informativeness_est(graph.market[a].df, graph.market[b].df, list(j), 0.5).first()["ji"], abs=1e-9)
    assert set(graph.restricted(["customer", "orders"]).weights) == {k for k in graph.weights if "nation" not in k[0]}


def test_a_lightest_tree_beyond_the_budget_gives_way_to_another(graph):
    """A third table is made the lightest way from customer to orders; at the direct plan's price only the direct edge is left."""
    orders = graph.market["orders"]
    key = graph.market.common("customer", "orders")[0]
    market = Marketplace({"customer": graph.market["customer"], "orders": orders, "ledger": Instance("ledger", orders.df.select(key, "orderkey"))})
    pairs = [("customer", "ledger"), ("customer", "orders"), ("ledger", "orders")]
    bent = G.JoinGraph(market, {(p, j): 0.5 if p == ("customer", "orders") else 0.01 for p in pairs for j in G.join_sets(market.common(*p))}, {}, dict(graph.prices))
    sketch = Q.landmark_sketch(bent, bent.market.names)
    assert Q.igraph_candidates(bent, REQUEST, sketch)[0][1] != TREE
    _, dear = report.budget_range(bent, REQUEST, 2)
    request = replace(REQUEST, budget=dear)
    assert Q.acquire(bent, request, 5, spare=False).status == "unaffordable"
    plan = Q.acquire(bent, request, 5)
    assert plan.status == "found" and plan.graph.instances == ["customer", "orders"] and plan.score.price <= dear + 1e-9
    assert Q.acquire(bent, replace(REQUEST, budget=1.0), 5).status == "unaffordable"
