import math

import pytest

from purchase_planner.functions import measures as M
from purchase_planner.functions import sqltext as T
from purchase_planner.plans import joingraph as G
from purchase_planner.plans import request as Q
from purchase_planner.plans import variants as V
from purchase_planner.sources.marketplace import star_marketplace
from tests.conftest import SMALL

SCHEMAS = {"a": ["s", "x", "y"], "b": ["x", "z"], "c": ["y", "z", "t"], "d": ["z", "t", "lone"]}


def worth(route):
    """A made-up objective: any order of routes will do."""
    return math.sin(sum(hash_of(f"{h.instance}{h.enters}{h.leaves}") for h in route)) / len(route)


def hash_of(s):
    return sum(ord(c) * 31**k for k, c in enumerate(s)) % 1009


def test_routes_hops_and_searches():
    routes = list(V.all_routes(SCHEMAS, "s", "t"))
    assert {tuple(h.instance for h in r) for r in routes} == {("a", "c"), ("a", "b", "d"), ("a", "b", "c"), ("a", "c", "d")}
    assert all("lone" not in (h.enters, h.leaves) for r in routes for h in r)
    best = V.dp_allpairs(SCHEMAS, "s", "t", worth)
    assert best in routes and worth(best) >= max(worth(r) for r in routes if len(r) <= 2)
    greedy = V.greedy_hop(SCHEMAS, "s", "t", worth)
    assert greedy in routes
    assert V.greedy_hop({"a": ["s", "x"], "b": ["t"]}, "s", "t", worth) is None
    assert V.dp_allpairs({"a": ["s", "x"], "b": ["t"]}, "s", "t", worth) is None
    assert V.dp_allpairs({"a": ["s", "t"]}, "s", "t", worth) == (V.Hop("a", "s", "t"),)


def test_join_strength_and_its_bound(spark):
    a = spark.createDataFrame([(1,), (1,), (2,), (None,)], "k int")
    b = spark.createDataFrame([(1,), (3,), (None,)], "k int")
    row = V.join_strength_df(a, b, ["k"]).first()
    assert (row["join_rows"], row["strength"]) == (2.0, pytest.approx(2 / 12))
    assert V.join_strength_df(a.limit(0), b, ["k"]).first()["strength"] == 0.0
    assert V.strength_bound([0.5, 0.2]) == 0.2 and V.scalar_objective(0.8, 0.4, 0.75) == pytest.approx(0.7)


def test_arbitrage(spark):
    rows = spark.createDataFrame([("a", 1.0, 1.0), ("b", 2.0, 0.5), ("c", 2.0, 1.0), ("d", 3.0, 0.9), ("e", 0.5, 0.1)], "attributes string, entropy double, price double")
    assert sorted(r["attributes"] for r in V.arbitrage(rows).collect()) == ["b", "d"]
    assert V.arbitrage(rows.withColumn("price", 2 * rows["entropy"])).count() == 0


def test_sql_texts_equal_the_measures(spark):
    rows = [(1, "p", "u"), (1, "p", "v"), (1, "q", "u"), (2, "q", None), (None, "q", "v"), (None, None, "v")]
    df = spark.createDataFrame(rows, "k int, x string, y string")
    other = spark.createDataFrame([(1, "u"), (1, "v"), (3, "u"), (None, "v")], "k int, y string")
    df.createOrReplaceTempView("left_side")
    other.createOrReplaceTempView("right_side")
    fd = M.FD(("k",), "x")
    assert spark.sql(T.fd_quality_sql("left_side", fd)).first()[0] == pytest.approx(M.fd_quality(df, fd))
    for join in (["k"], ["k", "y"]):
        got, want = spark.sql(T.informativeness_sql("left_side", "right_side", join)).first(), M.informativeness_df(df, other, join).first()
        assert tuple(got) == pytest.approx(tuple(want))
    assert spark.sql(T.correlation_sql("left_side", ["x"], ["k", "y"])).first()[0] == pytest.approx(M.correlation(df, ["x"], ["k", "y"], kinds={"x": "categorical"}), abs=1e-9)


def test_walks_and_sketch(spark):
    market = star_marketplace(spark, SMALL).restricted(["customer", "orders"])
    graph = G.build(market)
    supply = {"c_mktsegment": "customer", "o_orderpriority": "orders"}
    evaluator = Q.Evaluator(graph, Q.Request(("c_mktsegment",), ("o_orderpriority",)))
    start = Q.initial(graph, frozenset({("customer", "orders")}), supply)
    objective = V.RouteObjective(market)
    value = lambda p: V.scalar_objective(evaluator.score(p).quality, objective.strength(p.instances, evaluator.score(p).join_rows))
    plans = [V.TargetGraph.of({("customer", "orders"): j}, supply) for j in graph.choices("customer", "orders")]
    assert value(V.quality_walk(evaluator, start, value, 30, 1)) == max(map(value, plans))
    walked = V.directed_walk(evaluator, start, 30, 1)
    assert evaluator.score(walked).corr == max(evaluator.score(p).corr for p in plans)
    cheapest = min(evaluator.static(p)[0] for p in plans)
    tight = Q.Evaluator(graph, Q.Request(("c_mktsegment",), ("o_orderpriority",), budget=cheapest), memo=evaluator.memo)
    dearest = max(plans, key=lambda p: evaluator.static(p)[0])
    assert evaluator.static(V.directed_walk(tight, dearest, 30, 1))[0] == cheapest
    assert V.directed_walk(Q.Evaluator(graph, Q.Request(("c_mktsegment",), ("o_orderpriority",), budget=0.1)), start, 5) is None
    assert value(V.hop_sketch(graph, ("c_mktsegment", "customer"), ("o_orderpriority", "orders"), value)) == max(map(value, plans))
