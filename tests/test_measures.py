import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from purchase_planner.functions import measures as M
from purchase_planner.functions.measures import FD
from purchase_planner.plans import lattice as L
from purchase_planner.sources import examples


def test_worked_example_of_one_dependency(spark):
    df, fd = examples.frame(spark, "fd_five"), FD(("a",), "b")
    assert sorted(r["tid"] for r in M.correct_rows(df, fd).collect()) == ["t1", "t2", "t5"]
    assert M.fd_quality(df, fd) == pytest.approx(0.6)


def test_join_of_good_tables_is_bad(spark):
    got = {r["example"]: r["quality"] for r in examples.worked_qualities(spark).collect()}
    assert got == pytest.approx({"fd_five": 0.6, "dirt_left": 0.996, "dirt_right": 0.6, "dirt_join_printed": 0.2, "dirt_join_real": 1 / 6})


def test_goldens(spark):
    steps = spark.createDataFrame([(1.0,), (2.0,), (4.0,)], ["x"])
    assert M.cum_entropy(steps, "x") == pytest.approx(1.308271, abs=1e-6)
    one = lambda xs: spark.createDataFrame([(x,) for x in xs], "k long")
    assert M.informativeness(one([1, 2, 2, 3]), one([4, 5, 5]), ["k"]) == pytest.approx(0.559365, abs=1e-6)
    assert M.informativeness(examples.frame(spark, "ds"), examples.frame(spark, "d1"), ["zipcode"]) == pytest.approx(0.127783, abs=1e-6)


@pytest.mark.parametrize("left,right", [([None, 1, 1], [1, None]), ([], [1, 2]), ([], []), ([7], [7]), ([1] * 9 + [2], [1, 3]), ([None, None], [None])])
def test_informativeness_closed_form_is_the_outer_join(spark, left, right):
    a, b = (spark.createDataFrame([(x,) for x in xs], "k long") for xs in (left, right))
    value = M.informativeness(a, b, ["k"])
    assert 0 <= value <= 1
    assert value == pytest.approx(M.scalar(M.informativeness_outer_df(a, b, ["k"])), abs=1e-9)
    assert value == pytest.approx(M.informativeness(b, a, ["k"]), abs=1e-9)


@settings(max_examples=5, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 2), st.integers(0, 2), st.sampled_from([0.5, 1.0, 2.5, 7.0])), min_size=1, max_size=12))
def test_entropy_properties(spark, rows):
    df = spark.createDataFrame(rows, "x long, y long, v double")
    hx, hxy = M.entropy(df, ["x"]), M.entropy(df, ["x", "y"])
    assert hx <= hxy + 1e-9
    mi = M.correlation(df, ["x"], ["y"])
    assert -1e-9 <= mi <= hx + 1e-9
    assert mi == pytest.approx(M.correlation(df, ["y"], ["x"]), abs=1e-9)
    values = sorted(r[2] for r in rows)
    n = len(values)
    direct = -sum((b - a) * (i + 1) / n * math.log2((i + 1) / n) for i, (a, b) in enumerate(zip(values, values[1:], strict=False)))
    assert M.cum_entropy(df, "v") == pytest.approx(direct, abs=1e-9)
    weighted = M.counted(df, ["x", "y", "v"])
    assert M.correlation(weighted, ["v"], ["x"], weight=M.W) == pytest.approx(M.correlation(df, ["v"], ["x"]), abs=1e-9)
    q = M.joint_quality(df, [FD(("x",), "y"), FD(("y",), "x")])
    assert q <= min(M.fd_quality(df, FD(("x",), "y")), M.fd_quality(df, FD(("y",), "x"))) + 1e-9


def test_empty_and_constant(spark):
    empty = spark.createDataFrame([], "x long, v double")
    assert M.cum_entropy(empty, "v") == 0
    same = spark.createDataFrame([(1, 3.0)] * 4, "x long, v double")
    assert M.cum_entropy(same, "v") == 0 and M.entropy(same, ["x"]) == 0


def test_splitting_and_kinds(spark):
    assert M.split_fd(["a"], ["b", "a", "c", "b"]) == [FD(("a",), "b"), FD(("a",), "c")]
    df = spark.createDataFrame([({"a": 1}, 1)], "m map<string,int>, k int")
    with pytest.raises(TypeError):
        M.kind_of(df, "m")
    assert M.kind_of(df, "k") == "categorical" and M.kind_of(df, "k", {"k": "numeric"}) == "numeric"


def test_lattice_counts_and_covers():
    assert len(list(L.lattice("ABCD"))) == L.size(4) == 11 and L.height(4) == 3
    assert len([s for s in L.lattice("ABCD") if len(s) == 2]) == 6
    f = frozenset
    holders = {f("A"): ["v1", "v2", "v3", "v4"], f("B"): ["v1", "v2", "v3", "v5"], f("C"): ["v5", "v6"], f("AB"): ["v1", "v2", "v3"], f("BC"): ["v5", "v7"]}
    assert len(L.cover_sets(holders, "ABC")) == 42
    assert L.of_mask(L.as_mask(("A", "C"), "ABCD"), "ABCD") == ("A", "C") and L.is_ancestor("A", "AB") and ("A", "B", "C") in L.children(("A", "B"), "ABCD")


def test_afds_are_minimal(spark):
    df = spark.createDataFrame([(i, i % 3, (i % 3) * 2, i % 2) for i in range(12)], "k long, a long, b long, c long")
    found = {str(fd) for fd, _ in M.discover_afds(df, ["a", "b", "c"], 2, 1.0)}
    assert found == {"a->b", "b->a"}
