"""Queries that once answered from literals or schemas alone: they read the given tables."""

import pytest

from purchase_planner import queries as q
from purchase_planner.plans import joingraph as G
from purchase_planner.sources import examples
from purchase_planner.sources.marketplace import Marketplace
from tests.conftest import SMALL


@pytest.mark.parametrize("name, tables", [("emitted_sql_x1", {"customer", "orders"}), ("i_edges", {"customer", "orders", "lineitem", "part"}), ("lattice_sizes", {"nation", "customer", "part"}), ("rel_udtf_lattice", {"events"}), ("worked_qualities", {"customer", "orders", "part"})])
def test_reads_its_tables(spark, name, tables):
    out = q.QUERIES[name](spark, SMALL)
    assert {f.rpartition("/")[2].removesuffix(".parquet") for f in out.inputFiles()} >= tables
    assert out.count() > 0


def test_an_empty_attribute_makes_no_edge(spark):
    m = Marketplace.of({"a": spark.sql("SELECT 1 k, 2 x"), "b": spark.sql("SELECT 1 k, CAST(NULL AS INT) x")})
    assert [tuple(r) for r in G.instance_edges(G.filled_schema_table(m)).collect()] == [("a", "b", ["k"])]


def test_purchase_options_of_the_given_tables(spark):
    rows = {(r["option"], r["with_own"]): r for r in q.QUERIES["purchase_options_example"](spark, SMALL).collect()}
    customers, orders = (spark.read.parquet(f"{SMALL}/{n}.parquet") for n in ("customer", "orders"))
    assert sorted(rows) == [("1", True), ("2", True), ("3", True), ("4", False), ("4", True), ("5", False), ("5", True)]
    assert rows["2", True]["join_rows"] == rows["5", False]["join_rows"] == customers.count()
    assert rows["4", False]["join_rows"] == customers.join(orders, customers["c_custkey"] == orders["o_custkey"]).count()


def test_purchase_options_of_the_worked_instances(spark):
    assert examples.literal_options(spark).count() == 9
