"""The experiments over whole marketplaces: searches that nothing pins, on dirty tables, under limits that bind.

Registered beside the other queries. The SQL of the exhaustive searches enumerates the same plans from schemas alone.
"""

from __future__ import annotations

from dataclasses import replace
from decimal import Decimal
from types import SimpleNamespace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans import joingraph as G
from .plans import report
from .plans import request as Q
from .plans.evaluate import TargetGraph
from .queries import _COLUMNS, query, rows_sql, sql_corr, sql_entropy, sql_ji, sql_joint, star_sql
from .sources.marketplace import PLANTED, Instance, Marketplace, fragment_marketplace, star_marketplace

#: Requests over the dirty star marketplace with the largest plan that the exhaustive searches try, and an informativeness limit.
DIRTY = {
    "x1": (Q.Request(("c_acctbal",), ("o_orderdate", "o_year")), 3, 0.5),
    "x2": (Q.Request(("n_name",), ("ps_nation",)), 3, 0.5),
    "x3": (Q.Request(("o_totalprice",), ("c_regionkey", "r_name")), 4, 0.5),
}
#: What the requests ask for beside the shared attributes.
_PRIVATE = {"customer": ["c_acctbal", "c_regionkey"], "orders": ["o_orderdate", "o_year", "o_totalprice"], "nation": ["n_name"], "region": ["r_name"], "partsupp": ["ps_nation"]}
RATIOS = (0.13, 0.9, 1.0)
QUALITY = 0.9


def _schema_graph() -> G.JoinGraph:
    """The star marketplace as schemas without data: enough to enumerate plans."""
    market = Marketplace({n: Instance(n, SimpleNamespace(columns=[*c, *_PRIVATE.get(n, [])]), PLANTED.get(n, ())) for n, c in _COLUMNS.items()})
    return G.JoinGraph(market, {((a, b), j): 0.0 for i, a in enumerate(market.names) for b in market.names[i + 1 :] for j in G.join_sets(market.common(a, b))})


def _table(name: str) -> str:
    return ("d_" if name in PLANTED else "i_") + name


def _plan_sql(plan: TargetGraph, request: Q.Request, fds: dict) -> tuple[str, str]:
    """(the join of a plan's projections, its row: label, edges, corr, quality, ji, price)."""
    projections, joins = plan.projections, plan.joins
    parts = {n: f"(SELECT {', '.join(f'{a} {n}__{a}' for a in sorted(p))} FROM {_table(n)})" for n, p in projections.items()}
    order = plan.order(plan.supply[0][1])
    join = f"{parts[order[0][0]]} t0"
    for k, (n, parent) in enumerate(order[1:], 1):
        join += f" JOIN {parts[n]} t{k} ON " + " AND ".join(f"{parent}__{a} = {n}__{a}" for a in joins[G.pair(n, parent)])
    x, y = request.sides
    inside = [fd for n in plan.instances for fd in fds.get(n, ()) if set(fd.attributes) <= projections[n]]
    held = [type(fd)(tuple(f"{n}__{a}" for a in fd.lhs), f"{n}__{fd.rhs}") for n in plan.instances for fd in inside if fd in fds.get(n, ())]
    name = "p_" + "_".join(sorted("".join(c for c in f"{a}{b}{''.join(j)}" if c.isalnum()) for (a, b), j in plan.edges))
    quality = sql_joint(name, held) if held else "1.0::DOUBLE"
    weight = " + ".join(sql_ji(_table(a), _table(b), j) for (a, b), j in joins.items()) or "0"
    price = " + ".join(sql_entropy(_table(n), sorted(p)) for n, p in projections.items())
    numeric = x[0] in ("c_acctbal", "o_totalprice")
    corr = sql_corr(name, plan.column(x[0]), [plan.column(a) for a in y], numeric)
    return f"{name} AS MATERIALIZED (SELECT * FROM {join})", f"SELECT '{plan.label()}' plan, {len(plan.edges)} edges, {corr} corr, {quality} quality, {weight} ji, {price} price FROM (SELECT 1)"


def _cases_sql(x: str) -> str:
    request, most, alpha = DIRTY[x]
    made = [_plan_sql(p, request, PLANTED) for p in Q.all_plans(_schema_graph(), request, most)]
    limits = {"free": "true", "alpha": f"ji <= {alpha}", "beta": f"quality >= {QUALITY}", **{f"r={r}": f"price <= {r} * (SELECT max(price) FROM plans) + 1e-9" for r in RATIOS}}
    rows = [f"SELECT '{name}' limits, CASE WHEN count(*) = 0 THEN NULL ELSE arg_max(plan, o) END plan, round(arg_max(corr, o), 4) corr, round(arg_max(quality, o), 6) quality, round(arg_max(ji, o), 6) ji, round(arg_max(price, o), 6) price FROM (SELECT *, {{'a': round(corr, 9), 'b': -edges, 'c': plan}} o FROM plans WHERE {test})" for name, test in limits.items()]
    return star_sql(rows_sql(rows), *dict.fromkeys(m[0] for m in made), f"plans AS MATERIALIZED ({rows_sql([m[1] for m in made])})")


def _row(name: str, plan: Q.Plan) -> tuple:
    s = plan.score
    return (name, plan.graph.label() if s else None, *(round(v, k) if s else None for v, k in (((s.corr, 4), (s.quality, 6), (s.weight, 6), (s.price, 6)) if s else ((None, 0),) * 4)))


def _dirty_graph(spark: SparkSession, d: str) -> G.JoinGraph:
    return G.build(star_marketplace(spark, d, planted=True, dirty=True))


def _exhaustive(spark: SparkSession, d: str, x: str) -> DataFrame:
    """Exhaustive search over the whole dirty marketplace: unlimited, under each limit, and at shares of the dearest plan's price."""
    request, most, alpha = DIRTY[x]
    graph = _dirty_graph(spark, d)
    evaluator = Q.Evaluator(graph, request)
    _, high = report.budget_range(graph, request, most)
    cases = {"free": request, "alpha": replace(request, alpha=alpha), "beta": replace(request, beta=QUALITY), **{f"r={r}": replace(request, budget=r * high) for r in RATIOS}}
    rows = []
    for name, now in cases.items():
        evaluator.request = now
        rows.append(_row(name, Q.exhaustive(graph, now, most, evaluator)))
    return spark.createDataFrame(rows, "limits string, plan string, corr double, quality double, ji double, price double")


def _three(spark: SparkSession, d: str, x: str) -> DataFrame:
    """Planner, exhaustive search on samples and on full data over the whole dirty marketplace: their answers on full data, and times."""
    request, most, _ = DIRTY[x]
    graph = _dirty_graph(spark, d)
    _, high = report.budget_range(graph, request, most)
    sampled = G.build(graph.market, 0.5)
    rows = []
    for r in (0.13, 1.0):
        for c in report.compare(graph, replace(request, budget=r * high), most, rate=0.5, iterations=20, sampled=sampled):
            rows.append((float(r), c["approach"], c["status"], c["plan"], c["size"], c["corr"], c["quality"], c["ji"], c["price"], c["cd"], c["seconds"]))
    return spark.createDataFrame(rows, "ratio double, approach string, status string, plan string, size int, corr double, quality double, ji double, price double, cd double, seconds double")


def _budgets(spark: SparkSession, d: str, x: str) -> DataFrame:
    """Real correlation of the three searches at shares of the dearest plan's price."""
    request, most, _ = DIRTY[x]
    graph, sampled = G.build_at(star_marketplace(spark, d, planted=True, dirty=True), [1.0, 0.5])
    rows = report.algorithms_by_budget(graph, request, (0.13, 0.85, 0.9, 0.95, 1.0), most, rate=0.5, sampled=sampled)
    return spark.createDataFrame([(float(r["ratio"]), r["approach"], r["status"], r["corr"], r["price"]) for r in rows], "ratio double, approach string, status string, corr double, price double")


def _resampled(spark: SparkSession, d: str, x: str) -> DataFrame:
    """Correlation with re-sampling of intermediate joins beyond a tenth of the whole, against without; the gap closes as the rate grows."""
    request, most, _ = DIRTY[x]
    graph = _dirty_graph(spark, d)
    plan = next(iter(sorted(Q.all_plans(graph, request, most), key=lambda p: (len(p.edges), p.label()))))
    rows = report.resample_sweep(graph, request, plan, (0.1, 0.3, 0.5, 0.7, 0.9, 1.0), 0.1)
    return spark.createDataFrame([(float(r["resample"]), r["corr"], r["corr_plain"], r["gap"], r["rows"]) for r in rows], "resample double, corr double, corr_plain double, gap double, rows long")


for _x in DIRTY:
    query(_cases_sql(_x), f"gp_dirty_{_x}")(lambda spark, d, x=_x: _exhaustive(spark, d, x))
    query(None, f"compare_dirty_{_x}")(lambda spark, d, x=_x: _three(spark, d, x))
    query(None, f"budget_algorithms_{_x}")(lambda spark, d, x=_x: _budgets(spark, d, x))
for _x in ("x2", "x3"):  # a plan of two instances has no intermediate join
    query(None, f"resample_sweep_{_x}")(lambda spark, d, x=_x: _resampled(spark, d, x))


@query(None)
def sampling_sweep_x1(spark: SparkSession, d: str) -> DataFrame:
    """Correlation difference of the planner and of exhaustive search on samples, at each sampling rate."""
    request, most, _ = DIRTY["x1"]
    market = star_marketplace(spark, d, planted=True, dirty=True)
    rows = report.sampling_sweep(market, request, (0.1, 0.5, 1.0), most, iterations=10)
    return spark.createDataFrame([(float(r["rate"]), r["approach"], r["status"], r["corr"], r["cd"]) for r in rows], "rate double, approach string, status string, corr double, cd double")


# ------------------------------------------------------------------------------------------ all 29 fragments

FRAGMENTS = {
    "x4": Q.Request(("o_totalprice",), ("c_mktsegment",)),
    "x5": Q.Request(("l_quantity",), ("r_name",)),
    "x6": Q.Request(("r_name",), ("p_brand", "ev_k")),
}
_PATH = ["ord_price", "ord_core", "cust_core", "cust_bal"]


def _searched(spark: SparkSession, d: str, x: str) -> DataFrame:
    """The planner over all 29 fragments: landmarks, light tree, the whole walk; joins of any size are scored."""
    graph = G.build(fragment_marketplace(spark, d))
    plan = Q.acquire(graph, FRAGMENTS[x], seed=2)
    s = plan.score
    row = (plan.status, plan.graph.label() if s else None, plan.igraph_size, s.corr if s else None, Decimal(s.join_rows) if s else None, plan.evaluated, plan.seconds)
    return spark.createDataFrame([row], "status string, plan string, igraph_size int, corr double, join_rows decimal(38,0), evaluated int, seconds double")


for _x in FRAGMENTS:
    query(None, f"acquire_m29_{_x}")(lambda spark, d, x=_x: _searched(spark, d, x))


@query(None)
def size_sweep_m29(spark: SparkSession, d: str) -> DataFrame:
    """The planner's time and plan size as the marketplace grows to all 29 fragments."""
    graph = G.build(fragment_marketplace(spark, d))
    rows = report.size_sweep(graph, FRAGMENTS["x4"], _PATH, (10, 15, 20, 25, 29), iterations=2)
    return spark.createDataFrame([(r["n"], r["status"], r["size"], r["seconds"], r["evaluated"]) for r in rows], "n int, status string, size int, seconds double, evaluated int")


@query(None)
def size_sweep_m8(spark: SparkSession, d: str) -> DataFrame:
    """Planner against exhaustive search as the dirty star marketplace grows from five instances to eight."""
    request, most, _ = DIRTY["x1"]
    rows = report.size_sweep(_dirty_graph(spark, d), request, ["customer", "orders", "nation", "region"], (5, 6, 7, 8), iterations=10, exact=True, max_vertices=most)
    return spark.createDataFrame([(r["n"], r["status"], r["size"], r["seconds"], r["evaluated"], r["seconds_exact"], r["evaluated_exact"]) for r in rows], "n int, status string, size int, seconds double, evaluated int, seconds_exact double, evaluated_exact int")


@query(None)
def budget_time_m29(spark: SparkSession, d: str) -> DataFrame:
    """The planner's time at shares of the dearest three-fragment plan's price; N/A where nothing can be paid."""
    graph = G.build(fragment_marketplace(spark, d))
    _, high = report.budget_range(graph, FRAGMENTS["x4"], 3)
    rows = report.planner_budget_sweep(graph, FRAGMENTS["x4"], (0.04, 0.12, 0.8, 0.9, 1.0), high, iterations=2)
    return spark.createDataFrame([(float(r["ratio"]), r["status"], r["size"], r["corr"], r["seconds"]) for r in rows], "ratio double, status string, size int, corr double, seconds double")
