"""Registered queries of the SQL surface and of the optional variants; the oracles are those of the DataFrame measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import sqltext as T
from .plans import joingraph as G
from .plans import lattice as L
from .plans import request as Q
from .plans import variants as V
from .queries import PRICED, query, rounded, rows_sql, sql_corr, sql_entropy, sql_ji, sql_quality, star_sql
from .sources.marketplace import PLANTED, star_marketplace, star_tables


def _viewed(spark: SparkSession, d: str, name: str, text: str, dirty: bool = False) -> DataFrame:
    for n, df in star_tables(spark, d, dirty=dirty).items():
        df.createOrReplaceTempView(f"star_{n}")
    T.create_view(spark, name, text)
    return rounded(spark.table(name))


@query(star_sql(f"SELECT round({sql_quality('d_part', PLANTED['part'][0])}, 6) quality"))
def sql_fd_quality(spark: SparkSession, d: str) -> DataFrame:
    return _viewed(spark, d, "fd_quality_part", T.fd_quality_sql("star_part", PLANTED["part"][0]), dirty=True)


@query(star_sql(f"SELECT round({sql_ji('i_customer', 'i_orders', ['custkey', 'xj_g'])}, 6) ji, (SELECT count(*)::DOUBLE FROM i_customer JOIN i_orders USING (custkey, xj_g)) join_rows"))
def sql_join_info(spark: SparkSession, d: str) -> DataFrame:
    return _viewed(spark, d, "join_info_customer_orders", T.informativeness_sql("star_customer", "star_orders", ["custkey", "xj_g"]))


@query(star_sql(f"SELECT round({sql_corr('i_part', 'p_brand', ['p_type', 'p_size'], False)}, 6) corr"))
def sql_corr_gain(spark: SparkSession, d: str) -> DataFrame:
    return _viewed(spark, d, "corr_gain_part", T.correlation_sql("star_part", ["p_brand"], ["p_type", "p_size"]))


STRENGTHS = [("customer", "orders", ("custkey",)), ("customer", "orders", ("custkey", "xj_g")), ("nation", "supplier", ("nationkey",)), ("partsupp", "supplier", ("suppkey",)), ("customer", "supplier", ("xj_h",))]


@query(star_sql(rows_sql([f"SELECT '{a}' src, '{b}' dst, '{'+'.join(j)}' j, n join_rows, round(n / ((SELECT count(*) FROM i_{a}) * (SELECT count(*) FROM i_{b})::DOUBLE), 12) strength FROM (SELECT count(*)::DOUBLE n FROM i_{a} JOIN i_{b} USING ({', '.join(j)}))" for a, b, j in STRENGTHS])))
def join_strengths(spark: SparkSession, d: str) -> DataFrame:
    """Optional variant: join sizes over products of sizes."""
    t = star_tables(spark, d)
    out = None
    for a, b, j in STRENGTHS:
        one = V.join_strength_df(t[a], t[b], j).select(F.lit(a).alias("src"), F.lit(b).alias("dst"), F.lit("+".join(j)).alias("j"), "join_rows", "strength")
        out = one if out is None else out.unionByName(one)
    return rounded(out, 12)


def _priced_sql(price: str) -> str:
    sets = rows_sql([f"SELECT '{'+'.join(s)}' attributes, round({sql_entropy('i_customer', s)}, 9) h, {len(s)} size" for s in L.lattice(PRICED, 1)])
    return f"SELECT a.attributes FROM (SELECT *, {price} p FROM ({sets})) a WHERE EXISTS (SELECT 1 FROM (SELECT *, {price} p FROM ({sets})) b WHERE b.h < a.h AND b.p > a.p + 1e-9)"


@query(star_sql(_priced_sql("2 * h + 1")))
def arbitrage_by_entropy(spark: SparkSession, d: str) -> DataFrame:
    """Optional variant: prices that rise with entropy leave nothing to be had by arbitrage."""
    priced = G.vertex_prices(star_tables(spark, d)["customer"], PRICED)
    return V.arbitrage(priced.select("attributes", F.col("price").alias("entropy"), (2 * F.round("price", 9) + 1).alias("price"))).select("attributes")


@query(star_sql(_priced_sql("size")))
def arbitrage_by_width(spark: SparkSession, d: str) -> DataFrame:
    """Optional variant: prices by the number of attributes do."""
    priced = G.vertex_prices(star_tables(spark, d)["customer"], PRICED)
    return V.arbitrage(priced.select("attributes", F.col("price").alias("entropy"), F.size(F.split("attributes", r"\+")).cast("double").alias("price"))).select("attributes")


def _routes(spark: SparkSession, d: str):
    market = star_marketplace(spark, d, dirty=True).restricted(["nation", "customer", "orders"])
    schemas = {n: market[n].attributes for n in market.names}
    return market, schemas, V.RouteObjective(market)


@query(None)
def variant_routes(spark: SparkSession, d: str) -> DataFrame:
    """Optional variants: the routes of the all-pairs table, of the greedy search and of the whole enumeration, with their objectives."""
    _, schemas, objective = _routes(spark, d)
    ends = ("n_name", "o_orderpriority")
    found = {"all_pairs": V.dp_allpairs(schemas, *ends, objective), "greedy": V.greedy_hop(schemas, *ends, objective), "enumerated": max(sorted(V.all_routes(schemas, *ends)), key=objective, default=None)}
    rows = [(k, " > ".join(f"{h.instance}({h.enters}, {h.leaves})" for h in r) if r else None, round(objective(r), 9) if r else None) for k, r in found.items()]
    return spark.createDataFrame(rows, "search string, route string, objective double")


@query(None)
def variant_hop_sketch(spark: SparkSession, d: str) -> DataFrame:
    """Optional variant: fewest hops by landmarks, then the join sets of best quality and strength."""
    market, _, objective = _routes(spark, d)
    graph = G.build(market)
    x, y = ("n_name", "nation"), ("o_orderpriority", "orders")

    def value(plan) -> float:
        row = V.score_row(market, plan, (x[0],), (y[0],))
        return V.scalar_objective(row["quality"] if row["quality"] is not None else 0.0, objective.strength(plan.instances, row["join_rows"]))

    plan = V.hop_sketch(graph, x, y, value)
    return spark.createDataFrame([(plan.label() if plan else None, len(plan.instances) if plan else 0)], "plan string, instances int")


@query(None)
def variant_walks(spark: SparkSession, d: str) -> DataFrame:
    """Optional variants: a walk by quality ratios towards quality and strength, and one directed by the limit that is broken."""
    market, _, objective = _routes(spark, d)
    graph = G.build(market)
    tree = frozenset({G.pair("customer", "nation"), G.pair("customer", "orders")})
    start = Q.initial(graph, tree, {"n_name": "nation", "o_orderpriority": "orders"})
    found = {}
    free = Q.Evaluator(graph, Q.Request(("n_name",), ("o_orderpriority",)))
    found["by_quality"] = V.quality_walk(free, start, lambda p: V.scalar_objective(free.score(p).quality, objective.strength(p.instances, free.score(p).join_rows)), 20, 5)
    states = [start] + [V.TargetGraph.of({**dict(start.edges), e: j}, dict(start.supply)) for e, _ in start.edges for j in graph.choices(*e)]
    prices = [free.static(p)[0] for p in states]
    bound = Q.Evaluator(graph, Q.Request(("n_name",), ("o_orderpriority",), budget=(min(prices) + max(prices)) / 2), memo=free.memo)
    found["directed"] = V.directed_walk(bound, states[prices.index(max(prices))], 20, 5)
    return spark.createDataFrame([(k, p.label() if p else None, round(free.score(p).corr, 9) if p else None) for k, p in found.items()], "walk string, plan string, corr double")
