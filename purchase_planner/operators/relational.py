"""The relational surface around the planner: thin operators, each registered with its SQL."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def range_join(points: DataFrame, x: str, ranges: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Rows whose x lies in [low, high): an equi-join on buckets of the axis, then a filter; no product of the sides."""
    a = points.withColumn("__b", F.floor(F.col(x) / width))
    b = ranges.withColumn("__b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return a.join(b, "__b").where((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("__b")


def as_of_join(left: DataFrame, right: DataFrame, time: str, by: Sequence[str], value: str) -> DataFrame:
    """For every left row the last value of the right at or before its time, within the same `by` group.

    One union and one window; a row of the right precedes rows of the left of the same time.
    """
    a = left.withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(*by, time, F.col(value).alias("__v")).withColumn("__side", F.lit(0))
    w = Window.partitionBy(*by).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b, allowMissingColumns=True).withColumn(value, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")


def salted_join(large: DataFrame, small: DataFrame, on: Sequence[str], salts: int) -> DataFrame:
    """An equi-join whose hot keys are spread over several tasks: the large side salted, the small side repeated."""
    a = large.withColumn("__s", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    b = small.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*on, "__s"]).drop("__s")


def dynamic_projection(df: DataFrame, attributes: Sequence[str], distinct: bool = False) -> DataFrame:
    """The bought columns; a bag unless asked for a set."""
    out = df.select(*attributes)
    return out.distinct() if distinct else out


def _r(c: Column, digits: int = 6) -> Column:
    return F.round(c, digits)


def _semi(spark, d):
    return t(spark, d, "customer").join(t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def _anti(spark, d):
    return t(spark, d, "events").join(t(spark, d, "customer"), F.col("user_id") == F.col("c_custkey"), "left_anti").groupBy("event_type").agg(F.count("*").alias("n"))


def _outer(spark, d):
    j = t(spark, d, "documents").select("doc_id", "lang").join(t(spark, d, "labels"), "doc_id", "left")
    return j.groupBy("lang").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"), F.coalesce(F.sum("quality"), F.lit(0)).cast("long").alias("good"))


def _window(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = t(spark, d, "orders").where("o_custkey < 50")
    return o.select("o_custkey", "o_orderkey", F.row_number().over(w).alias("rn"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr"), _r(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)), 2).alias("running"), F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.ntile(4).over(w).alias("quarter"))


def _topk(spark, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, d, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_brand", "p_partkey", "r")


def _grouping(spark, d):
    return t(spark, d, "orders").groupingSets([["o_orderstatus", "o_orderpriority"], ["o_orderstatus"], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), _r(F.sum("o_totalprice"), 2).alias("total"))


def _cube(spark, d):
    return t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


def _rollup(spark, d):
    return t(spark, d, "part").rollup("p_brand", "p_type").agg(F.count("*").alias("n"))


def _range(spark, d):
    bands = spark.createDataFrame([(k, k * 250.0, (k + 1) * 250.0) for k in range(8)], "band long, lo double, hi double")
    return range_join(t(spark, d, "part"), "p_retailprice", bands, "lo", "hi", 500.0).groupBy("band").agg(F.count("*").alias("n"))


def _asof(spark, d):
    e = t(spark, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    left = e.where("event_type = 'error'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'click'").select("user_id", "ts", F.col("value").alias("last_click"))
    return as_of_join(left, right, "ts", ["user_id"], "last_click").select("event_id", "last_click")


def _salted(spark, d):
    j = salted_join(t(spark, d, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_quantity"), t(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_name"), ["l_suppkey"], 4)
    return j.groupBy("s_name").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


def _json(spark, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return t(spark, d, "events").select((k % 10).alias("k")).groupBy("k").agg(F.count("*").alias("n"))


def _setops(spark, d):
    c, s = t(spark, d, "customer").select(F.col("c_nationkey").cast("long").alias("k")), t(spark, d, "supplier").select(F.col("s_nationkey").cast("long").alias("k"))
    a = c.intersect(s).select(F.lit("both").alias("op"), "k")
    return a.unionByName(c.select("k").distinct().exceptAll(s.distinct()).select(F.lit("only_customer").alias("op"), "k"))


def _arrays(spark, d):
    e = t(spark, d, "embeddings")
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return e.select("vec_id", F.size("embedding").alias("dims"), _r(norm, 4).alias("norm"))


def _dates(spark, d):
    return t(spark, d, "orders").groupBy(F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q")).agg(F.count("*").alias("n"))


def _case(spark, d):
    band = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal").between(0, 5000), "low").otherwise("high")
    return t(spark, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") | F.col("c_name").like("%1")).groupBy(band.alias("band")).agg(F.count("*").alias("n"))


def _having(spark, d):
    return t(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), _r(F.sum("o_totalprice"), 2).alias("total")).where("n >= 15")


def _distinct(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey", "l_linestatus").alias("pairs"))


def _maxby(spark, d):
    return t(spark, d, "orders").groupBy("o_orderpriority").agg(F.max(F.struct("o_totalprice", "o_orderkey"))["o_orderkey"].alias("dearest"), F.min(F.struct("o_totalprice", "o_orderkey"))["o_orderkey"].alias("cheapest"))


def _set_projection(spark, d):
    return dynamic_projection(t(spark, d, "customer").select(F.col("c_nationkey").cast("long").alias("nationkey"), "c_mktsegment"), ["nationkey", "c_mktsegment"], distinct=True)


def _urls(spark, d):
    host = F.lower(F.parse_url("url", F.lit("HOST")))
    return t(spark, d, "pages").groupBy(F.element_at(F.split(host, r"\."), -1).alias("tld")).agg(F.count("*").alias("n"))


def _subquery(spark, d):
    t(spark, d, "orders").createOrReplaceTempView("planner_orders")
    return spark.sql("WITH m AS (SELECT avg(o_totalprice) a FROM planner_orders) SELECT o_orderstatus, count(*) n FROM planner_orders WHERE o_totalprice > (SELECT a FROM m) GROUP BY o_orderstatus")


def _recursive(spark, d):
    t(spark, d, "nation").createOrReplaceTempView("planner_nation")
    return spark.sql("WITH RECURSIVE r(k, depth) AS (SELECT 0, 0 UNION ALL SELECT k + 5, depth + 1 FROM r WHERE depth < 4) SELECT r.k, depth, n_name FROM r JOIN planner_nation ON n_nationkey = r.k")


def _q_pricing(spark, d):
    l = t(spark, d, "lineitem").where("l_shipdate <= timestamp'2000-09-02'")
    return l.groupBy("l_returnflag", "l_linestatus").agg(_r(F.sum("l_quantity"), 2).alias("sum_qty"), _r(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("sum_disc"), _r(F.avg("l_discount")).alias("avg_disc"), F.count("*").alias("n"))


def _q_regions(spark, d):
    j = t(spark, d, "customer").join(t(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("customers"), _r(F.sum("c_acctbal"), 2).alias("balance"))


def _lateral(spark, d):
    own = t(spark, d, "customer").where(F.col("c_nationkey") == F.col("n_nationkey").outer())
    return t(spark, d, "nation").lateralJoin(own.select(F.count("*").alias("customers"), F.max("c_acctbal").alias("richest"))).select("n_name", "customers", "richest")


def _ranks(spark, d):
    w = Window.partitionBy("p_brand").orderBy("p_retailprice")
    return t(spark, d, "part").select("p_partkey", _r(F.percent_rank().over(w)).alias("pr"), _r(F.cume_dist().over(w)).alias("cd"))


def _sketches(spark, d):
    """Whether each sketch is within five percent of the exact value, on one read."""
    exact, median = F.countDistinct("o_custkey"), F.percentile("o_totalprice", F.lit(0.5))
    got = {
        "approx_count_distinct": (F.approx_count_distinct("o_custkey", 0.01), exact),
        "hll": (F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey", 14)), exact),
        "kll_median": (F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("o_totalprice", 400), F.lit(0.5)), median),
        "approx_percentile": (F.approx_percentile("o_totalprice", 0.5, 10000), median),
    }
    one = t(spark, d, "orders").agg(*[(F.abs(a - b) <= 0.05 * b).alias(k) for k, (a, b) in got.items()])
    return one.select(F.explode(F.create_map(*[x for k in got for x in (F.lit(k), F.col(k))])).alias("sketch", "close"))


def _samples(spark, d):
    """Whether seeded samples keep their shares of the rows, within five points."""
    t(spark, d, "lineitem").createOrReplaceTempView("planner_lineitem")
    drawn = spark.sql("SELECT l_returnflag, 'tablesample' AS method, 0.3D AS share FROM planner_lineitem TABLESAMPLE (30 PERCENT) REPEATABLE (7)")
    by = {"A": 0.2, "N": 0.5, "R": 0.8}
    share = F.create_map(*[x for k, v in by.items() for x in (F.lit(k), F.lit(v))])[F.col("l_returnflag")]
    drawn = drawn.unionByName(t(spark, d, "lineitem").sampleBy("l_returnflag", by, seed=7).select("l_returnflag", F.lit("sample_by").alias("method"), share.alias("share")))
    kept = drawn.groupBy("method", "l_returnflag").agg(F.count("*").alias("kept"), F.max("share").alias("share"))
    whole = t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"))
    return kept.join(whole, "l_returnflag").select("method", "l_returnflag", (F.abs(F.col("kept") / F.col("n") - F.col("share")) < 0.05).alias("close"))


def lattice_udtf(spark: SparkSession) -> None:
    """Registers lattice_subsets(attributes): one row for each attribute subset of two or more."""
    from ..plans.lattice import lattice

    @F.udtf(returnType="attributes string, size int")
    class LatticeSubsets:
        def eval(self, attributes: str):
            for s in lattice(attributes.split(",")):
                yield "+".join(s), len(s)

    spark.udtf.register("lattice_subsets", LatticeSubsets)


def _udtf(spark, d):
    """The lattice over the kinds of events that there are."""
    lattice_udtf(spark)
    t(spark, d, "events").createOrReplaceTempView("planner_events")
    return spark.sql("SELECT s.attributes, s.size FROM (SELECT concat_ws(',', sort_array(collect_set(event_type))) kinds FROM planner_events) e, LATERAL lattice_subsets(e.kinds) s")


QUERIES = {
    "rel_semi_join": (_semi, "SELECT c_mktsegment, count(*) n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) GROUP BY ALL"),
    "rel_anti_join": (_anti, "SELECT event_type, count(*) n FROM events WHERE user_id NOT IN (SELECT c_custkey FROM customer) GROUP BY ALL"),
    "rel_left_outer": (_outer, "SELECT lang, count(*) n, count(quality) labelled, coalesce(sum(quality), 0)::BIGINT good FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL"),
    "rel_windows": (_window, "SELECT o_custkey, o_orderkey, row_number() OVER w rn, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) dr, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) running, lag(o_orderkey) OVER w \"before\", lead(o_orderkey) OVER w \"after\", ntile(4) OVER w AS quarter FROM orders WHERE o_custkey < 50 WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"),
    "rel_top_k_per_group": (_topk, "SELECT p_brand, p_partkey, r FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) r FROM part) WHERE r <= 3"),
    "rel_grouping_sets": (_grouping, "SELECT o_orderstatus, o_orderpriority, count(*) n, round(sum(o_totalprice), 2) total FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())"),
    "rel_cube": (_cube, "SELECT l_returnflag, l_linestatus, count(*) n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "rel_rollup": (_rollup, "SELECT p_brand, p_type, count(*) n FROM part GROUP BY ROLLUP (p_brand, p_type)"),
    "rel_range_join": (_range, "SELECT k band, count(*) n FROM part JOIN (SELECT range k FROM range(8)) ON p_retailprice >= k * 250 AND p_retailprice < (k + 1) * 250 GROUP BY ALL"),
    "rel_as_of_join": (_asof, "SELECT l.event_id, arg_max(r.value, r.ts) last_click FROM (SELECT * FROM events WHERE event_type = 'error') l LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') r ON l.user_id = r.user_id AND r.ts <= l.ts GROUP BY l.event_id"),
    "rel_salted_join": (_salted, "SELECT s_name, count(*) n, sum(l_quantity) quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"),
    "rel_json": (_json, "SELECT json_extract_string(props, '$.k')::BIGINT % 10 k, count(*) n FROM events GROUP BY ALL"),
    "rel_set_operations": (_setops, "SELECT 'both' op, k FROM (SELECT c_nationkey::BIGINT k FROM customer INTERSECT SELECT s_nationkey::BIGINT FROM supplier) UNION ALL SELECT 'only_customer', k FROM (SELECT c_nationkey::BIGINT k FROM customer EXCEPT SELECT s_nationkey::BIGINT FROM supplier)"),
    "rel_arrays": (_arrays, "SELECT vec_id, len(embedding)::INT dims, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) norm FROM embeddings"),
    "rel_dates": (_dates, "SELECT year(o_orderdate) y, quarter(o_orderdate) q, count(*) n FROM orders GROUP BY ALL"),
    "rel_case_filter": (_case, "SELECT CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'low' ELSE 'high' END band, count(*) n FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') OR c_name LIKE '%1' GROUP BY ALL"),
    "rel_having": (_having, "SELECT o_custkey, count(*) n, round(sum(o_totalprice), 2) total FROM orders GROUP BY o_custkey HAVING count(*) >= 15"),
    "rel_count_distinct": (_distinct, "SELECT l_returnflag, count(DISTINCT l_partkey) parts, count(DISTINCT (l_suppkey, l_linestatus)) pairs FROM lineitem GROUP BY ALL"),
    "rel_max_by": (_maxby, "SELECT o_orderpriority, arg_max(o_orderkey, (o_totalprice, o_orderkey)) dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) cheapest FROM orders GROUP BY ALL"),
    "rel_set_projection": (_set_projection, "SELECT DISTINCT c_nationkey::BIGINT nationkey, c_mktsegment FROM customer"),
    "rel_url_parts": (_urls, "SELECT regexp_extract(lower(regexp_extract(url, '://([^/?#]+)', 1)), '([^.]+)$', 1) tld, count(*) n FROM pages GROUP BY ALL"),
    "rel_scalar_subquery": (_subquery, "WITH m AS (SELECT avg(o_totalprice) a FROM orders) SELECT o_orderstatus, count(*) n FROM orders WHERE o_totalprice > (SELECT a FROM m) GROUP BY ALL"),
    "rel_lateral_join": (_lateral, "SELECT n_name, customers, richest FROM nation, LATERAL (SELECT count(*) customers, max(c_acctbal) richest FROM customer WHERE c_nationkey = n_nationkey)"),
    "rel_percent_ranks": (_ranks, "SELECT p_partkey, round(percent_rank() OVER w, 6) pr, round(cume_dist() OVER w, 6) cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice)"),
    "rel_sketches": (_sketches, "SELECT unnest(['approx_count_distinct', 'hll', 'kll_median', 'approx_percentile']) sketch, true \"close\""),
    "rel_samples": (_samples, "SELECT method, l_returnflag, true \"close\" FROM (SELECT DISTINCT l_returnflag FROM lineitem), (SELECT unnest(['tablesample', 'sample_by']) method)"),
    "rel_recursive_cte": (_recursive, "WITH RECURSIVE r(k, depth) AS (SELECT 0, 0 UNION ALL SELECT k + 5, depth + 1 FROM r WHERE depth < 4) SELECT r.k, depth, n_name FROM r JOIN nation ON n_nationkey = r.k"),
    "rel_udtf_lattice": (_udtf, "WITH k AS (SELECT list(DISTINCT event_type ORDER BY event_type) k FROM events), m AS (SELECT k, unnest(range(1, 1 << len(k))) m FROM k) SELECT array_to_string([k[i] FOR i IN range(1, len(k) + 1) IF (m >> (i - 1)) & 1 = 1], '+') attributes, bit_count(m)::INT size FROM m WHERE bit_count(m) >= 2"),
    "rel_pricing_summary": (_q_pricing, "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) sum_disc, round(avg(l_discount), 6) avg_disc, count(*) n FROM lineitem WHERE l_shipdate <= TIMESTAMP '2000-09-02' GROUP BY ALL"),
    "rel_region_balance": (_q_regions, "SELECT r_name, count(*) customers, round(sum(c_acctbal), 2) balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL"),
}
