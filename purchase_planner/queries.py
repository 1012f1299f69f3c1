"""The registered queries of the planner: each is (spark, sf_dir) -> DataFrame, with DuckDB SQL beside it where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import measures as M
from .functions.measures import FD
from .operators import relational as R
from .operators import sampling as S
from .plans import joingraph as G
from .plans import lattice as L
from .plans import report
from .plans import request as Q
from .plans import steiner
from .plans.evaluate import TargetGraph, plan_to_df
from .sources import examples
from .sources.marketplace import PLANTED, Marketplace, fragment_marketplace, star_marketplace, star_tables
from .streaming import live

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return put


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(F.col(c), digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# ------------------------------------------------------------------------------------- the fixtures in SQL


def _u32(s: str) -> str:
    return f"('0x' || substr(md5({s}), 1, 8))::BIGINT"


def _dirty(pk: str, v: str, d: int) -> str:
    return f"CASE WHEN {_u32(f'{pk} || chr(100) || chr(105) || chr(114) || chr(116)')} < {int(0.3 * 2**32)} THEN ({v} + 1 + {_u32(f'{pk} || chr(97) || chr(108) || chr(116)')} % {d - 1}) % {d} ELSE {v} END"


STAR = f"""
i_region AS (SELECT r_regionkey::BIGINT regionkey, r_name FROM region),
i_nation AS (SELECT n_nationkey::BIGINT nationkey, n_name, n_regionkey::BIGINT regionkey FROM nation),
i_customer AS (SELECT c_custkey custkey, c_name, c_nationkey::BIGINT nationkey, c_acctbal, c_mktsegment, {_u32("c_custkey::VARCHAR || 'g'")} % 120 xj_g, {_u32("c_custkey::VARCHAR || 'h'")} % 30 xj_h FROM customer),
i_supplier AS (SELECT s_suppkey suppkey, s_name, s_nationkey::BIGINT nationkey, s_acctbal, {_u32("s_suppkey::VARCHAR || 'e'")} % 40 xj_e, {_u32("s_suppkey::VARCHAR || 'f'")} % 40 xj_f, {_u32("s_suppkey::VARCHAR || 'h'")} % 25 xj_h FROM supplier),
i_part AS (SELECT p_partkey partkey, p_name, p_brand, p_type, p_size::BIGINT p_size, p_retailprice FROM part),
i_orders AS (SELECT o_orderkey orderkey, o_custkey custkey, o_orderstatus, o_totalprice, o_orderdate, o_orderpriority, {_u32("o_custkey::VARCHAR || 'g'")} % 150 xj_g FROM orders),
i_lineitem AS (SELECT l_orderkey orderkey, l_partkey partkey, l_suppkey suppkey, l_linenumber::BIGINT linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate, {_u32("l_suppkey::VARCHAR || 'f'")} % 60 xj_f FROM lineitem),
i_partsupp AS (SELECT partkey, suppkey, sum(l_quantity) ps_availqty, any_value({_u32("suppkey::VARCHAR || 'e'")} % 50) xj_e FROM i_lineitem GROUP BY partkey, suppkey),
d_customer AS (SELECT c.*, {_dirty("custkey::VARCHAR", "regionkey", 5)} c_regionkey FROM i_customer c JOIN i_nation USING (nationkey)),
d_supplier AS (SELECT s.*, {_dirty("suppkey::VARCHAR", "regionkey", 5)} s_regionkey FROM i_supplier s JOIN i_nation USING (nationkey)),
d_part AS (SELECT p.*, {_dirty("partkey::VARCHAR", "(regexp_extract(p_brand, '([0-9]+)', 1)::BIGINT % 5)", 5)} p_mfgr FROM i_part p),
d_orders AS (SELECT o.*, {_dirty("orderkey::VARCHAR", "(year(o_orderdate) - 1995)", 7)} o_year FROM i_orders o),
d_lineitem AS (SELECT l.*, {_dirty("(orderkey || chr(45) || linenumber || chr(45) || partkey || chr(45) || suppkey)", "(year(l_shipdate) - 1995)", 7)} l_shipyear FROM i_lineitem l),
d_partsupp AS (SELECT p.*, {_dirty("(partkey || chr(45) || suppkey)", "nationkey", 25)} ps_nation FROM i_partsupp p JOIN (SELECT suppkey, nationkey FROM i_supplier) USING (suppkey))
"""


def star_sql(body: str, *more: str) -> str:
    return "WITH RECURSIVE " + ",\n".join([STAR.strip(), *more]) + "\n" + body


def sql_quality(table: str, fd: FD) -> str:
    x = ", ".join(fd.lhs)
    return f"(SELECT sum(m) / sum(n) FROM (SELECT max(c) m, sum(c)::DOUBLE n FROM (SELECT {x}, {fd.rhs}, count(*) c FROM {table} GROUP BY ALL) GROUP BY {x}))"


def sql_entropy(source: str, x: Sequence[str]) -> str:
    return f"(SELECT log2(sum(c)) - sum(c * log2(c)) / sum(c) FROM (SELECT count(*)::DOUBLE c FROM {source} GROUP BY {', '.join(x)}))"


def sql_cumulative(source: str, x: str, y: Sequence[str] = ()) -> str:
    by = f"PARTITION BY {', '.join(y)}" if y else ""
    keys = "".join(f"{k}, " for k in y)
    return f"""(SELECT coalesce(sum(g), 0) FROM (SELECT -(lead(v) OVER (w) - v) * f * log2(f) * n / t g FROM (
SELECT {keys}v, sum(c) OVER ({by} ORDER BY v)::DOUBLE / sum(c) OVER ({by}) f, sum(c) OVER ({by})::DOUBLE n, sum(c) OVER ()::DOUBLE t
FROM (SELECT {keys}{x} v, count(*) c FROM {source} GROUP BY ALL)) WINDOW w AS ({by} ORDER BY v)))"""


def sql_corr(source: str, x: str, y: Sequence[str], numeric: bool) -> str:
    if numeric:
        return f"({sql_cumulative(source, x)} - {sql_cumulative(source, x, y)})"
    return f"({sql_entropy(source, [x])} + {sql_entropy(source, y)} - {sql_entropy(source, [x, *y])})"


def sql_ji(left: str, right: str, join: Sequence[str]) -> str:
    """By definition, over the full outer join of the keys collapsed to counts."""
    keys = ", ".join(join)
    on = " AND ".join(f"a.{k} = b.{k}" for k in join)
    some = join[0]
    pairs = f"SELECT a.{some} IS NULL nl, b.{some} IS NULL nr, coalesce(a.c, 1) * coalesce(b.c, 1)::DOUBLE w FROM (SELECT {keys}, count(*) c FROM {left} GROUP BY ALL) a FULL OUTER JOIN (SELECT {keys}, count(*) c FROM {right} GROUP BY ALL) b ON {on}"
    return f"""(SELECT CASE WHEN hp > 1e-12 THEN greatest(0, least(1, (2 * hp - hl - hr) / hp)) ELSE 0 END FROM (SELECT log2(n) - s / n hp,
log2(n) - (s - sr + CASE WHEN r > 0 THEN r * log2(r) ELSE 0 END) / n hl, log2(n) - (s - sl + CASE WHEN l > 0 THEN l * log2(l) ELSE 0 END) / n hr
FROM (SELECT sum(w) n, sum(w * log2(w)) s, coalesce(sum(w * log2(w)) FILTER (nl), 0) sr, coalesce(sum(w * log2(w)) FILTER (nr), 0) sl, coalesce(sum(w) FILTER (nl), 0) r, coalesce(sum(w) FILTER (nr), 0) l FROM ({pairs}))))"""


def rows_sql(rows: Sequence[str]) -> str:
    return "\nUNION ALL\n".join(rows)


# ------------------------------------------------------------------------------------------ quality measures

PLANTED_ORDER = sorted(PLANTED)


@query(star_sql("SELECT o_orderstatus, o_orderpriority, count(*) size FROM i_orders GROUP BY ALL"))
def class_sizes_orders(spark: SparkSession, d: str) -> DataFrame:
    return M.class_sizes(star_tables(spark, d)["orders"], ["o_orderstatus", "o_orderpriority"])


@query(star_sql("SELECT p_brand, p_mfgr::BIGINT p_mfgr, c correct_size, n::BIGINT class_size FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY c DESC, p_mfgr) r, sum(c) OVER (PARTITION BY p_brand) n FROM (SELECT p_brand, p_mfgr, count(*) c FROM d_part GROUP BY ALL)) WHERE r = 1"))
def dominant_classes_part(spark: SparkSession, d: str) -> DataFrame:
    return M.dominant_classes(star_tables(spark, d, dirty=True)["part"], PLANTED["part"][0])


@query(star_sql("SELECT partkey, p_brand, p_mfgr::BIGINT p_mfgr FROM d_part JOIN (SELECT p_brand, p_mfgr FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY c DESC, p_mfgr) r FROM (SELECT p_brand, p_mfgr, count(*) c FROM d_part GROUP BY ALL)) WHERE r = 1) USING (p_brand, p_mfgr)"))
def correct_rows_part(spark: SparkSession, d: str) -> DataFrame:
    return M.correct_rows(star_tables(spark, d, dirty=True)["part"], PLANTED["part"][0]).select("partkey", "p_brand", "p_mfgr")


@query(star_sql(rows_sql([f"SELECT '{n}' instance, '{PLANTED[n][0]}' fd, round({sql_quality('d_' + n, PLANTED[n][0])}, 6) quality" for n in PLANTED_ORDER])))
def fd_quality_planted(spark: SparkSession, d: str) -> DataFrame:
    t = star_tables(spark, d, dirty=True)
    out = None
    for n in PLANTED_ORDER:
        one = M.qualities_df(t[n], PLANTED[n]).select(F.lit(n).alias("instance"), "fd", "quality")
        out = one if out is None else out.unionByName(one)
    return rounded(out)


PART_FDS = [FD(("p_brand",), "p_mfgr"), FD(("p_brand",), "p_type"), FD(("p_type",), "p_mfgr")]


def sql_joint(table: str, fds: Sequence[FD]) -> str:
    flags = []
    source = f"SELECT *, row_number() OVER () rid FROM {table}"
    for k, fd in enumerate(fds):
        keys = " AND ".join(f"t.{a} IS NOT DISTINCT FROM m{k}.{a}" for a in fd.attributes)
        x = ", ".join(fd.lhs)
        best = f"(SELECT {x}, {fd.rhs} FROM (SELECT *, row_number() OVER (PARTITION BY {x} ORDER BY c DESC, {fd.rhs}) r FROM (SELECT {x}, {fd.rhs}, count(*) c FROM {table} GROUP BY ALL)) WHERE r = 1)"
        flags.append(f"LEFT JOIN (SELECT *, true ok{k} FROM {best}) m{k} ON {keys}")
    all_ok = " AND ".join(f"coalesce(ok{k}, false)" for k in range(len(fds)))
    return f"(SELECT avg(CASE WHEN {all_ok} THEN 1.0 ELSE 0.0 END) FROM ({source}) t {' '.join(flags)})"


@query(star_sql(f"SELECT round({sql_joint('d_part', PART_FDS)}, 6) quality"))
def joint_quality_part(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.joint_quality_df(star_tables(spark, d, dirty=True)["part"], PART_FDS))


JOINED_FDS = [FD(("nationkey",), "c_regionkey"), FD(("nationkey",), "s_regionkey")]


@query(star_sql(f"SELECT 'dirty' kind, round({sql_joint('j', JOINED_FDS)}, 6) quality, round({sql_quality('j', JOINED_FDS[0])}, 6) first, round({sql_quality('j', JOINED_FDS[1])}, 6) other", "j AS (SELECT nationkey, c_regionkey, s_regionkey FROM d_customer JOIN (SELECT nationkey, s_regionkey FROM d_supplier) USING (nationkey))"))
def join_quality_customer_supplier(spark: SparkSession, d: str) -> DataFrame:
    """Quality of a join result, jointly and singly, with eager aggregation below the join."""
    t = star_tables(spark, d, dirty=True)
    a = M.counted(t["customer"], ["nationkey", "c_regionkey"])
    b = M.counted(t["supplier"], ["nationkey", "s_regionkey"]).withColumnRenamed(M.W, "v")
    j = a.join(b, "nationkey").withColumn(M.W, F.col(M.W) * F.col("v")).drop("v")
    one = M.joint_quality_df(j, JOINED_FDS, M.W)
    one = one.crossJoin(M.fd_quality_df(j, JOINED_FDS[0], M.W).toDF("first")).crossJoin(M.fd_quality_df(j, JOINED_FDS[1], M.W).toDF("other"))
    return rounded(one.select(F.lit("dirty").alias("kind"), "*"))


def _quality_plan() -> TargetGraph:
    return TargetGraph.of({("customer", "orders"): ["custkey"]}, {"c_regionkey": "customer", "nationkey": "customer", "o_year": "orders", "o_orderdate": "orders"})


_XQ = [FD(("nationkey",), "c_regionkey"), FD(("o_orderdate",), "o_year")]
for _kind, _tables in (("clean", ("i_customer_p", "i_orders_p")), ("dirty", ("d_customer", "d_orders"))):

    def _join_quality(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        m = star_marketplace(spark, d, planted=True, dirty=kind == "dirty")
        fds = [FD(("customer__nationkey",), "customer__c_regionkey"), FD(("orders__o_orderdate",), "orders__o_year")]
        frame = plan_to_df(m, _quality_plan(), [a for fd in fds for a in fd.attributes])
        return rounded(M.joint_quality_df(frame, fds, M.W))

    query(
        star_sql(
            f"SELECT round({sql_joint('j', _XQ)}, 6) quality",
            "i_customer_p AS (SELECT c.*, regionkey c_regionkey FROM i_customer c JOIN i_nation USING (nationkey))",
            "i_orders_p AS (SELECT o.*, year(o_orderdate) - 1995 o_year FROM i_orders o)",
            f"j AS (SELECT nationkey, c_regionkey, o_orderdate, o_year FROM (SELECT custkey, nationkey, c_regionkey FROM {_tables[0]}) JOIN (SELECT custkey, o_orderdate, o_year FROM {_tables[1]}) USING (custkey))",
        ),
        f"join_quality_x1_{_kind}",
    )(_join_quality)


@query(star_sql("SELECT * FROM (" + rows_sql([f"SELECT '{PLANTED[n][0]}' fd, round({sql_quality('d_' + n, PLANTED[n][0])}, 6) quality" for n in PLANTED_ORDER]) + ") WHERE quality >= 0.7"))
def holds_theta(spark: SparkSession, d: str) -> DataFrame:
    """Dependencies kept at a threshold of 0.7."""
    return fd_quality_planted(spark, d).select("fd", "quality").where("quality >= 0.7")


PART_ATTRIBUTES = ["p_brand", "p_type", "p_size", "p_mfgr"]


def _afd_sql(table: str, attributes: Sequence[str], theta: float) -> str:
    from itertools import combinations

    single = [FD((x,), y) for x in attributes for y in attributes if x != y]
    double = [FD(x, y) for x in combinations(attributes, 2) for y in attributes if y not in x]
    rows = rows_sql([f"SELECT '{','.join(fd.lhs)}' lhs, '{fd.rhs}' rhs, {len(fd.lhs)} k, {sql_quality(table, fd)} q" for fd in [*single, *double]])
    return f"SELECT lhs, rhs, round(q, 6) quality FROM ({rows}) a WHERE q >= {theta} AND (k = 1 OR NOT EXISTS (SELECT 1 FROM ({rows}) b WHERE b.k = 1 AND b.rhs = a.rhs AND b.q >= {theta} AND list_contains(string_split(a.lhs, ','), b.lhs)))"


@query(star_sql(_afd_sql("d_part", PART_ATTRIBUTES, 0.4)))
def afd_levelwise_part(spark: SparkSession, d: str) -> DataFrame:
    """Minimal approximate dependencies of the dirty part table at a quality of 0.4."""
    found = M.discover_afds(star_tables(spark, d, dirty=True)["part"], PART_ATTRIBUTES, 2, 0.4)
    rows = [(",".join(fd.lhs), fd.rhs, round(q, 6)) for fd, q in found]
    return spark.createDataFrame(rows, "lhs string, rhs string, quality double")


_COUNTED = {"region": ["regionkey", "r_name"], "nation": ["nationkey", "n_name", "regionkey"], "part": PART_ATTRIBUTES, "supplier": ["suppkey", "nationkey", "s_regionkey"], "orders": ["o_orderstatus", "o_orderpriority", "o_year"]}


@query(star_sql(rows_sql([f"SELECT '{n}' instance, count(*) fds FROM ({_afd_sql(('d_' if n in PLANTED else 'i_') + n, a, 0.9)})" for n, a in sorted(_COUNTED.items())])))
def afd_counts_by_table(spark: SparkSession, d: str) -> DataFrame:
    """How many dependencies with at most 10 % violations each table has."""
    t = star_tables(spark, d, dirty=True)
    return spark.createDataFrame([(n, len(M.discover_afds(t[n], a, 2, 0.9))) for n, a in sorted(_COUNTED.items())], "instance string, fds long")


@query(star_sql(f"""SELECT round({sql_joint('j', JOINED_FDS)}, 6) quality_of_join, round((SELECT avg(CASE WHEN c.nationkey IS NOT NULL THEN 1.0 ELSE 0.0 END) FROM d_customer LEFT JOIN cc c USING (custkey)), 6) clean_share, (SELECT count(*) FROM cc JOIN sc ON cc.nationkey = sc.nationkey) cleaned_rows, round({sql_joint('jc', JOINED_FDS)}, 6) quality_after""",
    "j AS (SELECT nationkey, c_regionkey, s_regionkey FROM d_customer JOIN (SELECT nationkey, s_regionkey FROM d_supplier) USING (nationkey))",
    *[f"{s}c AS (SELECT t.* FROM d_{n} t JOIN (SELECT nationkey, {s}_regionkey FROM (SELECT *, row_number() OVER (PARTITION BY nationkey ORDER BY c DESC, {s}_regionkey) r FROM (SELECT nationkey, {s}_regionkey, count(*) c FROM d_{n} GROUP BY ALL)) WHERE r = 1) USING (nationkey, {s}_regionkey))" for s, n in (("c", "customer"), ("s", "supplier"))],
    "jc AS (SELECT nationkey, c_regionkey, s_regionkey FROM cc JOIN (SELECT nationkey, s_regionkey FROM sc) USING (nationkey))"))
def clean_then_join(spark: SparkSession, d: str) -> DataFrame:
    """Baseline: clean each table, then join; it drops rows that the quality of the join would judge."""
    t = star_tables(spark, d, dirty=True)
    c, s = t["customer"], t["supplier"]
    cc, sc = M.correct_rows(c, JOINED_FDS[0]), M.correct_rows(s, JOINED_FDS[1])

    def joined(a: DataFrame, b: DataFrame) -> DataFrame:
        return a.select("nationkey", "c_regionkey").join(b.select("nationkey", "s_regionkey"), "nationkey")

    one = M.joint_quality_df(joined(c, s), JOINED_FDS).toDF("quality_of_join")
    kept = c.agg(F.count("*").alias("n")).crossJoin(cc.agg(F.count("*").alias("m"))).select((F.col("m") / F.col("n")).alias("clean_share"))
    after = joined(cc, sc)
    return rounded(one.crossJoin(kept).crossJoin(after.agg(F.count("*").alias("cleaned_rows"))).crossJoin(M.joint_quality_df(after, JOINED_FDS).toDF("quality_after")))


# ------------------------------------------------------------------------------------------ informativeness

#: Columns of the star instances as the SQL fixtures name them.
_COLUMNS = {
    "region": ["regionkey"], "nation": ["nationkey", "regionkey"], "customer": ["custkey", "nationkey", "xj_g", "xj_h"], "supplier": ["suppkey", "nationkey", "xj_e", "xj_f", "xj_h"],
    "part": ["partkey"], "partsupp": ["partkey", "suppkey", "xj_e"], "orders": ["orderkey", "custkey", "xj_g"], "lineitem": ["orderkey", "linenumber", "partkey", "suppkey", "xj_f"],
}


def _edge_list() -> list[tuple[str, str, tuple[str, ...]]]:
    names = sorted(_COLUMNS)
    return [(a, b, j) for i, a in enumerate(names) for b in names[i + 1 :] for j in G.join_sets([c for c in _COLUMNS[a] if c in _COLUMNS[b]])]


_AS_EDGES = rows_sql([f"SELECT '{a}' src, '{b}' dst, '{'+'.join(j)}' j, round({sql_ji('i_' + a, 'i_' + b, j)}, 6) weight" for a, b, j in _edge_list()])


@query(star_sql(_AS_EDGES))
def as_edges(spark: SparkSession, d: str) -> DataFrame:
    """Weights of all pairs and join sets of the star marketplace: the off-line phase."""
    return rounded(G.edge_weights(star_marketplace(spark, d)).select("src", "dst", F.concat_ws("+", "j").alias("j"), "weight"))


@query(star_sql(f"SELECT src, dst, weight, j FROM (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY round(weight, 9), len(string_split(j, '+')), replace(j, '+', ',')) r FROM ({_AS_EDGES})) WHERE r = 1"))
def i_edge_min_weight(spark: SparkSession, d: str) -> DataFrame:
    return rounded(G.min_edge_weight(G.edge_weights(star_marketplace(spark, d))).select("src", "dst", "weight", F.concat_ws("+", "j").alias("j")))


@query(star_sql(f"SELECT a.src, a.dst, a.j small, b.j large, sign(round(b.weight - a.weight, 6))::INT moves FROM ({_AS_EDGES}) a JOIN ({_AS_EDGES}) b ON a.src = b.src AND a.dst = b.dst AND len(string_split(a.j, '+')) < len(string_split(b.j, '+')) AND list_has_all(string_split(b.j, '+'), string_split(a.j, '+'))"))
def weights_not_monotone(spark: SparkSession, d: str) -> DataFrame:
    moves = G.check_monotone(G.edge_weights(star_marketplace(spark, d)))
    return moves.select("src", "dst", F.concat_ws("+", "small").alias("small"), F.concat_ws("+", "large").alias("large"), F.signum(F.round(F.round("weight_large", 6) - F.round("weight_small", 6), 6)).cast("int").alias("moves"))


_SCHEMAS = rows_sql([f"SELECT '{n}' instance, unnest({list(_COLUMNS[n])}) attribute" for n in sorted(_COLUMNS)])


@query(f"SELECT a.instance src, b.instance dst, string_agg(a.attribute, '+' ORDER BY a.attribute) common FROM ({_SCHEMAS}) a JOIN ({_SCHEMAS}) b ON a.attribute = b.attribute AND a.instance < b.instance GROUP BY ALL")
def i_edges(spark: SparkSession, d: str) -> DataFrame:
    """The upper layer: attributes in common, of those that have values."""
    return G.instance_edges(G.filled_schema_table(star_marketplace(spark, d))).select("src", "dst", F.concat_ws("+", "common").alias("common"))


@query(star_sql(rows_sql([f"SELECT '{a}' src, '{b}' dst, '{'+'.join(j)}' j, round({sql_ji('i_' + a, 'i_' + b, j)}, 6) ji" for a, b, j in (("customer", "orders", ("custkey", "xj_g")), ("partsupp", "supplier", ("suppkey", "xj_e")), ("customer", "supplier", ("nationkey", "xj_h")))])))
def ji_composite_keys(spark: SparkSession, d: str) -> DataFrame:
    t = star_tables(spark, d)
    out = None
    for a, b, j in (("customer", "orders", ["custkey", "xj_g"]), ("partsupp", "supplier", ["suppkey", "xj_e"]), ("customer", "supplier", ["nationkey", "xj_h"])):
        one = M.informativeness_df(t[a], t[b], j).select(F.lit(a).alias("src"), F.lit(b).alias("dst"), F.lit("+".join(j)).alias("j"), "ji")
        out = one if out is None else out.unionByName(one)
    return rounded(out)


@query(f"SELECT round({sql_ji('ev', 'cu', ['custkey'])}, 6) ji".join(["WITH ev AS (SELECT user_id custkey FROM events), cu AS (SELECT c_custkey custkey FROM customer) ", ""]))
def ji_events_customer(spark: SparkSession, d: str) -> DataFrame:
    ev, cu = spark.read.parquet(f"{d}/events.parquet").select(F.col("user_id").alias("custkey")), star_tables(spark, d)["customer"]
    return rounded(M.informativeness_df(ev, cu, ["custkey"]).select("ji"))


@query(f"SELECT round({sql_ji('dd', 'll', ['doc_id'])}, 6) ji".join(["WITH dd AS (SELECT doc_id FROM documents), ll AS (SELECT doc_id FROM labels) ", ""]))
def ji_outer_reference(spark: SparkSession, d: str) -> DataFrame:
    """The literal definition over the physical full outer join."""
    return rounded(M.informativeness_outer_df(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"), ["doc_id"]))


@query(star_sql(rows_sql([f"SELECT '{a}' src, '{b}' dst, round({sql_ji('i_' + a, 'i_' + b, ['suppkey'])}, 6) ji, (SELECT sum(a.c * b.c)::DOUBLE FROM (SELECT suppkey, count(*) c FROM i_{a} GROUP BY ALL) a JOIN (SELECT suppkey, count(*) c FROM i_{b} GROUP BY ALL) b USING (suppkey)) join_rows" for a, b in (("lineitem", "partsupp"), ("lineitem", "supplier"), ("partsupp", "supplier"))])))
def ji_matrix_suppkey(spark: SparkSession, d: str) -> DataFrame:
    t = star_tables(spark, d)
    return rounded(M.informativeness_matrix({n: t[n] for n in ("lineitem", "partsupp", "supplier")}, ["suppkey"]))


@query(star_sql(f"SELECT src, dst, j, join_rows, rank() OVER (ORDER BY join_rows DESC, src, dst, j) rank FROM ({rows_sql([f'''SELECT '{a}' src, '{b}' dst, '{'+'.join(j)}' j, (SELECT coalesce(sum(a.c * b.c), 0)::BIGINT FROM (SELECT {', '.join(j)}, count(*) c FROM i_{a} GROUP BY ALL) a JOIN (SELECT {', '.join(j)}, count(*) c FROM i_{b} GROUP BY ALL) b USING ({', '.join(j)})) join_rows''' for a, b, j in _edge_list()])})"))
def join_size_ranking(spark: SparkSession, d: str) -> DataFrame:
    """Baseline: edges ranked by join size, forecast without joining."""
    w = G.edge_weights(star_marketplace(spark, d)).select("src", "dst", F.concat_ws("+", "j").alias("j"), F.col("join_rows").cast("long").alias("join_rows"))
    return w.withColumn("rank", F.rank().over(Window.orderBy(F.desc("join_rows"), "src", "dst", "j")).cast("long"))  # one row an edge


# ---------------------------------------------------------------------------------- entropy and correlation

CUSTOMER_SETS = [("c_mktsegment",), ("nationkey",), ("c_mktsegment", "nationkey"), ("custkey",), ("c_acctbal", "custkey"), ("nationkey", "xj_g")]


@query(star_sql(rows_sql([f"SELECT '{'+'.join(s)}' attributes, round({sql_entropy('i_customer', s)}, 6) entropy" for s in CUSTOMER_SETS])))
def entropy_sets_customer(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.entropies_df(star_tables(spark, d)["customer"], CUSTOMER_SETS))


@query(star_sql(f"SELECT round({sql_entropy('i_orders', ['o_orderstatus', 'o_orderpriority'])} - {sql_entropy('i_orders', ['o_orderpriority'])}, 6) cond_entropy"))
def cond_entropy(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.cond_entropy_df(star_tables(spark, d)["orders"], ["o_orderstatus"], ["o_orderpriority"]))


@query(star_sql(f"SELECT round({sql_corr('i_lineitem', 'l_returnflag', ['l_linestatus'], False)}, 6) mutual_information"))
def mutual_info(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.mutual_information_df(star_tables(spark, d)["lineitem"], ["l_returnflag"], ["l_linestatus"]))


@query(star_sql(f"SELECT round({sql_cumulative('i_orders', 'o_totalprice')}, 4) cum_entropy"))
def cum_entropy_totalprice(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.cum_entropy_df(star_tables(spark, d)["orders"], "o_totalprice"), 4)


@query(star_sql(f"SELECT round({sql_cumulative('i_orders', 'o_totalprice', ['o_orderpriority'])}, 4) cond_cum_entropy"))
def cond_cum_entropy_priority(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.cond_cum_entropy_df(star_tables(spark, d)["orders"], "o_totalprice", ["o_orderpriority"]), 4)


@query(star_sql(f"SELECT round({sql_corr('i_part', 'p_brand', ['p_type'], False)}, 6) corr"))
def corr_categorical(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.correlation_df(star_tables(spark, d)["part"], ["p_brand"], ["p_type"]))


@query(star_sql(f"SELECT round({sql_corr('i_part', 'p_brand', ['p_type'], False)} + {sql_corr('i_part', 'p_retailprice', ['p_type'], True)}, 4) corr"))
def corr_mixed(spark: SparkSession, d: str) -> DataFrame:
    """Several attributes of both kinds: categorical ones jointly, numeric ones summed."""
    return rounded(M.correlation_df(star_tables(spark, d)["part"], ["p_brand", "p_retailprice"], ["p_type"]), 4)


@query(star_sql(f"SELECT round({sql_corr('b', 'o_totalprice', ['bin'], True)}, 4) corr", "b AS (SELECT o_totalprice, least(floor((epoch(o_orderdate) - lo) / (hi - lo) * 16), 15) bin FROM i_orders, (SELECT min(epoch(o_orderdate)) lo, max(epoch(o_orderdate)) hi FROM i_orders))"))
def corr_binned(spark: SparkSession, d: str) -> DataFrame:
    """A condition of many values in sixteen equal bins."""
    return rounded(M.correlation_df(star_tables(spark, d)["orders"], ["o_totalprice"], ["o_orderdate"], y_bins=16), 4)


@query(star_sql("SELECT round(corr(l_quantity, l_extendedprice), 6) pearson FROM i_lineitem"))
def pearson_baseline(spark: SparkSession, d: str) -> DataFrame:
    return rounded(M.corr_pearson_df(star_tables(spark, d)["lineitem"], "l_quantity", "l_extendedprice"))


PRICED = ["custkey", "nationkey", "c_mktsegment", "xj_g"]


@query(star_sql(rows_sql([f"SELECT '{'+'.join(s)}' attributes, round({sql_entropy('i_customer', s)}, 6) price" for s in L.lattice(PRICED, 1)])))
def price_lattice_customer(spark: SparkSession, d: str) -> DataFrame:
    """Prices of every vertex over four attributes; they never fall when attributes are added."""
    return rounded(G.vertex_prices(star_tables(spark, d)["customer"], PRICED))


# ------------------------------------------------------------------------------------------- plans and baselines

X1 = (Q.Request(("c_acctbal",), ("o_orderpriority",)), frozenset({("customer", "orders")}))
X2 = (Q.Request(("n_name",), ("ps_availqty",)), frozenset({("nation", "supplier"), ("partsupp", "supplier")}))
X3 = (Q.Request(("o_totalprice",), ("r_name",)), frozenset({("customer", "orders"), ("customer", "supplier"), ("nation", "supplier"), ("nation", "region")}))
X3D = (X3[0], frozenset({("customer", "orders"), ("customer", "nation"), ("nation", "region")}))
#: For each pinned workload its instances with what each plan projects, and the swapped edge's choices.
_JOINS = {
    "x1": ["custkey", "xj_g", "custkey+xj_g"],
    "x2": ["suppkey", "xj_e", "suppkey+xj_e"],
    "x3": ["nationkey", "xj_h", "nationkey+xj_h"],
}


def _source_sql(x: str, j: str) -> str:
    on = j.split("+")
    using = f"USING ({', '.join(on)})"
    if x == "x1":
        return f"(SELECT c_acctbal, o_orderpriority FROM (SELECT {', '.join(on)}, c_acctbal FROM i_customer) JOIN (SELECT {', '.join(on)}, o_orderpriority FROM i_orders) {using})"
    if x == "x2":
        return f"(SELECT n_name, ps_availqty FROM (SELECT n.n_name, {', '.join('s.' + c for c in on)} FROM i_nation n JOIN i_supplier s USING (nationkey)) JOIN (SELECT {', '.join(on)}, ps_availqty FROM i_partsupp) {using})"
    co = f"(SELECT o_totalprice, {', '.join('c.' + c for c in on)} FROM i_orders o JOIN i_customer c ON o.custkey = c.custkey)"
    return f"(SELECT o_totalprice, r_name FROM {co} JOIN (SELECT s.*, r_name FROM i_supplier s JOIN i_nation n ON s.nationkey = n.nationkey JOIN i_region r ON r.regionkey = n.regionkey) {using})"


_SIDES = {"x1": ("c_acctbal", "o_orderpriority", True), "x2": ("n_name", "ps_availqty", False), "x3": ("o_totalprice", "r_name", True)}
_PRICES = {
    "x1": lambda on: [("i_customer", ["c_acctbal", *on]), ("i_orders", ["o_orderpriority", *on])],
    "x2": lambda on: [("i_nation", ["n_name", "nationkey"]), ("i_supplier", ["nationkey", *on]), ("i_partsupp", ["ps_availqty", *on])],
    "x3": lambda on: [("i_orders", ["o_totalprice", "custkey"]), ("i_customer", ["custkey", *on]), ("i_supplier", [*dict.fromkeys(["nationkey", *on])]), ("i_nation", ["nationkey", "regionkey"]), ("i_region", ["regionkey", "r_name"])],
}
_EDGE = {"x1": ("i_customer", "i_orders"), "x2": ("i_supplier", "i_partsupp"), "x3": ("i_customer", "i_supplier")}


def _plans_sql(x: str) -> str:
    a, b, numeric = _SIDES[x]
    rows = []
    for j in _JOINS[x]:
        on = j.split("+")
        src = _source_sql(x, j)
        price = " + ".join(sql_entropy(t, cols) for t, cols in _PRICES[x](on))
        rows.append(f"SELECT '{j}' j, round({sql_corr(src, a, [b], numeric)}, 6) corr, (SELECT count(*) FROM {src}) join_rows, round({price}, 6) price, round({sql_ji(*_EDGE[x], on)}, 6) weight")
    return rows_sql(rows)


def _swapped(x: str, plan: TargetGraph) -> str:
    edge = {"x1": ("customer", "orders"), "x2": ("partsupp", "supplier"), "x3": ("customer", "supplier")}[x]
    return "+".join(dict(plan.edges)[edge])


def _graph(spark: SparkSession, d: str, tree: frozenset) -> G.JoinGraph:
    """The graph over the instances of a pinned tree only; the third workload varies one edge, so the other bridge is left out."""
    m = star_marketplace(spark, d).restricted(sorted({v for e in tree for v in e}))
    if tree == X3[1]:
        m = Marketplace({n: replace(i, df=i.df.drop("xj_g")) for n, i in m.instances.items()})
    return G.build(m)


def _workload_plans(spark: SparkSession, d: str, x: str) -> tuple[Q.Evaluator, list[TargetGraph]]:
    request, tree = {"x1": X1, "x2": X2, "x3": X3}[x]
    graph = _graph(spark, d, tree)
    plans = [p for p in Q.all_plans(graph, request, len(tree) + 1, tree) if _swapped(x, p) in _JOINS[x]]
    return Q.Evaluator(graph, request), plans


for _x in _JOINS:

    def _corr(spark: SparkSession, d: str, x: str = _x) -> DataFrame:
        """All join choices of a pinned workload: correlation, join size, price and informativeness."""
        evaluator, plans = _workload_plans(spark, d, x)
        rows = [(_swapped(x, p), round(s.corr, 6), s.join_rows, round(s.price, 6), round(s.weight, 6)) for p, s in zip(plans, evaluator.scores(plans), strict=True)]
        return spark.createDataFrame(rows, "j string, corr double, join_rows long, price double, weight double")

    query(star_sql(_plans_sql(_x)), f"corr_{_x}")(_corr)

    def _gp(spark: SparkSession, d: str, x: str = _x) -> DataFrame:
        """Exhaustive search on full data over a pinned tree."""
        evaluator, plans = _workload_plans(spark, d, x)
        request, tree = {"x1": X1, "x2": X2, "x3": X3}[x]
        best = Q.exhaustive(evaluator.graph, request, len(tree) + 1, evaluator, tree)
        return spark.createDataFrame([(best.status, _swapped(x, best.graph), round(best.score.corr, 6), round(best.score.price, 6))], "status string, j string, corr double, price double")

    query(star_sql(f"SELECT 'found' status, j, corr, price FROM ({_plans_sql(_x)}) ORDER BY corr DESC LIMIT 1"), f"gp_{_x}")(_gp)

    def _limited(spark: SparkSession, d: str, x: str = _x) -> DataFrame:
        """The same under an informativeness limit of 0.5: the strongest plan is out of reach."""
        evaluator, plans = _workload_plans(spark, d, x)
        request, tree = {"x1": X1, "x2": X2, "x3": X3}[x]
        request = replace(request, alpha=0.5)
        best = Q.exhaustive(evaluator.graph, request, len(tree) + 1, Q.Evaluator(evaluator.graph, request), tree)
        return spark.createDataFrame([(_swapped(x, best.graph), round(best.score.corr, 6), round(best.score.weight, 6))], "j string, corr double, weight double")

    query(star_sql(f"SELECT j, corr, weight FROM ({_plans_sql(_x)}) WHERE weight <= 0.5 ORDER BY corr DESC LIMIT 1"), f"gp_alpha_{_x}")(_limited)

    def _walk(spark: SparkSession, d: str, x: str = _x) -> DataFrame:
        """The planner's walk on the same tree; with enough steps it ends where exhaustive search does."""
        evaluator, plans = _workload_plans(spark, d, x)
        request, tree = {"x1": X1, "x2": X2, "x3": X3}[x]
        supply = Q.supplies(evaluator.graph.market, request)[0]
        best = Q.refine(evaluator, Q.initial(evaluator.graph, tree, supply), 60, seed=5)
        s = evaluator.score(best)
        return spark.createDataFrame([(_swapped(x, best), round(s.corr, 6), round(s.price, 6))], "j string, corr double, price double")

    query(star_sql(f"SELECT j, corr, price FROM ({_plans_sql(_x)}) ORDER BY corr DESC LIMIT 1"), f"acquire_best_{_x}")(_walk)

    def _lp(spark: SparkSession, d: str, x: str = _x) -> DataFrame:
        """Exhaustive search on keyed samples at rate 0.5, its answer re-scored on full data, with its correlation difference."""
        full, _ = _workload_plans(spark, d, x)
        request, tree = {"x1": X1, "x2": X2, "x3": X3}[x]
        rows = report.compare(full.graph, request, len(tree) + 1, tree, rate=0.5)
        return spark.createDataFrame([(r["approach"], r["status"], r["plan"], r["corr"], r["quality"], r["ji"], r["price"], r["cd"]) for r in rows], "approach string, status string, plan string, corr double, quality double, ji double, price double, cd double")

    query(None, f"compare_{_x}")(_lp)


@query(star_sql(f"SELECT min(price) low, max(price) high FROM ({_plans_sql('x1')})"))
def budget_range_x1(spark: SparkSession, d: str) -> DataFrame:
    evaluator, _ = _workload_plans(spark, d, "x1")
    return rounded(spark.createDataFrame([report.budget_range(evaluator.graph, X1[0], 2, X1[1])], "low double, high double"))


RATIOS = (0.86, 0.87, 0.9, 0.95, 1.0)


@query(star_sql(rows_sql([f"SELECT {r}::DOUBLE ratio, max(corr) FILTER (price <= {r} * (SELECT max(price) FROM plans) + 1e-6) corr FROM plans" for r in RATIOS]), f"plans AS ({_plans_sql('x1')})"))
def budget_sweep_x1(spark: SparkSession, d: str) -> DataFrame:
    """Best correlation at each share of the dearest plan's price; none below the cheapest plan."""
    evaluator, _ = _workload_plans(spark, d, "x1")
    rows = report.budget_sweep(evaluator.graph, X1[0], RATIOS, 2, X1[1])
    return rounded(spark.createDataFrame([(float(r["ratio"]), r["corr"]) for r in rows], "ratio double, corr double"))


@query(star_sql("SELECT instance, projection, n FROM (VALUES ('customer', 'SELECT c_acctbal, custkey FROM customer', (SELECT count(c_acctbal) + count(custkey) FROM i_customer)), ('orders', 'SELECT custkey, o_orderpriority FROM orders', (SELECT count(custkey) + count(o_orderpriority) FROM i_orders))) t(instance, projection, n)"))
def emitted_sql_x1(spark: SparkSession, d: str) -> DataFrame:
    """The emitted projections, each run by Spark SQL, with its number of values."""
    m = star_marketplace(spark, d)
    plan = TargetGraph.of({("customer", "orders"): ["custkey"]}, {"c_acctbal": "customer", "o_orderpriority": "orders"})
    Q.register_instances(spark, m.restricted(plan.instances))
    made = [(s, spark.sql(s)) for s in Q.emit_sql(plan, m)]
    return reduce(DataFrame.unionByName, (df.agg(sum(map(F.count, df.columns)).alias("n")).select(F.lit(s.split(" FROM ")[1]).alias("instance"), F.lit(s).alias("projection"), "n") for s, df in made))


@query(star_sql("SELECT count(*) n, round(sum(c_acctbal), 2) total FROM i_customer"))
def emitted_sql_runs(spark: SparkSession, d: str) -> DataFrame:
    """The emitted projection of customer, run by Spark SQL."""
    m = star_marketplace(spark, d)
    Q.register_instances(spark, m.restricted(["customer"]))
    plan = TargetGraph.of({("customer", "orders"): ["custkey"]}, {"c_acctbal": "customer", "o_orderpriority": "orders"})
    return spark.sql(Q.emit_sql(plan, m)[0]).agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query(None)
def acquire_x1(spark: SparkSession, d: str) -> DataFrame:
    """The whole planner for the first workload: landmarks, light tree, walk, emitted SQL."""
    graph = G.build(star_marketplace(spark, d).restricted(["customer", "nation", "orders", "region", "supplier"]))
    plan = Q.acquire(graph, replace(X1[0], alpha=1.0), iterations=40, seed=3)
    s = plan.score
    return spark.createDataFrame([(plan.status, plan.graph.label(), plan.igraph_size, s.corr, s.quality, s.weight, s.price, "; ".join(Q.emit_sql(plan.graph, graph.market)))], "status string, plan string, igraph_size int, corr double, quality double, ji double, price double, purchase string")


@query(None)
def acquire_statuses(spark: SparkSession, d: str) -> DataFrame:
    """The outcomes of requests that cannot be met, beside one that can."""
    graph = _graph(spark, d, X1[1])
    cases = {"free": X1[0], "poor": replace(X1[0], budget=10.0), "cheap": replace(X1[0], budget=20.0), "strict": replace(X1[0], alpha=-1.0), "pure": replace(X1[0], beta=1.1)}
    return spark.createDataFrame([(k, Q.acquire(graph, r, 30, 1).status) for k, r in cases.items()], "request string, status string")


def _m29_plan(edges: dict, supply: dict):
    return TargetGraph.of({G.pair(*e): j for e, j in edges.items()}, supply)


_X4 = "(SELECT o_totalprice, c_mktsegment FROM i_orders JOIN i_customer ON i_orders.custkey = i_customer.custkey)"


@query(star_sql(f"SELECT round({sql_corr(_X4, 'o_totalprice', ['c_mktsegment'], True)}, 4) corr, (SELECT count(*) FROM {_X4}) join_rows"))
def plan_m29_x4(spark: SparkSession, d: str) -> DataFrame:
    """A three-fragment plan, evaluated with eager aggregation."""
    m = fragment_marketplace(spark, d)
    plan = _m29_plan({("ord_price", "ord_core"): ["orderkey"], ("ord_core", "cust_core"): ["custkey"]}, {"o_totalprice": "ord_price", "c_mktsegment": "cust_core"})
    from .plans.evaluate import score_df

    return rounded(score_df(m, plan, ["o_totalprice"], ["c_mktsegment"], fds=[]).select("corr", "join_rows"), 4)


_X5 = "(SELECT l_quantity, r_name FROM i_lineitem l JOIN i_orders o ON l.orderkey = o.orderkey JOIN i_customer c ON o.custkey = c.custkey JOIN i_nation n ON n.nationkey = c.nationkey JOIN i_region r ON r.regionkey = n.regionkey)"


@query(star_sql(f"SELECT round({sql_corr(_X5, 'l_quantity', ['r_name'], True)}, 6) corr, (SELECT count(*) FROM {_X5}) join_rows"))
def plan_m29_x5(spark: SparkSession, d: str) -> DataFrame:
    """A five-fragment plan."""
    m = fragment_marketplace(spark, d)
    plan = _m29_plan({("line_qty", "ord_core"): ["orderkey"], ("ord_core", "cust_core"): ["custkey"], ("cust_core", "nation"): ["nationkey"], ("nation", "region"): ["regionkey"]}, {"l_quantity": "line_qty", "r_name": "region"})
    from .plans.evaluate import score_df

    return rounded(score_df(m, plan, ["l_quantity"], ["r_name"], fds=[]).select("corr", "join_rows"))


_X6 = """(SELECT r_name, p_brand, ev_k, count(*) w FROM i_region r JOIN i_nation n ON r.regionkey = n.regionkey JOIN i_customer c ON c.nationkey = n.nationkey
JOIN (SELECT user_id, json_extract_string(props, '$.k')::BIGINT ev_k FROM events) e ON e.user_id = c.custkey JOIN i_orders o ON o.custkey = c.custkey JOIN i_lineitem l ON l.orderkey = o.orderkey JOIN i_part p ON p.partkey = l.partkey GROUP BY ALL)"""


def _weighted_entropy(source: str, x: Sequence[str]) -> str:
    return f"(SELECT log2(sum(c)) - sum(c * log2(c)) / sum(c) FROM (SELECT sum(w)::DOUBLE c FROM {source} GROUP BY {', '.join(x)}))"


@query(star_sql(f"SELECT round({_weighted_entropy('x6', ['r_name'])} + {_weighted_entropy('x6', ['p_brand', 'ev_k'])} - {_weighted_entropy('x6', ['r_name', 'p_brand', 'ev_k'])}, 6) corr, (SELECT sum(w)::BIGINT FROM x6) join_rows", f"x6 AS {_X6}"))
def plan_m29_x6(spark: SparkSession, d: str) -> DataFrame:
    """An eight-fragment tree; counts multiply, the join is never materialised."""
    m = fragment_marketplace(spark, d)
    edges = {("region", "nation"): ["regionkey"], ("nation", "cust_core"): ["nationkey"], ("cust_core", "ev_core"): ["custkey"], ("ev_core", "ev_value"): ["event_id"], ("cust_core", "ord_core"): ["custkey"], ("ord_core", "line_core"): ["orderkey"], ("line_core", "part_core"): ["partkey"]}
    plan = _m29_plan(edges, {"r_name": "region", "p_brand": "part_core", "ev_k": "ev_value"})
    from .plans.evaluate import score_df

    return rounded(score_df(m, plan, ["r_name"], ["p_brand", "ev_k"], fds=[]).select("corr", "join_rows"))


@query(star_sql(f"""SELECT '{"region"}' landmark, v vertex, round(min(dd), 6) dist FROM walk GROUP BY v""", f"e0 AS ({_AS_EDGES})", "e AS (SELECT src a, dst b, min(weight) w FROM e0 GROUP BY ALL UNION ALL SELECT dst, src, min(weight) FROM e0 GROUP BY ALL)",
    "walk(v, dd, hops) AS (SELECT 'region', 0.0::DOUBLE, 0 UNION SELECT e.b, walk.dd + e.w, hops + 1 FROM walk JOIN e ON e.a = walk.v WHERE hops < 7)"))
def landmark_distances(spark: SparkSession, d: str) -> DataFrame:
    """Distances to a landmark by distributed relaxation."""
    edges = settle_edges(spark, d)
    return rounded(steiner.sketch_distances(edges, ["region"]).select("landmark", "vertex", "dist"))


def settle_edges(spark: SparkSession, d: str) -> DataFrame:
    from .functions.storage import settle

    return settle(G.min_edge_weight(G.edge_weights(star_marketplace(spark, d))).select("src", "dst", "weight"))


# -------------------------------------------------------------------------------------------------- sampling


def _keep(cols: Sequence[str], rate: float, seed: int = 0) -> str:
    text = " || '|' || ".join(f"{c}::VARCHAR" for c in cols)
    return f"{_u32(f'''{text} || '|' || '{seed}' ''')} / 4294967296.0 < {rate}"


@query(star_sql(f"SELECT orderkey, custkey FROM i_orders WHERE {_keep(['custkey'], 0.3)}"))
def keyed_sample_orders(spark: SparkSession, d: str) -> DataFrame:
    return S.keyed_sample(star_tables(spark, d)["orders"], ["custkey"], 0.3, "md5").select("orderkey", "custkey")


@query(star_sql(f"SELECT count(*) join_rows, count(DISTINCT custkey) customers FROM (SELECT * FROM i_customer WHERE {_keep(['custkey'], 0.3)}) JOIN (SELECT custkey, orderkey FROM i_orders WHERE {_keep(['custkey'], 0.3)}) USING (custkey)"))
def keyed_sample_join(spark: SparkSession, d: str) -> DataFrame:
    """Samples keyed by the join value keep whole join groups on both sides."""
    t = star_tables(spark, d)
    a, b = S.keyed_sample(t["customer"], ["custkey"], 0.3, "md5"), S.keyed_sample(t["orders"], ["custkey"], 0.3, "md5")
    return a.select("custkey").join(b.select("custkey", "orderkey"), "custkey").agg(F.count("*").alias("join_rows"), F.countDistinct("custkey").alias("customers"))


@query(star_sql(f"SELECT round({sql_ji('a', 'b', ['xj_g'])}, 6) ji", f"a AS (SELECT * FROM i_customer WHERE {_keep(['xj_g'], 0.5)})", f"b AS (SELECT * FROM i_orders WHERE {_keep(['xj_g'], 0.5)})"))
def ji_estimate(spark: SparkSession, d: str) -> DataFrame:
    t = star_tables(spark, d)
    return rounded(S.informativeness_est(t["customer"], t["orders"], ["xj_g"], 0.5, "md5").select("ji"))


def _bounded_frames(t: dict[str, DataFrame]) -> list[tuple[DataFrame, list[str]]]:
    return [
        (t["orders"].select("orderkey", "custkey", "o_totalprice"), []),
        (t["customer"].select("custkey", "nationkey"), ["custkey"]),
        (t["nation"].select("nationkey", "regionkey"), ["nationkey"]),
    ]


_BOUNDED = [
    "oc AS (SELECT custkey, nationkey, o_totalprice, orderkey FROM (SELECT orderkey, custkey, o_totalprice FROM i_orders) JOIN (SELECT custkey, nationkey FROM i_customer) USING (custkey))",
    f"kept AS (SELECT * FROM (SELECT *, unnest(range(1, n + 1)) i FROM (SELECT custkey, nationkey, orderkey, count(*) n FROM oc GROUP BY ALL)) WHERE {_u32('''custkey::VARCHAR || '|' || nationkey::VARCHAR || '|' || orderkey::VARCHAR || '|2|' || i::VARCHAR''')} / 4294967296.0 < 0.5)",
]


@query(star_sql("SELECT orderkey, custkey, regionkey FROM kept JOIN i_nation USING (nationkey)", _BOUNDED[0].replace("o_totalprice, orderkey FROM (SELECT orderkey, custkey, o_totalprice", "orderkey FROM (SELECT orderkey, custkey"), _BOUNDED[1]))
def bounded_join_x3(spark: SparkSession, d: str) -> DataFrame:
    """Orders, customers, nations with the first join re-sampled, as it exceeds the bound."""
    frames = [(df.drop("o_totalprice"), j) for df, j in _bounded_frames(star_tables(spark, d))]
    return S.bounded_join(frames, eta=1000, rate=0.5, hash_name="md5").select("orderkey", "custkey", "regionkey")


@query(star_sql("SELECT count(*) n FROM i_orders JOIN i_customer ON i_orders.custkey = i_customer.custkey"))
def bounded_join_unbounded(spark: SparkSession, d: str) -> DataFrame:
    """Without a bound nothing is sampled."""
    return S.bounded_join(_bounded_frames(star_tables(spark, d)), eta=None).agg(F.count("*").alias("n"))


_EST = f"(SELECT o_orderstatus, c_mktsegment FROM (SELECT custkey, o_orderstatus FROM i_orders WHERE {_keep(['custkey'], 0.5)}) JOIN (SELECT custkey, c_mktsegment FROM i_customer WHERE {_keep(['custkey'], 0.5)}) USING (custkey))"


@query(star_sql(f"SELECT round({sql_corr(_EST, 'o_orderstatus', ['c_mktsegment'], False)}, 6) corr, (SELECT count(*) FROM {_EST}) n"))
def corr_estimate(spark: SparkSession, d: str) -> DataFrame:
    """Correlation on keyed samples of both sides."""
    t = star_tables(spark, d)
    frames = [(t["orders"].select("custkey", "o_orderstatus"), []), (t["customer"].select("custkey", "c_mktsegment"), ["custkey"])]
    return rounded(S.estimate_df(frames, ["o_orderstatus"], ["c_mktsegment"], 0.5, hash_name="md5").select("corr", F.col("rows").alias("n")))


_QEST = f"(SELECT * FROM d_orders WHERE {_keep(['custkey'], 0.5)})"


@query(star_sql(f"SELECT round({sql_quality('q', PLANTED['orders'][0])}, 6) quality", f"q AS {_QEST}"))
def quality_estimate(spark: SparkSession, d: str) -> DataFrame:
    """Quality on a keyed sample."""
    return rounded(M.fd_quality_df(S.keyed_sample(star_tables(spark, d, dirty=True)["orders"], ["custkey"], 0.5, "md5"), PLANTED["orders"][0]))


@query(None)
def estimate_bias(spark: SparkSession, d: str) -> DataFrame:
    """Estimates over seeds beside the truth."""
    t = star_tables(spark, d)
    return S.bias_report(t["customer"], t["orders"], ["xj_g"], 0.5, range(8))


def _thinned_sql(text: str, rate: float, seed: int, exact: int) -> str:
    """The kept count of n equal rows: row by row up to `exact`, by the normal approximation beyond."""
    unit = lambda i: f"({_u32(f"{text} || '|{seed}|' || ({i})::VARCHAR")} / 4294967296.0)"
    normal = f"sqrt(-2 * ln(greatest({unit('-1')}, 1e-12))) * cos(2 * pi() * {unit('-2')})"
    each = f"(SELECT count(*) FROM (SELECT unnest(range(1, least(n, {exact}) + 1)) i) WHERE {unit('i')} < {rate})"
    return f"CASE WHEN n <= {exact} THEN {each} ELSE greatest(0, least(n, round(n * {rate}::DOUBLE + sqrt(n * {rate}::DOUBLE * {1 - rate}::DOUBLE) * {normal})))::BIGINT END"


@query(star_sql(f"SELECT o_orderstatus, nationkey, n, ({_thinned_sql("o_orderstatus || '|' || nationkey::VARCHAR", 0.5, 3, S.EXACT)})::BIGINT kept FROM (SELECT o_orderstatus, nationkey, count(*) n FROM (SELECT custkey, o_orderstatus FROM i_orders) JOIN (SELECT custkey, nationkey FROM i_customer) USING (custkey) GROUP BY ALL)"))
def resampled_counts(spark: SparkSession, d: str) -> DataFrame:
    """How many rows of each group of a collapsed intermediate join a re-sample at one half keeps."""
    t = star_tables(spark, d)
    joined = t["orders"].select("custkey", "o_orderstatus").join(t["customer"].select("custkey", "nationkey"), "custkey")
    frame = M.counted(joined, ["o_orderstatus", "nationkey"]).withColumnRenamed(M.W, "n")
    return frame.withColumn("kept", S.thinned(F.col("n"), 0.5, ["o_orderstatus", "nationkey"], "md5", 3))


# -------------------------------------------------------------------------------------------- worked examples


@query(star_sql(rows_sql([f"SELECT '{n}' example, round({sql_quality(f'd_{n}', PLANTED[n][0])}, 6) quality" for n in ("part", "customer", "orders")] + [f"SELECT 'customer_orders' example, round({sql_joint('j', _XQ)}, 6) quality"]), "j AS (SELECT nationkey, c_regionkey, o_orderdate, o_year FROM d_customer JOIN d_orders USING (custkey))"))
def worked_qualities(spark: SparkSession, d: str) -> DataFrame:
    """Qualities of dirty tables by themselves, and of two of them joined: worse than either."""
    t = star_tables(spark, d, dirty=True)
    ones = [M.fd_quality_df(t[n], PLANTED[n][0]).select(F.lit(n).alias("example"), "quality") for n in ("part", "customer", "orders")]
    joined = t["customer"].select("custkey", "nationkey", "c_regionkey").join(t["orders"].select("custkey", "o_orderdate", "o_year"), "custkey")
    return rounded(reduce(DataFrame.unionByName, [*ones, M.joint_quality_df(joined, _XQ).select(F.lit("customer_orders").alias("example"), "quality")]))


@query(None)
def purchase_options_example(spark: SparkSession, d: str) -> DataFrame:
    """Five ways to learn what goes with the market segment of the shopper's own customers, each with and without these."""
    t = star_tables(spark, d)
    wanted = lambda n, column, *keys: t[n].select(*keys, F.col(column).alias("wanted"))
    segments = t["customer"].select("custkey", "nationkey", "c_mktsegment")
    paths = {
        "1": [(t["nation"].select("nationkey", "regionkey"), []), (wanted("region", "r_name", "regionkey"), ["regionkey"])],
        "2": [(wanted("nation", "n_name", "nationkey"), [])],
        "3": [(wanted("orders", "o_orderpriority", "custkey"), [])],
        "4": [(segments.select("custkey", "c_mktsegment"), []), (wanted("orders", "o_orderstatus", "custkey"), ["custkey"])],
        "5": [(segments, []), (wanted("nation", "n_name", "nationkey"), ["nationkey"])],
    }
    return rounded(examples.purchase_options(spark, segments, paths, "c_mktsegment", "wanted"))


_LATTICES = {"nation": ["nationkey", "n_name", "regionkey"], "customer": ["custkey", "c_name", "nationkey", "c_acctbal", "c_mktsegment", "xj_g", "xj_h"], "part": ["partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"]}


@query(star_sql(f"SELECT instance, attributes, (1 << attributes)::BIGINT - attributes - 1 vertices, attributes - 1 height FROM ({rows_sql([f"SELECT '{n}' instance, ({' + '.join(f'(count({a}) > 0)::INT' for a in c)})::INT attributes FROM i_{n}" for n, c in _LATTICES.items()])})"))
def lattice_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Vertices and height of the lattices over the attributes of three instances that have values."""
    m = star_marketplace(spark, d).restricted(list(_LATTICES))
    counts = G.filled_schema_table(m).groupBy("instance").agg(F.count("*").cast("int").alias("attributes"))
    most = max(len(m[n].attributes) for n in m.names)
    of = lambda f: F.array(*[F.lit(f(k)) for k in range(most + 1)])[F.col("attributes")]
    return counts.select("instance", "attributes", of(L.size).cast("long").alias("vertices"), of(L.height).cast("int").alias("height"))


for _name, (_f, _sql) in {**R.QUERIES, **live.QUERIES}.items():
    query(_sql, _name)(_f)
