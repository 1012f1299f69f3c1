"""The catalogue: instances for sale, their shared attribute names and dependencies, and the fixtures made of the given tables."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.measures import FD


@dataclass(frozen=True)
class Instance:
    """A table for sale: a lazy frame under canonical attribute names, dependencies, and whether the shopper owns it."""

    name: str
    df: DataFrame
    fds: tuple[FD, ...] = ()
    owned: bool = False

    @cached_property
    def attributes(self) -> tuple[str, ...]:
        return tuple(self.df.columns)


@dataclass(frozen=True)
class Marketplace:
    instances: dict[str, Instance] = field(default_factory=dict)

    def __getitem__(self, name: str) -> Instance:
        return self.instances[name]

    @property
    def names(self) -> list[str]:
        return sorted(self.instances)

    def restricted(self, names: Sequence[str]) -> Marketplace:
        return Marketplace({n: self.instances[n] for n in names})

    def with_owned(self, names: Sequence[str]) -> Marketplace:
        return Marketplace({n: replace(i, owned=n in names) for n, i in self.instances.items()})

    def common(self, a: str, b: str) -> tuple[str, ...]:
        """Attributes that two instances share, in the order of the first."""
        other = set(self[b].attributes)
        return tuple(x for x in self[a].attributes if x in other)

    def holders(self, attributes: Sequence[str]) -> list[str]:
        return [n for n in self.names if set(attributes) <= set(self[n].attributes)]

    @classmethod
    def of(cls, frames: dict[str, DataFrame], fds: dict[str, Sequence[FD]] | None = None) -> Marketplace:
        return cls({n: Instance(n, df, tuple((fds or {}).get(n, ()))) for n, df in frames.items()})


READERS = {"parquet": "parquet", "csv": "csv", "json": "json", "orc": "orc"}


def read_instance(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, attr_map: dict[str, str] | None = None) -> DataFrame:
    """A table under canonical names; text formats take an explicit schema and are never inferred."""
    reader = spark.read
    if schema is not None:
        reader = reader.schema(schema)
    elif kind in ("csv", "json"):
        raise ValueError(f"{kind} needs a schema")
    if kind == "csv":
        reader = reader.option("header", True)
    return canonical(reader.format(READERS[kind]).load(path), attr_map or {})


def directory_catalogue(spark: SparkSession, folder: str, names: Sequence[str], attr_maps: dict[str, dict[str, str]] | None = None) -> Marketplace:
    """A marketplace of the Parquet tables <folder>/<name>.parquet."""
    return Marketplace.of({n: read_instance(spark, f"{folder}/{n}.parquet", attr_map=(attr_maps or {}).get(n)) for n in names})


def canonical(df: DataFrame, attr_map: dict[str, str]) -> DataFrame:
    """Columns under their shared names; integer keys as bigint, so that joins and hashes agree between tables."""
    return df.select(*[(F.col(c).cast("bigint") if t in ("int", "smallint", "tinyint") else F.col(c)).alias(attr_map.get(c, c)) for c, t in df.dtypes])


def u32(text: Column) -> Column:
    """A 32-bit number from md5, the same in other SQL engines."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def bridge(key: str, salt: str, domain: int) -> Column:
    """An artificial join attribute: a hash of a key, in a domain of given size."""
    return F.pmod(u32(F.concat(F.col(key).cast("string"), F.lit(salt))), F.lit(domain)).cast("bigint")


def dirtied(df: DataFrame, row_id: Sequence[str], column: str, domain: int, share: float = 0.3) -> DataFrame:
    """A share of the rows, chosen by hash, gets a different value of an integer column with values 0 to domain - 1."""
    pk = F.concat_ws("-", *[F.col(c).cast("string") for c in row_id])
    other = F.pmod(F.col(column) + 1 + F.pmod(u32(F.concat(pk, F.lit("alt"))), F.lit(domain - 1)), F.lit(domain))
    hit = u32(F.concat(pk, F.lit("dirt"))) < F.lit(int(share * 2**32))
    return df.withColumn(column, F.when(hit, other).otherwise(F.col(column)).cast("bigint"))


# ------------------------------------------------------------------------------------------------ fixtures


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def star_tables(spark: SparkSession, sf_dir: str, planted: bool = False, dirty: bool = False) -> dict[str, DataFrame]:
    """The eight star-schema instances under canonical names, with bridge attributes.

    planted adds attributes that other attributes determine; dirty then breaks 30 % of them, in all but region and nation.
    """
    region = canonical(_t(spark, sf_dir, "region"), {"r_regionkey": "regionkey"})
    nation = canonical(_t(spark, sf_dir, "nation"), {"n_nationkey": "nationkey", "n_regionkey": "regionkey"})
    customer = canonical(_t(spark, sf_dir, "customer"), {"c_custkey": "custkey", "c_nationkey": "nationkey"})
    customer = customer.withColumn("xj_g", bridge("custkey", "g", 120)).withColumn("xj_h", bridge("custkey", "h", 30))
    supplier = canonical(_t(spark, sf_dir, "supplier"), {"s_suppkey": "suppkey", "s_nationkey": "nationkey"})
    for salt, domain in (("e", 40), ("f", 40), ("h", 25)):
        supplier = supplier.withColumn(f"xj_{salt}", bridge("suppkey", salt, domain))
    part = canonical(_t(spark, sf_dir, "part"), {"p_partkey": "partkey"})
    orders = canonical(_t(spark, sf_dir, "orders"), {"o_orderkey": "orderkey", "o_custkey": "custkey"}).withColumn("xj_g", bridge("custkey", "g", 150))
    lineitem = canonical(_t(spark, sf_dir, "lineitem"), {"l_orderkey": "orderkey", "l_partkey": "partkey", "l_suppkey": "suppkey", "l_linenumber": "linenumber"})
    lineitem = lineitem.withColumn("xj_f", bridge("suppkey", "f", 60))
    partsupp = lineitem.groupBy("partkey", "suppkey").agg(F.sum("l_quantity").alias("ps_availqty")).withColumn("xj_e", bridge("suppkey", "e", 50))
    if planted or dirty:
        of_nation = F.broadcast(nation.select("nationkey", F.col("regionkey").alias("__r")))  # 25 rows
        customer = customer.join(of_nation, "nationkey", "left").withColumnRenamed("__r", "c_regionkey")
        supplier = supplier.join(of_nation, "nationkey", "left").withColumnRenamed("__r", "s_regionkey")
        part = part.withColumn("p_mfgr", F.pmod(F.regexp_extract("p_brand", r"([0-9]+)", 1).cast("bigint"), F.lit(5)).cast("bigint"))
        orders = orders.withColumn("o_year", (F.year("o_orderdate") - 1995).cast("bigint"))
        lineitem = lineitem.withColumn("l_shipyear", (F.year("l_shipdate") - 1995).cast("bigint"))
        partsupp = partsupp.join(supplier.select("suppkey", F.col("nationkey").alias("ps_nation")), "suppkey", "left")
    if dirty:
        customer = dirtied(customer, ["custkey"], "c_regionkey", 5)
        supplier = dirtied(supplier, ["suppkey"], "s_regionkey", 5)
        part = dirtied(part, ["partkey"], "p_mfgr", 5)
        orders = dirtied(orders, ["orderkey"], "o_year", 7)
        lineitem = dirtied(lineitem, ["orderkey", "linenumber", "partkey", "suppkey"], "l_shipyear", 7)
        partsupp = dirtied(partsupp, ["partkey", "suppkey"], "ps_nation", 25)
    return {"region": region, "nation": nation, "customer": customer, "supplier": supplier, "part": part, "partsupp": partsupp, "orders": orders, "lineitem": lineitem}


#: Dependencies that hold by construction where nothing is dirty.
PLANTED = {
    "customer": (FD(("nationkey",), "c_regionkey"),),
    "supplier": (FD(("nationkey",), "s_regionkey"),),
    "part": (FD(("p_brand",), "p_mfgr"),),
    "orders": (FD(("o_orderdate",), "o_year"),),
    "lineitem": (FD(("l_shipdate",), "l_shipyear"),),
    "partsupp": (FD(("suppkey",), "ps_nation"),),
}
KEYS = {
    "region": (FD(("regionkey",), "r_name"),),
    "nation": (FD(("nationkey",), "n_name"), FD(("nationkey",), "regionkey")),
    "customer": (FD(("custkey",), "c_acctbal"), FD(("custkey",), "nationkey")),
    "supplier": (FD(("suppkey",), "s_acctbal"), FD(("suppkey",), "nationkey")),
    "part": (FD(("partkey",), "p_brand"), FD(("partkey",), "p_type")),
    "orders": (FD(("orderkey",), "custkey"), FD(("orderkey",), "o_totalprice"), FD(("orderkey",), "o_orderpriority")),
}


def star_marketplace(spark: SparkSession, sf_dir: str, planted: bool = False, dirty: bool = False) -> Marketplace:
    fds = {n: (*KEYS.get(n, ()), *(PLANTED.get(n, ()) if planted or dirty else ())) for n in {*KEYS, *PLANTED}}
    return Marketplace.of(star_tables(spark, sf_dir, planted, dirty), fds)


def fragment_marketplace(spark: SparkSession, sf_dir: str) -> Marketplace:
    """29 vertical fragments of the given tables, a stand-in for a marketplace of many narrow tables."""
    s = star_tables(spark, sf_dir)
    events = _t(spark, sf_dir, "events").select(
        "event_id", F.col("user_id").alias("custkey"), "event_type", "value",
        F.get_json_object("props", "$.k").cast("bigint").alias("ev_k"), F.to_date("ts").alias("ev_day"), F.hour("ts").cast("bigint").alias("ev_hour"),
    )
    n_customers = s["customer"].count()
    documents = _t(spark, sf_dir, "documents").select("doc_id", F.pmod("doc_id", F.lit(max(n_customers, 1))).alias("custkey"), "lang", "source", F.floor(F.col("n_chars") / 500).cast("bigint").alias("n_chars"))
    turns = _t(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("doc_id")).agg(F.count("*").alias("turns"), F.min(F.struct("turn", "role"))["role"].alias("first_role"))
    labels = _t(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("bigint").alias("quality"), F.col("toxic").cast("bigint").alias("toxic"))
    emb = _t(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("label").cast("bigint").alias("label"))
    orders = s["orders"]
    cut = lambda df, *cols: df.select(*cols)
    return Marketplace.of(
        {
            "region": s["region"], "nation": s["nation"],
            "cust_core": cut(s["customer"], "custkey", "nationkey", "c_mktsegment"), "cust_bal": cut(s["customer"], "custkey", "c_acctbal", "xj_g"), "cust_name": cut(s["customer"], "custkey", "c_name"),
            "supp_core": cut(s["supplier"], "suppkey", "nationkey"), "supp_bal": cut(s["supplier"], "suppkey", "s_acctbal", "xj_e"), "supp_name": cut(s["supplier"], "suppkey", "s_name"),
            "part_core": cut(s["part"], "partkey", "p_brand", "p_type"), "part_size": cut(s["part"], "partkey", "p_size", "p_retailprice"), "part_name": cut(s["part"], "partkey", "p_name"),
            "partsupp": cut(s["partsupp"], "partkey", "suppkey", "ps_availqty", "xj_e"),
            "ord_core": cut(orders, "orderkey", "custkey", "o_orderstatus"), "ord_price": cut(orders, "orderkey", "o_totalprice", "xj_g"), "ord_prio": cut(orders, "orderkey", "o_orderpriority"), "ord_date": cut(orders, "orderkey", "o_orderdate"),
            "line_core": cut(s["lineitem"], "orderkey", "linenumber", "partkey", "suppkey"), "line_qty": cut(s["lineitem"], "orderkey", "linenumber", "l_quantity", "l_extendedprice"),
            "line_disc": cut(s["lineitem"], "orderkey", "linenumber", "l_discount", "l_tax"), "line_flags": cut(s["lineitem"], "orderkey", "linenumber", "l_returnflag", "l_linestatus"), "line_ship": cut(s["lineitem"], "orderkey", "linenumber", "l_shipdate"),
            "ev_core": cut(events, "event_id", "custkey", "event_type"), "ev_value": cut(events, "event_id", "value", "ev_k"), "ev_time": cut(events, "event_id", "ev_day", "ev_hour"),
            "doc_core": cut(documents, "doc_id", "custkey", "lang", "source"), "doc_size": cut(documents, "doc_id", "n_chars"), "labels": labels, "conv_stat": turns, "emb_label": emb,
        },
    )
