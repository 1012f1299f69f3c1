"""The two-layer join graph: instances and their attribute sets, weighted by join informativeness, priced by entropy.

The off-line phase. Schemas give the upper layer; each distinct set of join attributes is weighed once for all pairs of
instances that share it, by one combinable pass over a tagged union of key counts; every instance is read once. Vertices of the lower layer are never materialised
beyond the sets that requests ask prices for: equal join attributes have equal weights, so edges need only their join set.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.measures import entropies_df, informativeness_of_samples
from ..operators.sampling import thinned, unit_hash
from ..sources.marketplace import Marketplace
from .lattice import lattice, size

Join = tuple[str, ...]
Pair = tuple[str, str]


def pair(a: str, b: str) -> Pair:
    return (a, b) if a < b else (b, a)


def schema_table(spark: SparkSession, market: Marketplace) -> DataFrame:
    """(instance, attribute): all that the upper layer needs."""
    return spark.createDataFrame([(n, a) for n in market.names for a in market[n].attributes], "instance string, attribute string")


def filled_schema_table(market: Marketplace) -> DataFrame:
    """(instance, attribute) of the attributes that have a value in some row: an empty one joins nothing."""
    out = None
    for n in market.names:
        df = market[n].df
        one = df.agg(*[(F.count(a) > 0).alias(a) for a in df.columns])
        one = one.select(F.explode(F.array(*[F.struct(F.lit(n).alias("instance"), F.lit(a).alias("attribute"), F.col(a).alias("filled")) for a in df.columns])).alias("e")).select("e.*")
        out = one if out is None else out.unionByName(one)
    return out.where("filled").select("instance", "attribute")


def instance_edges(schemas: DataFrame) -> DataFrame:
    """(src, dst, common): an equi-join on the attribute, not a product of instances."""
    a, b = schemas.select(F.col("instance").alias("src"), "attribute"), schemas.select(F.col("instance").alias("dst"), "attribute")
    return a.join(b, "attribute").where("src < dst").groupBy("src", "dst").agg(F.sort_array(F.collect_set("attribute")).alias("common"))


def join_sets(common: Sequence[str]) -> list[Join]:
    """All non-empty subsets of the common attributes, in a canonical order."""
    return [tuple(s) for k in range(1, len(common) + 1) for s in combinations(sorted(common), k)]


@dataclass
class JoinGraph:
    market: Marketplace
    weights: dict[tuple[Pair, Join], float]
    join_rows: dict[tuple[Pair, Join], float] = field(default_factory=dict)
    prices: dict[tuple[str, frozenset[str]], float] = field(default_factory=dict)
    rate: float = 1.0

    def choices(self, a: str, b: str) -> list[Join]:
        return [j for (p, j) in self.weights if p == pair(a, b)]

    def weight(self, a: str, b: str, join: Iterable[str]) -> float:
        return self.weights[pair(a, b), tuple(sorted(join))]

    def edges(self) -> dict[Pair, tuple[float, Join]]:
        """The upper layer: the lightest join set of each pair; ties go to fewer attributes, then to names."""
        best: dict[Pair, tuple[float, Join]] = {}
        for (p, j), w in sorted(self.weights.items(), key=lambda x: (x[0][0], round(x[1], 12), len(x[0][1]), x[0][1])):
            best.setdefault(p, (w, j))
        return best

    def price(self, name: str, attributes: Iterable[str]) -> float:
        """Entropy price of a projection; owned instances cost nothing. Computed once and kept."""
        if self.market[name].owned:
            return 0.0
        key = (name, frozenset(attributes))
        if key not in self.prices:
            self.add_prices([key])
        return self.prices[key]

    def add_prices(self, keys: Iterable[tuple[str, frozenset[str]]]) -> None:
        """Prices of many projections, one batched job for each instance, up to four at once."""
        todo: dict[str, list[frozenset[str]]] = {}
        for name, attributes in dict.fromkeys(keys):
            if attributes and (name, attributes) not in self.prices:
                todo.setdefault(name, []).append(attributes)
            elif not attributes:
                self.prices[name, attributes] = 0.0

        def priced(name: str) -> list[tuple[tuple[str, frozenset[str]], float]]:
            names = {"+".join(sorted(s)): s for s in todo[name]}
            found = entropies_df(self.market[name].df, [sorted(s) for s in todo[name]]).collect()  # one row an attribute set
            return [((name, names[r["attributes"]]), r["entropy"]) for r in found]

        if todo:
            with ThreadPoolExecutor(min(4, len(todo))) as pool:
                self.prices.update(p for found in pool.map(priced, todo) for p in found)

    def restricted(self, names: Sequence[str]) -> JoinGraph:
        """The graph over some of the instances; what is known of them is kept."""
        inside = set(names)
        weights = {k: w for k, w in self.weights.items() if set(k[0]) <= inside}
        return JoinGraph(self.market.restricted(sorted(inside)), weights, {k: self.join_rows[k] for k in weights if k in self.join_rows}, self.prices, self.rate)

    def stats(self) -> dict[str, int]:
        return {"instances": len(self.market.names), "as_vertices": sum(size(len(self.market[n].attributes)) for n in self.market.names), "i_edges": len(self.edges()), "weights": len(self.weights)}


def requested_sets(market: Marketplace) -> dict[Join, list[str]]:
    """Every distinct set of join attributes with the instances that hold it; at least two hold each."""
    out: dict[Join, list[str]] = {}
    for a, b in combinations(market.names, 2):
        for j in join_sets(market.common(a, b)):
            out.setdefault(j, market.holders(j))
    return out


def edge_weights(market: Marketplace, rate: float = 1.0, hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """(src, dst, j, weight, join_rows) of all pairs and join sets, on samples keyed by each join set when rate < 1."""
    return edge_weights_of_rates(market, [rate], hash_name, seed).drop("sample")


def edge_weights_of_rates(market: Marketplace, rates: Sequence[float], hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """(sample, src, dst, j, weight, join_rows): edge_weights at each rate, told by its place, in one pass.

    Whether a sample holds a row depends on its join value alone, so samples are drawn from the key counts; of rows without
    a join value a share is kept.
    """
    requested = requested_sets(market)
    if not requested:
        spark = next(iter(market.instances.values())).df.sparkSession
        return spark.createDataFrame([], "sample int, src string, dst string, j array<string>, weight double, join_rows double")
    shared = {a for j in requested for a in j}
    frames = {n: market[n].df.select(*[a for a in market[n].attributes if a in shared]) for n in market.names if shared & set(market[n].attributes)}

    def at(rate: float) -> Callable[[Sequence[str], Column], Column] | None:
        def kept(j: Sequence[str], count: Column) -> Column:
            return F.when(unit_hash(j, hash_name, seed) < rate, count).when(unit_hash(j, hash_name, seed).isNull(), thinned(count, rate, j, hash_name, seed)).otherwise(F.lit(0).cast("long"))

        return None if rate >= 1 else kept

    found = informativeness_of_samples(frames, sorted(requested), [at(r) for r in rates])
    return found.select("sample", "src", "dst", "j", F.col("ji").alias("weight"), "join_rows")


def build(market: Marketplace, rate: float = 1.0, hash_name: str = "xxhash64", seed: int = 0) -> JoinGraph:
    """The graph on the driver: its size is that of the schemas, not of the data."""
    return build_at(market, [rate], hash_name, seed)[0]


def build_at(market: Marketplace, rates: Sequence[float], hash_name: str = "xxhash64", seed: int = 0) -> list[JoinGraph]:
    """The graphs at several sampling rates, from one pass over the instances."""
    graphs = [JoinGraph(market, {}, rate=rate) for rate in rates]
    for r in edge_weights_of_rates(market, rates, hash_name, seed).collect():
        graph, key = graphs[r["sample"]], (pair(r["src"], r["dst"]), tuple(r["j"]))
        graph.weights[key], graph.join_rows[key] = r["weight"], r["join_rows"]
    return graphs


def min_edge_weight(weights: DataFrame) -> DataFrame:
    """(src, dst, weight, j): the lightest edge between each two instances."""
    w = Window.partitionBy("src", "dst").orderBy(F.round("weight", 9), F.size("j"), F.concat_ws(",", "j"))
    return weights.withColumn("r", F.row_number().over(w)).where("r = 1").select("src", "dst", "weight", "j")


def check_monotone(weights: DataFrame) -> DataFrame:
    """Pairs of nested join sets with how the weight moves from the smaller to the larger; it may rise or fall."""
    a = weights.select("src", "dst", F.col("j").alias("small"), F.col("weight").alias("weight_small"))
    b = weights.select("src", "dst", F.col("j").alias("large"), F.col("weight").alias("weight_large"))
    nested = (F.size("small") < F.size("large")) & (F.size(F.array_except("small", "large")) == 0)
    return a.join(b, ["src", "dst"]).where(nested).withColumn("moves", F.signum(F.round(F.col("weight_large") - F.col("weight_small"), 9)).cast("int"))


def vertex_prices(df: DataFrame, attributes: Sequence[str], min_size: int = 1) -> DataFrame:
    """(attributes, price) of all vertices of one instance's lattice."""
    return entropies_df(df, list(lattice(attributes, min_size))).select("attributes", F.col("entropy").alias("price"))


def save_graph(graph: JoinGraph, spark: SparkSession, path: str) -> None:
    rows = [(a, b, list(j), w, graph.join_rows.get(((a, b), j), 0.0)) for ((a, b), j), w in graph.weights.items()]
    spark.createDataFrame(rows, "src string, dst string, j array<string>, weight double, join_rows double").write.mode("overwrite").partitionBy("src").parquet(f"{path}/weights")
    prices = [(n, sorted(a), p) for (n, a), p in graph.prices.items()]
    spark.createDataFrame(prices, "instance string, attributes array<string>, price double").write.mode("overwrite").parquet(f"{path}/prices")


def load_graph(spark: SparkSession, market: Marketplace, path: str) -> JoinGraph:
    graph = JoinGraph(market, {})
    for r in spark.read.parquet(f"{path}/weights").collect():
        key = (pair(r["src"], r["dst"]), tuple(r["j"]))
        graph.weights[key], graph.join_rows[key] = r["weight"], r["join_rows"]
    for r in spark.read.parquet(f"{path}/prices").collect():
        graph.prices[r["instance"], frozenset(r["attributes"])] = r["price"]
    return graph
