"""Target graphs, and their measures as one Catalyst plan.

A target graph is evaluated without materialising its join: each instance is collapsed to (projected attributes, count)
before it is joined, counts multiply, and the frame is collapsed again whenever attributes are no longer needed. Bag
semantics are kept. All measures take the counts as weights.
"""

from __future__ import annotations

from collections.abc import Iterable, Mapping, Sequence
from dataclasses import dataclass
from functools import reduce

from py4j.protocol import Py4JJavaError
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from ..functions.measures import FD, W, correlation_df, counted, joint_quality_df, kind_of
from ..functions.storage import dropped, settle
from ..operators.sampling import keyed_sample, thinned
from ..sources.marketplace import Marketplace
from . import factored
from .joingraph import Join, JoinGraph, Pair, pair


@dataclass(frozen=True)
class TargetGraph:
    """Join sets chosen for the edges of a tree of instances, and the instance that supplies each requested attribute."""

    edges: tuple[tuple[Pair, Join], ...]
    supply: tuple[tuple[str, str], ...]  # (attribute, instance), source attributes first

    @classmethod
    def of(cls, edges: Mapping[Pair, Iterable[str]], supply: Mapping[str, str]) -> TargetGraph:
        return cls(tuple(sorted((p, tuple(sorted(j))) for p, j in edges.items())), tuple(supply.items()))

    @property
    def instances(self) -> list[str]:
        return sorted({v for p, _ in self.edges for v in p} | {n for _, n in self.supply})

    @property
    def projections(self) -> dict[str, frozenset[str]]:
        """What is bought of each instance: its edges' join attributes and the requested attributes that it supplies."""
        out: dict[str, set[str]] = {n: set() for n in self.instances}
        for (a, b), j in self.edges:
            out[a] |= set(j)
            out[b] |= set(j)
        for attribute, n in self.supply:
            out[n].add(attribute)
        return {n: frozenset(s) for n, s in out.items()}

    @property
    def joins(self) -> dict[Pair, Join]:
        """The attributes that each edge really joins on: all that both of its projections have."""
        p = self.projections
        return {(a, b): tuple(sorted(p[a] & p[b])) for (a, b), _ in self.edges}

    def order(self, root: str) -> list[tuple[str, str | None]]:
        """Instances breadth first from the root, each with its parent."""
        near: dict[str, list[str]] = {n: [] for n in self.instances}
        for (a, b), _ in self.edges:
            near[a].append(b)
            near[b].append(a)
        out: list[tuple[str, str | None]] = [(root, None)]
        seen = {root}
        for v, _ in out:
            for u in sorted(near[v]):
                if u not in seen:
                    seen.add(u)
                    out.append((u, v))
        if len(out) < len(self.instances):
            raise ValueError("the target graph is not connected")
        return out

    def column(self, attribute: str) -> str:
        return f"{dict(self.supply)[attribute]}__{attribute}"

    def label(self) -> str:
        return "; ".join(f"{a}-{b}({'+'.join(j)})" for (a, b), j in self.edges)


def plan_price(graph: JoinGraph, plan: TargetGraph) -> float:
    graph.add_prices([(n, a) for n, a in plan.projections.items() if not graph.market[n].owned])
    return sum(graph.price(n, a) for n, a in plan.projections.items())


def plan_weight(graph: JoinGraph, plan: TargetGraph) -> float:
    """Summed informativeness of the edges, on the attributes that they really join on."""
    return sum(graph.weight(a, b, j) for (a, b), j in plan.joins.items())


def plan_fds(market: Marketplace, plan: TargetGraph) -> list[FD]:
    """Dependencies that lie within a projection, under the columns of the joined frame."""
    p = plan.projections
    return [FD(tuple(f"{n}__{a}" for a in fd.lhs), f"{n}__{fd.rhs}") for n in plan.instances for fd in market[n].fds if set(fd.attributes) <= p[n]]


def instance_frames(market: Marketplace, plan: TargetGraph, rate: float = 1.0, hash_name: str = "xxhash64", seed: int = 0) -> dict[str, DataFrame]:
    """What is bought of each instance, sampled on its edges' join attributes and collapsed, with counts in W."""
    out = {}
    for name, attributes in plan.projections.items():
        df = market[name].df
        for e, j in plan.joins.items():
            if name in e:
                df = keyed_sample(df, j, rate, hash_name, seed)
        own = counted(df, sorted(attributes))
        out[name] = own.select(*[F.col(a).alias(f"{name}__{a}") for a in sorted(attributes)], W)
    return out


def plan_to_df(market: Marketplace, plan: TargetGraph, needed: Sequence[str], rate: float = 1.0, eta: float | None = None, resample: float = 0.5, hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """The join of a plan's projections, collapsed to the needed columns with counts in W.

    rate < 1 samples each instance on its own edges' join attributes. An intermediate join of more than eta rows, by a
    forecast from the key counts of its sides, is re-sampled: every one of its rows is kept or not on its own, which on the
    collapsed frame thins the counts.
    """
    joins = plan.joins
    root = plan.supply[0][1]
    order = plan.order(root)
    frames = instance_frames(market, plan, rate, hash_name, seed)
    out: DataFrame | None = None
    for k, (name, parent) in enumerate(order):
        own = frames[name].withColumnRenamed(W, "__v")
        too_large = False
        if out is None:
            out = own.withColumnRenamed("__v", W)
        else:
            if eta is not None and k < len(order) - 1:
                out, own = settle(out), settle(own)  # read twice, by the forecast and by the join
                too_large = forecast(out, own, [(f"{parent}__{a}", f"{name}__{a}") for a in joins[pair(name, parent)]]) > eta
            on = [F.col(f"{parent}__{a}") == F.col(f"{name}__{a}") for a in joins[pair(name, parent)]]
            out = out.join(own, reduce(lambda x, y: x & y, on)).withColumn(W, F.col(W) * F.col("__v")).drop("__v")
        # columns that later joins or the measures still need
        later = {v for v, _ in order[k + 1 :]}
        alive = {f"{u}__{a}" for v, u in order[k + 1 :] if u not in later for a in joins[pair(v, u)]} | set(needed)
        keep = [c for c in out.columns if c in alive]
        out = out.groupBy(*keep).agg(F.sum(W).alias(W)) if k else out.select(*keep, W).groupBy(*keep).agg(F.sum(W).alias(W))
        if too_large:
            out = out.withColumn(W, thinned(F.col(W), resample, keep, hash_name, seed + k)).where(F.col(W) > 0)
    return out


def forecast(left: DataFrame, right: DataFrame, on: Sequence[tuple[str, str]]) -> float:
    """Rows of the join of two collapsed frames, weighted by W and __v, from their key counts."""
    a = left.groupBy(*[F.col(x).alias(f"__k{i}") for i, (x, _) in enumerate(on)]).agg(F.sum(W).alias("__a"))
    b = right.groupBy(*[F.col(y).alias(f"__k{i}") for i, (_, y) in enumerate(on)]).agg(F.sum("__v").alias("__b"))
    return a.join(b, [f"__k{i}" for i in range(len(on))]).agg(F.sum(F.col("__a").cast("double") * F.col("__b"))).first()[0] or 0.0


def _measures(frame: DataFrame, xs: Sequence[str], ys: Sequence[str], fds: Sequence[FD], kinds: dict[str, str] | None) -> DataFrame:
    corr = correlation_df(frame, xs, ys, kinds, W)
    quality = joint_quality_df(frame, fds, W)
    return corr.crossJoin(quality).crossJoin(frame.agg(F.coalesce(F.sum(W), F.lit(0)).cast("long").alias("join_rows")))  # one row each


def _parts(market: Marketplace, plan: TargetGraph, a_s: Sequence[str], a_t: Sequence[str], fds: Sequence[FD] | None) -> tuple[list[str], list[str], Sequence[FD], list[str]]:
    xs, ys = [plan.column(a) for a in a_s], [plan.column(a) for a in a_t]
    fds = plan_fds(market, plan) if fds is None else fds
    return xs, ys, fds, list(dict.fromkeys([*xs, *ys, *(a for fd in fds for a in fd.attributes)]))


def score_df(market: Marketplace, plan: TargetGraph, a_s: Sequence[str], a_t: Sequence[str], kinds: dict[str, str] | None = None, fds: Sequence[FD] | None = None, **sampling) -> DataFrame:
    """corr, quality and join_rows of a plan, one row. The collapsed join is written once and read by all measures.

    Without a bound on intermediate joins, subtrees are collapsed before they are joined, so branches do not multiply.
    """
    xs, ys, fds, needed = _parts(market, plan, a_s, a_t, fds)
    if sampling.get("eta") is None:
        kept = {k: v for k, v in sampling.items() if k not in ("eta", "resample")}
        frame = factored.subtree(plan, instance_frames(market, plan, **kept), plan.supply[0][1], None, needed)
    else:
        frame = plan_to_df(market, plan, needed, **sampling)
    return _measures(settle(frame), xs, ys, fds, kinds)


def score_row(market: Marketplace, plan: TargetGraph, a_s: Sequence[str], a_t: Sequence[str], kinds: dict[str, str] | None = None, fds: Sequence[FD] | None = None, large: bool = False, **sampling) -> Row:
    """The row of score_df; its tables are dropped. A large join is scored from its tables, unless it is to be re-sampled.

    So is one with more rows than a long holds, with wide counts.
    """
    whole = fds is None and sampling.get("eta") is None

    def from_tables(wide: bool) -> Row:
        kept = {k: v for k, v in sampling.items() if k not in ("eta", "resample")}
        xs, ys, *_ = _parts(market, plan, a_s, a_t, fds)
        return factored.score(market, plan, instance_frames(market, plan, **kept), xs, ys, kinds, wide)

    try:
        with dropped():
            return from_tables(False) if large and whole else score_df(market, plan, a_s, a_t, kinds, fds, **sampling).first()
    except (PySparkException, Py4JJavaError) as e:
        if not whole or not _overflowed(e):
            raise
    with dropped():
        return from_tables(True)


def _overflowed(e: Exception) -> bool:
    """Whether a count grew beyond a long; where a table was being written, only the trace tells."""
    return "ARITHMETIC_OVERFLOW" in f"{e}{getattr(e, '_stackTrace', '')}"


def plan_kinds(market: Marketplace, plan: TargetGraph, a_s: Sequence[str], kinds: dict[str, str] | None = None) -> dict[str, str]:
    return {a: kind_of(market[dict(plan.supply)[a]].df, a, kinds) for a in a_s}


def forecast_rows(graph: JoinGraph, plan: TargetGraph) -> float:
    """The largest two-table join of a plan, known from key counts before anything runs."""
    return max((graph.join_rows.get((p, j), 0.0) for p, j in plan.joins.items()), default=0.0)
