"""Optional older forms of the search and its objective, kept apart from the planner: none of them is its default.

Join strength is the size of a join over the product of its tables' sizes; the scalar objective weighs it against quality.
The path searches go over two-attribute sets: a hop enters an instance by one attribute and leaves it by another, and the
next hop, in another instance, enters by the attribute that this one left by. Searches run on the driver over schemas;
only the objective of a path is a Spark job, and each is computed once.
"""

from __future__ import annotations

import math
import random
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field
from itertools import permutations, product

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.measures import W, counted
from ..sources.marketplace import Marketplace
from .evaluate import TargetGraph, score_row
from .joingraph import Join, JoinGraph, Pair, pair
from .request import Evaluator
from .steiner import landmark_sketch, minimal_igraphs, pick_landmarks


def join_strength_df(left: DataFrame, right: DataFrame, join: Sequence[str]) -> DataFrame:
    """(join_rows, strength) of two tables, from key counts: hot keys cost a row a task."""
    a, b = counted(left, join).withColumnRenamed(W, "a"), counted(right, join).withColumnRenamed(W, "b")
    both = a.select(*join, "a", F.lit(0).cast("long").alias("b")).unionByName(b.select(*join, F.lit(0).cast("long").alias("a"), "b"))
    per = both.groupBy(*join).agg(F.sum("a").cast("double").alias("a"), F.sum("b").cast("double").alias("b"))
    has_key = F.lit(True)
    for k in join:
        has_key = has_key & F.col(k).isNotNull()
    rows = F.coalesce(F.sum(F.when(has_key, F.col("a") * F.col("b"))), F.lit(0.0))
    size = F.sum("a") * F.sum("b")
    return per.agg(rows.alias("join_rows"), F.when(size > 0, rows / size).otherwise(F.lit(0.0)).alias("strength"))


def strength_bound(strengths: Sequence[float]) -> float:
    """No path is stronger than the weakest of the joins along it."""
    return min(strengths, default=1.0)


def scalar_objective(quality: float, strength: float, share: float = 0.5) -> float:
    return share * quality + (1 - share) * strength


@dataclass(frozen=True, order=True)
class Hop:
    instance: str
    enters: str
    leaves: str


Route = tuple[Hop, ...]
Objective = Callable[[Route], float]


def route_plan(route: Route) -> TargetGraph:
    edges = {pair(a.instance, b.instance): [a.leaves] for a, b in zip(route, route[1:], strict=False)}
    return TargetGraph.of(edges, {route[0].enters: route[0].instance, route[-1].leaves: route[-1].instance})


@dataclass
class RouteObjective:
    """The scalar objective of the join along a route, computed once each."""

    market: Marketplace
    share: float = 0.5
    known: dict[Route, float] = field(default_factory=dict)
    sizes: dict[str, int] = field(default_factory=dict)

    def __call__(self, route: Route) -> float:
        if route not in self.known:
            row = score_row(self.market, route_plan(route), (route[0].enters,), (route[-1].leaves,))
            self.known[route] = scalar_objective(row["quality"] if row["quality"] is not None else 0.0, self.strength([h.instance for h in route], row["join_rows"]), self.share)
        return self.known[route]

    def strength(self, instances: Sequence[str], rows: int) -> float:
        for n in instances:
            if n not in self.sizes:
                self.sizes[n] = self.market[n].df.count()
        size = math.prod(self.sizes[n] for n in instances)
        return rows / size if size else 0.0


def hops(schemas: dict[str, Sequence[str]], source: str, target: str) -> list[Hop]:
    """All hops that a route from source to target can use: over join attributes and the two ends."""
    holders: dict[str, int] = {}
    for attributes in schemas.values():
        for a in attributes:
            holders[a] = holders.get(a, 0) + 1
    useful = {a for a, n in holders.items() if n > 1} | {source, target}
    found = (Hop(n, a, b) for n, attributes in sorted(schemas.items()) for a, b in permutations(sorted(useful & set(attributes)), 2))
    return [h for h in found if h.leaves != source and h.enters != target]


def _follows(route: Route, hop: Hop) -> bool:
    return route[-1].leaves == hop.enters and all(h.instance != hop.instance for h in route)


def all_routes(schemas: dict[str, Sequence[str]], source: str, target: str) -> Iterator[Route]:
    """Every route from source to target that visits no instance twice."""
    every = hops(schemas, source, target)
    todo: list[Route] = [(h,) for h in every if h.enters == source]
    while todo:
        route = todo.pop()
        if route[-1].leaves == target:
            yield route
        else:
            todo += [(*route, h) for h in every if _follows(route, h)]


def dp_allpairs(schemas: dict[str, Sequence[str]], source: str, target: str, objective: Objective) -> Route | None:
    """The best route by a table over pairs of hops that admits one more hop in the middle at a time.

    The objective has no optimal substructure, so unlike all_routes this may miss the best route of many hops.
    """
    every = hops(schemas, source, target)
    best: dict[tuple[Hop, Hop], Route] = {(h, h): (h,) for h in every}
    best |= {(h, g): (h, g) for h in every for g in every if _follows((h,), g)}
    for middle in every:
        into = [(h, r) for (h, g), r in best.items() if g == middle and h != middle]
        onward = [(g, r) for (h, g), r in best.items() if h == middle and g != middle]
        for (h, first), (g, second) in product(into, onward):
            route = first + second[1:]
            if len({x.instance for x in route}) == len(route) and (best.get((h, g)) is None or objective(route) > objective(best[h, g])):
                best[h, g] = route
    ends = [r for (h, g), r in best.items() if h.enters == source and g.leaves == target]
    return max(sorted(ends), key=objective, default=None)


def greedy_hop(schemas: dict[str, Sequence[str]], source: str, target: str, objective: Objective) -> Route | None:
    """A route grown by the hop that makes it best, the target being taken as soon as it is in reach; None at a dead end."""
    every = hops(schemas, source, target)
    route: Route = ()
    while not route or route[-1].leaves != target:
        longer = [(*route, h) for h in every if (_follows(route, h) if route else h.enters == source)]
        longer = [r for r in longer if r[-1].leaves == target] or longer
        if not longer:
            return None
        route = max(sorted(longer), key=objective)
    return route


def hop_sketch(graph: JoinGraph, source: tuple[str, str], target: tuple[str, str], objective: Callable[[TargetGraph], float], seed: int = 0, landmarks: int | None = None) -> TargetGraph | None:
    """Of the trees of fewest hops between two (attribute, instance) ends, by landmarks, the join sets of the best objective."""
    sketch = landmark_sketch(graph, pick_landmarks(graph.market.names, seed, landmarks), hops=True)
    trees = minimal_igraphs(graph, [source[1], target[1]], sketch, keep="all")
    fewest = min(map(len, trees), default=0)
    plans = []
    for tree in trees:
        if len(tree) == fewest:
            edges = sorted(tree)
            plans += [TargetGraph.of(dict(zip(edges, joins, strict=True)), dict([source, target])) for joins in product(*[graph.choices(*e) for e in edges])]
    return max(sorted(plans, key=TargetGraph.label), key=objective, default=None)


def arbitrage(priced: DataFrame) -> DataFrame:
    """Rows of (attributes, entropy, price) that cost less than a set of smaller entropy; none if prices never fall with entropy.

    One row an attribute set, so the one window is as large as the lattice of a schema. Entropies equal to nine digits are ties.
    """
    rows = priced.withColumn("__h", F.round("entropy", 9))
    most = rows.groupBy("__h").agg(F.max("price").alias("__most"))
    below = most.select("__h", F.max("__most").over(Window.orderBy("__h").rowsBetween(Window.unboundedPreceding, -1)).alias("dearest_below"))
    return rows.join(below, "__h").where(F.col("price") < F.col("dearest_below") - 1e-9).drop("__h")


def _other_joins(graph: JoinGraph, state: TargetGraph) -> dict[Pair, list[Join]]:
    """The edges of a state that can be joined otherwise, with the other join sets."""
    found = {e: sorted(j for j in graph.choices(*e) if j != now) for e, now in state.edges}
    return {e: joins for e, joins in found.items() if joins}


def quality_walk(evaluator: Evaluator, start: TargetGraph, objective: Callable[[TargetGraph], float], iterations: int = 100, seed: int = 0) -> TargetGraph:
    """A walk that takes a step with the ratio of qualities as its probability; the state of the best objective that it met."""
    rng, now, best = random.Random(seed), start, start
    for _ in range(iterations):
        open_ = _other_joins(evaluator.graph, now)
        if not open_:
            break
        e = rng.choice(sorted(open_))
        step = TargetGraph.of({**dict(now.edges), e: rng.choice(open_[e])}, dict(start.supply))
        luck, old = rng.random(), evaluator.score(now).quality
        if old <= 0 or luck < evaluator.score(step).quality / old:
            now = step
            best = max(best, now, key=objective)
    return best


def directed_walk(evaluator: Evaluator, start: TargetGraph, iterations: int = 100, seed: int = 0) -> TargetGraph | None:
    """A walk over all states, also those beyond the limits; the feasible state of the highest correlation that it met.

    The edge to change is drawn by the price of its two projections while the price is above the budget, by its weight while
    the weight is above its limit, and evenly otherwise.
    """
    graph, request = evaluator.graph, evaluator.request
    rng, now = random.Random(seed), start
    met = {now} if evaluator.feasible(now) else set()
    for _ in range(iterations):
        open_ = _other_joins(graph, now)
        if not open_:
            break
        price, weight = evaluator.static(now)
        edges = sorted(open_)
        odds = [1.0] * len(edges)
        if price > request.budget:
            odds = [sum(graph.price(n, now.projections[n]) for n in e) for e in edges]
        elif weight > request.alpha:
            odds = [graph.weight(*e, now.joins[e]) for e in edges]
        e = rng.choices(edges, odds if sum(odds) > 0 else None)[0]
        now = TargetGraph.of({**dict(now.edges), e: rng.choice(open_[e])}, dict(start.supply))
        if now not in met and evaluator.feasible(now):
            met.add(now)
    return max(sorted(met, key=TargetGraph.label), key=lambda p: evaluator.score(p).corr, default=None)
