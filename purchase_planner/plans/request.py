"""Acquisition requests: the random-walk planner, exhaustive baselines, and the loop that answers a shopper."""

from __future__ import annotations

import math
import random
import time
from collections.abc import Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from itertools import product

from pyspark.sql import Row, SparkSession

from ..sources.marketplace import Marketplace
from .evaluate import TargetGraph, forecast_rows, plan_price, plan_weight, score_row
from .factored import FORMED
from .joingraph import JoinGraph, Pair, build, join_sets
from .lattice import assignments
from .steiner import Sketch, landmark_sketch, minimal_igraphs, pick_landmarks, trees

EPS = 1e-9


@dataclass(frozen=True)
class Request:
    """Attributes that the shopper has (a_s) and wants (a_t), and limits on price, informativeness and quality.

    Without a_s, the first wanted attribute is correlated with the others.
    """

    a_s: tuple[str, ...]
    a_t: tuple[str, ...]
    budget: float = math.inf
    alpha: float = math.inf
    beta: float = 0.0
    kinds: tuple[tuple[str, str], ...] = ()
    max_rows: float = math.inf

    @property
    def sides(self) -> tuple[tuple[str, ...], tuple[str, ...]]:
        return (self.a_s, self.a_t) if self.a_s else (self.a_t[:1], self.a_t[1:] or self.a_t[:1])


@dataclass(frozen=True)
class Score:
    corr: float
    quality: float
    join_rows: int
    price: float
    weight: float


@dataclass
class Plan:
    status: str  # found, no_igraph, unaffordable, low_quality
    graph: TargetGraph | None = None
    score: Score | None = None
    seconds: float = 0.0
    evaluated: int = 0
    bill: float = 0.0

    @property
    def igraph_size(self) -> int:
        return len(self.graph.instances) if self.graph else 0


@dataclass
class Evaluator:
    """Scores of plans, computed once each. Price and weight are known without a job, so they are tested first."""

    graph: JoinGraph
    request: Request
    market: Marketplace | None = None
    rate: float = 1.0
    eta: float | None = None
    resample: float = 0.5
    hash_name: str = "xxhash64"
    seed: int = 0
    memo: dict[TargetGraph, Score] = field(default_factory=dict)

    def static(self, plan: TargetGraph) -> tuple[float, float]:
        return plan_price(self.graph, plan), plan_weight(self.graph, plan)

    def affordable(self, plan: TargetGraph) -> bool:
        price, weight = self.static(plan)
        return price <= self.request.budget + EPS and weight <= self.request.alpha + EPS and forecast_rows(self.graph, plan) <= self.request.max_rows

    def row(self, plan: TargetGraph) -> Row:
        x, y = self.request.sides
        large = forecast_rows(self.graph, plan) >= FORMED
        return score_row(self.market or self.graph.market, plan, x, y, dict(self.request.kinds), large=large, rate=self.rate, eta=self.eta, resample=self.resample, hash_name=self.hash_name, seed=self.seed)

    def score(self, plan: TargetGraph) -> Score:
        return self.scores([plan])[0]

    def scores(self, plans: Sequence[TargetGraph]) -> list[Score]:
        """Many plans at once: their jobs are submitted together, so the cluster is busy while small stages end."""
        todo = [p for p in dict.fromkeys(plans) if p not in self.memo]
        if todo:
            self.graph.add_prices([(n, a) for p in todo for n, a in p.projections.items() if not self.graph.market[n].owned])
            with ThreadPoolExecutor(min(4, len(todo))) as pool:
                rows = list(pool.map(self.row, todo))
            for plan, r in zip(todo, rows, strict=True):
                price, weight = self.static(plan)
                corr, quality = (float(r[c]) if r[c] is not None else 0.0 for c in ("corr", "quality"))
                self.memo[plan] = Score(corr, quality, int(r["join_rows"]), price, weight)
        return [self.memo[p] for p in plans]

    def feasible(self, plan: TargetGraph) -> bool:
        """All limits, the cheapest test first."""
        return self.affordable(plan) and self.score(plan).quality >= self.request.beta - EPS


def initial(graph: JoinGraph, tree: frozenset[Pair], supply: dict[str, str]) -> TargetGraph:
    """The lightest join set on every edge."""
    best = graph.edges()
    return TargetGraph.of({e: best[e][1] for e in tree}, supply)


def refine(evaluator: Evaluator, start: TargetGraph, iterations: int = 100, seed: int = 0, batch: bool = False, paper_start: bool = False) -> TargetGraph | None:
    """A seeded random walk over the join sets of a fixed tree; the best feasible state that it met.

    A step proposes another join set for one edge. States beyond the limits are passed over; others are taken with
    probability min(1, new / current correlation). paper_start does not let the first state be the answer. batch scores
    all neighbours of a state in one go; the walk itself is the same, since proposals come from the seeded generator.
    """
    rng = random.Random(seed)
    graph = evaluator.graph
    supply = dict(start.supply)
    now, best = start, None
    if not paper_start and evaluator.feasible(start):
        best = start

    def neighbours(state: TargetGraph) -> Iterator[TargetGraph]:
        chosen = dict(state.edges)
        for e in sorted(chosen):
            for j in graph.choices(*e):
                if j != chosen[e]:
                    yield TargetGraph.of({**chosen, e: j}, supply)

    for _ in range(iterations):
        chosen = dict(now.edges)
        open_ = [e for e in sorted(chosen) if len(graph.choices(*e)) > 1]
        if not open_:
            break
        e = rng.choice(open_)
        j = rng.choice(sorted(c for c in graph.choices(*e) if c != chosen[e]))
        luck = rng.random()
        if batch:
            evaluator.scores([p for p in neighbours(now) if evaluator.affordable(p)])
        proposal = TargetGraph.of({**chosen, e: j}, supply)
        if not evaluator.feasible(proposal):
            continue
        new, old = evaluator.score(proposal).corr, evaluator.score(now).corr if evaluator.affordable(now) else 0.0
        if old <= 0 or luck < min(1.0, new / old):
            now = proposal
            if best is None or new > evaluator.score(best).corr:
                best = now
    return best


def refine_many(evaluator: Evaluator, start: TargetGraph, iterations: int, seeds: Sequence[int]) -> TargetGraph | None:
    """The best of several independent walks; they share one memo of scores."""
    found = [p for p in (refine(evaluator, start, iterations, s) for s in seeds) if p is not None]
    return max(found, key=lambda p: evaluator.score(p).corr, default=None)


def supplies(market: Marketplace, request: Request) -> list[dict[str, str]]:
    """All ways to take the requested attributes from instances. What the shopper has is taken from owned instances where any holds it."""
    x, y = request.sides
    wanted = list(dict.fromkeys([*x, *y]))
    holders = {n: list(market[n].attributes) for n in market.names}
    for a in request.a_s:
        if any(market[n].owned and a in market[n].attributes for n in market.names):
            for n in market.names:
                if not market[n].owned and a in holders[n]:
                    holders[n].remove(a)
    return list(assignments(wanted, holders))


Candidate = tuple[float, frozenset[Pair], dict[str, str]]


def igraph_candidates(graph: JoinGraph, request: Request, sketch: Sketch, keep: str = "one") -> list[Candidate]:
    """Light trees for every way to supply the attributes, the lightest first."""
    weight = {e: w for e, (w, _) in graph.edges().items()}
    out = []
    for supply in supplies(graph.market, request):
        for tree in minimal_igraphs(graph, list(supply.values()), sketch, request.alpha, keep):
            out.append((round(sum(weight[e] for e in tree), 12), len(tree), sorted(tree), tree, supply))
    out.sort(key=lambda c: (c[0], c[1], c[2], sorted(c[4].items())))
    return [(c[0], c[3], c[4]) for c in out]


def spare_candidates(graph: JoinGraph, request: Request, landmarks: Sequence[str]) -> list[Candidate]:
    """Trees to fall back on where no lightest one can be paid or is good enough: of all landmarks, the lightest first, then
    those of fewest instances, with the terminals as landmarks too."""
    ends = {n for supply in supplies(graph.market, request) for n in supply.values()}
    wider = sorted({*landmarks, *ends})
    lighter = igraph_candidates(graph, request, landmark_sketch(graph, wider), "all")
    shorter = igraph_candidates(graph, request, landmark_sketch(graph, wider, hops=True), "all")
    return lighter + sorted(shorter, key=lambda c: len(c[1]))


def acquire(graph: JoinGraph, request: Request, iterations: int = 60, seed: int = 0, landmarks: int | None = None, keep: str = "one", evaluator: Evaluator | None = None, starts: int = 1, spare: bool = True) -> Plan:
    """The planner: light trees by landmarks, then the walk on the lightest of them (the first `starts`).

    A lightest tree may have many instances and cost more than the budget. Where the walks found nothing and `spare` is set,
    the remaining trees are walked one by one, until one has an answer.
    """
    began = time.perf_counter()
    evaluator = evaluator or Evaluator(graph, request)
    chosen = pick_landmarks(graph.market.names, seed, landmarks)
    candidates = igraph_candidates(graph, request, landmark_sketch(graph, chosen), keep)
    if not candidates and spare:
        candidates, starts = spare_candidates(graph, request, chosen), 0
    if not candidates:
        return Plan("no_igraph", seconds=time.perf_counter() - began)
    walked: set[tuple] = set()
    found, any_affordable = [], False

    def walk(tree: frozenset[Pair], supply: dict[str, str]) -> None:
        nonlocal any_affordable
        if (tree, tuple(supply.items())) in walked:
            return
        walked.add((tree, tuple(supply.items())))
        start = initial(graph, tree, supply)
        best = refine(evaluator, start, iterations, seed)
        any_affordable = any_affordable or evaluator.affordable(start) or any(evaluator.affordable(p) for p in evaluator.memo)
        if best is not None:
            found.append(best)

    for _, tree, supply in candidates[:starts]:
        walk(tree, supply)
    if spare and not found:
        for _, tree, supply in [*candidates[starts:], *spare_candidates(graph, request, chosen)]:
            walk(tree, supply)
            if found:
                break
    seconds = time.perf_counter() - began
    if not found:
        return Plan("low_quality" if any_affordable else "unaffordable", seconds=seconds, evaluated=len(evaluator.memo))
    best = max(found, key=lambda p: evaluator.score(p).corr)
    return Plan("found", best, evaluator.score(best), seconds, len(evaluator.memo))


def escalate(market: Marketplace, request: Request, rates: Sequence[float] = (0.1, 0.2, 0.4, 0.8, 1.0), tariff: float = 1.0, **more) -> tuple[Plan, list[tuple[float, str]]]:
    """Plans on samples, at a higher rate each time that none is found; only the new part of a sample is billed.

    Returns the plan and the (rate, status) of each attempt. The sample's price is its share of the instances' entropy price.
    """
    history: list[tuple[float, str]] = []
    bill, before = 0.0, 0.0
    plan = Plan("no_igraph")
    whole = None
    for rate in rates:
        graph = build(market, rate)
        if whole is None:
            whole = sum(graph.price(n, market[n].attributes) for n in market.names)
        bill += tariff * (rate - before) * whole
        before = rate
        plan = acquire(graph, request, evaluator=Evaluator(graph, request, rate=rate), **more)
        history.append((rate, plan.status))
        if plan.status == "found":
            break
    return replace_bill(plan, bill), history


def replace_bill(plan: Plan, bill: float) -> Plan:
    return replace(plan, bill=bill)


def sample_bill(rates: Sequence[float], whole: float, tariff: float = 1.0) -> float:
    """What samples at rising rates have cost: samples are nested, so the last rate counts."""
    return tariff * max(rates, default=0.0) * whole


def all_plans(graph: JoinGraph, request: Request, max_vertices: int, pinned: frozenset[Pair] | None = None) -> Iterator[TargetGraph]:
    """Every tree over the terminals of every supply, with every choice of join sets."""
    near: dict[str, list[str]] = {n: [] for n in graph.market.names}
    for a, b in graph.edges():
        near[a].append(b)
        near[b].append(a)
    seen = set()
    for supply in supplies(graph.market, request):
        options = [pinned] if pinned is not None else trees(near, list(supply.values()), max_vertices)
        for tree in options:
            if pinned is not None and not set(supply.values()) <= {v for e in tree for v in e}:
                continue
            edges = sorted(tree)
            for choice in product(*(join_sets(graph.market.common(*e)) for e in edges)):
                plan = TargetGraph.of(dict(zip(edges, choice, strict=True)), supply)
                if plan not in seen:
                    seen.add(plan)
                    yield plan


def exhaustive(graph: JoinGraph, request: Request, max_vertices: int = 3, evaluator: Evaluator | None = None, pinned: frozenset[Pair] | None = None) -> Plan:
    """The exhaustive baselines: every affordable plan is scored, on full data or, with a sampling evaluator, on samples."""
    began = time.perf_counter()
    evaluator = evaluator or Evaluator(graph, request)
    plans = list(all_plans(graph, request, max_vertices, pinned))
    if not plans:
        return Plan("no_igraph", seconds=time.perf_counter() - began)
    light = [p for p in plans if plan_weight(graph, p) <= request.alpha + EPS]
    graph.add_prices([(n, a) for p in light for n, a in p.projections.items() if not graph.market[n].owned])
    affordable = [p for p in light if evaluator.affordable(p)]
    evaluator.scores(affordable)
    good = [p for p in affordable if evaluator.score(p).quality >= request.beta - EPS]
    seconds = time.perf_counter() - began
    if not good:
        return Plan("low_quality" if affordable else "unaffordable", seconds=seconds, evaluated=len(affordable))
    best = max(good, key=lambda p: (round(evaluator.score(p).corr, 9), -len(p.edges), p.label()))
    return Plan("found", best, evaluator.score(best), seconds, len(affordable))


def emit_sql(plan: TargetGraph, market: Marketplace) -> list[str]:
    """One projection query for each instance that has to be bought."""
    return [f"SELECT {', '.join(sorted(a))} FROM {n}" for n, a in sorted(plan.projections.items()) if not market[n].owned]


def register_instances(spark: SparkSession, market: Marketplace) -> None:
    """Views under the instances' names, for the emitted queries."""
    for n in market.names:
        market[n].df.createOrReplaceTempView(n)


def top_k_plans(evaluator: Evaluator, plans: Sequence[TargetGraph], k: int, weights: tuple[float, float, float, float] = (1.0, 1.0, -1.0, -0.01)) -> list[tuple[TargetGraph, float]]:
    """The k best plans by a combined score of correlation, quality, informativeness and price."""
    scored = [(p, s.corr * weights[0] + s.quality * weights[1] + s.weight * weights[2] + s.price * weights[3]) for p, s in zip(plans, evaluator.scores(plans), strict=True)]
    return sorted(scored, key=lambda x: (-x[1], x[0].label()))[:k]
