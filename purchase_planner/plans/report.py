"""Comparison measures and sweeps of the experiments."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence
from dataclasses import replace

from ..sources.marketplace import Marketplace
from .evaluate import TargetGraph, plan_price
from .joingraph import JoinGraph, Pair, build
from .request import Evaluator, Plan, Request, acquire, all_plans, exhaustive


def correlation_difference(optimal: float, got: float) -> float | None:
    """(optimal - got) / optimal, on real correlations; None if the optimum is 0. Negative if got is larger."""
    return None if not optimal else (optimal - got) / optimal


def budget_range(graph: JoinGraph, request: Request, max_vertices: int = 3, pinned: frozenset[Pair] | None = None) -> tuple[float, float]:
    """Prices of the cheapest and the dearest plan."""
    plans = list(all_plans(graph, request, max_vertices, pinned))
    graph.add_prices([(n, a) for p in plans for n, a in p.projections.items() if not graph.market[n].owned])
    prices = [plan_price(graph, p) for p in plans]
    return (min(prices), max(prices)) if prices else (math.nan, math.nan)


def plan_overlap(a: TargetGraph, b: TargetGraph) -> float:
    """Jaccard similarity of the bought (instance, attribute) pairs of two plans."""
    x, y = ({(n, c) for n, s in p.projections.items() for c in s} for p in (a, b))
    return len(x & y) / len(x | y) if x | y else 1.0


def timed(f: Callable, *args, **more) -> tuple[object, float]:
    began = time.perf_counter()
    return f(*args, **more), time.perf_counter() - began


def real_correlation(graph: JoinGraph, request: Request, plan: Plan) -> float:
    """The correlation of a plan on full data, whatever it was chosen on."""
    return Evaluator(graph, request).score(plan.graph).corr if plan.graph else math.nan


def compare(full: JoinGraph, request: Request, max_vertices: int = 3, pinned: frozenset[Pair] | None = None, rate: float = 1.0, iterations: int = 60, seed: int = 0, sampled: JoinGraph | None = None, known: dict | None = None) -> list[dict]:
    """Planner, exhaustive on samples, exhaustive on full data: the four measures on full data, time and plan sizes.

    sampled: the graph on samples at the rate, where it is at hand. known: scores on full data, which are used and added to; the
    searches at one rate then share theirs too, so that no plan is scored twice, and times and numbers of scores are not each
    approach's own.
    """
    truth = Evaluator(full, request)
    if known is not None:
        truth.memo = known
    sampled = full if rate >= 1 else sampled or build(full.market, rate)
    sampled.prices = full.prices
    trial, alone = Evaluator(sampled, request, rate=rate), Evaluator(sampled, request, rate=rate)
    if known is not None:
        trial.memo = alone.memo = known if rate >= 1 else {}
    if pinned is None:
        heuristic = acquire(sampled, request, iterations, seed, evaluator=trial)
    else:
        from .request import initial, refine, supplies

        began = time.perf_counter()
        supply = next(s for s in supplies(full.market, request) if set(s.values()) <= {v for e in pinned for v in e})
        best = refine(trial, initial(sampled, pinned, supply), iterations, seed)
        heuristic = Plan("found" if best else "unaffordable", best, trial.score(best) if best else None, time.perf_counter() - began, len(trial.memo))
    local = exhaustive(sampled, request, max_vertices, alone, pinned)
    optimal = exhaustive(full, request, max_vertices, truth, pinned)
    best_corr = optimal.score.corr if optimal.score else math.nan
    rows = []
    for name, plan in (("heuristic", heuristic), ("exhaustive_sample", local), ("exhaustive_full", optimal)):
        real = truth.score(plan.graph) if plan.graph else None
        rows.append({
            "approach": name, "status": plan.status, "plan": plan.graph.label() if plan.graph else None, "size": plan.igraph_size,
            "corr": real.corr if real else None, "quality": real.quality if real else None, "ji": real.weight if real else None, "price": real.price if real else None,
            "cd": correlation_difference(best_corr, real.corr) if real else None, "evaluated": plan.evaluated, "seconds": plan.seconds,
        })
    return rows


def budget_sweep(graph: JoinGraph, request: Request, ratios: Sequence[float], max_vertices: int = 3, pinned: frozenset[Pair] | None = None) -> list[dict]:
    """The best affordable plan at each share of the dearest plan's price; scores are shared by all ratios."""
    low, high = budget_range(graph, request, max_vertices, pinned)
    evaluator = Evaluator(graph, request)
    out = []
    for r in ratios:
        evaluator.request = replace(request, budget=r * high)
        plan = exhaustive(graph, evaluator.request, max_vertices, evaluator, pinned)
        out.append({"ratio": r, "status": plan.status, "corr": plan.score.corr if plan.score else None, "price": plan.score.price if plan.score else None, "affordable": r * high >= low})
    return out


def sampling_sweep(market: Marketplace, request: Request, rates: Sequence[float], max_vertices: int = 3, pinned: frozenset[Pair] | None = None, iterations: int = 60) -> list[dict]:
    """Correlation difference of the planner against the full-data optimum, at each sampling rate; scores on full data are shared by all rates."""
    full, known = build(market), {}
    out = []
    for rate in rates:
        for row in compare(full, request, max_vertices, pinned, rate, iterations, known=known):
            out.append({"rate": rate, **row})
    return out


def resample_sweep(graph: JoinGraph, request: Request, plan: TargetGraph, rates: Sequence[float], share: float = 0.1) -> list[dict]:
    """A plan's correlation with re-sampling of intermediate results beyond `share` of the join, against without."""
    plain = Evaluator(graph, request).score(plan)
    out = []
    for r in rates:
        s = Evaluator(graph, request, eta=share * plain.join_rows, resample=r).score(plan)
        out.append({"resample": r, "corr": s.corr, "corr_plain": plain.corr, "gap": abs(s.corr - plain.corr), "rows": s.join_rows})
    return out


def size_sweep(graph: JoinGraph, request: Request, keep: Sequence[str], numbers: Sequence[int], iterations: int = 40, seed: int = 0, exact: bool = False, max_vertices: int = 3, max_rows: float = 5e7) -> list[dict]:
    """Time and plan size over growing subsets of the instances that always hold `keep`; exact adds the exhaustive search."""
    others = [n for n in graph.market.names if n not in keep]
    out = []
    for n in numbers:
        part = graph.restricted([*keep, *others[: max(n - len(keep), 0)]])
        bounded = replace(request, max_rows=max_rows)
        plan = acquire(part, bounded, iterations, seed)
        row = {"n": n, "status": plan.status, "size": plan.igraph_size, "seconds": plan.seconds, "evaluated": plan.evaluated}
        if exact:
            best = exhaustive(part, bounded, max_vertices)
            row |= {"seconds_exact": best.seconds, "evaluated_exact": best.evaluated}
        out.append(row)
    return out


def planner_budget_sweep(graph: JoinGraph, request: Request, ratios: Sequence[float], top: float, iterations: int = 10, seed: int = 0) -> list[dict]:
    """The planner's status, plan size and time at each share of a top price; a request that cannot be paid is N/A."""
    out = []
    for r in ratios:
        plan = acquire(graph, replace(request, budget=r * top), iterations, seed)
        out.append({"ratio": r, "status": plan.status, "size": plan.igraph_size, "corr": plan.score.corr if plan.score else None, "seconds": plan.seconds if plan.score else None})
    return out


def algorithms_by_budget(full: JoinGraph, request: Request, ratios: Sequence[float], max_vertices: int, rate: float = 0.5, iterations: int = 30, seed: int = 0, sampled: JoinGraph | None = None) -> list[dict]:
    """Real correlation of planner, exhaustive search on samples and on full data, at shares of the dearest plan's price.

    sampled: the graph on samples at the rate, where it is at hand.
    """
    _, high = budget_range(full, request, max_vertices)
    truth = Evaluator(full, request)
    sampled = sampled or build(full.market, rate)
    sampled.prices = full.prices
    trials = {"heuristic": Evaluator(sampled, request, rate=rate), "exhaustive_sample": Evaluator(sampled, request, rate=rate), "exhaustive_full": truth}
    trials["exhaustive_sample"].memo = trials["heuristic"].memo  # one sample, one set of scores
    out = []
    for r in ratios:
        now = replace(request, budget=r * high)
        for name, evaluator in trials.items():
            evaluator.request = now
            plan = acquire(sampled, now, iterations, seed, evaluator=evaluator) if name == "heuristic" else exhaustive(evaluator.graph, now, max_vertices, evaluator)
            real = truth.score(plan.graph) if plan.graph else None
            out.append({"ratio": r, "approach": name, "status": plan.status, "corr": real.corr if real else None, "price": real.price if real else None})
    return out
