"""Upper-layer search: shortest paths to landmarks, light subgraphs that connect terminals, and an exact reference."""

from __future__ import annotations

import heapq
import math
import random
from collections.abc import Iterable, Iterator, Sequence
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .joingraph import JoinGraph, Pair, pair

Path = tuple[str, ...]
Sketch = dict[str, dict[str, tuple[float, Path]]]  # landmark -> vertex -> (distance, path from the vertex)


def adjacency(graph: JoinGraph, hops: bool = False) -> dict[str, dict[str, float]]:
    """Neighbours of every instance with the weight of the edge, or with 1 for it."""
    near: dict[str, dict[str, float]] = {n: {} for n in graph.market.names}
    for (a, b), (w, _) in graph.edges().items():
        near[a][b] = near[b][a] = 1.0 if hops else w
    return near


def pick_landmarks(names: Sequence[str], seed: int, k: int | None = None) -> list[str]:
    """Random vertices, by default about the binary logarithm of their number."""
    names = sorted(names)
    k = max(1, math.ceil(math.log2(max(len(names), 2)))) if k is None else k
    return sorted(random.Random(seed).sample(names, min(k, len(names))))


def shortest_paths(near: dict[str, dict[str, float]], source: str) -> dict[str, tuple[float, Path]]:
    """(distance, path to the source) of every vertex in reach; ties by hops, then by names."""
    done: dict[str, tuple[float, Path]] = {}
    heap = [(0.0, 0, (source,))]
    while heap:
        d, hops, path = heapq.heappop(heap)
        v = path[0]
        if v in done:
            continue
        done[v] = (d, path)
        for u, w in near[v].items():
            if u not in done:
                heapq.heappush(heap, (round(d + w, 12), hops + 1, (u, *path)))
    return done


def landmark_sketch(graph: JoinGraph, landmarks: Sequence[str], hops: bool = False) -> Sketch:
    near = adjacency(graph, hops)
    return {m: shortest_paths(near, m) for m in landmarks}


def sketch_distances(edges: DataFrame, landmarks: Sequence[str]) -> DataFrame:
    """(vertex, landmark, dist) by relaxation over an edge table (src, dst, weight), for graphs beyond the driver's memory.

    Every round is one join and one combinable minimum, written to cut lineage; it stops when no distance falls.
    """
    from ..functions.storage import settle

    both = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    spark = edges.sparkSession
    now = spark.createDataFrame([(m, m, 0.0) for m in landmarks], "vertex string, landmark string, dist double")
    total = None
    while True:  # ends, since distances only fall and paths have no more edges than there are vertices
        step = now.join(both, now["vertex"] == both["src"]).select(F.col("dst").alias("vertex"), "landmark", (F.col("dist") + F.col("weight")).alias("dist"))
        now = settle(now.unionByName(step).groupBy("vertex", "landmark").agg(F.min("dist").alias("dist")))
        mark = tuple(now.agg(F.count("*"), F.round(F.sum("dist"), 9)).first())
        if mark == total:
            break
        total = mark
    return now


def tree_of(edges: Iterable[Pair], weight: dict[Pair, float], terminals: Sequence[str]) -> frozenset[Pair] | None:
    """A lightest spanning tree of the given edges, without leaves that are no terminals; None if terminals are apart."""
    root: dict[str, str] = {}

    def find(v: str) -> str:
        while root.setdefault(v, v) != v:
            v = root[v]
        return v

    kept = set()
    for e in sorted(set(edges), key=lambda e: (round(weight[e], 12), e)):
        a, b = find(e[0]), find(e[1])
        if a != b:
            root[a] = b
            kept.add(e)
    if len({find(t) for t in terminals}) > 1:
        return None
    while True:
        degree: dict[str, int] = {}
        for e in kept:
            for v in e:
                degree[v] = degree.get(v, 0) + 1
        loose = {e for e in kept if any(degree[v] == 1 and v not in terminals for v in e)}
        if not loose:
            return frozenset(kept)
        kept -= loose


def minimal_igraphs(graph: JoinGraph, terminals: Sequence[str], sketch: Sketch, alpha: float = math.inf, keep: str = "one") -> list[frozenset[Pair]]:
    """For each landmark the union of its paths to all terminals, made a tree; the lightest, if within alpha.

    keep='ties' returns every lightest one, keep='all' those of all landmarks. Several terminals that are one instance need no edge: the empty graph.
    """
    terminals = sorted(set(terminals))
    if len(terminals) == 1:
        return [frozenset()]
    weight = {e: w for e, (w, _) in graph.edges().items()}
    found: list[tuple[float, int, list[Pair], frozenset[Pair]]] = []
    for _, reach in sorted(sketch.items()):
        if any(t not in reach for t in terminals):
            continue
        edges = {pair(a, b) for t in terminals for a, b in zip(reach[t][1], reach[t][1][1:], strict=False)}
        tree = tree_of(edges, weight, terminals)
        if tree is not None:
            found.append((round(sum(weight[e] for e in tree), 12), len(tree), sorted(tree), tree))
    found = sorted(f for f in found if f[0] <= alpha + 1e-12)
    if not found:
        return []
    if keep == "all":
        return list(dict.fromkeys(f[3] for f in found))
    best = [f[3] for f in found if (f[0], f[1]) == (found[0][0], found[0][1])]
    return list(dict.fromkeys(best)) if keep == "ties" else best[:1]


def steiner_exact(graph: JoinGraph, terminals: Sequence[str]) -> float:
    """The weight of a lightest tree over the terminals, by dynamic programming over their subsets."""
    near = adjacency(graph)
    terminals = sorted(set(terminals))
    dist = {v: {u: d for u, (d, _) in shortest_paths(near, v).items()} for v in near}
    best: dict[tuple[frozenset[str], str], float] = {}
    for t in terminals:
        for v in near:
            best[frozenset([t]), v] = dist[v].get(t, math.inf)
    for k in range(2, len(terminals) + 1):
        for group in map(frozenset, combinations(terminals, k)):
            parts = [frozenset(p) for s in range(1, k // 2 + 1) for p in combinations(sorted(group), s)]
            meet = {v: min(best[p, v] + best[group - p, v] for p in parts) for v in near}
            for v in near:
                best[group, v] = min(meet[u] + dist[v].get(u, math.inf) for u in near)
    return min(best[frozenset(terminals), v] for v in near)


def trees(near: dict[str, Iterable[str]], terminals: Sequence[str], max_vertices: int) -> Iterator[frozenset[Pair]]:
    """Every tree of at most max_vertices instances whose leaves are terminals and that holds all terminals; each once."""
    terminals = sorted(set(terminals))
    others = [v for v in sorted(near) if v not in terminals]
    for extra in range(max(max_vertices - len(terminals), -1) + 1):
        for more in combinations(others, extra):
            vertices = sorted({*terminals, *more})
            inside = [(a, b) for a, b in combinations(vertices, 2) if b in near[a]]
            if len(vertices) == 1:
                yield frozenset()
                continue
            for edges in combinations(inside, len(vertices) - 1):
                degree: dict[str, int] = {}
                root = {v: v for v in vertices}

                def find(v: str, root: dict[str, str] = root) -> str:
                    while root[v] != v:
                        v = root[v]
                    return v

                joined = True
                for a, b in edges:
                    x, y = find(a), find(b)
                    if x == y:
                        joined = False
                        break
                    root[x] = y
                    degree[a], degree[b] = degree.get(a, 0) + 1, degree.get(b, 0) + 1
                if joined and all(degree.get(v, 0) > 1 for v in more):
                    yield frozenset(edges)
