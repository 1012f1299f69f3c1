"""Distributed connected components by alternating large and small stars.

Each round links every node to the smallest node in its surroundings; edges only ever point to smaller nodes, so their
number never grows. Before the first round every partition joins its own edges in memory and passes on one edge a node,
so long chains and hubs mostly vanish before anything is shuffled. Hot nodes do no harm: the minimum of a node's surroundings is a combinable aggregate, and the edges
meet it in an equi-join that adaptive execution may split. No link or component ever reaches the driver; it only
learns whether a round left any node to do. Up to ONE_TASK edges are joined by one task instead, without rounds.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import Settled, pieced

#: Edges up to which one task joins all in memory (about 100 bytes a node).
ONE_TASK = 100_000


def _contracted(edges: DataFrame) -> DataFrame:
    """(x, y): for every node of a partition the smallest node that its partition's edges connect it to."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        root: dict[int, int] = {}

        def find(v: int) -> int:
            top = v
            while (up := root.setdefault(top, top)) != top:
                top = up
            while root[v] != top:
                root[v], v = top, root[v]
            return top

        for batch in batches:
            for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                a, b = find(x), find(y)
                if a != b:
                    root[max(a, b)] = min(a, b)
        nodes = list(root)
        for i in range(0, len(nodes), 1 << 16):
            part = nodes[i : i + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array([find(v) for v in part], pa.int64())], ["x", "y"])

    return edges.mapInArrow(run, "x long, y long")


def components(edges: DataFrame, src: str = "src", dst: str = "dst", size: int | None = None) -> DataFrame:
    """(node, component) for every node that occurs in an edge; component is its smallest reachable node.

    Self-loops count as a node without links; repeated edges and nulls in either column (ignored) do no harm; an empty
    table gives an empty result. size: the edges' bytes, roughly, if they are known.
    """
    raw = edges.select(F.col(src).cast("long").alias("x"), F.col(dst).cast("long").alias("y")).where("x is not null and y is not null")
    raw = _contracted(pieced(raw, size))
    held = Settled(raw.select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b")).distinct(), size)
    if held.df.count() <= ONE_TASK:
        joined = Settled(_contracted(held.df.coalesce(1)).toDF("node", "component"))
        held.drop()
        return joined.df
    first = held
    while True:
        links = held.df.where("a <> b")
        # large star: every larger neighbour of b joins the smallest node around b
        around = links.select(F.col("a").alias("b"), F.col("b").alias("m")).unionByName(links.select("b", F.col("b").alias("m"))).groupBy("b").agg(F.min("m").alias("m"))
        large = links.join(around, "b").select("a", F.col("m").alias("b"))
        # small star: the smaller neighbours of a, and a, join the smallest of them
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        pairs = large.join(low, "a")
        small = pairs.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b"))).distinct()
        new = Settled(small, size)
        if held is not first:
            held.drop()
        held = new
        # done when every node has one smaller neighbour and that one has none
        ends = held.df.select(F.col("a").alias("v"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(held.df.select(F.col("b").alias("v"), F.lit(0).alias("up"), F.lit(1).alias("down")))
        per = ends.groupBy("v").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
        if not per.where("up > 1 or (up > 0 and down > 0)").limit(1).count():
            break
    stars = held.df.select(F.col("a").alias("node"), F.col("b").alias("component"))
    roots = first.df.select(F.col("b").alias("node"), F.col("b").alias("component")).join(stars.select("node"), "node", "left_anti").distinct()
    loops = first.df.where("a = b").select(F.col("a").alias("node"), F.col("a").alias("component")).join(stars.select("node"), "node", "left_anti")
    return stars.unionByName(roots.unionByName(loops).distinct())
