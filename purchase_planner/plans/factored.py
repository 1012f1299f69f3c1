"""Scores of plans whose join is much larger than its tables, without forming that join.

Every subtree of a plan is collapsed to its key towards the root and the columns still wanted before it is joined, so a
join is formed from collapsed sides only. A dependency lies within one instance: its rows weigh as much as the rest of the
tree gives them, and a row of the join is correct if its parts are. The conditional cumulative entropy of a numeric
attribute is summed in cells, a range of its values against a part of the groups: within one, each group's distribution
function is a running sum over the values, so pairs of values and groups are computed and never written or shuffled.
All results equal those of plans.evaluate on the whole join. Counts are longs; where one does not fit, the plan is scored
again with wide counts, see `score`.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from ..functions.measures import FD, W, _flagged, cond_cum_entropy_df, counted, cum_entropy_df, kind_of, mutual_information_df, number, scalar
from ..functions.storage import settle
from ..sources.marketplace import Marketplace
from .joingraph import pair

#: Cells hold so many groups and about so many values; a step in a cell so many pairs of them.
GROUPS, VALUES, STEP = 2048, 250_000, 1 << 20
#: At least so many cells, so that all cores are busy.
CELLS = 64
#: Cells hold at most so many numbers of groups times join values.
TABLE = 1 << 22
#: A join of fewer rows than this, or less than so many times what the cells would be sent, is formed.
FORMED, GAIN = 2_000_000, 4


def _near(plan, name: str, parent: str | None) -> list[str]:
    return sorted(u for e, _ in plan.edges if name in e for u in e if u not in (name, parent))


def _on(plan, a: str, b: str) -> list[tuple[str, str]]:
    return [(f"{a}__{x}", f"{b}__{x}") for x in plan.joins[pair(a, b)]]


def subtree(plan, frames: dict[str, DataFrame], name: str, parent: str | None, wanted: Sequence[str], beside: Sequence[str] = ()) -> DataFrame:
    """The join of the tree under an instance, collapsed to its key towards the parent and the wanted columns, with counts in W.

    `beside` are neighbours whose subtrees are left out.
    """
    out = frames[name]
    key = [x for x, _ in _on(plan, name, parent)] if parent else []
    key += [x for u in beside for x, _ in _on(plan, name, u)]
    below = [u for u in _near(plan, name, parent) if u not in beside]
    for k, u in enumerate(below):
        out = met(plan, out, subtree(plan, frames, u, name, wanted), name, u)
        still = {*key, *wanted, *(x for v in below[k + 1 :] for x, _ in _on(plan, name, v))}
        if k < len(below) - 1 and not still.issuperset(x for x, _ in _on(plan, name, u)):
            out = _collapsed(out, still)  # its key falls away: else every row of it would meet all of the next subtree's
    return _collapsed(out, {*key, *wanted})


def _collapsed(df: DataFrame, columns: set[str]) -> DataFrame:
    return df.groupBy(*[c for c in df.columns if c in columns]).agg(F.sum(W).alias(W))


def met(plan, out: DataFrame, below: DataFrame, name: str, child: str) -> DataFrame:
    """Two sides joined on their edge; counts multiply."""
    pairs = _on(plan, name, child)
    below = below.withColumnRenamed(W, "__v")
    on = reduce(lambda x, y: x & y, (F.col(a) == F.col(b) for a, b in pairs))
    return out.join(below, on).withColumn(W, F.col(W) * F.col("__v")).drop("__v")


# ----------------------------------------------------------------------------------------------------- quality


def quality(market: Marketplace, plan, frames: dict[str, DataFrame]) -> tuple[float | None, int]:
    """The share of the join's rows that are correct under every dependency within a projection, and the number of rows."""
    p = plan.projections
    fds = {n: [FD(tuple(f"{n}__{a}" for a in fd.lhs), f"{n}__{fd.rhs}") for fd in market[n].fds if set(fd.attributes) <= p[n]] for n in plan.instances}
    fds = {n: own for n, own in fds.items() if own}
    if not fds:
        rows = subtree(plan, frames, plan.supply[0][1], None, []).first()[W] or 0
        return 1.0, rows
    good, flags = dict(frames), {}
    for n, own in fds.items():
        weighed = frames[n]
        for u in _near(plan, n, None):
            weighed = met(plan, weighed, subtree(plan, frames, u, n, []), n, u).select(*frames[n].columns)
        sizes = counted(weighed, list(dict.fromkeys(a for fd in own for a in fd.attributes)), W)
        columns = [c for c in sizes.columns if c != W]
        for k, fd in enumerate(own):
            sizes = _flagged(sizes, fd, f"__ok{k}", W)
        ok = reduce(lambda x, y: x & y, (F.col(f"__ok{k}") for k in range(len(own))))
        flags[n] = settle(sizes.select(*columns, W, ok.alias("__ok")))
    if len(flags) == 1:
        got = next(iter(flags.values())).agg(F.sum(W), F.sum(F.when(F.col("__ok"), F.col(W)).otherwise(0))).first()
        return (got[1] / got[0] if got[0] else None), got[0] or 0
    rows = next(iter(flags.values())).agg(F.sum(W)).first()[0] or 0
    for n, flagged in flags.items():
        columns = [c for c in flagged.columns if c not in (W, "__ok")]
        wrong = flagged.where(~F.col("__ok")).select(*[F.col(c).alias(f"__{c}") for c in columns])
        good[n] = frames[n].join(wrong, reduce(lambda x, y: x & y, (F.col(c).eqNullSafe(F.col(f"__{c}")) for c in columns)), "left_anti")
    right = subtree(plan, good, plan.supply[0][1], None, []).first()[W] or 0
    return (right / rows if rows else None), rows


# ------------------------------------------------------------------------------------ conditional cumulative entropy


def cell(values: pa.Table, groups: pa.Table, following: dict[int, float], step: int = STEP) -> float:
    """The sum over a cell's groups of their rows times their share of the integral of -F log2 F over the cell's values.

    values: b, id, x, v (rows of value x under join value id), and a row without x for every join value with its rows
    before the cell, `v`, and altogether, `total`. groups: ids and ws, the rows of a group under each join value.
    """
    x, ids, v = values["x"].to_numpy(), values["id"].to_numpy(), values["v"].to_numpy().astype(float)
    known = np.isnan(x)
    order = np.argsort(ids[known])
    keys, before, total = ids[known][order], v[known][order], values["total"].to_numpy()[known][order].astype(float)
    x, ids, v = x[~known], ids[~known], v[~known]
    if not len(x) or not groups.num_rows:
        return 0.0
    order = np.argsort(x, kind="stable")
    x, at, v = x[order], np.searchsorted(keys, ids[order]), v[order]
    gap = np.append(x[1:], following.get(values["b"][0].as_py(), x[-1])) - x
    lists, weights = groups["ids"].combine_chunks(), groups["ws"].combine_chunks()
    table = np.zeros((len(keys), groups.num_rows))
    table[np.searchsorted(keys, lists.flatten().to_numpy()), np.repeat(np.arange(groups.num_rows), np.diff(lists.offsets.to_numpy()))] = weights.flatten().to_numpy()
    n, upto, out = total @ table, before @ table, 0.0
    rows = max(step // groups.num_rows, 1)
    for i in range(0, len(x), rows):
        run = table[at[i : i + rows]]
        run *= v[i : i + rows, None]
        run[0] += upto
        np.cumsum(run, axis=0, out=run)
        upto = run[-1].copy()
        moves = gap[i : i + rows] > 0
        share = run[moves] / n
        logs = np.zeros_like(share)
        np.log2(share, out=logs, where=share > 0)
        logs *= share
        out -= float((gap[i : i + rows][moves] @ logs) @ n)
    return out


def conditional(left: DataFrame, right: DataFrame, x: str, keys: Sequence[tuple[str, str]], y: Sequence[str]) -> float | None:
    """h(x | y) over the join of (x, key, W) with (key, y, W) on the pairs of key columns; None where that join is as well formed."""
    a, b = [k for k, _ in keys], [k for _, k in keys]
    left = left.withColumn("__x", number(F.col(x), left.schema[x].dataType)).where("__x is not null and not isnan(__x)")
    sides = left.groupBy(*[F.col(k).alias(f"__k{i}") for i, k in enumerate(a)]).agg(F.count("*").alias("__l"), F.sum(W).alias("__n"))
    sides = sides.join(right.groupBy(*[F.col(k).alias(f"__k{i}") for i, k in enumerate(b)]).agg(F.count("*").alias("__r"), F.sum(W).alias("__m")), [f"__k{i}" for i in range(len(a))])
    known = settle(sides.withColumn("__id", F.monotonically_increasing_id()))  # ids are fixed by being written
    size = known.agg(F.count("*").alias("k"), F.sum("__l").alias("l"), F.sum("__r").alias("r"), F.sum(F.col("__l").cast("double") * F.col("__r")).alias("joined"), F.sum(F.col("__n").cast("double") * F.col("__m")).alias("rows")).first()
    if not size["k"] or size["joined"] < FORMED:
        return None
    found = right.select(*y).distinct().count()
    wide = max(min(GROUPS, TABLE // size["k"]), 1)
    parts = -(-found // wide)
    blocks = max(-(-size["l"] // VALUES), -(-CELLS // parts), 4)
    if GAIN * (size["l"] * parts + (size["r"] + size["k"]) * blocks) > size["joined"]:
        return None
    same = lambda df, names: df.join(known, reduce(lambda p, q: p & q, (F.col(c) == F.col(f"__k{i}") for i, c in enumerate(names))))
    edges = left.agg(F.percentile_approx("__x", [k / blocks for k in range(1, blocks)], 10_000)).first()[0]
    block = F.size(F.filter(F.array(*[F.lit(e) for e in edges]), lambda e: e < F.col("__x")))
    values = settle(same(left, a).groupBy(block.alias("b"), F.col("__id").alias("id"), F.col("__x").alias("x")).agg(F.sum(W).alias("v")))
    firsts = sorted(values.groupBy("b").agg(F.min("x")).collect())  # a row a block
    following = {p[0]: q[1] for p, q in zip(firsts, firsts[1:], strict=False)}
    sums = values.groupBy("id", "b").agg(F.sum("v").alias("v")).groupBy("id").agg(F.collect_list(F.struct("b", "v")).alias("own"))  # an entry a block
    none = F.lit(0).cast(values.schema["v"].dataType)
    adds = lambda c: F.aggregate(c, none, lambda s, e: s + e["v"])
    starts = sums.select("id", "own", F.explode(F.array(*[F.lit(r[0]) for r in firsts])).alias("b"))
    starts = starts.select("b", "id", F.lit(None).cast("double").alias("x"), adds(F.filter("own", lambda e: e["b"] < F.col("b"))).alias("v"), adds(F.col("own")).alias("total"))
    rows = values.select("b", "id", "x", "v", none.alias("total")).unionByName(starts)
    each = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    rows = rows.withColumn("c", each)
    groups = same(right, b).groupBy(*[F.col(c).alias(f"__y{i}") for i, c in enumerate(y)]).agg(F.collect_list("__id").alias("ids"), F.collect_list(W).alias("ws"))  # an entry a join value
    # group numbers are spread evenly, so that no cell holds many more than `wide`
    groups = groups.select(F.pmod(F.xxhash64(*[f"__y{i}" for i in range(len(y))]), F.lit(parts)).cast("int").alias("c"), "ids", "ws", F.explode(F.array(*[F.lit(r[0]) for r in firsts])).alias("b"))

    def run(values: pa.Table, groups: pa.Table) -> pa.Table:
        return pa.table({"s": [cell(values, groups, following)]})

    cells = max(parts * len(firsts), 1)
    sides = [df.repartition(cells, "b", "c").groupBy("b", "c") for df in (rows, groups)]
    total = sides[0].cogroup(sides[1]).applyInArrow(run, "s double").agg(F.sum("s")).first()[0]
    return (total or 0.0) / size["rows"]


# ------------------------------------------------------------------------------------------------------- scores


def score(market: Marketplace, plan, frames: dict[str, DataFrame], xs: Sequence[str], ys: Sequence[str], kinds: dict[str, str] | None, wide: bool = False) -> Row:
    """corr, quality and join_rows of a plan.

    wide: rows are counted in decimals of 38 digits, exactly, and weighed as doubles in the correlation, whose terms are
    doubles in any case.
    """
    frames = {n: settle(df) for n, df in frames.items()}
    share, rows = quality(market, plan, _counts_as(frames, "decimal(38,0)") if wide else frames)
    if wide:
        share, rows, frames = share if share is None else float(share), int(rows), _counts_as(frames, "double")
    categorical = [x for x in xs if kind_of(frames[x.partition("__")[0]], x, kinds) == "categorical"]
    corr = 0.0
    if categorical:
        whole = subtree(plan, frames, plan.supply[0][1], None, [*categorical, *ys])
        corr += scalar(mutual_information_df(whole, categorical, ys, W))
    for x in (x for x in xs if x not in categorical):
        corr += _gain(plan, frames, x, ys)
    return Row(corr=corr, quality=share, join_rows=rows)


def _counts_as(frames: dict[str, DataFrame], kind: str) -> dict[str, DataFrame]:
    return {n: df.withColumn(W, F.col(W).cast(kind)) for n, df in frames.items()}


def _gain(plan, frames: dict[str, DataFrame], x: str, ys: Sequence[str]) -> float:
    """h(x) - h(x|y) of a numeric attribute; the cells are used where one subtree beside its instance holds all of y."""
    root = x.partition("__")[0]
    alone = scalar(cum_entropy_df(subtree(plan, frames, root, None, [x]), x, W))
    holders = {u for u in _near(plan, root, None) for y in ys if y.partition("__")[0] in _under(plan, u, root)}
    if len(holders) == 1 and not any(y.partition("__")[0] == root for y in ys):
        (u,) = holders
        left = settle(subtree(plan, frames, root, None, [x], beside=[u]))
        right = settle(subtree(plan, frames, u, root, ys))
        given = conditional(left, right, x, _on(plan, root, u), list(dict.fromkeys(ys)))
        if given is not None:
            return alone - given
    whole = settle(subtree(plan, frames, root, None, [x, *ys]))
    return alone - scalar(cond_cum_entropy_df(whole, x, list(dict.fromkeys(ys)), W))


def _under(plan, name: str, parent: str) -> set[str]:
    return {name}.union(*(_under(plan, u, name) for u in _near(plan, name, parent)))
