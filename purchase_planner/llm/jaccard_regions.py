"""Exact Jaccard self-join of word-shingle sets in metric-space regions, giving the connected groups of linked documents.

Jaccard distance is a metric, but unrelated documents are all at distance 1 from any document, so document pivots alone
would put nearly all of a corpus on every boundary. The first cut therefore takes one-shingle sets as pivots: a document's
nearest pivots are its own rarest shingles, and the boundary window is exact - two documents within distance r share one
of the n - ceil((1 - r) n) + 1 rarest shingles of each, so a document is replicated to the cells of these. Cells that
share documents make a region, and no link leaves a region.

Within a region, sampled documents are pivots and cut it into Voronoi cells: every document's distances to the pivots are
measured, it belongs to the cell of its nearest pivot if that is within RADIUS, else to the outer cell, and by the
triangle inequality it is replicated to the cells of all pivots within min(nearest + 2 r, RADIUS + r), since a document
within r of it may live there. Two linked documents thus always meet in the cell of one of them or in the outer cell.
Cells are cut again in the same way until few documents are left, which are compared directly; a cell whose windows hold
nearly all of its region is not cut but goes on without the pivots, which have met everyone. Documents that are linked so
far carry one label; only pairs of different labels are left to test, so cells of one label are done, and a pivot that is
linked to an earlier one steps back. Regions of up to LOCAL documents recur in one task's memory, larger ones by Spark.

What keeps this linear in the input: equal sets are one representative; a representative with more than r * n shingles
that occur nowhere else is linked to nothing (first judged on a fixed share of the hash range, then on all shingles of
the rest), which takes two combinable counts and no pairs; members of a large region are dealt by salts of about MEMBERS,
with chunks of pivots replicated to each salt.

Words are [^\\x20\\x09-\\x0D]+ after lower-casing A-Z; shingles are told apart by 64-bit hashes, sets by 128 further bits.

Defined cases: a null text or one without words has no shingles and is its own group; fewer words than a shingle make
one shingle of all; repeated rows are linked; a null id gives a null group but its row stays; an empty table gives an
empty result; only the id and text columns are read, so other columns may have any names.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import _text as tx
from ._shared import Settled, pieced, settle, settle_last
from .components import components

U = np.uint64
#: Members of a task's block; pivots of a chunk; pivots of a region and level; documents up to which pairs are compared directly.
MEMBERS, CHUNK, MOST, LEAF = 128, 128, 1024, 12
#: Documents and bytes of shingles up to which a region recurs in one task; farthest distance from its pivot within a cell.
LOCAL, LOCAL_BYTES, RADIUS = 1024, 8 << 20, 0.5
EPS = 1e-9
GROUP = ["region", "salt", "chunk"]
#: A table of at most so many ids is broadcast (16 bytes a row and the hash table); a larger one is joined by shuffle.
BROADCAST_IDS = 250_000


def shingle_sets(data: np.ndarray, offsets: np.ndarray, words: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of every row of a slice."""
    lower = tx.LOWER[data]
    starts, ends, rows = tx.words(lower, offsets)
    h = tx.span_hashes(lower, starts, ends)
    n = len(h)
    odd = [U(pow(0xD6E8FEB86659FD93, k + 1, 1 << 64)) for k in range(words)]
    joined = np.zeros(max(n - words + 1, 0), U)
    for k in range(words):
        joined += h[k : n - words + 1 + k] * odd[k] if n >= words else U(0)
    joined = tx.mix(joined)
    out = []
    for a, b in zip(rows[:-1].tolist(), rows[1:].tolist(), strict=True):
        if b - a >= words:
            out.append(np.unique(joined[a : b - words + 1]))
        elif b > a:
            part = h[a:b] * np.array(odd[: b - a], U)
            out.append(tx.mix(np.array([part.sum(dtype=U) + U(b - a)], U) ^ U(0xA5A5A5A5A5A5A5A5)))
        else:
            out.append(np.zeros(0, U))
    return out


def _signed(x: np.ndarray) -> np.ndarray:
    return np.asarray(x, U).view(np.int64)


def _table(docs: DataFrame, id_col: str, text_col: str, words: int, below: int | None) -> DataFrame:
    """id, n, f1, f2 (128 bits of the set) and the shingles, all of them or those below a bound of the hash range."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(1)):
                sets = shingle_sets(data, offsets, words)
                ones = _signed(np.array([tx.mix(s ^ U(0x1234567)).sum(dtype=U) for s in sets], U))
                twos = _signed(np.array([np.bitwise_xor.reduce(tx.mix(s * U(0xC2B2AE3D27D4EB4F))) if len(s) else 0 for s in sets], U))
                kept = [(s if below is None else s[: np.searchsorted(s, U(below))]).tobytes() for s in sets]
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], pa.array([len(s) for s in sets], pa.int64()), pa.array(ones), pa.array(twos), pa.array(kept, pa.binary())], ["id", "n", "f1", "f2", "part"])

    return rows.mapInArrow(run, "id long, n long, f1 long, f2 long, part binary")


def _exploded(sets: DataFrame) -> DataFrame:
    """(s, id, n): one row a shingle."""
    names = ["id", "n"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = tx.utf8(batch.column(len(names)))
            counts = np.diff(offsets) // 8
            for i, j in tx.slices(offsets):
                s = np.frombuffer(data[offsets[i] : offsets[j]].tobytes(), np.int64)
                others = [np.repeat(batch.column(k).to_numpy(zero_copy_only=False)[i:j], counts[i:j]) for k in range(len(names))]
                yield pa.RecordBatch.from_arrays([pa.array(s), *(pa.array(x, pa.int64()) for x in others)], ["s", *names])

    return sets.select(*names, "part").mapInArrow(run, "s long, " + ", ".join(f"{c} long" for c in names))


def _few(df: DataFrame) -> DataFrame:
    """A written table of ids, marked for broadcast if it is known to be small."""
    return F.broadcast(df) if df.count() <= BROADCAST_IDS else df


def _lone(sets: DataFrame) -> DataFrame:
    """(id, lone): how many of a set's shingles are in no other set. Both counts combine before they are shuffled."""
    return _exploded(sets).groupBy("s").agg(F.count("*").alias("c"), F.min("id").alias("id")).where("c = 1").groupBy("id").agg(F.count("*").alias("lone"))


class Sets:
    """Shingle sets of some documents, with their overlaps with one set at a time."""

    def __init__(self, parts: list[bytes]):
        self.n = np.array([len(p) // 8 for p in parts], np.int64)
        self.universe, self.codes = np.unique(np.frombuffer(b"".join(parts), U), return_inverse=True)
        self.firsts = np.cumsum(self.n) - self.n
        self.mark = np.zeros(len(self.universe), np.int32)

    def part(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes of the shingles of some members, one after the other, and where each begins."""
        return self.codes[tx.ragged(self.firsts[at], self.n[at])], np.cumsum(self.n[at]) - self.n[at]

    def own(self, i: int) -> np.ndarray:
        return self.codes[self.firsts[i] : self.firsts[i] + self.n[i]]

    def coded(self, part: bytes) -> np.ndarray:
        """Codes of the shingles of any set that some member has too."""
        pivot = np.frombuffer(part, U)
        at = np.minimum(np.searchsorted(self.universe, pivot), len(self.universe) - 1)
        return at[self.universe[at] == pivot]

    def shared(self, pivot: np.ndarray, codes: np.ndarray, firsts: np.ndarray) -> np.ndarray:
        self.mark[pivot] = 1
        out = np.add.reduceat(self.mark[codes], firsts)
        self.mark[pivot] = 0
        return out


def _near(shared: np.ndarray, n: np.ndarray, m: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Distances to a set of m shingles, and whether they are links."""
    union = n + m - shared
    return 1 - shared / union, 100 * shared >= percent * union


def solve(sets: Sets, labels: np.ndarray, percent: int, rng: np.random.Generator) -> list[tuple[int, int]]:
    """Pairs of linked members that join all labels which links join, by recursive Voronoi cells in memory."""
    r = (100 - percent) / 100
    label = np.unique(labels, return_inverse=True)[1].astype(np.int64)
    links: list[tuple[int, int]] = []
    todo = [np.arange(len(label))]
    while todo:
        at = todo.pop()
        counts = np.bincount(label[at])
        test = np.flatnonzero(label[at] != counts.argmax())
        if not len(test):
            continue
        whole = len(test) <= LEAF
        chosen = test if whole else rng.permutation(test)[: min(32, math.isqrt(len(at)))]
        codes, firsts = sets.part(at)
        n = sets.n[at]
        rows, pivots = [], []
        for c in chosen:
            if any(d[c] <= r + EPS for d in rows) and not whole:
                continue  # linked to an earlier pivot
            far, linked = _near(sets.shared(sets.own(at[c]), codes, firsts), n, n[c], percent)
            for i in np.flatnonzero(linked & (label[at] != label[at[c]])):
                if label[at[i]] != label[at[c]]:
                    links.append((int(at[c]), int(at[i])))
                    label[label == label[at[i]]] = label[at[c]]
            rows.append(far)
            pivots.append(c)
        if whole:
            continue
        distance = np.array(rows)
        nearest = distance.min(0)
        rest = np.ones(len(at), bool)
        rest[pivots] = False
        home = np.where(nearest <= RADIUS, distance.argmin(0), -1)
        reach = np.minimum(nearest + 2 * r, RADIUS + r) + EPS
        cells = [at[rest & (d <= reach)] for k, d in enumerate(distance) if (rest & (home == k)).any()]
        cells.append(at[rest & (home < 0)])
        cut = sum(len(c) ** 2 for c in cells) < int(rest.sum()) ** 2
        todo += [c for c in cells if len(c) > 1] if cut else [at[rest]]
    return links


def _by_group(rows: DataFrame, keys: list[str], schema: str, group: Callable[[pd.DataFrame], pd.DataFrame], size: int) -> DataFrame:
    """`group` of each run of equal keys. Groups are small, so a task takes many from its sorted rows; one that goes on in the next batch waits for it."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []

        def out(rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
            mark = reduce(lambda x, y: x | y, (rows[k].ne(rows[k].shift()) for k in keys))
            at = np.append(np.flatnonzero(mark.to_numpy()), len(rows))
            done = [group(rows.iloc[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
            done = [d for d in done if len(d)]
            if done:
                yield pd.concat(done)

        for batch in batches:
            if len(batch):
                same = reduce(lambda x, y: x & y, (batch[k] == batch[k].iloc[-1] for k in keys)).to_numpy()
                if same.all() and held and all(held[-1][k].iloc[-1] == batch[k].iloc[-1] for k in keys):
                    held.append(batch)
                    continue
                rows = pd.concat([*held, batch])
                last = reduce(lambda x, y: x & y, (rows[k] == batch[k].iloc[-1] for k in keys)).to_numpy()
                if not last.all():
                    yield from out(rows[~last])
                held = [rows[last]]
        if held:
            yield from out(pd.concat(held))

    # partitions in one piece follow each other, so equal keys still do
    return pieced(rows.repartition(*keys).sortWithinPartitions(*keys), size).mapInPandas(run, schema)


def _solved(rows: DataFrame, percent: int, size: int) -> DataFrame:
    """(src, dst) links of whole small regions."""

    def group(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("id")
        ids = rows["id"].to_numpy()
        found = solve(Sets(rows["part"].tolist()), rows["label"].to_numpy(), percent, np.random.default_rng(7))
        return pd.DataFrame({"src": ids[[a for a, _ in found]], "dst": ids[[b for _, b in found]]})

    return _by_group(rows.select("region", "id", "part", "label"), ["region"], "src long, dst long", group, size)


def measure(pivots: pd.DataFrame, members: pd.DataFrame, percent: int) -> pd.DataFrame:
    """For every member the pivots of this chunk that it is linked to, those within reach with their distances, and whether it is one.

    Where not all that has to be tested is a pivot, a pivot that is linked to an earlier one of the chunk steps back.
    """
    r = (100 - percent) / 100
    pivots = pivots.sort_values("id")
    whole = bool(pivots["whole"].iloc[0])
    among = Sets(pivots["part"].tolist())
    kept: list[int] = []
    close = np.zeros(len(pivots), bool)
    for k in range(len(pivots)):
        if whole or not close[k]:
            kept.append(k)
            close |= whole or _near(among.shared(among.own(k), among.codes, among.firsts), among.n, among.n[k], percent)[1]
    sets = Sets(members["part"].tolist())
    n, labels = sets.n, members["label"].to_numpy()
    links: list[list[int]] = [[] for _ in n]
    reach: list[list[dict]] = [[] for _ in n]
    ids, of, parts = pivots["id"].tolist(), pivots["label"].to_numpy(), pivots["part"].tolist()
    for k in kept:
        far, linked = _near(sets.shared(sets.coded(parts[k]), sets.codes, sets.firsts), n, among.n[k], percent)
        for i in np.flatnonzero(linked & (labels != of[k])):
            links[i].append(ids[k])
        for i in np.flatnonzero((far <= RADIUS + r + EPS) & (not whole)):
            reach[i].append({"d": float(far[i]), "p": ids[k]})
    own = {ids[k] for k in kept}
    return pd.DataFrame({"region": members["region"].to_numpy(), "id": members["id"].to_numpy(), "linked": links, "reach": reach, "done": [whole or i in own for i in members["id"].tolist()]})


def _measured(dealt: DataFrame, percent: int, size: int) -> DataFrame:
    def group(rows: pd.DataFrame) -> pd.DataFrame:
        as_pivot = rows["as_pivot"].to_numpy()
        if as_pivot.all() or not as_pivot.any():
            return rows.iloc[:0]
        return measure(rows[as_pivot], rows[~as_pivot], percent)

    return _by_group(dealt, GROUP, "region long, id long, linked array<long>, reach array<struct<d: double, p: long>>, done boolean", group, size)


def _cut(members: DataFrame, sized: DataFrame, percent: int, first: bool, size: int) -> Settled:
    """One level over large regions: their members with links and distances to the pivots of their region.

    The pivots are all members outside the largest label where these are few (MOST after the first level), which ends the
    region; else the least ids of shares of them, so that no task sees the whole region.
    """
    columns = ["region", "id", "n", "part", "label", "salts", "chunks", "whole"]
    bound = F.least(F.lit(MOST), F.ceil(F.col("c") / 64)) if first else F.lit(MOST)
    sized = sized.withColumn("a", F.col("c") - F.col("held")).withColumn("whole", F.col("a") <= bound)
    sized = sized.select("region", "c", "largest", "whole", F.least("a", bound).cast("int").alias("most"))
    sized = members.join(sized, "region")
    sized = sized.withColumn("salts", F.ceil(F.col("c") / MEMBERS).cast("int")).withColumn("chunks", F.ceil(F.col("most") / CHUNK).cast("int"))
    test = sized.where(F.col("label") != F.col("largest"))
    share = F.pmod(F.xxhash64("id"), F.col("most")).alias("share")
    least = test.where("not whole").groupBy("region", share).agg(F.min("id").alias("id")).select("region", "id")
    chosen = test.where("whole").select(*columns).unionByName(test.where("not whole").join(least, ["region", "id"], "left_semi").select(*columns))
    pivots = chosen.withColumn("chunk", F.pmod(F.hash("id", F.lit(1)), F.col("chunks"))).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
    dealt = sized.select(*columns).withColumn("salt", F.pmod(F.hash("id"), F.col("salts"))).withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    last = [*GROUP, "id", "part", "label", "whole"]
    return Settled(_measured(dealt.select(*last, F.lit(False).alias("as_pivot")).unionByName(pivots.select(*last, F.lit(True).alias("as_pivot"))), percent, size))


def _cells(done: DataFrame, sized: DataFrame, percent: int, size: int) -> DataFrame:
    """(region, id) of the next level: Voronoi cells with their windows, or the region without its pivots where cells would not shrink it."""
    r = (100 - percent) / 100
    per = done.groupBy("region", "id").agg(F.flatten(F.collect_list("reach")).alias("reach"), F.max("done").alias("done")).where("not done")
    per = per.withColumn("nearest", F.coalesce(F.array_min(F.transform("reach", lambda z: z["d"])), F.lit(1.0)))
    within = F.filter("reach", lambda z: z["d"] <= F.least(F.col("nearest") + 2 * r, F.lit(RADIUS + r)) + EPS)
    inner, outer = F.transform(within, lambda z: F.xxhash64("region", z["p"])), F.array(F.xxhash64("region"))
    held = settle(per.select("region", "id", F.when(F.col("nearest") <= RADIUS, inner).otherwise(F.concat(inner, outer)).alias("cells")), size)
    sums = held.select("region", F.explode("cells").alias("cell")).groupBy("region", "cell").agg(F.count("*").alias("k")).groupBy("region").agg(F.sum("k").alias("rows"), F.sum(F.col("k") * F.col("k")).alias("squares"))
    worth = sums.join(sized, "region").select("region", ((F.col("squares") < F.col("c") * F.col("c")) & (F.col("rows") <= 4 * F.col("c"))).alias("cut"))
    return held.join(worth, "region").select("id", F.explode(F.when(F.col("cut"), F.col("cells")).otherwise(outer)).alias("region"))


def _bytes(sets: DataFrame) -> int:
    """Bytes of the rows of a written table of sets, about."""
    rows, shingles = sets.agg(F.count("*"), F.sum("n")).first()
    return 40 * rows + 8 * (shingles or 0)


def _links(sets: DataFrame, percent: int) -> DataFrame | None:
    """(src, dst) links that connect all linked sets; sets: written table of id, n, part.

    Small regions are finished at once, larger ones are cut into Voronoi cells, which are the regions of the next level.
    """
    found: DataFrame | None = None
    of = sets.select("id", "n", "part", F.col("id").alias("label"))
    first = True
    size = _bytes(sets)
    members = Settled(regions(sets, percent, size).join(of, "id").select("region", "id", "n", "part", "label"), size)
    while True:
        size = _bytes(members.df)
        per = members.df.groupBy("region", "label").agg(F.count("*").alias("c"), F.sum("n").alias("n"))
        most = F.max(F.struct("c", "label"))
        sized = Settled(per.groupBy("region").agg(F.sum("c").alias("c"), F.sum("n").alias("n"), most["label"].alias("largest"), most["c"].alias("held"), F.count("*").alias("labels")).where("labels > 1"), size)
        small = (F.col("c") <= LOCAL) & (F.col("n") * 8 <= LOCAL_BYTES) | (F.col("c") <= LEAF)
        large = sized.df.where(~small)
        solved = Settled(_solved(members.df.join(sized.df.where(small).select("region"), "region", "left_semi"), percent, size))
        found = solved.df if found is None else found.unionByName(solved.df)
        if not large.limit(1).count():
            members.drop()
            return found
        done = _cut(members.df, large, percent, first, size)
        first = False
        linked = done.df.select(F.col("id").alias("src"), F.explode("linked").alias("dst"))
        found = found.unionByName(linked)
        # labels that are linked by now, within large regions and small ones
        label = members.df.select("id", "label").distinct()
        joined = found.join(label.toDF("src", "a"), "src").join(label.toDF("dst", "b"), "dst").select("a", "b").where("a <> b")
        of = components(joined, "a", "b", size)
        # small regions are done: their sets go no further
        rows = members.df.join(large.select("region"), "region", "left_semi").select("id", "n", "part", "label").dropDuplicates(["id"])
        rows = rows.join(of, F.col("label") == F.col("node"), "left").select("id", "n", "part", F.coalesce("component", "label").alias("label"))
        following = Settled(_cells(done.df, large, percent, size).join(rows, "id").select("region", "id", "n", "part", "label"), size)
        members.drop()
        members = following


def _open(percent: int) -> Column:
    """Whether a set has few enough lone shingles to be linked to anything."""
    return F.coalesce(F.col("lone"), F.lit(0)) * 100 <= F.col("n") * (100 - percent)


def regions(sets: DataFrame, percent: int, size: int) -> DataFrame:
    """(region, id) of the sets that share a cell of a rare shingle with another; sets: written table of id, n, part."""
    rows = _exploded(sets)
    often = rows.groupBy("s").agg(F.count("*").alias("df")).where("df > 1")
    # a shingle of one set comes first in the order of rarity, so it takes a place of the window
    order = Window.partitionBy("id").orderBy("df", "s")
    window = F.floor(F.col("n") * (100 - percent) / 100) + 1
    ranked = rows.join(often, "s").withColumn("r", F.row_number().over(order)).withColumn("shared", F.count("*").over(Window.partitionBy("id")))
    cells = settle(ranked.where(F.col("r") <= window - (F.col("n") - F.col("shared"))).select("s", "id"), size)
    hubs = cells.groupBy("s").agg(F.min("id").alias("hub"), F.count("*").alias("k")).where("k > 1").select("s", "hub")
    of = components(cells.join(hubs, "s").where("id <> hub").select(F.col("id").alias("src"), F.col("hub").alias("dst")), size=size)
    return of.select(F.col("component").alias("region"), F.col("node").alias("id"))


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """id, n_shingles and component_id (smallest id reachable over links) of every row."""
    share = min(1.0, 2 * (100 - percent) / 100)
    below = min(int(share * (1 << 64)), (1 << 64) - 1)
    base = Settled(_table(docs, id_col, text_col, words, below))
    keys = ["n", "f1", "f2"]
    # a class is named by f1, 64 bits of its set; its representative is the smallest id, a null one coming last
    last = F.lit((1 << 63) - 1)
    rows = base.df.where("n > 0").withColumn("at", F.coalesce("id", last))
    all_rows, shingles = base.df.agg(F.count("*"), F.sum("n")).first()
    few = 40 * all_rows  # bytes of a table of a few numbers a row
    classes = settle(rows.groupBy(*keys).agg(F.min("at").alias("rep"), F.count("*").alias("copies")), few)
    named = classes.select(F.col("rep").alias("at"), F.col("f1").alias("id"))
    firsts = Settled(rows.select("at", F.col("f1").alias("id"), "n", "part").join(_few(named), ["at", "id"], "left_semi").select("id", "n", "part"))
    firsts = _single(firsts, classes)
    # representatives with more lone shingles than a link allows are done
    suspects = settle(firsts.join(_lone(firsts), "id", "left").where(_open(percent)).select("id").join(classes.select(F.col("f1").alias("id"), "rep"), "id"), few + int(8 * share * (shingles or 0)))
    where = F.coalesce(F.col(id_col).cast("long"), last)
    again = docs.withColumn("__id", where).join(_few(suspects.select(F.col("rep").alias("__id")).distinct()), "__id", "left_semi")
    sets = _table(again, "__id", text_col, words, None).where("n > 0").select(F.col("f1").alias("id"), "n", "part")
    sets = _single(Settled(sets.join(_few(suspects.select("id")), "id", "left_semi")), suspects)
    # the same count over all shingles of the suspects
    rest = settle(sets.join(_lone(sets), "id", "left").where(_open(percent)).select("id", "n", "part"), _bytes(sets))
    links = _links(rest, percent)
    label = F.col("rep")
    named = classes
    if links is not None:
        linked = components(links, size=few)
        named = classes.join(linked, F.col("f1") == F.col("node"), "left")
        least = named.where("component is not null").groupBy("component").agg(F.min("rep").alias("least"))
        named = named.join(least, "component", "left")
        label = F.coalesce("least", "rep")
    of_class = settle(named.select(*keys, F.nullif(label, last).alias("component_id")), few)
    out = base.df.select("id", *keys).join(of_class, keys, "left")
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"))


def _single(sets: Settled, named: DataFrame) -> DataFrame:
    """One row a class; several rows of one id and text are rare, so only then are the sets dealt by class."""
    return sets.df if sets.df.count() == named.count() else settle(sets.df.dropDuplicates(["id"]))


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """docs with one document of each group: the one of smallest id. Rows without an id or without words all stay."""
    of = settle_last(lambda: groups(docs, id_col, text_col, words, percent))
    gone = settle(of.where(F.col(id_col) != F.col("component_id")).select(id_col).distinct())
    out = docs.join(_few(gone), id_col, "left_anti")
    twice = settle(of.where((F.col(id_col) == F.col("component_id")) & (F.col("n_shingles") > 0)).groupBy(id_col).count().where("count > 1").select(id_col))
    if twice.limit(1).count():  # rows that share an id: one of each text
        same = out.join(_few(twice), id_col, "left_semi").dropDuplicates([id_col, text_col])
        out = out.join(_few(twice), id_col, "left_anti").unionByName(same)
    return out.select(*docs.columns)

