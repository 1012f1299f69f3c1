"""Document fingerprints from closed syncmers.

A k-mer of code points is a closed syncmer when the smallest hash among its inner s-mers lies at its first or last
inner place. Whether a k-mer is chosen depends on its own characters alone, so equal passages give equal anchors
wherever they stand; and every window of k - s + 1 consecutive k-mers holds an anchor. A fingerprint keeps the `size`
anchors of smallest hash with the place of each one's first occurrence; likeness is the bottom-sketch estimate of the
Jaccard similarity of two anchor sets, counting only anchors on the longest chain whose places rise in both texts, so that
insertions and deletions of any length leave the passages around them shared.

Defined cases: a null text counts as empty and has no anchors; a text shorter than k is one anchor as a whole; two
empty fingerprints have likeness 1, an empty and another one 0. Rows keep their multiplicity. Only the id and text
columns are read.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import _text as tx

U = np.uint64
_STEP = 0xC2B2AE3D27D4EB4F


def _kmer_hashes(mixed: np.ndarray, length: int) -> np.ndarray:
    """A hash of every run of `length` code points, by doubling."""
    have, h = 1, mixed
    while have < length:
        take = min(have, length - have)
        shift = U(pow(_STEP, take, 1 << 64))
        tail = mixed if take == 1 else h[: len(h)] if take == have else _kmer_hashes(mixed, take)
        n = len(mixed) - have - take + 1
        h = h[:n] * shift + tail[have : have + n]
        have += take
    return tx.mix(h)


def _window_min(x: np.ndarray, w: int) -> np.ndarray:
    have = 1
    while have < w:
        take = min(have, w - have)
        x = np.minimum(x[: len(x) - take], x[take:])
        have += take
    return x


def anchors(cps: np.ndarray, k: int, s: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes of the closed syncmers in one array of code points."""
    if len(cps) < k:
        return np.zeros(0, np.int64), np.zeros(0, U)
    mixed = tx.mix(cps.astype(U) + U(0x632BE59BD9B4E019))
    inner = _kmer_hashes(mixed, s)
    w = k - s + 1
    least = _window_min(inner, w)
    n = len(least)
    at = np.flatnonzero((inner[:n] == least) | (inner[w - 1 : w - 1 + n] == least))
    return at, _kmer_hashes(mixed, k)[at]


def sketch(cps: np.ndarray, offsets: np.ndarray, k: int, s: int, size: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For every row of a slice the `size` smallest distinct anchor hashes, ascending, and their first places."""
    at, h = anchors(cps, k, s)
    row = np.searchsorted(offsets, at, "right") - 1
    inside = at + k <= offsets[row + 1] if len(at) else np.zeros(0, bool)  # not across two rows
    at, h, row = at[inside], h[inside], row[inside]
    bounds = np.searchsorted(row, np.arange(len(offsets)))
    out = []
    for r in range(len(offsets) - 1):
        a, b, lo, hi = bounds[r], bounds[r + 1], int(offsets[r]), int(offsets[r + 1])
        if a == b:
            short = cps[lo:hi]
            whole = np.frombuffer(hashlib.blake2b(short.tobytes(), digest_size=8).digest(), U) if hi > lo else np.zeros(0, U)
            out.append((whole, np.zeros(len(whole), np.int64)))
            continue
        own = h[a:b]
        if len(own) > 4 * size:  # only small hashes can stay; all of them if too few are distinct
            near = np.flatnonzero(own <= np.partition(own, 3 * size)[3 * size])
        else:
            near = np.arange(len(own))
        values, first = np.unique(own[near], return_index=True)
        if len(values) < size and len(near) < len(own):
            values, first = np.unique(own, return_index=True)
            near = np.arange(len(own))
        out.append((values[:size], at[a:b][near[first[:size]]] - lo))
    return out


def likeness(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray], size: int) -> float:
    """Between 0 and 1: shared anchors in the same order among the smallest hashes of both."""
    if not len(one[0]) or not len(two[0]):
        return float(len(one[0]) == len(two[0]))
    union = np.union1d(one[0], two[0])[:size]
    _, i, j = np.intersect1d(one[0], two[0], assume_unique=True, return_indices=True)
    keep = one[0][i] <= union[-1]
    if not keep.any():
        return 0.0
    ends: list[int] = []  # the least last place of a rising chain of each length
    for place in two[1][j[keep]][np.argsort(one[1][i[keep]])].tolist():
        at = bisect_left(ends, place)
        ends[at : at + 1] = [place]
    return len(ends) / len(union)


def text_of(fingerprint: tuple[np.ndarray, np.ndarray]) -> str:
    """hash.place pairs in hexadecimal; the empty string without anchors."""
    return " ".join(f"{h:016x}.{p:x}" for h, p in zip(fingerprint[0].tolist(), fingerprint[1].tolist(), strict=True))


def parsed(text: str) -> tuple[np.ndarray, np.ndarray]:
    pairs = [x.split(".") for x in text.split()]
    return np.array([int(h, 16) for h, _ in pairs], U), np.array([int(p, 16) for _, p in pairs], np.int64)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 24, s: int = 10, size: int = 64) -> DataFrame:
    """The id column, n_chars and the fingerprint of every text."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(1)):
                cps = tx.code_points(data)
                bounds = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])[offsets]
                found = [text_of(x) for x in sketch(cps, bounds, k, s, size)]
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], pa.array(np.diff(bounds), pa.int64()), pa.array(found, pa.string())], ["id", "n_chars", "fingerprint"])

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, n_chars long, fingerprint string").withColumnRenamed("id", id_col)


def edit_study(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 24, s: int = 10, size: int = 64) -> DataFrame:
    """Fingerprint every text and an edited one, whose second half is the beginning of the next text by id.

    Rows are dealt once, by id ranges of about even numbers of rows. The first row of each range is also sent, whole, to
    the range before, so no task needs another task's rows. A null id comes first; rows with one id are ordered by a hash
    of the text; other columns are not read. Returns the columns of the contract of op1.
    """
    spark = docs.sparkSession
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body")).withColumn("at", F.coalesce("doc_id", F.lit(-(1 << 63))))
    base = base.withColumn("tie", F.xxhash64("body"))
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = max(4 * width, 2)  # several ranges a task, so that tasks are about even
    cuts = sorted({int(x) for x in base.select("at").approxQuantile("at", [i / parts for i in range(1, parts)], 0.2 / parts)})
    part = F.size(F.filter(F.array(*map(F.lit, cuts)).cast("array<bigint>"), lambda c: c < F.col("at"))).alias("part")
    placed = base.withColumn("part", part)
    firsts = {r["part"]: r["first"] for r in placed.groupBy("part").agg(F.min("at").alias("first")).collect()}  # a row a range
    if not firsts:
        return spark.createDataFrame([], _SCHEMA)
    order = sorted(firsts)
    send = spark.createDataFrame([(firsts[p], order[i - 1]) for i, p in enumerate(order)], "at long, part int")  # the first of all goes to the last range
    lead = base.join(F.broadcast(send), "at").groupBy("at", "part").agg(F.min(F.struct("tie", "doc_id", "body")).alias("x"))  # a row a range
    lead = lead.select("x.doc_id", "x.body", "at", "x.tie", "part", F.lit(True).alias("lead"))
    both = placed.withColumn("lead", F.lit(False)).unionByName(lead).select("doc_id", "body", "part", "lead", "at", "tie")
    placed = both.repartition(width, "part").sortWithinPartitions("part", "lead", "at", "tie")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []  # the last row, which waits for the next one
        lead: tuple | None = None
        for batch in batches:
            ids, parts_, leads = (batch.column(k).to_pylist() for k in (0, 2, 3))
            data, offsets = tx.utf8(batch.column(1))
            for i, j in tx.slices(offsets, tx.SLICE_BYTES // 2):
                raw = data[offsets[i] : offsets[j]].tobytes()
                texts = [raw[a - offsets[i] : b - offsets[i]].decode("utf-8", "replace") for a, b in zip(offsets[i:j].tolist(), offsets[i + 1 : j + 1].tolist(), strict=True)]
                ready = []
                for d, t, p, is_lead in zip(ids[i:j], texts, parts_[i:j], leads[i:j], strict=True):
                    if held and held[0][2] == p and not (is_lead and lead):
                        ready.append((*held[0], t))
                        held = []
                    if is_lead:
                        lead = (p,)
                    else:
                        held, lead = [(d, t, p)], None
                if ready:
                    yield _compare(ready, k, s, size)
        if held:  # no next row: cannot be, as each range gets a lead
            yield _compare([(*held[0], "")], k, s, size)

    return placed.mapInArrow(run, _SCHEMA)


_SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _compare(ready: list[tuple[int, str, int, str]], k: int, s: int, size: int) -> pa.RecordBatch:
    own = [t for _, t, _, _ in ready]
    edited = [t[: len(t) - len(t) // 2] + following[: len(t) // 2] for _, t, _, following in ready]
    nexts = [own[i + 1] if i + 1 < len(ready) and ready[i][3] is own[i + 1] else following for i, (_, _, _, following) in enumerate(ready)]
    tail = [nexts[-1]]  # the others are in own already
    extra = {i: x for i, x in enumerate(nexts[:-1]) if i + 1 >= len(own) or x is not own[i + 1]}
    texts = [*own, *edited, *tail, *extra.values()]
    lengths = np.array([len(t) for t in texts], np.int64)
    offsets = np.concatenate([[0], np.cumsum(lengths)])
    cps = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    found = sketch(cps, offsets, k, s, size)
    n = len(own)
    following = {i: found[2 * n + 1 + x] for x, i in enumerate(extra)} | {n - 1: found[2 * n]}
    nears = [likeness(found[i], following.get(i) or found[i + 1], size) for i in range(n)]
    return pa.RecordBatch.from_arrays(
        [
            pa.array([d for d, *_ in ready], pa.int64()),
            pa.array(lengths[:n], pa.int64()),
            pa.array([hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in edited]),
            pa.array([text_of(x) for x in found[:n]], pa.string()),
            pa.array([text_of(x) for x in found[n : 2 * n]], pa.string()),
            pa.array([likeness(found[i], found[n + i], size) for i in range(n)], pa.float64()),
            pa.array(nears, pa.float64()),
        ],
        ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
    )
