"""Keyed (correlated) samples and joins whose intermediate results are bounded by re-sampling."""

from __future__ import annotations

import math
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.measures import W, correlation_df, counted, informativeness_df, joint_quality_df


def unit_hash(columns: Sequence[str], hash_name: str = "xxhash64", seed: int = 0) -> Column:
    """A number in [0, 1) from the values of some columns; null where any of them is null."""
    parts = [F.col(c).cast("string") for c in columns]
    if hash_name == "md5":  # other SQL engines have it too
        text = F.concat(*[x for p in parts for x in (p, F.lit("|"))], F.lit(str(seed)))
        return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(2.0**32)
    some_null = reduce(lambda x, y: x | y, (p.isNull() for p in parts))
    return F.when(~some_null, F.shiftrightunsigned(F.xxhash64(F.lit(seed), *parts), 11).cast("double") / F.lit(2.0**53))


def keyed_sample(df: DataFrame, join: Sequence[str], rate: float, hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """The rows whose join value hashes below the rate: a filter next to the scan.

    The same values survive on every side of a join, and a sample at a lower rate is contained in one at a higher rate.
    Rows with a null join value stand for unmatched rows and are kept by a hash of the whole row.
    """
    if rate >= 1:
        return df
    h = unit_hash(join, hash_name, seed)
    rest = unit_hash_nullable(df.columns, hash_name, seed)
    return df.where(F.coalesce(h, rest) < rate)


def unit_hash_nullable(columns: Sequence[str], hash_name: str = "xxhash64", seed: int = 0) -> Column:
    """A number in [0, 1) from a whole row, nulls included."""
    parts = [F.coalesce(F.col(c).cast("string"), F.lit("\\N")) for c in columns]
    if hash_name == "md5":
        return F.conv(F.substring(F.md5(F.concat(*[x for p in parts for x in (p, F.lit("|"))], F.lit(str(seed)))), 1, 8), 16, 10).cast("double") / F.lit(2.0**32)
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *parts), 11).cast("double") / F.lit(2.0**53)


#: Counts up to this size are thinned row by row, larger ones by the normal approximation of the binomial.
EXACT = 256


def thinned(count: Column, rate: float, columns: Sequence[str], hash_name: str = "xxhash64", seed: int = 0, exact: int = EXACT) -> Column:
    """How many of `count` equal rows a sample of rows at a rate keeps: each row by its own hash, of the values and its number.

    Rows that agree in all columns are as many rows, not one: they stay or go independently. Unbiased at every count.
    """
    if rate >= 1:
        return count

    def unit(extra: Column) -> Column:
        parts = [F.coalesce(F.col(c).cast("string"), F.lit("\\N")) for c in columns]
        if hash_name == "md5":
            text = F.concat(*[x for p in parts for x in (p, F.lit("|"))], F.lit(f"{seed}|"), extra.cast("string"))
            return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(2.0**32)
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *parts, extra.cast("long")), 11).cast("double") / F.lit(2.0**53)

    each = F.size(F.filter(F.sequence(F.lit(1).cast("long"), F.least(count, F.lit(exact))), lambda i: unit(i) < rate)).cast("long")
    # two uniform numbers make a normal one
    normal = F.sqrt(-2 * F.log(F.greatest(unit(F.lit(-1)), F.lit(1e-12)))) * F.cos(2 * math.pi * unit(F.lit(-2)))
    many = F.round(count * rate + F.sqrt(count * rate * (1 - rate)) * normal).cast("long")
    return F.when(count <= 0, F.lit(0).cast("long")).when(count <= exact, each).otherwise(F.greatest(F.lit(0).cast("long"), F.least(count, many)))


def informativeness_est(left: DataFrame, right: DataFrame, join: Sequence[str], rate: float, hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """Informativeness of two keyed samples at one rate."""
    return informativeness_df(keyed_sample(left, join, rate, hash_name, seed), keyed_sample(right, join, rate, hash_name, seed), join)


def bounded_join(frames: Sequence[tuple[DataFrame, Sequence[str]]], eta: float | None, rate: float = 0.5, hash_name: str = "xxhash64", seed: int = 1) -> DataFrame:
    """Joins frames left to right, each with its join attributes; an intermediate result of more than eta rows is re-sampled.

    The first entry's join attributes are ignored. Sizes are forecast from key counts before a join runs, so an exploding
    join is never executed: the sample is fused with it. Every row is kept or not on its own, also one of several that
    agree in all columns: equal rows are counted, and the count is thinned. eta=None never samples. The last result is not
    sampled.
    """
    out = frames[0][0]
    for k, (df, join) in enumerate(frames[1:], 1):
        too_large = False
        if eta is not None and k < len(frames) - 1:
            too_large = informativeness_df(out, df, join).first()["join_rows"] > eta
        if too_large:
            out, df = counted(out, out.columns), counted(df, df.columns).withColumnRenamed(W, "__v")
            out = out.join(df, list(join)).withColumn("__n", F.col(W) * F.col("__v")).drop(W, "__v")
            columns = sorted(c for c in out.columns if c != "__n")
            left = thinned(F.col("__n"), rate, columns, hash_name, seed + k)
            out = out.withColumn("__n", left).where(F.col("__n") > 0).withColumn("__n", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__n")))).drop("__n")
        else:
            out = out.join(df, list(join))
    return out


def estimate_df(frames: Sequence[tuple[DataFrame, Sequence[str]]], a_s: Sequence[str], a_t: Sequence[str], sample: float = 1.0, eta: float | None = None, rate: float = 0.5, fds: Sequence = (), hash_name: str = "xxhash64", seed: int = 0) -> DataFrame:
    """corr, quality and rows of the bounded join of keyed samples; each frame is sampled on its own edge's attributes."""
    sampled = []
    for k, (df, join) in enumerate(frames):
        keys = [join] if k else []
        if k + 1 < len(frames):
            nxt = [a for a in frames[k + 1][1] if a in df.columns]
            if len(nxt) == len(frames[k + 1][1]):
                keys.append(nxt)
        for j in keys:
            df = keyed_sample(df, j, sample, hash_name, seed)
        sampled.append((df, join))
    joined = bounded_join(sampled, eta, rate, hash_name, seed + 1)
    one = correlation_df(joined, a_s, a_t).crossJoin(joint_quality_df(joined, fds))  # one row each
    return one.crossJoin(joined.agg(F.count("*").alias("rows")))


def bias_report(left: DataFrame, right: DataFrame, join: Sequence[str], rate: float, seeds: Sequence[int]) -> DataFrame:
    """(seed, estimate, truth) of informativeness over many seeds, in one job."""
    truth = informativeness_df(left, right, join).select(F.col("ji").alias("truth"))
    out = None
    for s in seeds:
        one = informativeness_est(left, right, join, rate, seed=s).select(F.lit(s).alias("seed"), F.col("ji").alias("estimate"))
        out = one if out is None else out.unionByName(one)
    return out.crossJoin(F.broadcast(truth))  # one row
