"""Quality, informativeness, entropy and correlation measures over (optionally weighted) DataFrames.

Every `*_df` function returns a lazy one-row DataFrame; the function of the same name without the suffix is its scalar.
`weight` names a column with multiplicities, so that frames may be collapsed to (attributes, count) before joins and
measures (see plans.evaluate). Entropies are in bits. A set of attributes is a list of column names.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterable, Sequence
from dataclasses import dataclass
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

W = "__w"
#: Running sums over a numeric attribute are cut at so many quantiles of its values, and each part into as many equal widths.
RANGES = 32


@dataclass(frozen=True)
class FD:
    """lhs determines rhs, a single attribute."""

    lhs: tuple[str, ...]
    rhs: str

    @property
    def attributes(self) -> tuple[str, ...]:
        return (*self.lhs, self.rhs)

    def __str__(self) -> str:
        return f"{','.join(self.lhs)}->{self.rhs}"


def split_fd(lhs: Sequence[str], rhs: Iterable[str]) -> list[FD]:
    """A dependency with several attributes on its right as single ones; trivial ones are left out."""
    return [FD(tuple(lhs), y) for y in dict.fromkeys(rhs) if y not in lhs]


def same(a: Column, b: Column) -> Column:
    return a.eqNullSafe(b)


def _all(conditions: Iterable[Column]) -> Column:
    return reduce(lambda x, y: x & y, conditions, F.lit(True))


def multiplicity(weight: str | None) -> Column:
    return F.lit(1).cast("long") if weight is None else F.col(weight)


def counted(df: DataFrame, attributes: Sequence[str], weight: str | None = None) -> DataFrame:
    """The frame collapsed to its distinct attribute values with their number of rows, in column W."""
    return df.groupBy(*attributes).agg(F.sum(multiplicity(weight)).alias(W))


def class_sizes(df: DataFrame, attributes: Sequence[str], weight: str | None = None) -> DataFrame:
    """The partition of the rows by `attributes`, as keys and sizes; row ids are never gathered."""
    return counted(df, attributes, weight).withColumnRenamed(W, "size")


def scalar(df: DataFrame) -> float:
    value = df.first()[0]
    return float(value) if value is not None else float("nan")


# ---------------------------------------------------------------------------------------------- dependencies


def dominant_classes(df: DataFrame, fd: FD, tie: str = "value", seed: int = 0, weight: str | None = None) -> DataFrame:
    """For each left side the right side of its largest class, with both sizes; ties go to the least value, or by seeded hash."""
    sizes = counted(df, fd.attributes, weight)
    second = F.col(fd.rhs) if tie == "value" else F.xxhash64(F.lit(seed), *fd.attributes)
    best = F.min(F.struct((-F.col(W)).alias("k"), second.alias("t"), F.col(fd.rhs).alias("y")))
    out = sizes.groupBy(*fd.lhs).agg(best.alias("best"), F.sum(W).alias("class_size"))
    return out.select(*fd.lhs, F.col("best.y").alias(fd.rhs), (-F.col("best.k")).alias("correct_size"), "class_size")


def _flagged(df: DataFrame, fd: FD, name: str, weight: str | None) -> DataFrame:
    dom = dominant_classes(df, fd, weight=weight)
    keys = [f"__k{i}" for i in range(len(fd.lhs))]
    dom = dom.select(*[F.col(a).alias(k) for a, k in zip(fd.lhs, keys, strict=True)], F.col(fd.rhs).alias("__y"))
    on = _all(same(F.col(a), F.col(k)) for a, k in zip(fd.lhs, keys, strict=True))
    return df.join(dom, on, "left").withColumn(name, same(F.col(fd.rhs), F.col("__y"))).drop("__y", *keys)


def correct_rows(df: DataFrame, fd: FD) -> DataFrame:
    """The rows in the largest class of their left side."""
    return _flagged(df, fd, "__ok", None).where("__ok").drop("__ok")


def fd_quality_df(df: DataFrame, fd: FD, weight: str | None = None) -> DataFrame:
    """The share of correct rows; two combinable aggregates, no join back."""
    per = counted(df, fd.attributes, weight).groupBy(*fd.lhs).agg(F.max(W).alias("m"), F.sum(W).alias("n"))
    return per.agg((F.sum("m") / F.sum("n")).alias("quality"))


def fd_quality(df: DataFrame, fd: FD, weight: str | None = None) -> float:
    return scalar(fd_quality_df(df, fd, weight))


def joint_quality_df(df: DataFrame, fds: Sequence[FD], weight: str | None = None) -> DataFrame:
    """The share of rows that are correct under every dependency; 1 without dependencies."""
    attributes = list(dict.fromkeys(a for fd in fds for a in fd.attributes))
    if not attributes:
        return df.agg(F.lit(1.0).alias("quality"))
    frame = counted(df, attributes, weight)
    for k, fd in enumerate(fds):
        frame = _flagged(frame, fd, f"__ok{k}", W)
    ok = _all(F.col(f"__ok{k}") for k in range(len(fds)))
    return frame.agg((F.sum(F.when(ok, F.col(W)).otherwise(0)) / F.sum(W)).alias("quality"))


def joint_quality(df: DataFrame, fds: Sequence[FD], weight: str | None = None) -> float:
    return scalar(joint_quality_df(df, fds, weight))


def holds(df: DataFrame, fd: FD, theta: float = 0.9, weight: str | None = None) -> bool:
    """Whether the dependency is kept: its quality is at least theta."""
    return fd_quality(df, fd, weight) >= theta


def qualities_df(df: DataFrame, fds: Sequence[FD], weight: str | None = None) -> DataFrame:
    """(fd, quality) of many dependencies in one job over one collapsed frame."""
    out = None
    for fd in fds:
        one = fd_quality_df(df, fd, weight).select(F.lit(str(fd)).alias("fd"), "quality")
        out = one if out is None else out.unionByName(one)
    if out is None:
        return df.sparkSession.createDataFrame([], "fd string, quality double")
    return out


def discover_afds(df: DataFrame, attributes: Sequence[str] | None = None, max_lhs: int = 2, theta: float = 0.9, batch: int = 24) -> list[tuple[FD, float]]:
    """Minimal approximate dependencies with up to max_lhs attributes on the left, level by level.

    Quality never falls when the left side grows, so supersets of a holding left side are not tried. A batch of left sides
    is one job: the frame is expanded by grouping sets, once for each (left, right) pair, and aggregated twice.
    """
    from itertools import combinations

    names = list(attributes or df.columns)
    found: list[tuple[FD, float]] = []
    for size in range(1, max_lhs + 1):
        todo = [FD(lhs, y) for lhs in combinations(names, size) for y in names if y not in lhs and not any(f.rhs == y and set(f.lhs) <= set(lhs) for f, _ in found)]
        level: list[tuple[FD, float]] = []
        for i in range(0, len(todo), batch):
            part = todo[i : i + batch]
            level += [(fd, q) for fd, q in zip(part, _batch_qualities(df, part), strict=True) if q is not None and q >= theta]
        found += level
    return found


def grouping(columns: Sequence[str], group: Iterable[str]) -> int:
    """The grouping id of one set among the grouping columns: a bit for each column left out, the first one highest."""
    group = set(group)
    return sum(1 << (len(columns) - 1 - i) for i, c in enumerate(columns) if c not in group)


def rolled_up(df: DataFrame, sets: Sequence[Sequence[str]], weight: str | None = None) -> tuple[DataFrame, list[str]]:
    """Counts W of many attribute sets, each set told by its grouping id in `gid`, and the columns: those outside a set are null.

    The frame is collapsed to the attributes of all sets first, so it is the collapsed rows that grouping sets multiply.
    """
    columns = list(dict.fromkeys(a for s in sets for a in s))
    fine = counted(df, columns, weight)
    distinct = [list(s) for s in {frozenset(s): s for s in sets}.values()]
    out = fine.groupingSets([[F.col(a) for a in s] for s in distinct], *columns).agg(F.sum(W).alias(W), F.grouping_id().alias("gid"))
    return out, columns


def _batch_qualities(df: DataFrame, fds: Sequence[FD]) -> list[float | None]:
    counts, columns = rolled_up(df, [fd.attributes for fd in fds])
    of: dict[int, list[int]] = {}
    for k, fd in enumerate(fds):
        of.setdefault(grouping(columns, fd.attributes), []).append(k)
    # each count serves all dependencies over its attributes; what is not on their left side is blanked
    serves = F.create_map(*[x for gid, ks in of.items() for x in (F.lit(gid).cast("long"), F.array(*map(F.lit, ks)))])
    long = counts.withColumn("__fd", F.explode(serves[F.col("gid").cast("long")]))
    keys = [F.when(F.col("__fd").isin([k for k, fd in enumerate(fds) if a in fd.lhs]), F.col(a)).alias(a) for a in columns]
    per = long.select("__fd", *keys, W).groupBy("__fd", *columns).agg(F.max(W).alias("m"), F.sum(W).alias("n"))
    got = {r["__fd"]: r["q"] for r in per.groupBy("__fd").agg((F.sum("m") / F.sum("n")).alias("q")).collect()}  # a row a dependency
    return [got.get(k) for k in range(len(fds))]


# -------------------------------------------------------------------------------------------- informativeness


def _xlog(c: Column) -> Column:
    return F.when(c > 0, c * F.log2(F.when(c > 0, c).otherwise(F.lit(1.0)))).otherwise(F.lit(0.0))


def _ji(lone_left: Column, lone_right: Column, log_left: Column, log_right: Column, null_pairs: Column, matched: Column, log_matched: Column) -> Column:
    """Informativeness from sums over join values: rows unmatched on either side, their c*log2(c), rows with a null key, and joined rows."""
    rest = _xlog(lone_right + null_pairs) + _xlog(lone_left + null_pairs) - log_left - log_right - 2 * _xlog(null_pairs)
    n = lone_left + lone_right + null_pairs + matched
    entropy = _xlog(n) - log_matched - log_left - log_right - _xlog(null_pairs)
    return F.when(entropy > 1e-12, F.greatest(F.lit(0.0), F.least(F.lit(1.0), rest / entropy))).otherwise(F.lit(0.0))


def _ji_columns(a: Column, b: Column, null_key: Column) -> dict[str, Column]:
    """Terms of one join value with a rows on the left and b on the right, to be summed."""
    a, b = a.cast("double"), b.cast("double")
    left, right, both = ~null_key & (a > 0) & (b == 0), ~null_key & (b > 0) & (a == 0), ~null_key & (a > 0) & (b > 0)
    zero = F.lit(0.0)
    return {
        "lone_left": F.when(left, a).otherwise(zero), "lone_right": F.when(right, b).otherwise(zero),
        "log_left": F.when(left, _xlog(a)).otherwise(zero), "log_right": F.when(right, _xlog(b)).otherwise(zero),
        "null_pairs": F.when(null_key, a + b).otherwise(zero),
        "matched": F.when(both, a * b).otherwise(zero), "log_matched": F.when(both, _xlog(a * b)).otherwise(zero),
    }


def _any_null(attributes: Sequence[str]) -> Column:
    return reduce(lambda x, y: x | y, (F.col(a).isNull() for a in attributes))


def informativeness_df(left: DataFrame, right: DataFrame, join: Sequence[str], weight_left: str | None = None, weight_right: str | None = None) -> DataFrame:
    """(H - I) / H of the two sides' keys over their full outer join, from key counts alone.

    The outer join is never built: one union of two counted frames, one shuffle on the key with map-side combining, so a
    hot key costs a row a task. Null keys match nothing; their pair counts as (null, null).
    """
    both = counted(left, join, weight_left).select(*join, F.col(W).alias("a"), F.lit(0).cast("long").alias("b"))
    both = both.unionByName(counted(right, join, weight_right).select(*join, F.lit(0).cast("long").alias("a"), F.col(W).alias("b")))
    per = both.groupBy(*join).agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    sums = per.agg(*[F.coalesce(F.sum(c), F.lit(0.0)).alias(k) for k, c in _ji_columns(F.col("a"), F.col("b"), _any_null(join)).items()])
    return sums.select(_ji(*[F.col(c) for c in sums.columns]).alias("ji"), F.col("matched").alias("join_rows"))


def informativeness(left: DataFrame, right: DataFrame, join: Sequence[str]) -> float:
    return scalar(informativeness_df(left, right, join))


def informativeness_outer_df(left: DataFrame, right: DataFrame, join: Sequence[str]) -> DataFrame:
    """The same by its definition, from the physical full outer join; a cross-check, quadratic in hot keys."""
    r = right.select(*[F.col(a).alias(f"r_{a}") for a in join])
    out = left.select(*join).join(r, _all(F.col(a) == F.col(f"r_{a}") for a in join), "full_outer")
    # a key counts as a whole: null if any part is null
    pair = lambda cols: F.when(~reduce(lambda x, y: x | y, (F.col(c).isNull() for c in cols)), F.struct(*cols))
    pairs = out.select(pair(join).alias("x"), pair([f"r_{a}" for a in join]).alias("y"))
    sums = _entropies(pairs, {"xy": ["x", "y"], "x": ["x"], "y": ["y"]}, None)
    h, i = F.col("xy"), F.col("x") + F.col("y") - F.col("xy")
    return sums.select(F.when(h > 1e-12, F.greatest(F.lit(0.0), (h - i) / h)).otherwise(F.lit(0.0)).alias("ji"))


def informativeness_matrix(instances: dict[str, DataFrame], join: Sequence[str]) -> DataFrame:
    """(src, dst, ji, join_rows) of all pairs of instances that hold `join`, in one pass over a tagged union."""
    return informativeness_of_sets({n: df.select(*join) for n, df in instances.items()}, [tuple(join)]).drop("j")


def informativeness_of_sets(instances: dict[str, DataFrame], joins: Sequence[Sequence[str]], kept: Callable[[Sequence[str], Column], Column] | None = None) -> DataFrame:
    """(src, dst, j, ji, join_rows) of all pairs of instances and of all given join sets that both hold.

    kept: the count that a sample keeps of a key, from the set and the count; all or nothing of a key without nulls.
    """
    return informativeness_of_samples(instances, joins, [kept]).drop("sample")


def _shared_types(instances: dict[str, DataFrame], attributes: Iterable[str]) -> dict[str, T.DataType]:
    """The type of each attribute, the widest where instances differ."""
    out = {}
    for a in attributes:
        held = [df for df in instances.values() if a in df.schema.names]
        kinds = {df.schema[a].dataType for df in held}
        out[a] = kinds.pop() if len(kinds) == 1 else reduce(DataFrame.union, [df.select(a) for df in held]).schema[a].dataType
    return out


def informativeness_of_samples(instances: dict[str, DataFrame], joins: Sequence[Sequence[str]], kepts: Sequence[Callable[[Sequence[str], Column], Column] | None]) -> DataFrame:
    """(sample, src, dst, j, ji, join_rows): informativeness_of_sets for each entry of `kepts`, a sample or (None) all rows.

    Each instance is read once, a row giving its key in every set. The keys of all sets and instances meet in one combinable
    shuffle, their counts side by side, a column for each holder of the set; few columns hold the keys, as sets share them
    by type. Keys with the same counts say the same, so these are collapsed to counts and number of keys before pairs of
    instances are formed.
    """
    names = sorted(instances)
    sets = [tuple(j) for j in joins]
    held = {n: set(instances[n].columns) for n in names}
    holders = [[n for n in names if set(s) <= held[n]] for s in sets]
    types = _shared_types(instances, dict.fromkeys(a for s in sets for a in s))
    places: list[dict[str, tuple[T.DataType, int]]] = []
    for s in sets:
        seen: Counter = Counter()
        places.append({})
        for a in s:
            places[-1][a] = (types[a], seen[types[a]])
            seen[types[a]] += 1
    keys = {at: f"__x{i}" for i, at in enumerate(dict.fromkeys(at for p in places for at in p.values()))}
    counts = [f"__c{i}" for i in range(max(map(len, holders)))]
    union = None
    for name in names:
        rows = []
        for i, s in enumerate(sets):
            if name in holders[i]:
                of = {at: F.col(a).cast(at[0]) for a, at in places[i].items()}
                rows.append(F.struct(F.lit(i).alias("__j"), F.lit(holders[i].index(name)).alias("__k"), *[of.get(at, F.lit(None).cast(at[0])).alias(x) for at, x in keys.items()]))
        if rows:
            one = instances[name].select(F.inline(F.array(*rows)))
            union = one if union is None else union.union(one)
    per = union.groupBy("__j", *keys.values()).agg(*[F.count(F.when(F.col("__k") == i, 1)).alias(c) for i, c in enumerate(counts)])

    def by_set(values: Sequence[tuple[int, object]], make: Callable[[object], Column]) -> Column | None:
        """A value that depends on the set: one branch for all sets that agree."""
        agree: dict[object, list[int]] = {}
        for i, v in values:
            agree.setdefault(v, []).append(i)
        return reduce(lambda c, e: c.when(F.col("__j").isin(e[1]), make(e[0])), agree.items(), F)

    null_key = by_set([(i, tuple(keys[at] for at in p.values())) for i, p in enumerate(places)], _any_null)
    back = [by_set([(i, keys[p[a]]) for i, p in enumerate(places) if a in p], F.col).alias(a) for a in types]
    named = per.select("__j", null_key.alias("null_key"), *counts, *(back if any(kepts) else []))

    def sampled(kept: Callable[[Sequence[str], Column], Column] | None) -> Column:
        if kept is None:
            return F.array(*counts)
        share = lambda c: by_set(list(enumerate(sets)), lambda s: kept(s, c))
        whole = F.when(share(F.lit(1).cast("long")) > 0, F.array(*counts)).otherwise(F.array(*[F.lit(0).cast("long") for _ in counts]))
        return F.when(F.col("null_key"), F.transform(F.array(*counts), share)).otherwise(whole)

    samples = F.array(*[F.struct(F.lit(v).alias("sample"), sampled(kept).alias("c")) for v, kept in enumerate(kepts)])
    seen_by = named.select("__j", "null_key", F.inline(samples)) if any(kepts) else named.select("__j", "null_key", F.explode(F.array(*[F.lit(v) for v in range(len(kepts))])).alias("sample"), F.array(*counts).alias("c"))
    alike = seen_by.groupBy("sample", "__j", "null_key", "c").agg(F.count("*").cast("double").alias("__m"))
    pairs = {i: list(combinations(range(len(h)), 2)) for i, h in enumerate(holders) if len(h) > 1}
    listed = F.create_map(*[x for i, p in pairs.items() for x in (F.lit(i), F.array(*[F.struct(F.lit(a).alias("i"), F.lit(b).alias("k")) for a, b in p]))])
    met = alike.select("*", F.inline(listed[F.col("__j")])).select("sample", "__j", "i", "k", "null_key", "__m", F.get("c", F.col("i")).alias("a"), F.get("c", F.col("k")).alias("b")).where("a > 0 or b > 0")
    terms = _ji_columns(F.col("a"), F.col("b"), F.col("null_key"))
    sums = met.groupBy("sample", "__j", "i", "k").agg(*[F.sum(c * F.col("__m")).alias(n) for n, c in terms.items()])
    # pairs of which no key was seen on either side
    every = F.array(*[F.struct(F.lit(j).alias("__j"), F.lit(x).alias("i"), F.lit(y).alias("k"), *[F.lit(v).alias(n) for n, v in (("src", holders[j][x]), ("dst", holders[j][y]))], F.array(*map(F.lit, sets[j])).alias("j")) for j, p in pairs.items() for x, y in p])
    frame = next(iter(instances.values()))
    wanted = frame.sparkSession.range(1).select(F.inline(every)).select(F.explode(F.array(*[F.lit(v) for v in range(len(kepts))])).alias("sample"), "*")
    sums = wanted.join(sums, ["sample", "__j", "i", "k"], "left").na.fill(0.0, list(terms))
    return sums.select("sample", "src", "dst", "j", _ji(*[F.col(n) for n in terms]).alias("ji"), F.col("matched").alias("join_rows"))


# ------------------------------------------------------------------------------------------------- entropies


def _entropies(df: DataFrame, sets: dict[str, Sequence[str]], weight: str | None) -> DataFrame:
    """One row with the Shannon entropy of each named attribute set; coarser sets are rolled up from the finest frame."""
    everything = list(dict.fromkeys(a for s in sets.values() for a in s))
    fine = counted(df, everything, weight)
    parts = None
    for name, attributes in sets.items():
        one = fine if set(attributes) == set(everything) else fine.groupBy(*attributes).agg(F.sum(W).alias(W))
        one = one.select(F.lit(name).alias("set"), F.col(W).cast("double").alias("c"))
        parts = one if parts is None else parts.unionByName(one)
    per = parts.groupBy("set").agg(F.sum("c").alias("n"), F.sum(_xlog(F.col("c"))).alias("s"))
    h = F.greatest(F.lit(0.0), F.log2("n") - F.col("s") / F.col("n"))
    return per.select("set", h.alias("h")).agg(*[F.coalesce(F.max(F.when(F.col("set") == name, F.col("h"))), F.lit(0.0)).alias(name) for name in sets])


def entropy_df(df: DataFrame, x: Sequence[str], weight: str | None = None) -> DataFrame:
    return _entropies(df, {"entropy": x}, weight)


def entropy(df: DataFrame, x: Sequence[str], weight: str | None = None) -> float:
    return scalar(entropy_df(df, x, weight))


def cond_entropy_df(df: DataFrame, x: Sequence[str], y: Sequence[str], weight: str | None = None) -> DataFrame:
    """H(X | Y), by the chain rule."""
    h = _entropies(df, {"xy": [*x, *y], "y": y}, weight)
    return h.select(F.greatest(F.lit(0.0), F.col("xy") - F.col("y")).alias("cond_entropy"))


def mutual_information_df(df: DataFrame, x: Sequence[str], y: Sequence[str], weight: str | None = None) -> DataFrame:
    h = _entropies(df, {"xy": [*x, *y], "x": x, "y": y}, weight)
    return h.select(F.greatest(F.lit(0.0), F.col("x") + F.col("y") - F.col("xy")).alias("mutual_information"))


def entropies_df(df: DataFrame, sets: Sequence[Sequence[str]], batch: int = 32) -> DataFrame:
    """(attributes, entropy) of many attribute sets: one scan per batch, rolled up by grouping sets from the collapsed frame."""
    out = None
    for i in range(0, len(sets), batch):
        part = sets[i : i + batch]
        counts, columns = rolled_up(df, part)
        names: dict[int, list[str]] = {}
        for s in part:
            names.setdefault(grouping(columns, s), []).append("+".join(s))
        c = F.col(W).cast("double")
        per = counts.groupBy("gid").agg(F.sum(c).alias("n"), F.sum(_xlog(c)).alias("s"))
        named = F.create_map(*[x for gid, ns in names.items() for x in (F.lit(gid).cast("long"), F.array(*map(F.lit, ns)))])
        one = per.select(F.explode(named[F.col("gid").cast("long")]).alias("attributes"), F.greatest(F.lit(0.0), F.log2("n") - F.col("s") / F.col("n")).alias("entropy"))
        out = one if out is None else out.unionByName(one)
    return out


def number(c: Column, kind: T.DataType) -> Column:
    """A numeric attribute as a double; timestamps and dates in seconds."""
    if isinstance(kind, T.DateType):
        c = c.cast("timestamp")
    if isinstance(kind, T.TimestampNTZType):
        c = c.cast("timestamp")
    return c.cast("double")


def _cumulative(df: DataFrame, x: str, keys: Sequence[str], weight: str | None) -> DataFrame:
    """(keys, n, h): cumulative entropy of x within each key group.

    h is the integral of -F log2 F over the empirical distribution function. Values are collapsed to counts and cut at
    RANGES approximate quantiles, each part into RANGES equal widths; running sums are taken within a range on top of the
    ranges' offsets, so neither one group nor the whole column is ever sorted in one task, and an outlier leaves at most a
    part in one range. The result does not depend on the cut.
    """
    frame = df.withColumn("__x", number(F.col(x), df.schema[x].dataType)).where("__x is not null and not isnan(__x)")
    values = counted(frame, [*keys, "__x"], weight)
    cuts = F.percentile_approx("__x", [k / RANGES for k in range(1, RANGES)], 1000)
    bounds = values.agg(F.concat(F.array(F.min("__x")), cuts, F.array(F.max("__x"))).alias("__edges"))
    # the part: how many inner edges lie below the value
    values = values.crossJoin(F.broadcast(bounds)).withColumn("__q", F.size(F.filter(F.slice("__edges", 2, RANGES - 1), lambda e: e < F.col("__x"))))  # bounds is one row
    lo, hi = F.get("__edges", F.col("__q")), F.get("__edges", F.col("__q") + 1)
    inner = F.when(hi > lo, F.greatest(F.lit(0), F.least(F.floor((F.col("__x") - lo) / (hi - lo) * RANGES), F.lit(RANGES - 1)))).otherwise(F.lit(0))
    values = values.withColumn("__r", (F.col("__q") * RANGES + inner).cast("int")).drop("__q", "__edges")
    ranges = values.groupBy(*keys, "__r").agg(F.sum(W).alias("rw"), F.min("__x").alias("first"))
    across = Window.partitionBy(*keys).orderBy("__r")
    whole = Window.partitionBy(*keys).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ranges = ranges.select(
        *[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys)], F.col("__r").alias("__rr"),
        F.coalesce(F.sum("rw").over(across.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"),
        F.lead("first").over(across).alias("following"), F.sum("rw").over(whole).alias("n"),
    )
    inside = Window.partitionBy(*keys, "__r").orderBy("__x")
    values = values.withColumn("upto", F.sum(W).over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow))).withColumn("next", F.lead("__x").over(inside))
    joined = values.join(ranges, _all([F.col("__r") == F.col("__rr"), *(same(F.col(k), F.col(f"__k{i}")) for i, k in enumerate(keys))]))
    share = (F.col("offset") + F.col("upto")) / F.col("n")
    term = F.coalesce(F.coalesce("next", "following") - F.col("__x"), F.lit(0.0)) * -share * F.log2(share)
    return joined.groupBy(*keys).agg(F.max("n").alias("n"), F.sum(term).alias("h"))


def cum_entropy_df(df: DataFrame, x: str, weight: str | None = None) -> DataFrame:
    return _cumulative(df, x, [], weight).agg(F.coalesce(F.sum("h"), F.lit(0.0)).alias("cum_entropy"))


def cum_entropy(df: DataFrame, x: str, weight: str | None = None) -> float:
    return scalar(cum_entropy_df(df, x, weight))


def binned(df: DataFrame, y: Sequence[str], bins: int) -> tuple[DataFrame, list[str]]:
    """Numeric attributes of y in equal-width bins, so that a condition of many values does not look like a perfect one."""
    kinds = {a: kind_of(df, a) for a in y}
    names = []
    for a in y:
        if kinds[a] == "numeric":
            v = number(F.col(a), df.schema[a].dataType)
            bounds = df.agg(F.min(v).alias("__lo"), F.max(v).alias("__hi"))
            df = df.crossJoin(F.broadcast(bounds))  # one row
            df = df.withColumn(f"__bin_{a}", F.when(F.col("__hi") > F.col("__lo"), F.least(F.floor((v - F.col("__lo")) / (F.col("__hi") - F.col("__lo")) * bins), F.lit(bins - 1))).otherwise(F.lit(0))).drop("__lo", "__hi")
            names.append(f"__bin_{a}")
        else:
            names.append(a)
    return df, names


def cond_cum_entropy_df(df: DataFrame, x: str, y: Sequence[str], weight: str | None = None, y_bins: int | None = None) -> DataFrame:
    """h(X | Y): the mean of the groups' cumulative entropies, weighted by their share of rows."""
    if y_bins:
        df, y = binned(df, y, y_bins)
    per = _cumulative(df, x, y, weight)
    return per.agg(F.coalesce(F.sum(F.col("n") * F.col("h")) / F.sum("n"), F.lit(0.0)).alias("cond_cum_entropy"))


# ----------------------------------------------------------------------------------------------- correlation


def kind_of(df: DataFrame, attribute: str, kinds: dict[str, str] | None = None) -> str:
    """numeric or categorical: by the caller's word, else by type; integers and keys are categorical."""
    base = attribute.rpartition("__")[2]
    if kinds and (attribute in kinds or base in kinds):
        return kinds.get(attribute) or kinds[base]
    t = df.schema[attribute].dataType
    if isinstance(t, T.MapType | T.ArrayType | T.StructType | T.DayTimeIntervalType | T.YearMonthIntervalType):
        raise TypeError(f"{attribute}: {t.simpleString()} is no attribute type; derive a scalar from it")
    return "numeric" if isinstance(t, T.DoubleType | T.FloatType | T.DecimalType | T.TimestampType | T.TimestampNTZType) else "categorical"


def correlation_df(df: DataFrame, x: Sequence[str], y: Sequence[str], kinds: dict[str, str] | None = None, weight: str | None = None, y_bins: int | None = None) -> DataFrame:
    """Entropy gain of x from y: H(X) - H(X|Y) of the categorical attributes together, plus h(x) - h(x|Y) of each numeric one."""
    if y_bins:
        df, y = binned(df, y, y_bins)
    x, y = list(x), list(y)
    frame = counted(df, list(dict.fromkeys([*x, *y])), weight)
    categorical = [a for a in x if kind_of(df, a, kinds) == "categorical"]
    parts = []
    if categorical:
        parts.append(mutual_information_df(frame, categorical, y, W).select(F.col("mutual_information").alias("gain")))
    for a in (a for a in x if a not in categorical):
        whole = cum_entropy_df(frame, a, W).select(F.col("cum_entropy").alias("gain"))
        parts += [whole, cond_cum_entropy_df(frame, a, y, W).select((-F.col("cond_cum_entropy")).alias("gain"))]
    return reduce(DataFrame.unionByName, parts).agg(F.sum("gain").alias("corr"))


def correlation(df: DataFrame, x: Sequence[str], y: Sequence[str], **more) -> float:
    return scalar(correlation_df(df, x, y, **more))


def corr_pearson_df(df: DataFrame, x: str, y: str) -> DataFrame:
    """The single-kind baseline measure: Pearson's coefficient of two numeric attributes."""
    return df.agg(F.corr(number(F.col(x), df.schema[x].dataType), number(F.col(y), df.schema[y].dataType)).alias("pearson"))


def price_df(df: DataFrame, attributes: Sequence[str], a: float = 1.0, b: float = 0.0, weight: str | None = None) -> DataFrame:
    """Entropy price of a set of columns: a * H + b."""
    return entropy_df(df, attributes, weight).select((F.col("entropy") * a + b).alias("price"))


def join_size_df(left: DataFrame, right: DataFrame, join: Sequence[str]) -> DataFrame:
    """Rows of the equi-join, forecast from key counts."""
    return informativeness_df(left, right, join).select(F.col("join_rows").cast("long").alias("join_rows"))
