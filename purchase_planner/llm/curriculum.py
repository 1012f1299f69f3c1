"""Mixing sources to target weights along a time-varying curriculum.

Each source has a target number of words: weights shared out over a total, no target above `most` times its source
(the excess goes to the others by weight: water filling, in closed form over the sorted ratios). A source's documents
are put in a fixed pseudo-random order; passes over it follow until the target is met, the last document being cut at a
word, so taken words equal the target rounded down.

When a word is needed is set by the source's schedule, a density over training time 0 to 1 of 1 + slope * (2t - 1): its
integral F(t) = t + slope * (t*t - t) is the cumulative demand, and its inverse turns a document's place in the source's
stream into a training position. Documents of all sources are then range-sorted by position.

Running sums stay distributed under a hot source: a source's order is cut into BUCKETS hash ranges, sums per range come
first, and windows run within a range. Id and text decide the order, so reruns agree; rows of one id, text and source are
one entry with a number of copies, so neither a repeated id nor a repeated row makes a range hot.

Defined cases: a null text or one without words has size 0 and takes nothing; a null source is a source of its own,
last; targets of sources of size 0 are 0; repeated rows each take their share; an empty table gives an empty result; other
columns, whatever their names, are kept by `mixed` only.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._shared import renamed, settle, settle_last

WEIGHTS, SHARE, MOST, BUCKETS = (5.0, 2.0, 1.0), 1.5, 2, 1024
#: Slopes of the schedules, repeating over sources: rising, even, falling.
SLOPES = (0.8, 0.0, -0.8)


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def tie(text: Column) -> Column:
    """60 bits of a text, as other SQL engines can compute them too."""
    return F.conv(F.substring(F.md5(F.coalesce(text, F.lit(""))), 1, 15), 16, 10).cast("long")


def place(doc_id: Column, tie_: Column) -> Column:
    """Pseudo-random 32-bit order of ids and texts that other SQL engines can compute too."""
    return F.conv(F.substring(F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("null")), F.lit("|"), tie_.cast("string"))), 1, 8), 16, 10).cast("long")


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """source, source_size, weight, target, slope: one row a source, from rows (source, size)."""
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    # windows without a partition: one row a source, after the aggregate
    number = F.row_number().over(Window.orderBy(F.col("source").isNull(), F.col("source"))) - 1

    def pick(values: tuple[float, ...]) -> Column:
        return F.element_at(F.array(*[F.lit(float(w)) for w in values]), (number % len(values) + 1).cast("int"))

    per = per.withColumn("weight", pick(weights)).withColumn("slope", pick(SLOPES)).withColumn("cap", F.col("source_size") * float(most))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), F.col("source"))
    below = order.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    per = per.withColumn("left", F.sum("source_size").over(everything) * float(share) - F.coalesce(F.sum("cap").over(below), F.lit(0.0)))
    per = per.withColumn("open", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(below), F.lit(0.0)))
    # the level is that of the first source that stays below its limit; all before it stop at theirs
    per = per.withColumn("level", F.col("left") / F.col("open")).withColumn("under", F.col("level") * F.col("weight") <= F.col("cap"))
    level = F.min(F.when(F.col("under"), F.struct(F.col("cap") / F.col("weight"), "level")))
    per = per.withColumn("chosen", level.over(everything)["level"])
    return per.select("source", "source_size", "weight", "slope", F.least(F.col("cap"), F.coalesce(F.col("chosen") * F.col("weight"), F.col("cap"))).alias("target"))


def _streams(docs: DataFrame, weights: tuple[float, ...], share: float, most: int) -> DataFrame:
    """Every document with its size, its source's figures, the words that precede it in one pass (`before`) and, of several
    rows of one id, text and source, the number of the copy."""
    text = F.col("text").cast("string")
    named = docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), n_words(text).alias("size"), tie(text).alias("tie"))
    # ids and sizes only: texts are counted once
    sized = settle(named.groupBy("doc_id", "source", "size", "tie").agg(F.count("*").alias("copies")).withColumn("place", place(F.col("doc_id"), F.col("tie"))))
    words = F.col("size") * F.col("copies")
    goal = settle(targets(sized.select("source", words.alias("size")), weights, share, most))
    cut = sized.withColumn("bucket", F.shiftright("place", 32 - (BUCKETS.bit_length() - 1)))
    sums = cut.groupBy("source", "bucket").agg(F.sum(words).alias("words"))
    start = F.coalesce(F.sum("words").over(Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sums.select(F.col("source").alias("s"), F.col("bucket").alias("b"), start.alias("start"))
    own = Window.partitionBy("source", "bucket").orderBy("place", "doc_id", "size", "tie").rowsBetween(Window.unboundedPreceding, -1)
    inner = cut.withColumn("inside", F.coalesce(F.sum(words).over(own), F.lit(0)))
    placed = inner.join(starts, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("b"))).drop("s", "b")
    figures = goal.select(F.col("source").alias("s"), "source_size", "target", "slope")
    found = placed.join(figures, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    found = found.withColumn("copy", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)))
    return found.withColumn("before", F.col("start") + F.col("inside") + F.col("copy") * F.col("size"))


def position(done: Column, slope: Column) -> Column:
    """The training time by which a share `done` of a source's demand is met: the inverse of t + slope * (t*t - t)."""
    linear = F.lit(1.0) - slope
    return F.when(F.abs(slope) < 1e-9, done).otherwise((-linear + F.sqrt(linear * linear + slope * 4 * done)) / (slope * 2))


def plan(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, first_position of every document."""
    return _plan(_streams(docs, weights, share, most), most).drop("tie", "copy")


def _plan(streams: DataFrame, most: int) -> DataFrame:
    goal = F.floor("target").cast("long")
    # what pass p takes: from before + p * source_size to the target, the document's size at most
    per_pass = [F.greatest(F.lit(0), F.least(F.col("size"), goal - F.col("before") - F.col("source_size") * p)) for p in range(most)]
    taken = sum(per_pass[1:], per_pass[0]).cast("long")
    done = F.when(F.col("target") > 0, F.least(F.lit(1.0), F.col("before") / F.col("target")))
    return streams.select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), F.array(*per_pass).alias("passes"), F.when(taken > 0, position(done, F.col("slope"))).alias("first_position"), "slope", "before", "tie", "copy")


def mixed(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """The mix itself: the rows of docs, once per pass that takes them and cut where the target ends, range-sorted by training position.

    Keeps the columns of docs, whose last copy of a source may be cut; n_chars, where there, follows the cut.
    """

    inner, names = renamed(docs)
    own = {c: F.col(names[c]) for c in ("doc_id", "text", "source")}
    body = own["text"].cast("string")
    known = inner.select(own["doc_id"].alias("doc_id"), body.alias("text"), own["source"].alias("source"))

    def per_document() -> DataFrame:
        taken = _plan(_streams(known, weights, share, most), most).where("taken > 0")
        done = (F.col("before") + F.col("pass") * F.col("source_size")) / F.col("target")
        entries = taken.select("doc_id", "source", "tie", "copy", "before", "source_size", "target", "slope", "size", F.posexplode("passes").alias("pass", "words")).where("words > 0")
        entry = F.struct("pass", "words", "size", position(done, F.col("slope")).alias("position"))
        # at most `most` entries a copy
        return entries.groupBy("doc_id", "source", "tie", "copy").agg(F.sort_array(F.collect_list(entry)).alias("entries"))

    chosen = settle_last(per_document)  # a row a taken document, without its text
    several = settle(chosen.where("copy > 0").select("doc_id", "source", "tie").distinct())
    keys = {"doc_id": own["doc_id"], "source": own["source"].cast("string"), "tie": tie(body)}
    rows = inner.withColumns({f"__{k}": c for k, c in keys.items()}).withColumn("__copy", F.lit(0).cast("long"))
    if several.limit(1).count():  # rows of one id, text and source: number them, first within the tasks that read them
        mark = several.select(*[F.col(k).alias(f"__r_{k}") for k in keys])
        twice = [F.col(f"__{k}").eqNullSafe(F.col(f"__r_{k}")) for k in keys]
        same = reduce(lambda x, y: x & y, twice)
        part = settle(rows.join(mark, same, "left_semi").withColumn("__part", F.spark_partition_id()))
        group = [f"__{k}" for k in keys]
        per = part.groupBy(*group, "__part").agg(F.count("*").alias("n"))
        offset = F.coalesce(F.sum("n").over(Window.partitionBy(*group).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        offsets = per.select(*[F.col(g).alias(f"__o{g}") for g in group], F.col("__part").alias("__o__part"), offset.alias("__offset"))
        number = F.row_number().over(Window.partitionBy(*group, "__part").orderBy(F.lit(1))) - 1
        meets = reduce(lambda x, y: x & y, [F.col(g).eqNullSafe(F.col(f"__o{g}")) for g in [*group, "__part"]])
        numbered = part.withColumn("__number", number).join(offsets, meets).withColumn("__copy", F.col("__number") + F.col("__offset"))
        rows = rows.join(mark, same, "left_anti").unionByName(numbered.select(*rows.columns))
    of = chosen.select(*[F.col(k).alias(f"__e_{k}") for k in [*keys, "copy"]], F.col("entries").alias("__entries"))
    out = rows.join(of, reduce(lambda x, y: x & y, [F.col(f"__{k}").eqNullSafe(F.col(f"__e_{k}")) for k in [*keys, "copy"]])).withColumn("__entry", F.explode("__entries"))
    pieces = F.split(body, r"(?<=[^\x20\x09-\x0D])(?=[\x20\x09-\x0D])")
    whole = F.col("__entry")["words"] >= F.col("__entry")["size"]
    cut = F.array_join(F.slice(pieces, 1, F.col("__entry")["words"].cast("int")), "")
    out = out.withColumn(names["text"], F.when(whole, body).otherwise(cut))
    if "n_chars" in names:
        n = names["n_chars"]
        out = out.withColumn(n, F.when(whole, F.col(n)).otherwise(F.length(names["text"]).cast("long")))
    position_ = F.col("__entry")["position"]
    out = out.repartitionByRange(position_, own["doc_id"]).sortWithinPartitions(position_, own["doc_id"])
    return out.select(*[F.col(n).alias(c) for c, n in names.items()])
