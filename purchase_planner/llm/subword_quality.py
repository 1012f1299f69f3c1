"""Quality classifier: supervised subword embeddings with a softmax on top, trained by stochastic gradient descent.

Every word [^\\x20\\x09-\\x0D]+ and its character n-grams (code points, with word boundaries) are hashed to vectors; a
word's vector is the mean of theirs, a document's the mean over its words. Of the word bigrams those of one word twice
share a vector of their own; other bigrams have none. After training, vectors and softmax weights fold into one number per bucket, so scoring needs one lookup per
distinct feature of a slice.

The training sample is bounded: the SAMPLE labelled rows of smallest hash among those that training may use, as far as
their texts have SAMPLE_BYTES together (documented parameters); everything else covers all rows.

Defined cases: a null or empty text has no words and scores as the model's bias says; rows keep their multiplicity;
labels that are null are not used, of several labels for one id the largest counts; long texts are scored whole, slice by
slice; carried columns may have any names; with no usable labels, or labels
of one class only, the score is the share of label 1 (0.5 without labels).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import _text as tx
from ._shared import renamed, settle

U = np.uint64
SAMPLE, SAMPLE_BYTES, BUCKETS, DIMENSIONS, EPOCHS, RATE, GRAMS = 3000, 64 << 20, 1 << 16, 8, 6, 40.0, (3, 4)


@dataclass
class Model:
    folded: np.ndarray  # log-odds of label 1 for each bucket
    bias: float


def word_features(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of every word and of its n-grams, word after word, and how many each word has. Bucket 0 is kept free."""
    lengths = ends - starts
    n = len(starts)
    # the words with a boundary byte before and after each
    wide = np.full(int(lengths.sum()) + 2 * n, 1, np.uint8)
    first = np.cumsum(lengths + 2) - (lengths + 2)
    wide[tx.ragged(first + 1, lengths)] = data[tx.ragged(starts, lengths)]
    wide[first + 1 + lengths] = 2
    up, down = tx.powers(len(wide) + 1)
    sums = np.zeros(len(wide) + 1, U)
    np.cumsum(tx.TABLES[0][wide] * up[:-1], out=sums[1:])

    def hashed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return (tx.mix((sums[b] - sums[a]) * down[a] + (b - a).astype(U) * U(0x9FB21C651E98DF25)) % U(BUCKETS - 1)).astype(np.int64) + 1

    buckets, owners = [hashed(first, first + lengths + 2)], [np.arange(n)]
    # where the code points of the words with their boundaries begin, and the end of the last
    place = np.append(np.flatnonzero((wide & 0xC0) != 0x80), len(wide))
    begin = np.searchsorted(place, np.append(first, len(wide)))
    points = np.diff(begin)
    for g in GRAMS:
        count = np.maximum(points + 1 - g, 0)
        at = tx.ragged(begin[:-1], count)
        buckets.append(hashed(place[at], place[at + g]))
        owners.append(np.repeat(np.arange(n), count))
    owner = np.concatenate(owners)
    order = np.argsort(owner, kind="stable")
    return np.concatenate(buckets)[order], np.bincount(owner, minlength=n)


def _distinct_words(data: np.ndarray, offsets: np.ndarray):
    """Distinct words of a slice (start, end), the distinct word at each place, places of each row, and which places repeat the word before."""
    starts, ends, rows = tx.words(data, offsets)
    h = tx.span_hashes(data, starts, ends)
    _, index, inverse = np.unique(h, return_index=True, return_inverse=True)
    again = np.zeros(len(h), bool)
    again[1:] = h[1:] == h[:-1]
    again[rows[:-1][rows[:-1] < len(h)]] = False
    return starts[index], ends[index], inverse, rows, again


def scores(model: Model, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    starts, ends, inverse, rows, again = _distinct_words(data, offsets)
    total = np.zeros(len(offsets) - 1)
    if len(inverse):
        buckets, counts = word_features(data, starts, ends)
        firsts = np.cumsum(counts) - counts
        word = np.add.reduceat(model.folded[buckets], firsts) / counts
        sums = np.concatenate([[0.0], np.cumsum(word[inverse])])
        more = np.concatenate([[0], np.cumsum(again)])
        n, k = np.diff(rows), np.diff(more[rows])
        total = (np.diff(sums[rows]) + k * model.folded[0]) / np.maximum(n + k, 1)
    return 1 / (1 + np.exp(-np.clip(total + model.bias, -30, 30)))


def fit(texts: list[str], labels: list[int], seed: int = 7) -> Model:
    """Plain stochastic gradient descent, one document at a time, over a fixed order of the sample for each epoch."""
    y = np.array(labels, np.int64)
    share = y.mean() if len(y) else 0.5
    if len(y) == 0 or share in (0.0, 1.0):
        return Model(np.zeros(BUCKETS), float(np.log(np.clip(share, 1e-3, 1 - 1e-3) / np.clip(1 - share, 1e-3, 1 - 1e-3))))
    rows: list[tuple[np.ndarray, np.ndarray]] = []
    for _, _, data, offsets in tx.each_slice(pa.array(texts, pa.string())):
        starts, ends, inverse, at, again = _distinct_words(data, offsets)
        buckets, counts = word_features(data, starts, ends) if len(starts) else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        firsts = np.cumsum(counts) - counts
        for r in range(len(offsets) - 1):
            ids, times = np.unique(inverse[at[r] : at[r + 1]], return_counts=True)
            extra = int(again[at[r] : at[r + 1]].sum())
            all_words = max(at[r + 1] - at[r] + extra, 1)
            own = buckets[tx.ragged(firsts[ids], counts[ids])]
            weight = np.bincount(np.append(own, 0), np.append(np.repeat(times / counts[ids] / all_words, counts[ids]), extra / all_words), BUCKETS)
            keep = np.flatnonzero(weight)
            rows.append((keep, weight[keep]))
    rng = np.random.default_rng(seed)
    vectors = rng.normal(0, 0.1, (BUCKETS, DIMENSIONS))
    out, bias = rng.normal(0, 0.5, (DIMENSIONS, 2)), np.array([np.log(1 - share), np.log(share)])
    steps, step = EPOCHS * len(y), 0
    for _ in range(EPOCHS):
        for i in rng.permutation(len(y)):
            ids, w = rows[i]
            hidden = w @ vectors[ids]
            z = hidden @ out + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            rate = RATE * (1 - step / steps)
            back = out @ p
            out -= 0.005 * rate * np.outer(hidden, p)
            bias -= 0.0005 * rate * p
            vectors[ids] -= rate * np.outer(w, back)
            step += 1
    return Model(vectors @ (out[:, 1] - out[:, 0]), float(bias[1] - bias[0]))


def train(docs: DataFrame, labels: DataFrame, usable: Column, sample: int = SAMPLE, label: str = "quality") -> Model:
    """Fit on the `sample` rows of smallest id hash among the labelled ones that `usable` admits."""
    known = labels.where(F.col(label).isNotNull() & usable).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    texts = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")  # `sample` rows at most
    # several rows may share an id: one of them is enough
    one = settle(texts.groupBy("doc_id").agg(F.min("text").alias("text"), F.first("y").alias("y")))
    before = F.sum(F.octet_length("text")).over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))  # over `sample` rows
    ids = one.select("doc_id", before.alias("upto")).where(F.col("upto") <= SAMPLE_BYTES).select("doc_id")
    got = sorted((r["doc_id"], r["text"], r["y"]) for r in one.join(F.broadcast(ids), "doc_id").collect())
    return fit([t for _, t, _ in got], [y for _, _, y in got])


def score(docs: DataFrame, model: Model, text_col: str = "text", carry: list[str] | None = None, into: str = "score") -> DataFrame:
    """The carried columns, whatever their names, and the score of every text in the column `into`, the last one."""
    carry = carry or ["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast(model)  # one number a bucket
    rows, names = renamed(docs)
    rows = rows.select(F.col(names[text_col]).cast("string").alias("__body"), *[names[c] for c in carry])
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[1:])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(0)):
                yield pa.RecordBatch.from_arrays([*(batch.column(k)[i:j] for k in range(1, batch.num_columns)), pa.array(scores(shared.value, data, offsets))], [*batch.schema.names[1:], "__score"])

    return rows.mapInArrow(run, f"{kinds}, __score double").toDF(*carry, into)


def accepted(docs: DataFrame, model: Model, least: float, text_col: str = "text") -> DataFrame:
    """The rows of docs whose score is `least` or more, with all their columns."""
    inner, names = renamed(docs)
    kept = score(inner, model, names[text_col], list(names.values()), "__score").where(F.col("__score") >= least)
    return kept.drop("__score").toDF(*docs.columns)


def held_out(id_col: str = "doc_id") -> Column:
    """Whether a row is kept from training: every fifth by the checksum of its id."""
    return F.crc32(F.col(id_col).cast("string")) % 5 == 0
