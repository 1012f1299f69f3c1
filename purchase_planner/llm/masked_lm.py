"""Masked pseudo-likelihood: a bidirectional window network predicts every token from both sides.

Words are the tokens. The VOCABULARY most frequent words of the corpus keep entries of their own, all others share
HASHED entries by hash. Output is factored: the network predicts one of CLASSES classes of a token (frequency bins of
about equal mass), and a token within its class follows corpus counts, so probabilities sum to one over the words seen.
`score` takes the counts of all words as a table, which grows with the corpus and is joined to the words outside the
vocabulary; without that table these get the mean count of their shared entry.

Network: embeddings of SIDE words on either side (with a padding entry at the ends), one tanh layer, softmax. Training is
numpy stochastic gradient descent, data-parallel over the whole corpus: each task makes one pass over its rows from a
common start, and the tasks' weights are averaged, embeddings by how often an entry was used; that is repeated ROUNDS
times. Word counts and the averages are combinable sums in numeric columns; the driver only ever sees the fixed-size
vocabulary and weights.

Defined cases: a null or empty text has no tokens, log-likelihood 0 and a null mean; repeated rows repeat; an empty
corpus gives an empty result (and, to an explicit `train`, an untrained network); a word that the table of counts does not
hold counts as half a time; only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import _text as tx
from ._shared import settle

U = np.uint64
VOCABULARY, HASHED, CLASSES, SIDE, EMBEDDED, HIDDEN = 3839, 256, 32, 2, 8, 16
ROUNDS, RATE, BATCH = 1, 0.25, 2048
ENTRIES = 1 + HASHED + VOCABULARY  # entry 0 pads


@dataclass
class Lexicon:
    hashes: np.ndarray  # of the frequent words, ascending
    entries: np.ndarray  # of those
    classes: np.ndarray  # of every entry
    within: np.ndarray  # log P(word | class) of every entry; shared entries spread over the words seen
    average: np.ndarray  # log of the mean count of the words of a shared entry; 0 for the others

    def encode(self, h: np.ndarray) -> np.ndarray:
        shared = (h % U(HASHED)).astype(np.int64) + 1
        if not len(self.hashes):
            return shared
        at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return np.where(self.hashes[at] == h, self.entries[at], shared)


@dataclass
class Network:
    embedding: np.ndarray
    inner: np.ndarray
    bias: np.ndarray
    outer: np.ndarray
    prior: np.ndarray

    def arrays(self) -> list[np.ndarray]:
        return [self.embedding, self.inner, self.bias, self.outer, self.prior]

    def copy(self) -> Network:
        return Network(*(x.copy() for x in self.arrays()))


def _hashes(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    for i, j, data, offsets in tx.each_slice(column):
        starts, ends, rows = tx.words(data, offsets)
        yield i, j, tx.span_hashes(data, starts, ends), rows


def word_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """(h, c): how often each word occurs in the whole corpus; counted per batch before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, h, _ in _hashes(batch.column(0)):
                words, counts = np.unique(h, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(counts)], ["h", "c"])

    return docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def lexicon(counts: DataFrame) -> Lexicon:
    """From a table (h, c) of word counts; only the VOCABULARY largest and sums per shared entry reach the driver."""
    top = [(r["h"], r["c"]) for r in counts.orderBy(F.desc("c"), "h").limit(VOCABULARY).collect()]
    hashes = np.array([h for h, _ in top], np.int64).view(U)
    own = np.array([c for _, c in top], np.float64)
    # h modulo HASHED as unsigned: the low bits, as HASHED is a power of two
    per = counts.groupBy(F.col("h").bitwiseAND(F.lit(HASHED - 1)).alias("k")).agg(F.sum("c").alias("c"), F.count("*").alias("n")).collect()
    shared, seen = np.zeros(HASHED), np.zeros(HASHED)
    for r in per:
        shared[r["k"]], seen[r["k"]] = r["c"], r["n"]
    low = (hashes % U(HASHED)).astype(np.int64)
    shared -= np.bincount(low, own, HASHED)
    seen -= np.bincount(low, minlength=HASHED)
    mass = np.zeros(ENTRIES)
    mass[1 : 1 + HASHED] = shared
    mass[1 + HASHED : 1 + HASHED + len(own)] = own
    order = np.argsort(-mass[1:], kind="stable") + 1
    total = max(mass.sum(), 1.0)
    classes = np.zeros(ENTRIES, np.int64)
    before = np.cumsum(mass[order]) - mass[order]
    classes[order] = np.minimum((before / total * CLASSES).astype(np.int64), CLASSES - 1)
    spread = np.ones(ENTRIES)
    spread[1 : 1 + HASHED] = np.maximum(seen, 1)
    per_class = np.bincount(classes[1:], mass[1:], CLASSES)
    with np.errstate(divide="ignore"):
        within = np.log(np.maximum(mass, 0.5) / np.maximum(per_class[classes], 1.0)) - np.log(spread)
    average = np.zeros(ENTRIES)
    average[1 : 1 + HASHED] = np.log(np.maximum(mass, 0.5) / spread)[1 : 1 + HASHED]
    order = np.argsort(hashes)
    return Lexicon(hashes[order], (np.arange(len(hashes)) + 1 + HASHED)[order], classes, within, average)


def start(seed: int = 11) -> Network:
    rng = np.random.default_rng(seed)
    f = lambda s, *shape: rng.normal(0, s, shape).astype(np.float32)
    return Network(f(0.3, ENTRIES, EMBEDDED), f((2 * SIDE * EMBEDDED) ** -0.5, 2 * SIDE * EMBEDDED, HIDDEN), np.zeros(HIDDEN, np.float32), f(HIDDEN**-0.5, HIDDEN, CLASSES), np.zeros(CLASSES, np.float32))


def contexts(tokens: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """For each token the entries of its neighbours, left to right; 0 beyond its row."""
    n = len(tokens)
    row = np.repeat(np.arange(len(rows) - 1), np.diff(rows))
    out = np.zeros((n, 2 * SIDE), np.int32)
    for k, d in enumerate([*range(-SIDE, 0), *range(1, SIDE + 1)]):
        a, b = (slice(-d, n), slice(0, n + d)) if d < 0 else (slice(0, n - d), slice(d, n))
        if n > abs(d):
            out[a, k] = np.where(row[a] == row[b], tokens[b], 0)
    return out


def forward(net: Network, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Inputs, hidden layer and class log-probabilities."""
    x = net.embedding[near].reshape(len(near), -1)
    hidden = np.tanh(x @ net.inner + net.bias)
    z = hidden @ net.outer + net.prior
    z -= z.max(1, keepdims=True)
    z -= np.log(np.exp(z).sum(1, keepdims=True))
    return x, hidden, z


def train_on(net: Network, used: np.ndarray, near: np.ndarray, goal: np.ndarray, rate: float = RATE) -> None:
    """One pass of minibatch gradient descent, in place; used counts the uses of each entry."""
    for i in range(0, len(goal), BATCH):
        c, y = near[i : i + BATCH], goal[i : i + BATCH]
        x, hidden, z = forward(net, c)
        g = np.exp(z)
        g[np.arange(len(y)), y] -= 1
        g /= len(y)
        back = (g @ net.outer.T) * (1 - hidden * hidden)
        inward = (back @ net.inner.T).reshape(-1, EMBEDDED)
        net.outer -= rate * (hidden.T @ g)
        net.prior -= rate * g.sum(0)
        net.inner -= rate * (x.T @ back)
        net.bias -= rate * back.sum(0)
        flat = c.ravel()
        times = np.bincount(flat, minlength=ENTRIES)
        hit = np.flatnonzero(times)
        step = np.stack([np.bincount(flat, inward[:, k], ENTRIES)[hit] for k in range(EMBEDDED)], 1)
        net.embedding[hit] -= (rate * len(y) / times[hit][:, None] * step * np.minimum(1, times[hit] / 8)[:, None]).astype(np.float32)
        used += times


def _row_names() -> int:
    """Rows of width EMBEDDED that hold all dense weights."""
    dense = 2 * SIDE * EMBEDDED * HIDDEN + HIDDEN + HIDDEN * CLASSES + CLASSES
    return -(-dense // EMBEDDED)


def train(docs: DataFrame, lex: Lexicon, text_col: str = "text", rounds: int = ROUNDS) -> Network:
    """Data-parallel descent over all rows; tasks' weights are averaged by combinable sums."""
    sc = docs.sparkSession.sparkContext
    net = start()
    rows = docs.select(F.col(text_col).cast("string").alias("text"))
    columns = [f"d{k}" for k in range(EMBEDDED)]
    for _ in range(rounds):
        shared = sc.broadcast((lex, net))  # of fixed size

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words, base = shared.value
            own, used, tokens_seen = base.copy(), np.zeros(ENTRIES), 0
            for batch in batches:
                for _, _, h, at in _hashes(batch.column(0)):
                    tokens = words.encode(h)
                    train_on(own, used, contexts(tokens, at), words.classes[tokens])
                    tokens_seen += len(tokens)
            if not tokens_seen:
                return
            dense = np.concatenate([x.ravel() for x in own.arrays()[1:]])
            dense = np.append(dense, np.zeros(_row_names() * EMBEDDED - len(dense), np.float32)).reshape(-1, EMBEDDED)
            hit = np.flatnonzero(used)
            values = np.concatenate([own.embedding[hit] * used[hit][:, None], dense * tokens_seen]).astype(np.float64)
            names = np.concatenate([hit, ENTRIES + np.arange(len(dense))])
            weight = np.concatenate([used[hit], np.full(len(dense), float(tokens_seen))])
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(weight), *(pa.array(np.ascontiguousarray(values[:, k])) for k in range(EMBEDDED))], ["row", "w", *columns])

        parts = rows.mapInArrow(run, "row long, w double, " + ", ".join(f"{c} double" for c in columns))
        # sums of doubles in the order of arrival would differ between reruns; decimals do not
        fixed = lambda c: F.sum(F.col(c).cast("decimal(28,8)")).alias(c)
        got = parts.groupBy("row").agg(fixed("w"), *map(fixed, columns)).collect()  # ENTRIES and the dense rows at most
        dense = np.concatenate([x.ravel() for x in net.arrays()[1:]])
        dense = np.append(dense, np.zeros(_row_names() * EMBEDDED - len(dense), np.float32)).reshape(-1, EMBEDDED)
        embedding = net.embedding.copy()
        for r in got:
            value = np.array([float(r[c]) for c in columns]) / float(r["w"])
            if r["row"] < ENTRIES:
                embedding[r["row"]] = value
            else:
                dense[r["row"] - ENTRIES] = value
        flat, arrays = dense.ravel(), [embedding]
        for x in net.arrays()[1:]:
            arrays.append(flat[: x.size].reshape(x.shape).astype(np.float32))
            flat = flat[x.size :]
        net = Network(*arrays)
    return net


def score(docs: DataFrame, lex: Lexicon, net: Network, id_col: str = "doc_id", text_col: str = "text", counts: DataFrame | None = None) -> DataFrame:
    """id, n_tokens, pseudo_log_likelihood (natural logarithm, summed over all tokens) and its mean per token.

    counts: the table (h, c) of all words that lex was made from.
    """
    if counts is not None:
        return _counted(docs, lex, net, id_col, text_col, counts)
    shared = docs.sparkSession.sparkContext.broadcast((lex, net))  # of fixed size
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, own = shared.value
        for batch in batches:
            for i, j, h, at in _hashes(batch.column(1)):
                each = token_scores(words, own, words.encode(h), at)
                sums = np.concatenate([[0.0], np.cumsum(each)])
                n = np.diff(at)
                total = np.round(np.diff(sums[at]), 6)
                mean = pa.array(total / np.maximum(n, 1), mask=n == 0)
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], pa.array(n, pa.int64()), pa.array(total), mean], ["id", "n_tokens", "pseudo_log_likelihood", "mean"])

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, n_tokens long, pseudo_log_likelihood double, mean double").withColumnRenamed("id", id_col)


def _counted(docs: DataFrame, lex: Lexicon, net: Network, id_col: str, text_col: str, counts: DataFrame) -> DataFrame:
    """score with every word's own count: the words that share entries are joined to the table of counts."""
    shared = docs.sparkSession.sparkContext.broadcast((lex, net))  # of fixed size
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, own = shared.value
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            for i, j, h, at in _hashes(batch.column(1)):
                tokens = words.encode(h)
                sums = np.concatenate([[0.0], np.cumsum(token_scores(words, own, tokens, at) - words.average[tokens])])
                rare = tokens <= HASHED
                ends = np.concatenate([[0], np.cumsum(rare)])[at]
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(h[rare].view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(row, row + j - i)), batch.column(0)[i:j], pa.array(np.diff(at), pa.int64()), pa.array(np.diff(sums[at])), lists], ["row", "id", "n", "known", "rare"])
                row += j - i

    # written, as the numbers of the rows must not change between the two reads
    held = settle(rows.mapInArrow(run, f"row long, id {rows.schema['id'].dataType.simpleString()}, n long, known double, rare array<long>"))
    # logarithms as integers, so that sums do not depend on the order of arrival
    unit = 1e9
    each = held.select("row", F.explode("rare").alias("h")).join(counts.select("h", F.round(F.log("c") * unit).cast("long").alias("w")), "h", "left")
    sums = each.groupBy("row").agg(F.sum(F.coalesce("w", F.lit(round(np.log(0.5) * unit)))).alias("w"))
    total = F.round(F.col("known") + F.coalesce("w", F.lit(0)) / unit, 6)
    out = held.drop("rare").join(sums, "row", "left").withColumn("total", total)
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_tokens"), F.col("total").alias("pseudo_log_likelihood"), F.when(F.col("n") > 0, F.col("total") / F.col("n")).alias("mean"))


def token_scores(lex: Lexicon, net: Network, tokens: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """log P(token | both sides) of every token."""
    near, out = contexts(tokens, rows), np.zeros(len(tokens))
    goal = lex.classes[tokens]
    for i in range(0, len(tokens), BATCH):
        z = forward(net, near[i : i + BATCH])[2]
        y = goal[i : i + BATCH]
        out[i : i + BATCH] = z[np.arange(len(y)), y]
    return out + lex.within[tokens]
