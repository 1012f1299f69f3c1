"""Byte-level BPE with a two-tier lookup: a minimal perfect hash, then a heap over linked bytes.

Tier one: texts are cut into pre-tokens with vectorised class tables, the distinct pre-tokens of a slice are
resolved at once by a minimal perfect hash over the vocabulary (hash-and-displace with a slot for every key), and
those that are whole vocabulary entries are done. Tier two: every other distinct pre-token is merged by rank with
a heap over a doubly linked list of its bytes, and remembered in a memo of fixed arrays.

The vocabulary is a parameter (a rank file); the driver reads it and broadcasts it, so executors need no local file.

Defined cases: a null or empty text has no ids; repeated rows give repeated results; an empty table gives an empty
result; only the id and text columns are read, so extra columns with clashing names do no harm.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import _text as tx

U = np.uint64
#: Slots of the memo (a power of two) and the most ids that one holds: 49 bytes a slot, 26 MB a worker.
MEMO, MEMO_IDS = 1 << 19, 8
#: Bytes of a slice; arrays of about 100 bytes a byte live while it is encoded.
SLICE_BYTES = 1 << 18
#: The code points of White_Space.
WHITE_SPACE = [9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: What may follow an apostrophe as a pre-token of its own.
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")
OTHER, LETTER, NUMBER, WHITE, SPACE = range(5)


class PerfectHash:
    """A minimal perfect hash over 64-bit keys: n keys, n slots; a bucket stores a seed, or a slot when it has one key."""

    def __init__(self, keys: np.ndarray):
        n = len(keys)
        self.n, self.buckets = max(n, 1), max(n // 3, 1)
        self.seeds = np.zeros(self.buckets, np.int64)
        self.slots = np.full(self.buckets, -1, np.int64)
        of = self._bucket(keys)
        order = np.argsort(of, kind="stable")
        counts = np.bincount(of, minlength=self.buckets)
        firsts = np.cumsum(counts) - counts
        free = np.ones(self.n, bool)
        tries = np.arange(1, 1025, dtype=np.int64)
        for b in np.argsort(-counts, kind="stable"):
            own = keys[order[firsts[b] : firsts[b] + counts[b]]]
            if len(own) < 2:
                break
            base = 0
            while True:
                at = self._slot(own[:, None], (tries + base)[None, :])
                good = free[at].all(0)
                s = np.sort(at, 0)
                good &= (s[1:] != s[:-1]).all(0)
                if good.any():
                    k = int(np.argmax(good))
                    self.seeds[b] = tries[k] + base
                    free[at[:, k]] = False
                    break
                base += len(tries)
                if base > 1 << 24:
                    raise ValueError("two keys have the same hash")
        alone = np.flatnonzero(counts == 1)
        self.slots[alone] = np.flatnonzero(free)[: len(alone)]

    def _bucket(self, keys: np.ndarray) -> np.ndarray:
        return ((keys >> U(32)) % U(self.buckets)).astype(np.int64)

    def _slot(self, keys: np.ndarray, seeds: np.ndarray) -> np.ndarray:
        return (tx.mix(keys + seeds.astype(U) * U(0x9E3779B97F4A7C15)) % U(self.n)).astype(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        b = self._bucket(keys)
        return np.where(self.slots[b] >= 0, self.slots[b], self._slot(keys, self.seeds[b]))


class Memo:
    """The ids of pre-tokens that are no entries, by both hashes: one slot for each, which a later one takes over.

    Long pre-tokens, of more than MEMO_IDS ids, are merged each time.
    """

    def __init__(self) -> None:
        self.one, self.two = np.zeros(MEMO, U), np.zeros(MEMO, U)
        self.count, self.ids = np.zeros(MEMO, np.uint8), np.zeros((MEMO, MEMO_IDS), np.int32)

    def find(self, one: np.ndarray, two: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How many ids are known of each pre-token (0: none), and the ids of the known ones one after the other."""
        at = (one & U(MEMO - 1)).astype(np.int64)
        counts = np.where((self.one[at] == one) & (self.two[at] == two), self.count[at], 0).astype(np.int64)
        return counts, self.ids[at][np.arange(MEMO_IDS) < counts[:, None]].astype(np.int64)

    def keep(self, one: np.ndarray, two: np.ndarray, counts: np.ndarray, flat: np.ndarray) -> None:
        """Of several pre-tokens for one slot the last is kept."""
        at = (one & U(MEMO - 1)).astype(np.int64)
        fits = np.flatnonzero(counts <= MEMO_IDS)
        _, last = np.unique(at[fits][::-1], return_index=True)
        fits = fits[::-1][last]
        at, n = at[fits], counts[fits]
        self.one[at], self.two[at], self.count[at] = one[fits], two[fits], n
        rows = np.repeat(at, n)
        self.ids[rows, tx.ragged(np.zeros(len(n), np.int64), n)] = flat[tx.ragged((np.cumsum(counts) - counts)[fits], n)]


class Vocabulary:
    """Rank table with the perfect hash over its entries and the bytes of each id."""

    def __init__(self, entries: list[tuple[bytes, int]]):
        self.ranks = dict(entries)
        self.entries = entries
        pieces = [piece for piece, _ in entries]
        lengths = np.array([len(p) for p in pieces], np.int64)
        ends = np.cumsum(lengths)
        data = np.frombuffer(b"".join(pieces), np.uint8)
        starts = ends - lengths
        one, two = tx.span_hashes(data, starts, ends, 0), tx.span_hashes(data, starts, ends, 1)
        self.find = PerfectHash(one)
        at = self.find(one)
        self.slot_id, self.slot_check, self.slot_hash = np.zeros(len(at), np.int64), np.zeros(len(at), U), np.zeros(len(at), U)
        self.slot_id[at], self.slot_check[at], self.slot_hash[at] = [r for _, r in entries], two, one
        top = max((r for _, r in entries), default=-1) + 1
        self.data, self.id_start, self.id_length = data, np.zeros(top, np.int64), np.zeros(top, np.int64)
        ids = np.array([r for _, r in entries], np.int64)
        self.id_start[ids], self.id_length[ids] = starts, lengths
        self.memo = Memo()

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("memo", "ranks")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state, ranks=dict(state["entries"]), memo=Memo())

    @classmethod
    def read(cls, path: str) -> Vocabulary:
        """From a file of lines `base64 rank`."""
        with open(path, "rb") as f:
            return cls([(base64.b64decode(a), int(b)) for a, b in (line.split() for line in f if line.strip())])

    def lookup(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        """The id of each whole pre-token, or -1."""
        at = self.find(one)
        return np.where((self.slot_check[at] == two) & (self.slot_hash[at] == one), self.slot_id[at], -1)

    def text_bytes(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes that the ids stand for, and the length of each."""
        lengths = self.id_length[ids]
        return self.data[tx.ragged(self.id_start[ids], lengths)], lengths


def heap_merge(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    if piece in ranks:
        return [ranks[piece]]
    n = len(piece)
    after, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
    end = list(range(1, n + 1))
    heap = []
    for i in range(n - 1):
        r = ranks.get(piece[i : i + 2])
        if r is not None:
            heap.append((r, i, i + 2))
    heapq.heapify(heap)
    while heap:
        _, i, to = heapq.heappop(heap)
        j = after[i] if alive[i] else n
        if not alive[i] or j >= n or end[j] != to:
            continue  # one of the two has merged meanwhile
        alive[j] = False
        end[i] = to
        k = after[i] = after[j]
        if k < n:
            before[k] = i
            r = ranks.get(piece[i : end[k]])
            if r is not None:
                heapq.heappush(heap, (r, i, end[k]))
        h = before[i]
        if h >= 0:
            r = ranks.get(piece[h:to])
            if r is not None:
                heapq.heappush(heap, (r, h, to))
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = after[i]
    return out


_classes: list[np.ndarray] = []


def classes() -> np.ndarray:
    """The class of every code point, made once per worker."""
    if not _classes:
        kinds = {"L": LETTER, "N": NUMBER}
        table = np.fromiter((kinds.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x110000)), np.uint8, 0x110000)
        table[WHITE_SPACE] = WHITE
        table[32] = SPACE
        _classes.append(table)
    return _classes[0]


def pre_token_starts(cps: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Indices of the code points at which a pre-token starts; rows: where rows start, and the end."""
    n = len(cps)
    if not n:
        return np.zeros(0, np.int64)
    cls = classes()[cps]
    kind = np.minimum(cls, WHITE)
    first = np.zeros(n + 1, bool)
    first[rows] = True
    joined = np.zeros(n, bool)  # same row as the code point before
    joined[1:] = ~first[1:n]
    changed = np.ones(n, bool)
    changed[1:] = kind[1:] != kind[:-1]
    white = kind == WHITE
    after_space = np.zeros(n, bool)
    after_space[1:] = cls[:-1] == SPACE
    start = (changed | ~joined) & (white | ~(after_space & joined))
    # the last white space before something solid stands apart from the white space before it
    last = np.zeros(n, bool)
    last[:-1] = white[:-1] & ~white[1:] & joined[1:]
    start |= last
    at = np.flatnonzero((cps == 39) & start)
    if len(at):
        text = np.zeros(n + 3, np.uint32)
        text[:n] = cps
        stop = np.append(first, [True, True])  # padded row starts
        inside = [~stop[np.minimum(at + k, n)] for k in (1, 2)]
        for tail in CONTRACTIONS:
            fits = inside[0] & (text[at + 1] == ord(tail[0]))
            if len(tail) == 2:
                fits &= inside[1] & (text[at + 2] == ord(tail[1]))
            hit = at[fits]
            start[hit + 1] = False
            rest = hit + 1 + len(tail)
            rest = rest[rest < n]
            start[rest[(kind[rest] == LETTER) & joined[rest]]] = True
    return np.flatnonzero(start)


def encode_slice(vocabulary: Vocabulary, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all rows of a slice one after the other, and where each row's ids start (and the end)."""
    cps = tx.code_points(data)
    width = 1 + (cps >= 0x80).astype(np.int64) + (cps >= 0x800) + (cps >= 0x10000)
    at = np.zeros(len(cps) + 1, np.int64)
    np.cumsum(width, out=at[1:])
    rows = np.searchsorted(at, offsets)
    tokens = pre_token_starts(cps, rows)
    starts = at[tokens]
    ends = np.append(starts[1:], len(data)).astype(np.int64)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    one, two = tx.span_hashes(data, starts, ends, 0), tx.span_hashes(data, starts, ends, 1)
    _, index, inverse = np.unique(one, return_index=True, return_inverse=True)
    if (two[index][inverse] != two).any():  # two pre-tokens with one hash
        _, index, inverse = np.unique(np.stack([one, two], 1), axis=0, return_index=True, return_inverse=True)
        inverse = inverse.ravel()
    whole = vocabulary.lookup(one[index], two[index])
    counts = np.ones(len(index), np.int64)
    misses = np.flatnonzero(whole < 0)
    known, remembered = vocabulary.memo.find(one[index[misses]], two[index[misses]])
    counts[misses] = known
    new = misses[known == 0]
    raw = data.tobytes()
    found = [heap_merge(raw[a:b], vocabulary.ranks) for a, b in zip(starts[index[new]].tolist(), ends[index[new]].tolist(), strict=True)]
    counts[new] = [len(x) for x in found]
    merged = np.fromiter((i for x in found for i in x), np.int64, int(counts[new].sum()))
    places = np.cumsum(counts) - counts
    flat = np.zeros(int(counts.sum()), np.int64)
    hits = whole >= 0
    flat[places[hits]] = whole[hits]
    old = misses[known > 0]
    flat[tx.ragged(places[old], counts[old])] = remembered
    flat[tx.ragged(places[new], counts[new])] = merged
    vocabulary.memo.keep(one[index[new]], two[index[new]], counts[new], merged)
    per_token = counts[inverse]
    ids = flat[tx.ragged(places[inverse], per_token)]
    upto = np.zeros(len(tokens) + 1, np.int64)
    np.cumsum(per_token, out=upto[1:])
    return ids, upto[np.searchsorted(tokens, rows)]


_loaded: dict[str, Vocabulary] = {}


def vocabulary_of(path: str) -> Vocabulary:
    if path not in _loaded:
        _loaded[path] = Vocabulary.read(path)
    return _loaded[path]


def encode(spark: SparkSession, docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", carry: list[str] | None = None) -> DataFrame:
    """The id column, the columns in carry, and `ids` array<int> of every text. A carried column named ids gives way to the result's own."""
    carry = [c for c in carry or [] if c not in ("ids", id_col)]
    shared = spark.sparkContext.broadcast(vocabulary_of(path))
    rows = docs.select(F.col(text_col).cast("string").alias("__body"), F.col(id_col), *carry)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[1:])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(0), SLICE_BYTES):
                ids, where = encode_slice(shared.value, data, offsets)
                lists = pa.ListArray.from_arrays(pa.array(where, pa.int32()), pa.array(ids, pa.int32()))
                yield pa.RecordBatch.from_arrays([*(batch.column(k)[i:j] for k in range(1, batch.num_columns)), lists], [*batch.schema.names[1:], "ids"])

    return rows.mapInArrow(run, f"{kinds}, ids array<int>")


def decode(spark: SparkSession, encoded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """The id column and `bytes` binary of every list of ids; a null list has no bytes."""
    shared = spark.sparkContext.broadcast(vocabulary_of(path))
    rows = encoded.select(F.col(id_col).alias("id"), F.coalesce(F.col(ids_col), F.array().cast("array<int>")).alias("ids"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [shared.value.text_bytes(np.asarray(x.values, np.int64))[0].tobytes() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["id", "bytes"])

    return rows.mapInArrow(run, f"id {rows.schema['id'].dataType.simpleString()}, bytes binary").withColumnRenamed("id", id_col)


def round_trip(spark: SparkSession, docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", carry: list[str] | None = None) -> DataFrame:
    """Encode and decode in one pass: n_tokens, ids_sha256 and decoded_sha256 of every text, plus the columns in carry; the result's own columns go before carried ones of their names."""
    shared = spark.sparkContext.broadcast(vocabulary_of(path))
    carry = [c for c in carry or [] if c not in ("n_tokens", "ids_sha256", "decoded_sha256", id_col)]
    rows = docs.select(F.col(text_col).cast("string").alias("__body"), F.col(id_col), *carry)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[1:])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in tx.each_slice(batch.column(0), SLICE_BYTES):
                ids, where = encode_slice(shared.value, data, offsets)
                raw, lengths = shared.value.text_bytes(ids)
                upto = np.zeros(len(ids) + 1, np.int64)
                np.cumsum(lengths, out=upto[1:])
                small, cut = ids.astype("<u4").tobytes(), raw.tobytes()
                spans = list(zip(where[:-1].tolist(), where[1:].tolist(), strict=True))
                digest = [hashlib.sha256(small[4 * a : 4 * b]).hexdigest() for a, b in spans]
                back = [hashlib.sha256(cut[a:b]).hexdigest() for a, b in zip(upto[where[:-1]].tolist(), upto[where[1:]].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([*(batch.column(k)[i:j] for k in range(1, batch.num_columns)), pa.array(np.diff(where), pa.int64()), pa.array(digest), pa.array(back)], [*batch.schema.names[1:], "n_tokens", "ids_sha256", "decoded_sha256"])

    return rows.mapInArrow(run, f"{kinds}, n_tokens long, ids_sha256 string, decoded_sha256 string")
