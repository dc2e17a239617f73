"""Byte-level BPE encoding and decoding by rounds over padded matrices.

Texts are cut by the tokenizer's pattern; each different piece of a batch is encoded once. Pieces go by length into
buckets, and each bucket is one padded matrix of token ids. In every round each row looks up the ranks of its
neighbouring pairs in a sorted table of hashed pairs, merges its leftmost pair of smallest rank and closes the gap;
rows without a mergeable pair leave the matrix. Pieces over ``WIDEST`` bytes are merged in the same order by a heap,
in n log n steps, since a matrix would need n rounds over n columns.

Results for odd input: null text is empty text, without tokens; characters that the pattern leaves out would not be
encoded (the given pattern leaves none out); repeated rows are encoded each; an empty table gives no rows; very long
texts are encoded whole; further columns are left alone.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

#: Upper lengths of the buckets, in bytes.
BUCKETS = (2, 4, 6, 8, 12, 16, 24, 32, 64, 128)
WIDEST = BUCKETS[-1]
#: Pieces remembered by one Python worker; the memory is emptied when it is full.
MEMORY = 300_000


class Vocabulary:
    """Ranks of byte strings, and the pairs of tokens that merge into a token."""

    def __init__(self, path: str, pattern: str) -> None:
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.pattern = regex.compile(pattern)
        self.bytes = {r: t for t, r in self.ranks.items()}
        self.of_byte = np.array([self.ranks[bytes([b])] for b in range(256)], np.int64)
        self.shift = max(self.bytes).bit_length()
        pairs = {}
        for token, rank in self.ranks.items():
            for i in range(1, len(token)):
                a, b = self.ranks.get(token[:i]), self.ranks.get(token[i:])
                if a is not None and b is not None:
                    pairs[a << self.shift | b] = rank
        self.pairs = pairs
        self._table(pairs)

    def _table(self, pairs: dict[int, int]) -> None:
        """Open addressing with linear probing, filled at a fifth at most; self.probes is the longest run."""
        self.bits = (5 * len(pairs)).bit_length()
        self.none = max(self.bytes) + 1
        keys, ranks = np.fromiter(pairs, np.int64, len(pairs)), np.fromiter(pairs.values(), np.int64, len(pairs))
        self.keys, self.found = np.full(1 << self.bits, -1, np.int64), np.full(1 << self.bits, self.none, np.int64)
        left, at, self.probes = np.arange(len(keys)), self._slot(keys), 0
        while len(left):
            self.probes += 1
            free = self.keys[at[left]] < 0
            self.keys[at[left[free]]] = keys[left[free]]  # of several that want one slot, the last is in
            won = self.keys[at[left]] == keys[left]
            self.found[at[left[won]]] = ranks[left[won]]
            left = left[~won]
            at[left] = at[left] + 1 & (1 << self.bits) - 1

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def pair_ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The rank each pair merges into, or ``none``; negative ids are padding."""
        keys = a << self.shift | b
        keys[b < 0] = -2
        at = self._slot(keys)
        out = np.where(self.keys[at] == keys, self.found[at], self.none)
        open_ = np.flatnonzero((self.keys[at] != keys) & (self.keys[at] >= 0) & (keys >= 0))
        flat, at, keys = out.reshape(-1), at.reshape(-1), keys.reshape(-1)
        open_ = np.flatnonzero(((self.keys[at] != keys) & (self.keys[at] >= 0) & (keys >= 0)))
        for _ in range(self.probes):
            if not len(open_):
                break
            at[open_] = at[open_] + 1 & (1 << self.bits) - 1
            hit = self.keys[at[open_]] == keys[open_]
            flat[open_[hit]] = self.found[at[open_[hit]]]
            open_ = open_[~hit & (self.keys[at[open_]] >= 0)]
        return out

    def merge_rows(self, pieces: list[bytes]) -> list[np.ndarray]:
        """Token ids of pieces that fit one matrix."""
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        width = int(sizes.max())
        ids = np.full((len(pieces), width), -1, np.int64)
        ids[np.arange(width) < sizes[:, None]] = self.of_byte[np.frombuffer(b"".join(pieces), np.uint8)]
        out: list = [None] * len(pieces)
        rows = np.arange(len(pieces))
        ranks = self.pair_ranks(ids[:, :-1], ids[:, 1:]) if width > 1 else None
        while len(rows):
            best = ranks.argmin(axis=1) if width > 1 and ranks.shape[1] else np.zeros(len(rows), np.int64)
            rank = ranks[np.arange(len(rows)), best] if width > 1 and ranks.shape[1] else np.full(len(rows), self.none)
            done = rank == self.none
            for r in np.flatnonzero(done):
                x = ids[r]
                out[rows[r]] = x[: int((x >= 0).sum())]
            go = ~done
            if not go.any():
                break
            ids, ranks, rows, best, rank = ids[go], ranks[go], rows[go], best[go], rank[go]
            n, k = len(rows), np.arange(ids.shape[1])
            ids[np.arange(n), best] = rank
            ids = ids[k != best[:, None] + 1].reshape(n, -1)  # compaction: the merged pair's second token goes
            ranks = ranks[k[:-1] != best[:, None]].reshape(n, -1)
            if ids.shape[1] > 1:  # only the pairs on both sides of the merged token are new
                r = np.arange(n)
                for p, ok in ((best - 1, best > 0), (best, best < ids.shape[1] - 1)):
                    ranks[r[ok], p[ok]] = self.pair_ranks(ids[r[ok], p[ok]], ids[r[ok], p[ok] + 1])
        return out

    def merge_long(self, piece: bytes) -> np.ndarray:
        """The same order of merges with a heap over linked tokens."""
        ids = [int(x) for x in self.of_byte[np.frombuffer(piece, np.uint8)]]
        n = len(ids)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.pairs.get(ids[i] << self.shift | ids[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            rank, i, a, b = heapq.heappop(heap)
            j = right[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = rank, -1
            right[i] = k = right[j]
            if k < n:
                left[k] = i
                if (r := self.pairs.get(rank << self.shift | ids[k])) is not None:
                    heapq.heappush(heap, (r, i, rank, ids[k]))
            if (h := left[i]) >= 0 and (r := self.pairs.get(ids[h] << self.shift | rank)) is not None:
                heapq.heappush(heap, (r, h, ids[h], rank))
        return np.array([x for x in ids if x >= 0], np.int64)

    def encode_pieces(self, pieces: list[bytes]) -> list[np.ndarray]:
        out: list = [None] * len(pieces)
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        bucket = np.searchsorted(BUCKETS, sizes)
        for b in np.unique(bucket):
            at = np.flatnonzero(bucket == b)
            if b == len(BUCKETS):
                for i in at:
                    out[i] = self.merge_long(pieces[i])
                continue
            for lo in range(0, len(at), 20_000):
                some = at[lo : lo + 20_000]
                for i, ids in zip(some, self.merge_rows([pieces[i] for i in some]), strict=True):
                    out[i] = ids
        return out


class Encoder:
    """Encodes texts, remembering pieces: one flat array of ids, and where each piece's ids begin and end."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        self.v = vocabulary
        self.clear()

    def clear(self) -> None:
        self.place: dict[str, int] = {}
        self.starts, self.ids = np.zeros(1, np.int64), np.empty(0, np.uint32)

    def encode(self, texts: list[str]) -> Iterator[np.ndarray]:
        """Ids of each text as unsigned 32-bit integers."""
        if len(self.place) > MEMORY:
            self.clear()
        cut = [self.v.pattern.findall(t) for t in texts]
        fresh = [p for p in {p for x in cut for p in x} if p not in self.place]
        if fresh:
            ids = self.v.encode_pieces([p.encode("utf-8", "surrogatepass") for p in fresh])
            n = len(self.place)
            self.place.update(zip(fresh, range(n, n + len(fresh)), strict=True))
            self.starts = np.concatenate([self.starts, self.starts[-1] + np.cumsum([len(x) for x in ids])])
            self.ids = np.concatenate([self.ids, np.concatenate(ids).astype(np.uint32)])
        find = self.place.__getitem__
        for pieces in cut:
            at = np.fromiter(map(find, pieces), np.int64, len(pieces))
            lo, size = self.starts[at], self.starts[at + 1] - self.starts[at]
            before = np.cumsum(size) - size
            yield self.ids[np.repeat(lo - before, size) + np.arange(int(size.sum()))]


@lru_cache(2)
def vocabulary(path: str, pattern: str) -> Vocabulary:
    """Read once in each Python worker."""
    return Vocabulary(path, pattern)


@lru_cache(2)
def _decoder(path: str, pattern: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    v = vocabulary(path, pattern)
    tokens = [v.bytes.get(i, b"") for i in range(max(v.bytes) + 1)]
    sizes = np.fromiter(map(len, tokens), np.int64, len(tokens))
    return np.frombuffer(b"".join(tokens), np.uint8), np.cumsum(sizes) - sizes, sizes


def decode(ids: np.ndarray, path: str, pattern: str) -> bytes:
    """The bytes that the ids stand for."""
    data, starts, sizes = _decoder(path, pattern)
    size = sizes[ids]
    before = np.cumsum(size) - size
    return data[np.repeat(starts[ids] - before, size) + np.arange(int(size.sum()))].tobytes()


@lru_cache(2)
def _encoder(path: str, pattern: str) -> Encoder:
    return Encoder(vocabulary(path, pattern))


def _parts(texts: list[str], most: int = 2_000_000) -> Iterator[list[str]]:
    """Runs of texts of about ``most`` characters, so that one batch's pieces stay small."""
    run, size = [], 0
    for t in texts:
        run.append(t)
        size += len(t)
        if size >= most:
            yield run
            run, size = [], 0
    if run:
        yield run


def encode(docs: DataFrame, path: str, pattern: str, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, if wanted, the ids of every row of ``docs`` (doc_id, text)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(path, pattern)
        for batch in batches:
            at = 0
            for texts in _parts([x or "" for x in batch.column("text").to_pylist()]):
                counts, shas, backs, kept = [], [], [], []
                for ids in encoder.encode(texts):
                    counts.append(len(ids))
                    shas.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                    backs.append(hashlib.sha256(decode(ids, path, pattern)).hexdigest())
                    if with_ids:
                        kept.append(ids.astype(np.int32))
                columns = [batch.column("doc_id").slice(at, len(texts)), pa.array(counts, pa.int64()), pa.array(shas, pa.string()), pa.array(backs, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    columns, names = [*columns, pa.array(kept, pa.list_(pa.int32()))], [*names, "ids"]
                at += len(texts)
                yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return docs.select("doc_id", "text").mapInArrow(work, schema)
