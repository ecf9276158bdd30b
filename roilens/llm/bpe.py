"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

The bytes of many pre-tokens form one linked list whose parts never merge across pre-tokens.  Every
adjacent pair that the vocabulary can merge puts its left position into the bucket of its merge rank,
and a bitmap of three levels of 64-bit words marks the buckets in use, so "lowest rank waiting" is a
find-first-set from the top level down.  A position is stale, and skipped, if its pair no longer has
that rank.  A bucket is taken whole and sorted, so equal ranks merge leftmost first, as the reference
tokenizers do; if a merge opens a lower rank, the rest of the bucket goes back and that rank is next.
A merge pushes at most two positions, so n bytes cost O(n) queue steps and O(n log n) for the sorting,
however long a pre-token is (a rescan for the best pair would cost O(n^2)).

All distinct pre-tokens of a block of texts that are not remembered go through one queue together.  The
memory of short pre-tokens holds two generations of at most ``MEMO_ENTRIES`` entries besides one block's;
ids in it are packed, four bytes each.  Workers keep it from task to task; it changes no result.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .textscan import slices, tidy

MEMO_BYTES = 32
MEMO_ENTRIES = 150_000
BLOCK_BYTES = 512 << 10  # text that is encoded together; a longer text is a block of its own
LONG_LIST = 1 << 22  # positions from which on links are packed


class RankQueue:
    """Buckets of positions by rank under a bitmap of three levels of 64-bit words."""

    def __init__(self, n_ranks: int):
        if n_ranks > 1 << 18:
            raise ValueError("three levels of 64-bit words hold 2**18 ranks")
        self.buckets: list[list[int] | None] = [None] * n_ranks
        self.low = [0] * ((n_ranks >> 6) + 1)
        self.mid = [0] * ((n_ranks >> 12) + 1)
        self.top = 0

    def open(self, rank: int, positions: list[int]) -> None:
        """Begin the bucket of a rank that has none."""
        self.buckets[rank] = positions
        word = rank >> 6
        if not self.low[word]:
            if not self.mid[rank >> 12]:
                self.top |= 1 << (rank >> 12)
            self.mid[rank >> 12] |= 1 << (word & 63)
        self.low[word] |= 1 << (rank & 63)

    def take(self) -> tuple[int, list[int]] | None:
        """The lowest rank and its positions from left to right, or None when empty."""
        top = self.top
        if not top:
            return None
        i = (top & -top).bit_length() - 1
        mid = self.mid[i]
        j = i << 6 | (mid & -mid).bit_length() - 1
        low = self.low[j]
        rank = j << 6 | (low & -low).bit_length() - 1
        bucket = self.buckets[rank]
        self.buckets[rank] = None
        self.low[j] = low = low & (low - 1)
        if not low:
            self.mid[i] = mid = mid & (mid - 1)
            if not mid:
                self.top = top & (top - 1)
        bucket.sort()
        return rank, bucket


class ByteBPE:
    """Encoder and decoder for one rank file (token bytes in base 64, then the rank, a line each)."""

    def __init__(self, rank_file: str, pattern: str):
        with open(rank_file, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.tokens = [b""] * (max(self.ranks.values()) + 1)
        for token, rank in self.ranks.items():
            self.tokens[rank] = token
        self.pattern = regex.compile(pattern)
        self.decimal = [str(i) for i in range(len(self.tokens))]
        self.single = np.array([self.ranks[bytes((a,))] for a in range(256)], np.int32)
        self.pair = np.array([self.ranks.get(bytes((a, b)), -1) for a in range(256) for b in range(256)], np.int32)
        self.queue = RankQueue(len(self.tokens))  # empty again after every run
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def merged(self, pieces: Sequence[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids one after another, how many of each pre-token): ``pieces`` merged in one run of the queue."""
        data = b"".join(pieces)
        n = len(data)
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        if not n:
            return np.empty(0, np.int32), np.zeros(len(pieces), np.int64)
        ends = np.cumsum(sizes)
        begins = np.zeros(n + 1, np.uint8)  # where a pre-token begins, the end of the last one included
        begins[ends] = begins[0] = 1
        begins = begins.tobytes()
        flat = np.frombuffer(data, np.uint8)
        first = np.full(n, -1, np.int32)  # the rank at which a part may merge with its right neighbour
        first[:-1] = self.pair[flat[:-1].astype(np.int32) << 8 | flat[1:]]
        first[ends[sizes > 0] - 1] = -1
        queue = self.queue
        order = np.argsort(first, kind="stable")
        order = order[np.searchsorted(first[order], 0) :]
        cuts = np.flatnonzero(np.diff(first[order])) + 1
        for some in np.split(order, cuts) if len(order) else ():
            queue.open(int(first[some[0]]), some.tolist())
        pack = (lambda x: x.tolist()) if n < LONG_LIST else (lambda x: array("i", x.astype(np.int32).tobytes()))
        waiting, ids = pack(first), pack(self.single[flat])
        end, before = pack(np.arange(1, n + 1)), pack(np.arange(-1, n - 1))
        gone = bytearray(n)
        get, buckets = self.ranks.get, queue.buckets
        while (taken := queue.take()) is not None:
            rank, bucket = taken
            lower = False
            for at, i in enumerate(bucket):
                if waiting[i] != rank:
                    continue
                j = end[i]
                end[i] = k = end[j]
                waiting[j] = -1
                gone[j] = 1
                ids[i] = rank
                r = -1
                if not begins[k]:
                    before[k] = i
                    r = get(data[i : end[k]], -1)
                    if r >= 0:
                        if buckets[r] is None:
                            queue.open(r, [i])
                        else:
                            buckets[r].append(i)
                        lower = r < rank
                waiting[i] = r
                if not begins[i]:
                    h = before[i]
                    r = get(data[h:k], -1)
                    if r != waiting[h]:
                        waiting[h] = r
                        if r >= 0:
                            if buckets[r] is None:
                                queue.open(r, [h])
                            else:
                                buckets[r].append(h)
                            lower = lower or r < rank
                if lower:
                    if at + 1 < len(bucket):
                        queue.open(rank, bucket[at + 1 :])
                    break
        alive = np.flatnonzero(np.frombuffer(gone, np.uint8) == 0)
        upto = np.searchsorted(alive, ends)
        return np.array(ids, np.int32)[alive], np.diff(upto, prepend=0)

    def remember(self, pieces: set[str]) -> dict[str, bytes]:
        """Packed ids of all these pre-tokens at least; those of the young generation."""
        young, old = self.young, self.old
        new = pieces - young.keys()
        for piece in new & old.keys():
            young[piece] = old[piece]
        ranks, rest, raw = self.ranks, [], []
        for piece in new - old.keys():
            as_bytes = piece.encode()
            whole = ranks.get(as_bytes)
            if whole is None:
                rest.append(piece)
                raw.append(as_bytes)
            else:
                young[piece] = whole.to_bytes(4, "little")
        ids, counts = self.merged(raw)
        packed = ids.astype("<i4").tobytes()
        upto = (np.cumsum(counts) * 4).tolist()
        for piece, a, b in zip(rest, [0, *upto], upto, strict=False):
            young[piece] = packed[a:b]
        return young

    def forget(self, pieces: set[str]) -> None:
        """Drop long pre-tokens, and the older generation when the young one is full."""
        young = self.young
        for piece in pieces:
            if len(piece) > MEMO_BYTES:
                young.pop(piece, None)
        if len(young) > MEMO_ENTRIES:
            self.old, self.young = young, {}
            while len(self.old) > MEMO_ENTRIES:  # one block had more
                self.old.popitem()

    def encode_many(self, texts: Sequence[str]) -> list[np.ndarray]:
        """Ids of whole texts, every match of the pattern by itself; no special tokens."""
        found = [self.pattern.findall(t) for t in texts]
        pieces = set().union(*found)
        packed = self.remember(pieces)
        out = [np.frombuffer(b"".join(map(packed.__getitem__, f)), "<i4") for f in found]
        self.forget(pieces)
        return out

    def encode(self, text: str) -> list[int]:
        return self.encode_many([text])[0].tolist()

    def decode(self, ids: Sequence[int]) -> bytes:
        """The bytes that the ids stand for; decoding undoes encoding exactly."""
        return b"".join(map(self.tokens.__getitem__, ids))


_loaded: dict[tuple[str, str], ByteBPE] = {}


def tokenizer(rank_file: str, pattern: str) -> ByteBPE:
    """One encoder per worker process and rank file."""
    key = (rank_file, pattern)
    if key not in _loaded:
        _loaded[key] = ByteBPE(rank_file, pattern)
    return _loaded[key]


def encode_column(docs: DataFrame, rank_file: str, pattern: str) -> DataFrame:
    """``docs`` with ``token_ids`` (array<int>); a null text counts as empty and has no ids.

    ``rank_file`` must be readable at that path on every executor (it is part of the installed
    vocabulary package).
    """
    schema = T.StructType([*(f for f in docs.schema if f.name != "token_ids"), T.StructField("token_ids", T.ArrayType(T.IntegerType()))])
    kept = docs.select(*(c for c in docs.columns if c != "token_ids"))
    at = kept.columns.index("text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(rank_file, pattern)
        for b in batches:
            for lo, hi in slices(b.column(at), BLOCK_BYTES):
                part = b.slice(lo, hi - lo)
                ids = bpe.encode_many([t or "" for t in part.column(at).to_pylist()])
                ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids)))
                yield pa.RecordBatch.from_arrays([*part.columns, lists], schema.names)

    return kept.mapInArrow(tidy(rows), schema)


def digests(docs: DataFrame, rank_file: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every row, encoded and decoded in one pass."""
    base = docs.select("doc_id", "text")
    schema = T.StructType([base.schema["doc_id"], T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(rank_file, pattern)
        decimal = bpe.decimal
        for b in batches:
            for lo, hi in slices(b.column(1), BLOCK_BYTES):
                n, ids_hash, text_hash = [], [], []
                for ids in bpe.encode_many([t or "" for t in b.column(1).slice(lo, hi - lo).to_pylist()]):
                    ids = ids.tolist()
                    n.append(len(ids))
                    ids_hash.append(hashlib.sha256(" ".join(map(decimal.__getitem__, ids)).encode()).hexdigest())
                    text_hash.append(hashlib.sha256(bpe.decode(ids)).hexdigest())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(n, pa.int64()), pa.array(ids_hash), pa.array(text_hash)], schema.names)

    return base.mapInArrow(tidy(rows), schema)
