"""Byte-level BPE encoding and decoding in length-bucketed numpy matrices.

Texts are cut by the splitting pattern; every distinct piece that a worker has not
met yet is encoded once. New pieces of similar length form one padded matrix: in
each round every row finds the leftmost of its pairs of least rank by a hashed
lookup, merges it and is compacted; rows without a pair leave the matrix. Pieces
above ``LONG_PIECE`` bytes (a run of letters without a space can be a whole
document) take a heap of pairs instead, whose work grows as n log n.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.staging import ship_package

LONG_PIECE = 192
MEMO_PIECES = 400_000
NONE = np.int32(2**31 - 1)


class PairTable:
    """Open-addressing hash of (left id, right id) to the id of their join, in numpy arrays."""

    def __init__(self, left: np.ndarray, right: np.ndarray, joined: np.ndarray):
        bits = max(4, int(np.ceil(np.log2(max(1, len(left)) * 3))))
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys = np.full(1 << bits, -1, np.int64)
        self.values = np.full(1 << bits, NONE, np.int32)
        keys = (left.astype(np.int64) << 32) | right.astype(np.int64)
        at, todo, self.probes = self._home(keys), np.arange(len(keys)), 0
        while len(todo):
            self.probes += 1
            free = todo[self.keys[at[todo]] == -1]
            _, first = np.unique(at[free], return_index=True)
            won = free[first]
            self.keys[at[won]], self.values[at[won]] = keys[won], joined[won]
            todo = todo[self.keys[at[todo]] != keys[todo]]
            at[todo] = (at[todo] + 1) & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Joined ids, ``NONE`` where a pair has none."""
        keys = (left.astype(np.int64) << 32) | right.astype(np.int64)
        at = self._home(keys)
        held = self.keys[at]
        out = np.where(held == keys, self.values[at], NONE)
        todo = np.flatnonzero((held != keys) & (held != -1))
        while len(todo):
            at[todo] = (at[todo] + 1) & self.mask
            held = self.keys[at[todo]]
            got = held == keys[todo]
            out[todo[got]] = self.values[at[todo[got]]]
            todo = todo[~got & (held != -1)]
        return out


class BpeCodec:
    """Encoder and decoder for one rank file and one splitting pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.bytes_of = [b""] * (max(ranks.values()) + 1)
        for piece, rank in ranks.items():
            self.bytes_of[rank] = piece
        self.byte_ids = np.array([ranks[bytes([b])] for b in range(256)], np.int32)
        splits = [(ranks[p[:i]], ranks[p[i:]], r) for p, r in ranks.items() for i in range(1, len(p)) if p[:i] in ranks and p[i:] in ranks]
        left, right, joined = (np.array(x, np.int32) for x in zip(*splits))
        self.pairs = PairTable(left, right, joined)
        self.pair_of = {(a, b): r for a, b, r in splits}
        self.memo: dict[str, bytes] = {}

    @classmethod
    def from_file(cls, path: str, pattern: str) -> BpeCodec:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, pattern)

    def encode_pieces(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of each piece as packed unsigned 32-bit integers."""
        out = [b""] * len(pieces)
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        for i in np.flatnonzero(sizes > LONG_PIECE):
            out[i] = self._encode_long(pieces[i])
        low = 0
        for high in (2, 4, 6, 8, 12, 16, 24, 32, 64, 128, LONG_PIECE):
            rows = np.flatnonzero((sizes > low) & (sizes <= high))
            step = max(1, (1 << 19) // high)
            for k in range(0, len(rows), step):
                self._encode_bucket(pieces, rows[k : k + step], high, out)
            low = high
        return out

    def _encode_bucket(self, pieces: list[bytes], rows: np.ndarray, width: int, out: list[bytes]) -> None:
        padded = np.frombuffer(b"".join(pieces[i].ljust(width, b"\0") for i in rows), np.uint8).reshape(len(rows), width)
        length = np.fromiter((len(pieces[i]) for i in rows), np.int64, len(rows))
        ids = self.byte_ids[padded]
        ids[np.arange(width) >= length[:, None]] = -1
        while len(rows):
            rank = np.full((len(rows), width), NONE, np.int32)
            if width > 1:
                a, b = ids[:, :-1], ids[:, 1:]
                there = b >= 0
                rank[:, :-1][there] = self.pairs.find(a[there], b[there])
            at = rank.argmin(axis=1)
            least = rank[np.arange(len(rows)), at]
            done = least == NONE
            for k in np.flatnonzero(done):
                out[rows[k]] = ids[k, : length[k]].astype("<u4").tobytes()
            go = ~done
            if not go.any():
                return
            ids, length, rows, at, least = ids[go], length[go] - 1, rows[go], at[go], least[go]
            ids[np.arange(len(rows)), at] = least
            # compaction: what stands right of the merged pair moves one place to the left
            source = np.arange(width - 1)[None, :]
            source = source + (source > at[:, None])
            ids = np.take_along_axis(ids, source, axis=1)
            width = int(length.max())
            ids = ids[:, :width]

    def _encode_long(self, piece: bytes) -> bytes:
        ids = [int(self.byte_ids[b]) for b in piece]
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i) for i in range(n - 1) if (r := self.pair_of.get((ids[i], ids[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            r, i = heapq.heappop(heap)
            j = after[i]
            if ids[i] < 0 or j >= n or self.pair_of.get((ids[i], ids[j])) != r:
                continue
            ids[i], ids[j] = r, -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (s := self.pair_of.get((r, ids[k]))) is not None:
                    heapq.heappush(heap, (s, i))
            if (h := before[i]) >= 0 and (s := self.pair_of.get((ids[h], r))) is not None:
                heapq.heappush(heap, (s, h))
        return array("I", [x for x in ids if x >= 0]).tobytes()

    def encode_batch(self, texts: Iterable[str]) -> list[bytes]:
        """Ids of each text as packed little-endian unsigned 32-bit integers."""
        cut = [self.pattern.findall(t) for t in texts]
        memo = self.memo
        new = list(set().union(*cut).difference(memo)) if cut else []
        raw = [p.encode("utf-8", "surrogatepass") for p in new]
        fresh, known = [], self.ranks
        for p, b in zip(new, raw):
            whole = known.get(b)
            if whole is None:
                fresh.append((p, b))
            else:
                memo[p] = array("I", [whole]).tobytes()
        for (p, _), ids in zip(fresh, self.encode_pieces([b for _, b in fresh])):
            memo[p] = ids
        get = memo.__getitem__
        out = [b"".join(map(get, c)) for c in cut]
        if len(memo) > MEMO_PIECES:
            memo.clear()
        return out

    def decode(self, ids: bytes) -> bytes:
        """The bytes that packed ids stand for."""
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


_codecs: dict[tuple[str, str], BpeCodec] = {}


def codec(path: str, pattern: str) -> BpeCodec:
    """The worker's codec for a rank file, built once in a process."""
    if (path, pattern) not in _codecs:
        _codecs[path, pattern] = BpeCodec.from_file(path, pattern)
    return _codecs[path, pattern]


def slices(batch: pa.RecordBatch, most_bytes: int, column: int = 1) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that the texts of each part stay near ``most_bytes`` (one row at least)."""
    col = batch.column(column)
    sizes = np.asarray(pc.fill_null(pc.binary_length(col), 0))
    ends = np.cumsum(sizes)
    start = 0
    while start < batch.num_rows:
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + most_bytes, "right")))
        yield batch.slice(start, stop - start)
        start = stop


def encode_documents(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Token ids of every text: doc_id, text bytes kept out, ids as packed binary.

    A null or empty text has no ids. Repeated ids are separate rows; other columns
    are ignored; an empty table gives an empty result.
    """
    ship_package(docs.sparkSession)

    def run(batches):
        bpe = codec(path, pattern)
        for whole in batches:
            for b in slices(whole, 4 << 20):
                ids = bpe.encode_batch([t or "" for t in b.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.binary())], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids binary")


def decode_documents(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """The bytes of every row of ``encode_documents``: doc_id, decoded. Null ids decode to nothing."""
    ship_package(encoded.sparkSession)

    def run(batches):
        bpe = codec(path, pattern)
        for b in batches:
            out = [bpe.decode(x or b"") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], ["doc_id", "decoded"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, decoded binary")


def round_trip_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encode every text and decode the ids again in one pass; digests of both.

    A null or empty text has no ids and the digest of nothing. Repeated ids are separate
    rows; other columns are ignored; an empty table gives an empty result.
    """
    ship_package(docs.sparkSession)

    def run(batches):
        bpe = codec(path, pattern)
        for whole in batches:
            for b in slices(whole, 4 << 20):
                ids = bpe.encode_batch([t or "" for t in b.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0),
                        pa.array([len(x) // 4 for x in ids], pa.int64()),
                        pa.array([hashlib.sha256(x).hexdigest() for x in ids]),
                        pa.array([hashlib.sha256(bpe.decode(x)).hexdigest() for x in ids]),
                    ],
                    ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
