"""Token-id files compressed by pair replacement, and tokenizer files that feed them.

Documents are dealt to shards by ranges of their id and encoded in ascending order;
a shard's ids are cut into chunks at document ends. In a chunk, frequent id pairs
are replaced by nonterminals, round after round; rules, expansion lengths, the
remaining symbols and each document's place in them make the chunk's record, so a
single document can be decoded without its neighbours. Records are written through
Spark's own writer: any store that Spark reaches can hold the files.
"""

from __future__ import annotations

import json
import re
import struct
import zlib
from array import array

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from kmfold.llm.blobs import release
from kmfold.llm.encoding import slices
from kmfold.numbering import bucket_of, range_bounds
from kmfold.staging import pieces_for, scratch_path, ship_package

MAGIC = b"KMTK"
#: Several shards share a partition, so that their sizes even out.
SHARD_BYTES, SHARDS_A_PARTITION = 2 << 20, 3
CHUNK_IDS = 1 << 18
MOST_SHARDS = 1 << 16
PAIRS_A_ROUND = 3500
LEAST_COUNT = 8
END_ID = 0
#: Fixed value: the splitting pattern of the byte-level pre-tokenizer.
BYTE_LEVEL_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def byte_letters() -> dict[str, int]:
    """The printable stand-in of every byte in a byte-level vocabulary file."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(printable)]
    return {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(rest)}


class JsonTokenizer:
    """Ids of a tokenizers-library file.

    A plain byte-level BPE file (no normalizer, the standard splitting pattern, merges
    in the order of their ids) is run by the rank-merging engine, which gives the
    library's ids about five times as fast; any other file is run by the library, and
    so is a text that holds an added token of the file, which then has its own id (as
    all queries ask). With ``spell_added`` such a token is text like any other.
    """

    def __init__(self, path: str, spell_added: bool = True):
        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = spell_added
        self.engine = self._engine(path)
        added = [] if spell_added else [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.added = re.compile("|".join(map(re.escape, added))) if added else None

    @staticmethod
    def _engine(path: str) -> tiktoken.Encoding | None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec["model"], spec.get("pre_tokenizer") or {}
        plain = (
            model.get("type", "BPE") == "BPE" and not model.get("dropout") and not model.get("continuing_subword_prefix")
            and not model.get("end_of_word_suffix") and not model.get("byte_fallback") and not model.get("ignore_merges") and not spec.get("normalizer")
            and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
        )
        if not plain:
            return None
        letters, special = byte_letters(), {t["content"] for t in spec.get("added_tokens", [])}
        vocab = {k: v for k, v in model["vocab"].items() if k not in special}
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        order = [vocab.get("".join(m), -1) for m in merges]
        if any(a >= b for a, b in zip(order, order[1:])) or any(c not in letters for k in vocab for c in k):
            return None
        ranks = {bytes(letters[c] for c in k): v for k, v in vocab.items()}
        return tiktoken.Encoding("file", pat_str=BYTE_LEVEL_PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(self, texts: list[str]) -> list[array]:
        if self.engine is None:
            return self._by_library(texts)
        if self.added is None:
            return [array("I", self.engine.encode_ordinary(t)) for t in texts]
        return [self._by_library([t])[0] if self.added.search(t) else array("I", self.engine.encode_ordinary(t)) for t in texts]

    def _by_library(self, texts: list[str]) -> list[array]:
        return [array("I", e.ids) for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]


_tokenizers: dict[tuple[str, bool], JsonTokenizer] = {}


def tokenizer(path: str, spell_added: bool = True) -> JsonTokenizer:
    """The worker's tokenizer for a file, built once in a process."""
    key = path, spell_added
    if key not in _tokenizers:
        _tokenizers[key] = JsonTokenizer(path, spell_added)
    return _tokenizers[key]


def replace_pairs(ids: np.ndarray, ends: np.ndarray, first: int, most: int = 65536) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols, their document-end flags and the rules (two symbols each, ids from ``first``).

    A round counts all pairs inside documents, takes the most frequent, and replaces
    their occurrences where no better pair overlaps. No rule spans two documents.
    Rounds end when no pair occurs ``LEAST_COUNT`` times or no nonterminal is free.
    """
    seq, rules, free = ids.astype(np.uint32), [], most - first
    while len(seq) >= 2 and free > 0:
        # a rough count by hash (symbols have at most 20 bits) spares most pairs the exact one
        mixed = seq[:-1] * np.uint32(0x9E3779B1)
        mixed += seq[1:]
        mixed *= np.uint32(0x85EBCA6B)
        mixed >>= np.uint32(14)
        rough = np.bincount(mixed, minlength=1 << 18) >= LEAST_COUNT
        maybe = np.flatnonzero(rough[mixed] & ~ends[:-1])
        key = (seq[maybe].astype(np.int64) << 20) | seq[maybe + 1]
        # of a run of one symbol every second pair counts, so that the best pair is replaced as often as it is counted
        place = np.arange(len(maybe))
        follows = np.append(False, np.diff(key) == 0)[: len(maybe)] & np.append(False, np.diff(maybe) == 1)[: len(maybe)]
        counted = (place - np.maximum.accumulate(np.where(follows, 0, place))) % 2 == 0
        maybe, key = maybe[counted], key[counted]
        if not len(maybe):
            break
        pairs, inverse, counts = np.unique(key, return_inverse=True, return_counts=True)
        order = np.argsort(-counts, kind="stable")[: min(PAIRS_A_ROUND, free)]
        order = order[counts[order] >= LEAST_COUNT]
        if not len(order):
            break
        score_of = np.zeros(len(pairs), np.int32)
        score_of[order] = np.arange(len(order), 0, -1)
        score = np.zeros(len(seq) + 1, np.int32)
        score[maybe + 1] = score_of[inverse]
        here = score[1:]
        left = score[:-1]
        right = np.append(score[2:], 0)
        chosen = np.flatnonzero((here > 0) & (here >= left) & (here >= right))
        picked, times = np.unique(here[chosen], return_counts=True)
        good = picked[times >= LEAST_COUNT - 1]
        if not len(good):
            break
        new_of = np.full(len(order) + 1, -1, np.int64)
        new_of[good] = first + np.arange(len(good))
        symbol = new_of[here[chosen]]
        chosen, symbol = chosen[symbol >= 0], symbol[symbol >= 0]
        by_rank = pairs[order[len(order) - good]]
        rules.append(np.stack([by_rank >> 20, by_rank & 0xFFFFF], axis=1))
        seq[chosen] = symbol
        keep = np.ones(len(seq), bool)
        keep[chosen + 1] = False
        ends[chosen] |= ends[chosen + 1]
        seq, ends = seq[keep], ends[keep]
        first += len(good)
        free -= len(good)
    table = np.concatenate(rules) if rules else np.zeros((0, 2), np.int64)
    return seq, ends, table


def expansion_lengths(rules: np.ndarray, first: int) -> np.ndarray:
    """How many ids each rule stands for; every pass settles one more level of nesting."""
    lengths = np.full(len(rules) + 1, 1, np.int64)
    inner = np.where(rules >= first, rules - first, len(rules))
    while len(rules):
        new = lengths[inner].sum(axis=1)
        if (new == lengths[:-1]).all():
            break
        lengths[:-1] = new
    return lengths[:-1]


def expand(symbols: np.ndarray, rules: np.ndarray, first: int) -> np.ndarray:
    """The ids that symbols stand for, one level of nesting a pass."""
    seq = symbols.astype(np.int64)
    while len(seq):
        high = seq >= first
        if not high.any():
            break
        at = np.cumsum(1 + high) - (1 + high)
        out = np.empty(len(seq) + int(high.sum()), np.int64)
        out[at[~high]] = seq[~high]
        used = rules[seq[high] - first]
        out[at[high]], out[at[high] + 1] = used[:, 0], used[:, 1]
        seq = out
    return seq.astype("<u4")


def expand_all(symbols: np.ndarray, rules: np.ndarray, lengths: np.ndarray, first: int) -> np.ndarray:
    """The same for many symbols: every used rule is expanded once, then its ids are copied to all its places."""
    seq = symbols.astype(np.int64)
    high = seq >= first
    used, which = np.unique(seq[high], return_inverse=True)
    ids = expand(used, rules, first)
    if int(lengths[used - first].sum()) != len(ids):
        raise ValueError("rules and their lengths disagree")
    size = lengths[used - first].astype(np.int64)
    start = np.cumsum(size) - size
    table = np.concatenate([ids, seq[~high].astype("<u4")])  # plain symbols stand behind the rules' ids
    count, base = np.ones(len(seq), np.int64), np.empty(len(seq), np.int64)
    count[high], base[high] = size[which], start[which]
    base[~high] = len(ids) + np.arange(len(seq) - len(which))
    place = np.cumsum(count) - count
    return table[np.repeat(base - place, count) + np.arange(int(count.sum()))]


def write_chunk(doc_ids: list[int | None], ids: list[array], first: int) -> bytes:
    """One record: header, rules, expansion lengths, documents, symbols."""
    counts = np.fromiter(map(len, ids), np.int64, len(ids))
    flat = np.frombuffer(b"".join(x.tobytes() for x in ids), np.uint32)
    ends = np.zeros(len(flat), bool)
    ends[np.cumsum(counts) - 1] = True
    seq, ends, rules = replace_pairs(flat, ends, first)
    wide = first > 65535 or first + len(rules) > 65536
    kind = "<u4" if wide else "<u2"
    places = np.flatnonzero(ends) + 1
    null = np.array([d is None for d in doc_ids], np.uint8)
    named = np.array([0 if d is None else d for d in doc_ids], "<i8")
    head = MAGIC + struct.pack("<BIIII", wide, first, len(rules), len(doc_ids), len(seq))
    lengths = expansion_lengths(rules, first)
    return b"".join([head, rules.astype(kind).tobytes(), lengths.astype("<u4").tobytes(), null.tobytes(), named.tobytes(), counts.astype("<i8").tobytes(), places.astype("<u4").tobytes(), seq.astype(kind).tobytes()])


class Chunk:
    """A record read back; documents can be decoded one by one."""

    def __init__(self, raw: bytes):
        if raw[:4] != MAGIC:
            raise ValueError("not a token record")
        wide, self.first, n_rules, n_docs, n_symbols = struct.unpack_from("<BIIII", raw, 4)
        kind, at = ("<u4" if wide else "<u2"), 4 + struct.calcsize("<BIIII")

        def take(dtype: str, n: int) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(raw, dtype, n, at)
            at += out.nbytes
            return out

        self.rules = take(kind, 2 * n_rules).reshape(-1, 2).astype(np.int64)
        self.lengths = take("<u4", n_rules)
        null = take("u1", n_docs)
        self.doc_ids = [None if z else int(d) for z, d in zip(null, take("<i8", n_docs))]
        self.counts, self.places = take("<i8", n_docs), take("<u4", n_docs)
        self.symbols = take(kind, n_symbols)

    def ids(self) -> np.ndarray:
        """The ids of all documents of the record."""
        return expand_all(self.symbols, self.rules, self.lengths, self.first)

    def document(self, i: int) -> np.ndarray:
        """The ids of document ``i`` alone."""
        start = int(self.places[i - 1]) if i else 0
        return expand(self.symbols[start : int(self.places[i])], self.rules, self.first)

    def ids_between(self, i: int, low: int, high: int) -> np.ndarray:
        """Ids ``low`` to ``high`` of a document: expansion lengths find the symbols to expand."""
        start = int(self.places[i - 1]) if i else 0
        part = self.symbols[start : int(self.places[i])].astype(np.int64)
        size = np.ones(len(part), np.int64)
        size[part >= self.first] = self.lengths[part[part >= self.first] - self.first]
        stop = np.cumsum(size)
        a, b = int(np.searchsorted(stop, low, "right")), int(np.searchsorted(stop, high, "left")) + 1
        base = int(stop[a - 1]) if a else 0
        return expand(part[a:b], self.rules, self.first)[low - base : high - base]


def write_token_files(docs: DataFrame, path: str, out: str, vocabulary: int = 50257, shard_bytes: int = SHARD_BYTES) -> None:
    """Encode all documents in ascending doc_id order and write the shards below ``out``.

    A null text has the end id alone. Null ids come first, repeated ids follow one
    another in the order of their texts; other columns are ignored; an empty table
    gives files without records.
    """
    ship_package(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    shards = pieces_for(docs.select("doc_id", "text"), shard_bytes, most=MOST_SHARDS)  # their bounds stand in the plan; memory is that of a chunk
    bounds = range_bounds(rows, "doc_id", shards)
    dealt = rows.withColumn("shard", F.coalesce(bucket_of(F.col("doc_id"), bounds), F.lit(0)) if bounds else F.lit(0))
    dealt = dealt.withColumn("shard", F.when(F.col("doc_id").isNull(), 0).otherwise(F.col("shard")))
    dealt = dealt.repartition(-(-(len(bounds) + 1) // SHARDS_A_PARTITION), "shard").sortWithinPartitions("shard", "doc_id", "text")

    def run(batches):
        tok = tokenizer(path, spell_added=False)
        shard, chunk, names, held, n = None, 0, [], [], 0

        def record():
            return pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "chunk": pa.array([chunk], pa.int32()), "n_ids": pa.array([n], pa.int64()), "payload": pa.array([write_chunk(names, held, vocabulary)], pa.binary())})

        for whole in batches:
            release()
            for b in slices(whole, 1 << 20):
                for s, d, ids in zip(b.column(2).to_pylist(), b.column(0).to_pylist(), tok.encode(b.column(1).to_pylist())):
                    if names and (s != shard or n >= CHUNK_IDS):
                        yield record()
                        chunk, names, held, n = (chunk + 1 if s == shard else 0), [], [], 0
                    elif s != shard:
                        chunk = 0
                    shard = s
                    ids.append(END_ID)
                    names.append(d)
                    held.append(ids)
                    n += len(ids)
        if names:
            yield record()

    dealt.mapInArrow(run, "shard int, chunk int, n_ids long, payload binary").write.parquet(out)


def read_token_files(spark: SparkSession, out: str) -> DataFrame:
    """One row a document from the files: doc_id, start, n_tokens, ids_crc32."""
    ship_package(spark)
    files = spark.read.schema("shard int, chunk int, n_ids long, payload binary").parquet(out)

    def run(batches):
        for b in batches:
            release()
            for k in range(b.num_rows):
                c = Chunk(b.column(2)[k].as_py())
                ids, stop = c.ids(), np.cumsum(c.counts)
                start = stop - c.counts
                view = memoryview(ids.tobytes())
                sums = [zlib.crc32(view[4 * i : 4 * j]) for i, j in zip(start.tolist(), stop.tolist())]
                n = len(sums)
                yield pa.RecordBatch.from_pydict({"shard": pa.array([b.column(0)[k].as_py()] * n, pa.int32()), "chunk": pa.array([b.column(1)[k].as_py()] * n, pa.int32()), "doc_id": pa.array(c.doc_ids, pa.int64()), "local": pa.array(start, pa.int64()), "n_tokens": pa.array(c.counts, pa.int64()), "ids_crc32": pa.array(sums, pa.int64())})

    told = files.select("shard", "chunk", "payload").mapInArrow(run, "shard int, chunk int, doc_id long, local long, n_tokens long, ids_crc32 long")
    sizes = files.groupBy("shard", "chunk").agg(F.sum("n_ids").alias("n"))
    # one row a shard: their number is bounded by pieces_for
    shards = sizes.groupBy("shard").agg(F.sum("n").alias("n"))
    base = shards.select("shard", F.coalesce(F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("shard_base"))
    inner = Window.partitionBy("shard").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    places = sizes.select("shard", "chunk", F.coalesce(F.sum("n").over(inner), F.lit(0)).alias("chunk_base")).join(base, "shard")
    return told.join(places, ["shard", "chunk"]).select("doc_id", (F.col("shard_base") + F.col("chunk_base") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")


def token_file_digests(docs: DataFrame, path: str) -> DataFrame:
    """Write the files to the shared folder, read them back, and tell of each document.

    Nulls, empty texts, repeated ids and empty tables: as ``write_token_files`` says.
    """
    spark = docs.sparkSession
    out = scratch_path(spark, "token_files")
    write_token_files(docs, path, out)
    return read_token_files(spark, out)
