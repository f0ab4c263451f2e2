"""Sequences of a fixed length packed by a configuration linear program.

Only the histogram of piece lengths reaches the driver: at most ``capacity``
numbers, whatever the input. A covering program over configurations (multisets of
lengths that fit one sequence) is solved by multiplicative weights: the weights
price the lengths, one knapsack dynamic program finds the best configuration that
holds each length, the weights of what they cover fall. The solution is rounded
within what there is, and what rounding leaves is the next, smaller program. The
plan is a table of slots by length; pieces are numbered inside their length without
a one-task window and look up their slot.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.llm.blobs import release
from kmfold.llm.encoding import slices
from kmfold.llm.tokenfiles import END_ID, tokenizer
from kmfold.numbering import number_within
from kmfold.staging import ship_package, stage

CAPACITY = 2048
ROUNDS = 80
#: Rounds of the program for what rounding leaves, how many such programs at most, and the share
#: of what is left that a program has to place before more room may stay unused.
REST_ROUNDS, RESTARTS, LEAST_PROGRESS = 10, 100, 0.2
SLOW_RATE, FAST_RATE = 0.01, 3.0
PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"

Plan = list[tuple[int, list[tuple[int, int]]]]  # (copies, [(length, times)])


class Pricing:
    """Knapsack tables for one set of weights: the multiset of lengths of greatest value for every room."""

    def __init__(self, value: np.ndarray, capacity: int):
        self.worth, self.pick = np.zeros(capacity + 1), np.zeros(capacity + 1, np.int64)
        lengths = np.flatnonzero(value > 0)
        values, below = value[lengths], np.searchsorted(lengths, np.arange(capacity + 1), "right")
        worth = self.worth
        for c in range(int(lengths[0]) if len(lengths) else capacity + 1, capacity + 1):
            n = below[c]
            total = worth[c - lengths[:n]] + values[:n]
            k = int(total.argmax())
            if total[k] > worth[c - 1]:
                worth[c], self.pick[c] = total[k], lengths[k]
            else:
                worth[c] = worth[c - 1]

    def fill(self, room: int, config: dict[int, int], left: np.ndarray | None = None) -> dict[int, int]:
        """Add the best content of ``room`` to ``config``, of each length at most what is left."""
        while room > 0:
            n = int(self.pick[room])
            if n and (left is None or config.get(n, 0) < left[n]):
                config[n] = config.get(n, 0) + 1
                room -= n
            else:
                room -= 1
        return config


def price(value: np.ndarray, capacity: int) -> list[tuple[int, int]]:
    """The multiset of lengths of greatest value that fits (unbounded knapsack); value[L] is that of length L."""
    return sorted(Pricing(value, capacity).fill(capacity, {}).items(), reverse=True)


def greedy(counts: np.ndarray, capacity: int) -> Plan:
    """Longest first, each gap filled by the longest piece that fits; equal sequences in one step."""
    left, plan = counts.copy(), []
    while True:
        there = np.flatnonzero(left)
        if not len(there):
            return plan
        room, config = capacity, []
        while room > 0:
            k = int(np.searchsorted(there, room, "right")) - 1
            if k < 0:
                break
            length = int(there[k])
            times = min(room // length, int(left[length]))
            config.append((length, times))
            room -= times * length
            there = there[:k]
        copies = min(int(left[n]) // t for n, t in config)
        for n, t in config:
            left[n] -= copies * t
        plan.append((copies, config))


def cover(need: np.ndarray, capacity: int, rounds: int, rate: float) -> dict[tuple, float]:
    """A fractional cover of ``need[L]`` pieces of each length: amounts of configurations.

    Each round prices the lengths by their weights. Every length that is covered less
    than the round's share of its need, longest first, gets the best configuration
    that holds it, in the amount that it lacks; the weights then fall exponentially
    with what is covered beyond the share. After the last round all needs are met.
    """
    there = np.flatnonzero(need)
    # full sequences first, long pieces before many short ones: the second term is below one unit of length
    start = there + 0.2 * (there / capacity) ** 2
    weight, covered, amounts = np.zeros(capacity + 1), np.zeros(capacity + 1), {}
    for r in range(1, rounds + 1):
        share = r / rounds
        weight[there] = start * np.exp(-rate * np.maximum(covered[there] / need[there] - share, 0.0).clip(0, 100))
        tables = Pricing(weight, capacity)
        for n in there[::-1].tolist():
            lack = share * need[n] - covered[n]
            if lack <= 1e-9 * need[n]:
                continue
            config = tables.fill(capacity - n, {n: 1}, need)
            amount = lack / config[n]
            for k, t in config.items():
                covered[k] += amount * t
            key = tuple(sorted(config.items(), reverse=True))
            amounts[key] = amounts.get(key, 0.0) + amount
    return amounts


def round_off(counts: np.ndarray, capacity: int, rounds: int, rate: float, slack: int) -> tuple[Plan, int]:
    """A plan by the program with one rate, and how many pieces the program placed.

    The configurations of the fractional cover are taken in whole copies, longest and
    fullest first, as far as there are pieces; up to ``slack`` of room may stay unused.
    What rounding leaves is a smaller instance of the same program, in which more
    room is let through where too little was placed. Pieces that no program places go
    longest first.
    """
    left, plan, placed = counts.copy(), [], 0

    def take(config: tuple, most: int) -> None:
        nonlocal placed
        copies = min(most, *(int(left[n]) // t for n, t in config)) if len(config) > 1 else min(most, int(left[config[0][0]]) // config[0][1])
        if copies > 0:
            for n, t in config:
                left[n] -= copies * t
            placed += copies * sum(t for _, t in config)
            plan.append((copies, list(config)))

    for k in range(RESTARTS):
        if not left.any():
            break
        amounts = cover(left, capacity, rounds if k == 0 else REST_ROUNDS, rate)
        room = {c: capacity - sum(n * t for n, t in c) for c in amounts}
        before = placed
        for c in sorted(amounts, key=lambda c: (-c[0][0], room[c], -amounts[c], c)):
            if room[c] <= slack:
                take(c, int(np.ceil(amounts[c])))
        if placed - before < LEAST_PROGRESS * left.sum():
            slack = min(capacity, 2 * slack + 1)
    return plan + greedy(left, capacity), placed


def solve(counts: np.ndarray, capacity: int = CAPACITY, rounds: int = ROUNDS) -> tuple[Plan, int]:
    """A plan for ``counts[L]`` pieces of each length, and how many of them the program placed.

    Slow weights keep sequences full, which is best where the lengths allow it; fast
    weights find what lengths are scarce, which is best where they do not. The plan with
    fewer sequences counts.
    """
    made = [round_off(counts, capacity, rounds, SLOW_RATE, 0), round_off(counts, capacity, rounds, FAST_RATE, capacity)]
    return min(made, key=lambda m: sum(copies for copies, _ in m[0]))


class Slots:
    """Place of the r-th piece of a length: sequence and offset."""

    def __init__(self, plan: Plan):
        rows: dict[int, list[tuple[int, int, int, int]]] = {}
        taken: dict[int, int] = {}
        base = 0
        for copies, config in plan:
            offset = 0
            for n, t in config:
                rows.setdefault(n, []).append((taken.get(n, 0), base, t, offset))
                taken[n] = taken.get(n, 0) + copies * t
                offset += n * t
            base += copies
        self.sequences = base
        self.rows = {n: np.array(r, np.int64).T for n, r in rows.items()}

    def find(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
        order = np.argsort(length, kind="stable")
        cuts = np.flatnonzero(np.diff(length[order])) + 1
        for part in np.split(order, cuts) if len(order) else []:
            n = int(length[part[0]])
            first, base, times, place = self.rows[n]
            k = np.searchsorted(first, rank[part], "right") - 1
            copy, slot = np.divmod(rank[part] - first[k], times[k])
            sequence[part] = base[k] + copy
            offset[part] = place[k] + slot * n
        return sequence, offset


def cut_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """Pieces of every document's ids and end id: only the first may be shorter than ``capacity``."""
    ship_package(docs.sparkSession)

    def run(batches):
        tok = tokenizer(path, spell_added=False)
        for whole in batches:
            release()
            for b in slices(whole, 1 << 20):
                out = [[], [], [], [], []]
                for d, ids in zip(b.column(0).to_pylist(), tok.encode(b.column(1).to_pylist())):
                    ids.append(END_ID)
                    n, view = len(ids), memoryview(ids).cast("B")
                    stop = n % capacity or capacity
                    start, piece = 0, 0
                    while start < n:
                        for col, v in zip(out, (d, piece, start, stop - start, zlib.crc32(view[4 * start : 4 * stop]))):
                            col.append(v)
                        start, stop, piece = stop, stop + capacity, piece + 1
                types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, PIECE_SCHEMA)


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Add sequence_id and offset to staged pieces (rows with a length of 1 to ``capacity``)."""
    spark = pieces.sparkSession
    ship_package(spark)
    counts = np.zeros(capacity + 1, np.int64)
    for r in pieces.groupBy("length").count().collect():  # at most `capacity` rows
        counts[r["length"]] = r["count"]
    slots = spark.sparkContext.broadcast(Slots(solve(counts, capacity)[0]))  # bounded by rounds and capacity
    names = pieces.columns

    def run(batches):
        for b in batches:
            sequence, offset = slots.value.find(b.column(names.index("length")).to_numpy(), b.column(len(names)).to_numpy())
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(names))), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema) + ", sequence_id long, offset long"
    order = [c for c in ("doc_id", "piece", "start", "ids_crc32") if c in names]
    return number_within(pieces, ["length"], order, "_rank").select(*names, "_rank").mapInArrow(run, ddl)


def pack_documents(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """Pack all documents: one row a piece with its place.

    A null text has the end id alone. Repeated ids and texts are separate pieces;
    other columns are ignored; an empty table gives an empty result.
    """
    return pack_pieces(stage(cut_pieces(docs, path, capacity), "pieces"), capacity)


def sequence_rows(pieces: DataFrame, ids: DataFrame) -> DataFrame:
    """The packed sequences themselves: sequence_id and its ids, from placed pieces and ``doc_id, ids`` rows."""
    cut = pieces.join(ids, "doc_id").select("sequence_id", "offset", F.expr("slice(ids, cast(start + 1 as int), cast(length as int))").alias("part"))
    parts = cut.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "part"))).alias("p"))
    return parts.select("sequence_id", F.flatten(F.transform("p", lambda x: x["part"])).alias("ids"))
