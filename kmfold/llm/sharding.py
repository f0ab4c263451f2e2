"""Shards of near-equal bytes by differencing, with groups of equal texts kept whole.

Texts never leave the scan: it yields one narrow row a document (size, checksum,
128-bit group key). Groups are summed with map-side combining, so a group that
holds a third of all rows is one number by the time it is shuffled. Groups above
a share of ``1 / heavy`` of all bytes stay single items (there are at most
``heavy`` of them, whatever the input); all others fall by hash into ``cells``
cells. The differencing therefore sees at most ``heavy + cells`` sizes on the
driver, at any scale.
"""

from __future__ import annotations

import heapq
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.numbering import number_within
from kmfold.staging import stage

LAWS = ("bytes", "rows", "key")


def difference(sizes: list[int], ways: int) -> list[int]:
    """Way of each size: the two partial partitions of largest spread are combined,
    largest of one with smallest of the other, until one is left. Empty input: []."""
    tick = count()
    heap = []
    for item, size in enumerate(sizes):
        parts = [(0, ())] * (ways - 1) + [(size, item)]
        heap.append((-size, next(tick), parts))
    heapq.heapify(heap)
    while len(heap) > 1:
        _, _, a = heapq.heappop(heap)
        _, _, b = heapq.heappop(heap)
        joined = sorted(((x + y, (p, q)) for (x, p), (y, q) in zip(a, reversed(b), strict=True)), key=lambda t: t[0])
        floor = joined[0][0]
        parts = [(x - floor, p) for x, p in joined]
        heapq.heappush(heap, (-parts[-1][0], next(tick), parts))
    ways_of = [0] * len(sizes)
    for way, (_, tree) in enumerate(heap[0][2] if heap else []):
        todo = [tree]
        while todo:
            node = todo.pop()
            if isinstance(node, tuple):
                todo.extend(node)
            else:
                ways_of[node] = way
    return ways_of


def rendezvous(key, shards: int):
    """The shard whose hash with the key is largest: one more shard takes rows only into itself."""
    return F.array_max(F.array(*[F.struct(F.xxhash64(key, F.lit(s)).alias("h"), F.lit(s).alias("s")) for s in range(shards)]))["s"]


def shard_documents(docs: DataFrame, shards: int = 8, law: str = "bytes", cells: int = 4096, heavy: int = 2048) -> DataFrame:
    """Deal documents to ``shards`` shards under one law.

    ``bytes``: groups of equal texts stay whole, byte sums as near as differencing
    gets them. ``rows``: counts differ by one at most. ``key``: the id and the
    number of shards decide alone.

    A null text counts as empty (size 1). Repeated ids are separate rows. A null
    id is a key like any other. Other columns are ignored; an empty table gives
    an empty result.
    """
    if law not in LAWS:
        raise ValueError(f"law must be one of {LAWS}")
    text = F.coalesce(F.col("text"), F.lit(""))
    narrow = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(F.encode(text, "utf-8")).alias("text_crc32"),
        F.xxhash64(text).alias("_k1"),
        F.xxhash64(F.lit(1), text).alias("_k2"),
    )
    rows = stage(narrow, "shard_rows")
    if law == "bytes":
        placed = _by_bytes(rows, shards, cells, heavy)
    elif law == "rows":
        one = number_within(rows.withColumn("_all", F.lit(0)), ["_all"], ["doc_id", "text_crc32", "size"], "_row")
        placed = one.withColumn("shard", F.pmod("_row", F.lit(shards)).cast("int")).drop("_row", "_all")
    else:
        placed = rows.withColumn("shard", rendezvous(F.col("doc_id"), shards))
    grown = rendezvous(F.col("doc_id"), shards + 1) if law == "key" else F.lit(None)
    numbered = number_within(placed.select("doc_id", "size", "text_crc32", "shard"), ["shard"], ["doc_id", "text_crc32", "size"], "slot")
    return numbered.select("doc_id", "size", "text_crc32", F.lit(law).alias("law"), F.col("shard").cast("int").alias("shard"), "slot", grown.cast("int").alias("grown_shard"))


def _by_bytes(rows: DataFrame, shards: int, cells: int, heavy: int) -> DataFrame:
    spark = rows.sparkSession
    groups = rows.groupBy("_k1", "_k2").agg(F.sum("size").alias("bytes"))
    total = rows.agg(F.sum("size")).first()[0] or 0
    groups = stage(groups.withColumn("_heavy", F.col("bytes") * heavy > F.lit(total)), "shard_groups")
    large = groups.filter("_heavy").orderBy(F.desc("bytes"), "_k1", "_k2").collect()  # at most `heavy` rows
    cell = F.pmod("_k1", F.lit(cells)).cast("int")
    small = groups.filter("not _heavy").groupBy(cell.alias("_cell")).agg(F.sum("bytes").alias("bytes")).orderBy("_cell").collect()  # at most `cells` rows
    ways = difference([r["bytes"] for r in large] + [r["bytes"] for r in small], shards)
    of_large = spark.createDataFrame([(r["_k1"], r["_k2"], w) for r, w in zip(large, ways)], "_k1 long, _k2 long, _own int")
    of_cell = spark.createDataFrame([(r["_cell"], w) for r, w in zip(small, ways[len(large) :])], "_cell int, _shared int")
    keyed = rows.withColumn("_cell", cell)
    # both maps have a fixed bound on their rows, so they are broadcast at any input size
    keyed = keyed.join(F.broadcast(of_large), ["_k1", "_k2"], "left").join(F.broadcast(of_cell), ["_cell"], "left")
    return keyed.withColumn("shard", F.coalesce("_own", "_shared"))
