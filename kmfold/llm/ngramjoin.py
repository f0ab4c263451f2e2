"""Exact Jaccard links between n-gram sets by a prefix-tree join.

Sets are ordered by the number of documents that hold an n-gram, rarest first. Since
an n-gram of one document is never shared, a set with too many of them can have no
partner: a first exchange of 32-bit codes counts documents by n-gram and leaves out
most sets. What remains is grouped by the n-grams of each set's prefix (two sets
that link share one there), groups that share a set are joined to clusters, and
inside a cluster the sets stand in a tree, most frequent n-grams first. The tree is
walked level by level with the overlap so far, common to all sets below a node;
subtrees whose rest is too short, or that hold only sets already linked, are cut.

Equal sets are one from the start. Clusters above ``BLOCK`` sets are dealt to blocks.
First each block is walked alone, with a few leaders of its cluster beside it: a tight
group of near copies is joined by its leaders in work that grows with its size. Only
what is not in the cluster's largest component then meets other blocks, and of these
only those that set sizes and the triangle inequality (Jaccard distances to the
leaders) do not exclude.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.llm.blobs import byte_values, mix, pack, tidy, unpack
from kmfold.llm.components import components
from kmfold.numbering import number_within
from kmfold.staging import MOST_PARTITIONS, pieces_for, ship_package, stage

PART_BYTES, EXCHANGE_BYTES, BUCKET_BYTES, SLICE = 1 << 20, 4 << 20, 2 << 20, 1 << 20
BLOCK, LEADERS = 512, 4
BASE = 0x9E3779B97F4A7C15 | 1
VALUES = byte_values()
LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint8)
BLANK = np.isin(np.arange(256), [32, 9, 10, 11, 12, 13])
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``n`` powers of the base and of its inverse modulo 2^64."""
    if len(_powers.get("up", ())) < n:
        for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
            p = np.full(n, base, np.uint64)
            p[0] = 1
            _powers[name] = np.cumprod(p)
    return _powers["up"], _powers["down"]


def word_codes(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Code and first byte of each word of a buffer (bytes lower-cased A to Z)."""
    if not len(buf):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    low = LOWER[buf]
    edge = np.diff(np.concatenate([[False], ~BLANK[low], [False]]).astype(np.int8))
    start, stop = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    up, down = powers(len(buf) + 1)
    total = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(VALUES[low] * up[: len(buf)], out=total[1:])
    return mix((total[stop] - total[start]) * down[start]), start


def ngram_sets(texts: list[bytes], n: int) -> tuple[np.ndarray, np.ndarray]:
    """Document and code of all distinct n-grams, ordered by both."""
    docs, codes = [], []
    i = 0
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    ends = np.cumsum(size + 1)
    while i < len(texts):
        base = ends[i - 1] if i else 0
        stop = max(i + 1, int(np.searchsorted(ends, base + SLICE)))
        word, at = word_codes(np.frombuffer(b" ".join(texts[i:stop]) + b" ", np.uint8))
        doc = np.searchsorted(ends[i:stop] - base, at, "right")
        for d, c in _grams(doc, word, n):
            docs.append(d + i)
            codes.append(c)
        i = stop
    if not docs:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    doc, code = np.concatenate(docs), np.concatenate(codes)
    order = np.lexsort((code, doc))
    doc, code = doc[order], code[order]
    new = np.append(True, (doc[1:] != doc[:-1]) | (code[1:] != code[:-1])) if len(doc) else np.zeros(0, bool)
    return doc[new], code[new]


def _grams(doc: np.ndarray, word: np.ndarray, n: int):
    def fold(width: int, at: np.ndarray) -> np.ndarray:
        h = np.full(len(at), width, np.uint64)
        for k in range(width):
            h = mix(h * np.uint64(0xC2B2AE3D27D4EB4F) + word[at + k])
        return h

    if len(word) >= n:
        at = np.flatnonzero(doc[: len(doc) - n + 1] == doc[n - 1 :])
        yield doc[at], fold(n, at)
    first = np.flatnonzero(np.append(True, doc[1:] != doc[:-1])) if len(doc) else np.zeros(0, np.int64)
    count = np.diff(np.append(first, len(doc)))
    for width in range(1, n):
        at = first[count == width]
        if len(at):
            yield doc[at], fold(width, at)


class Sets:
    """The n-gram sets of a part; ``distinct`` has one document of each set, known by both keys."""

    def __init__(self, table: pa.Table, n: int):
        self.ids = table.column("doc_id").to_pylist()
        texts = [(t or "").encode("utf-8", "surrogatepass") for t in table.column("text").to_pylist()]
        doc, code = ngram_sets(texts, n)
        count = np.bincount(doc, minlength=len(texts))
        start = np.cumsum(count) - count
        scrambled = mix(code + np.uint64(11))
        one, two = np.zeros(len(texts), np.uint64), np.zeros(len(texts), np.uint64)
        some = count > 0
        if some.any():
            one[some] = np.add.reduceat(scrambled, start[some])
            two[some] = np.add.reduceat(mix(scrambled), start[some])
        self.key1, self.key2 = mix(one + count.astype(np.uint64)), mix(two)
        self.count, self.start, self.code = count, start, code
        order = np.lexsort((self.key2, self.key1))
        one, two = self.key1[order], self.key2[order]
        first = order[np.append(True, (one[1:] != one[:-1]) | (two[1:] != two[:-1]))] if len(order) else order
        self.distinct = first[some[first]]

    def flat(self) -> tuple[np.ndarray, np.ndarray]:
        """Owner (a distinct document) and code of the n-grams of all distinct sets."""
        size = self.count[self.distinct]
        owner = np.repeat(self.distinct, size)
        at = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size) + self.start[owner]
        return owner, self.code[at]


def bucket_keys(code: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket in the high half, 32-bit code in the low half."""
    return (((code >> np.uint64(33)) % np.uint64(buckets)) << np.uint64(32)) | (code & np.uint64(0xFFFFFFFF))


def by_bucket(key: np.ndarray, *values: np.ndarray):
    """Slices of sorted keys by their bucket."""
    if not len(key):
        return
    bucket = (key >> np.uint64(32)).astype(np.int64)
    cuts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
    for a, z in zip(cuts, np.append(cuts[1:], len(key))):
        yield int(bucket[a]), (key[a:z] & np.uint64(0xFFFFFFFF)).astype(np.uint32), *(v[a:z] for v in values)


def count_cells(cells: list[bytes]) -> list[bytes | None]:
    """For each part's cell of a bucket: its codes that several sets hold, and how many."""
    parts = [unpack(c) for c in cells]
    code, times = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    known, inverse = np.unique(code, return_inverse=True)
    total = np.bincount(inverse, times, len(known)).astype(np.uint32)
    out, at = [], 0
    for p in parts:
        mine = total[inverse[at : at + len(p[0])]]
        at += len(p[0])
        out.append(pack(p[0][mine > 1], mine[mine > 1]) if (mine > 1).any() else None)
    return out


def least_overlap(size: np.ndarray | int, num: int, den: int):
    """The fewest common n-grams of a set of this size with any partner."""
    return -(-num * size // den)


def surviving(sets: Sets, replies: list[tuple[int, bytes]], buckets: int, num: int, den: int):
    """Distinct sets that may have a partner: document, shared n-grams rarest first, and how many of them are its prefix."""
    if not replies or not len(sets.distinct):
        return
    key, times = [], []
    for b, cell in replies:
        c, t = unpack(cell)
        key.append((np.uint64(b) << np.uint64(32)) | c.astype(np.uint64))
        times.append(t)
    key, times = np.concatenate(key), np.concatenate(times)
    order = np.argsort(key)
    key, times = key[order], times[order]
    owner, code = sets.flat()
    asked = bucket_keys(code, buckets)
    place = np.minimum(np.searchsorted(key, asked), len(key) - 1)
    shared = key[place] == asked
    owner, code, held = owner[shared], code[shared], times[place[shared]]
    order = np.lexsort((code, held, owner))
    owner, code = owner[order], code[order]
    first = np.flatnonzero(np.append(True, owner[1:] != owner[:-1])) if len(owner) else np.zeros(0, np.int64)
    for a, z in zip(first, np.append(first[1:], len(owner))):
        d = int(owner[a])
        size, need = int(sets.count[d]), least_overlap(int(sets.count[d]), num, den)
        if z - a >= need:
            yield d, code[a:z], z - a - need + 1


class Forest:
    """Union-find with the least member as root."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.find(i), self.find(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        return True


class PrefixTree:
    """Sets of ranks (ascending) in lexicographic order, as a tree of compressed edges."""

    def __init__(self, rows: list[np.ndarray]):
        self.rows = rows
        parent, low, high, leaf = [-1], [0], [0], [-1]  # an edge is a slice of one row's ranks
        owner = [0]
        stack = [0]
        depth = [0]
        for i, r in enumerate(rows):
            common = 0
            if i:
                p = rows[i - 1]
                m = min(len(p), len(r))
                differ = np.flatnonzero(p[:m] != r[:m])
                common = int(differ[0]) if len(differ) else m
            while depth[stack[-1]] > common:
                top = stack.pop()
                above = stack[-1]
                if depth[above] < common:  # split the edge
                    middle = len(parent)
                    parent.append(above)
                    owner.append(owner[top])
                    low.append(low[top])
                    high.append(common)
                    leaf.append(-1)
                    depth.append(common)
                    parent[top], low[top] = middle, common
                    stack.append(middle)
            parent.append(stack[-1])
            owner.append(i)
            low.append(common)
            high.append(len(r))
            leaf.append(i)
            depth.append(len(r))
            stack.append(len(parent) - 1)
        self.parent, self.leaf, self.depth = np.array(parent), np.array(leaf), np.array(depth)
        owner, low, high = np.array(owner), np.array(low), np.array(high)
        n = len(parent)
        size = high - low
        self.begin = np.cumsum(size) - size
        self.token = np.concatenate([rows[o][a:z] for o, a, z in zip(owner, low, high)]) if n else np.zeros(0, np.int64)
        self.size = size
        level = np.zeros(n, np.int64)
        todo = np.argsort(self.depth, kind="stable")
        for v in todo.tolist():
            if self.parent[v] >= 0:
                level[v] = level[self.parent[v]] + 1
        self.levels = level
        by_parent = np.argsort(self.parent, kind="stable")
        self.kids = by_parent
        self.kid_from = np.searchsorted(self.parent[by_parent], np.arange(n))
        self.kid_to = np.searchsorted(self.parent[by_parent], np.arange(n), "right")

    def summarize(self, sizes: np.ndarray, label: np.ndarray) -> tuple[np.ndarray, ...]:
        """Below each node: longest rest, least and greatest set size, least and greatest label."""
        n = len(self.parent)
        big = np.iinfo(np.int64).max
        rest, least, most = np.zeros(n, np.int64), np.full(n, big), np.zeros(n, np.int64)
        low, high = np.full(n, big), np.full(n, -1)
        at = self.leaf >= 0
        least[at] = most[at] = sizes[self.leaf[at]]
        low[at] = high[at] = label[self.leaf[at]]
        for lv in range(int(self.levels.max()), 0, -1):
            v = np.flatnonzero(self.levels == lv)
            p = self.parent[v]
            np.maximum.at(rest, p, rest[v] + self.size[v])
            np.minimum.at(least, p, least[v])
            np.maximum.at(most, p, most[v])
            np.minimum.at(low, p, low[v])
            np.maximum.at(high, p, high[v])
        return rest, least, most, low, high


def link_sets(sets: list[np.ndarray], sizes: list[int], num: int, den: int) -> list[tuple[int, int]]:
    """Links that join all sets with ``den * common >= num * union``: a forest, not all pairs.

    ``sets`` hold the n-grams that several sets share, ``sizes`` count all of them.
    """
    n = len(sets)
    if n < 2:
        return []
    flat = np.concatenate(sets)
    known, inverse, times = np.unique(flat, return_inverse=True, return_counts=True)
    rank = np.empty(len(known), np.int64)
    rank[np.lexsort((known, -times))] = np.arange(len(known))
    ranks = rank[inverse]
    cuts = np.cumsum([len(s) for s in sets])[:-1]
    rows = [np.sort(r) for r in np.split(ranks, cuts)]
    order = sorted(range(n), key=lambda i: rows[i].astype(">i8").tobytes())
    rows = [rows[i] for i in order]
    size = np.array([sizes[i] for i in order], np.int64)
    forest, links = Forest(n), []

    def fits(common: int, a: int, b: int) -> bool:
        return common > 0 and den * common >= num * (a + b - common)

    mask = np.zeros(len(known) + 1, bool)
    for i in range(n - 1):
        common = len(np.intersect1d(rows[i], rows[i + 1], assume_unique=True))
        if fits(common, int(size[i]), int(size[i + 1])) and forest.join(i, i + 1):
            links.append((order[i], order[i + 1]))
    label = np.array([forest.find(i) for i in range(n)])
    if (label == label[0]).all():
        return links
    tree = PrefixTree(rows)
    rest, least, most, low, high = tree.summarize(size, label)
    changed = 0
    for i in range(n):
        if changed > 64 + n // 16:  # labels grow coarser: cut more subtrees
            label = np.array([forest.find(k) for k in range(n)])
            if (label == label[0]).all():
                break
            rest, least, most, low, high = tree.summarize(size, label)
            changed = 0
        mine = int(label[i])
        x, a = rows[i], int(size[i])
        mask[x] = True
        before = np.zeros(1, np.int64)
        node = np.zeros(1, np.int64)
        while len(node):
            count = tree.kid_to[node] - tree.kid_from[node]
            if not count.sum():
                break
            had = np.repeat(before, count)
            kid = tree.kids[np.repeat(tree.kid_from[node], count) + np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)]
            go = ~((low[kid] == mine) & (high[kid] == mine)) & (den * most[kid] >= num * a) & (den * a >= num * least[kid])
            kid, had = kid[go], had[go]
            if not len(kid):
                break
            width = tree.size[kid]
            token = tree.token[np.repeat(tree.begin[kid] - (np.cumsum(width) - width), width) + np.arange(int(width.sum()))]
            inside = np.concatenate([[0], np.cumsum(mask[token])])
            stop = np.cumsum(width)
            got = had + inside[stop] - inside[stop - width]
            last = np.where(width > 0, token[np.maximum(stop - 1, 0)] if len(token) else -1, -1)
            left = np.where(width > 0, len(x) - np.searchsorted(x, last, "right"), len(x))
            best = got + np.minimum(left, rest[kid])
            floor = np.maximum(least[kid], least_overlap(a, num, den))
            go = den * best >= num * (a + floor - best)
            kid, got = kid[go], got[go]
            for k, common in zip(kid[tree.leaf[kid] >= 0].tolist(), got[tree.leaf[kid] >= 0].tolist()):
                j = int(tree.leaf[k])
                if j != i and fits(common, a, int(size[j])) and forest.join(i, j):
                    links.append((order[i], order[j]))
                    changed += 1
            node, before = kid, got
        mask[x] = False
    return links


def text_hashes():
    """Two hashes that tell texts apart (null as empty)."""
    text = F.coalesce("text", F.lit(""))
    return F.xxhash64(text), F.xxhash64(F.lit(1), text)


def told_sets(docs: DataFrame, n: int, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """Every row's set (size and two keys), and the least doc_id and first row of its group by the keys.

    Staged: ``doc_id, text1, text2, n_shingles, key1, key2, ...`` and ``key1, key2,
    component_id, keeper``. ``text1, text2`` are hashes of the text.
    """
    ship_package(docs.sparkSession)
    known = docs.select("doc_id", "text")
    parts, buckets = pieces_for(known, PART_BYTES), pieces_for(known, BUCKET_BYTES)
    text1, text2 = text_hashes()
    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", text1.alias("text1"), text2.alias("text2"))
    dealt = dealt.withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int")).repartition(pieces_for(known, EXCHANGE_BYTES, most=MOST_PARTITIONS), "part")

    def offer(table):
        sets = Sets(table, n)
        _, code = sets.flat()
        key, times = np.unique(bucket_keys(code, buckets), return_counts=True)
        rows = [(b, pack(c, t.astype(np.uint32))) for b, c, t in by_bucket(key, times)]
        part = table.column("part")[0].as_py()
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "part": pa.array([part] * len(rows), pa.int32()), "cell": pa.array([r[1] for r in rows], pa.binary())})

    def answer(table):
        bucket = table.column("bucket")[0].as_py()
        rows = [(p, c) for p, c in zip(table.column("part").to_pylist(), count_cells(table.column("cell").to_pylist())) if c is not None]
        return pa.table({"part": pa.array([r[0] for r in rows], pa.int32()), "bucket": pa.array([bucket] * len(rows), pa.int32()), "cell": pa.array([r[1] for r in rows], pa.binary())})

    def tell(left, right):
        names = ["doc_id", "text1", "text2", "n_shingles", "key1", "key2", "prefix", "shared"]
        types = [pa.int64()] * 7 + [pa.binary()]
        if not left.num_rows:
            return pa.table([pa.array([], t) for t in types], names)
        sets = Sets(left, n)
        prefix, shared = [None] * len(sets.ids), [None] * len(sets.ids)
        for d, code, width in surviving(sets, list(zip(right.column("bucket").to_pylist(), right.column("cell").to_pylist())), buckets, num, den):
            prefix[d], shared[d] = width, pack(code)
        columns = [sets.count, sets.key1.view(np.int64), sets.key2.view(np.int64), prefix, shared]
        return pa.table([*(left.column(c) for c in names[:3]), *(pa.array(c, t) for c, t in zip(columns, types[3:]))], names)

    offered = dealt.groupBy("part").applyInArrow(tidy(offer), "bucket int, part int, cell binary")
    answered = offered.groupBy("bucket").applyInArrow(tidy(answer), "part int, bucket int, cell binary")
    told = dealt.groupBy("part").cogroup(answered.groupBy("part")).applyInArrow(tidy(tell), "doc_id long, text1 long, text2 long, n_shingles long, key1 long, key2 long, prefix long, shared binary")
    told = stage(told, "sets")

    # one row a distinct set; equal sets of different parts meet here, one row a part at most; the numbers are fixed by the write
    sets = told.filter("shared is not null").groupBy("key1", "key2").agg(F.first("n_shingles").alias("n"), F.first("prefix").alias("prefix"), F.first("shared").alias("shared"))
    sets = stage(sets.withColumn("node", F.monotonically_increasing_id()), "distinct_sets")

    def prefixes(batches):
        for b in batches:
            for node, width, cell in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                code = unpack(cell)[0][:width]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(code), node), pa.int64()), pa.array(code.view(np.int64), pa.int64())], ["node", "gram"])

    rows = sets.select("node", "prefix", "shared").mapInArrow(prefixes, "node long, gram long")
    rows = stage(rows, "prefixes")
    heads = rows.groupBy("gram").agg(F.min("node").alias("head"), F.count("*").alias("m")).filter("m > 1").drop("m")
    near = components(rows.join(heads, "gram").select(F.col("node").alias("a"), F.col("head").alias("b")))
    clusters = sets.select("node", "n", "shared").join(near.withColumnRenamed("component", "cluster"), "node")
    linked = components(_walk(stage(clusters, "clusters"), num, den))

    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text1", "text2")
    firsts = told.filter("n_shingles > 0").groupBy("key1", "key2").agg(F.min("doc_id").alias("first"), F.min(row).alias("row"))
    owned = firsts.join(sets.select("key1", "key2", "node").join(linked, "node").drop("node"), ["key1", "key2"], "left")
    leasts = owned.filter("component is not null").groupBy("component").agg(F.min("first").alias("least"), F.min("row").alias("least_row"))
    placed = owned.join(leasts, "component", "left").select("key1", "key2", F.when(F.col("component").isNull(), F.col("first")).otherwise(F.col("least")).alias("component_id"), F.when(F.col("component").isNull(), F.col("row")).otherwise(F.col("least_row")).alias("keeper"))
    return told, placed


def ngram_components(docs: DataFrame, n: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """Every document's set size and the least doc_id it reaches over links.

    Words are runs of bytes that are neither space nor tab to carriage return, A to Z
    lower-cased; a set holds the distinct runs of ``n`` words, of fewer words the whole
    sequence. A null text, or one without words, has the empty set and links with
    nothing. Two documents link when ``den * common >= num * union``. Repeated ids are
    separate rows (their rows may differ); a null id is a component of its own unless
    it links. Other columns are ignored; an empty table gives an empty result.
    """
    told, placed = told_sets(docs, n, num, den)
    out = told.select("doc_id", "n_shingles", "key1", "key2").join(placed.drop("keeper"), ["key1", "key2"], "left")
    alone = F.col("n_shingles") == 0
    return out.select("doc_id", "n_shingles", F.when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def first_of_each_group(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """The rows of ``docs`` without near copies: of each group of linked rows one of least doc_id stays.

    Rows are told apart by id and text, not by the id alone: a row that is linked with
    nothing stays, whatever other rows of its id are. A null id is larger than all
    others. Rows without words stay, repeated ones too; an empty table stays empty.
    """
    told, placed = told_sets(docs, n, num, den)
    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text1", "text2")
    judged = told.filter("n_shingles > 0").select("doc_id", "text1", "text2", "key1", "key2").join(placed, ["key1", "key2"]).withColumn("gone", row != F.col("keeper"))
    # one row for each id and text that goes, or that stays but is there more than once
    special = judged.groupBy("doc_id", "text1", "text2").agg(F.every("gone").alias("gone"), F.count("*").alias("times")).filter("gone or times > 1")
    special = stage(special.select(F.col("doc_id").alias("_id"), F.col("text1").alias("_1"), F.col("text2").alias("_2"), "gone"), "near_copies")
    text1, text2 = text_hashes()
    rows = docs.withColumn("_text1", text1).withColumn("_text2", text2)
    here = F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (F.col("_text1") == F.col("_1")) & (F.col("_text2") == F.col("_2"))
    if special.filter("not gone").limit(1).count() == 0:
        return rows.join(special, here, "left_anti").select(*docs.columns)
    met = rows.join(special, here, "left")
    several = met.filter("not gone").dropDuplicates(["doc_id", "_text1", "_text2"])
    return met.filter("gone is null").unionByName(several).select(*docs.columns)


def _walk(clusters: DataFrame, num: int, den: int) -> DataFrame:
    """Links inside clusters of ``node, n, shared, cluster``, enough to join all that link."""
    sizes = stage(clusters.groupBy("cluster").agg(F.count("*").alias("_m")), "cluster_sizes")
    small = clusters.join(sizes.filter(F.col("_m") <= BLOCK), "cluster").select("cluster", "node", "n", "shared")
    links = small.groupBy("cluster").applyInArrow(tidy(_walker(num, den)), "a long, b long")
    if sizes.filter(F.col("_m") > BLOCK).limit(1).count() == 0:
        return links
    links = stage(links, "links_of_small_clusters")
    large = clusters.join(sizes.filter(F.col("_m") > BLOCK), "cluster")
    large = stage(number_within(large, ["cluster"], ["n", "node"], "_row").withColumn("_b", F.floor(F.col("_row") / BLOCK).cast("int")), "large_clusters")

    # every block with the leaders of its cluster: LEADERS rows a block, so work grows with the cluster
    stride = F.ceil(F.col("_m") / LEADERS)
    leaders = large.filter(F.col("_row") % stride == 0).withColumn("leader", F.floor(F.col("_row") / stride).cast("int"))
    beside = leaders.withColumn("_b", F.explode(F.sequence(F.lit(0), F.floor((F.col("_m") - 1) / BLOCK).cast("int"))))
    columns = ["cluster", "_b", "leader", "node", "n", "shared"]
    tasks = large.withColumn("leader", F.lit(-1)).select(*columns).unionByName(beside.select(*columns))

    def alone(table):
        leader = np.array(table.column("leader").to_pylist())
        members, heads = table.take(np.flatnonzero(leader < 0)), table.take(np.flatnonzero(leader >= 0))
        far = np.ones((members.num_rows, LEADERS))
        size = np.array(members.column("n").to_pylist(), np.int64)
        sets = [unpack(c)[0] for c in members.column("shared").to_pylist()]
        flat, width = np.concatenate(sets), np.fromiter(map(len, sets), np.int64, len(sets))
        stop = np.cumsum(width)
        node = members.column("node").to_pylist()
        told = walk(members)
        a, b = told.column("a").to_pylist(), told.column("b").to_pylist()
        for k, name, m, cell in zip(heads.column("leader").to_pylist(), heads.column("node").to_pylist(), heads.column("n").to_pylist(), heads.column("shared").to_pylist()):
            inside = np.concatenate([[0], np.cumsum(np.isin(flat, unpack(cell)[0]))])
            common = inside[stop] - inside[stop - width]
            union = size + m - common
            far[:, k] = 1.0 - common / union
            hit = np.flatnonzero((common > 0) & (den * common >= num * union))
            a += [name] * len(hit)
            b += [node[i] for i in hit]
        rows = len(node) + len(a)
        lists = pa.ListArray.from_arrays(pa.array(np.append(np.arange(0, far.size + 1, LEADERS), np.full(len(a), far.size)).astype(np.int32)), pa.array(far.ravel()))
        return pa.table({"node": pa.array(node + a, pa.int64()), "other": pa.array([None] * len(node) + b, pa.int64()), "far": lists.slice(0, rows)})

    walk = _walker(num, den)
    first = stage(tasks.groupBy("cluster", "_b").applyInArrow(tidy(alone), "node long, other long, far array<double>"), "blocks_alone")
    near = first.filter("other is not null").select(F.col("node").alias("a"), F.col("other").alias("b"))
    label = components(near)
    members = large.drop("_b", "_row", "_m").join(first.filter("other is null").select("node", "far"), "node").join(label, "node", "left").withColumn("label", F.coalesce("component", "node")).drop("component")
    members = stage(members, "members")
    counts = members.groupBy("cluster", "label").agg(F.count("*").alias("c"))
    main = counts.groupBy("cluster").agg(F.max_by("label", F.struct("c", "label")).alias("main"))
    sided = members.join(main, "cluster").withColumn("_main", F.col("label") == F.col("main")).drop("main")
    placed = number_within(sided, ["cluster", "_main"], ["n", "node"], "_row").withColumn("_b", F.floor(F.col("_row") / BLOCK).cast("int"))
    placed = stage(placed.select("cluster", "_main", "_b", "node", "n", "shared", "far", "label"), "placed_members")
    ends = [f(F.col("far")[k]).alias(f"{name}{k}") for k in range(LEADERS) for name, f in (("low", F.min), ("high", F.max))]
    block = placed.groupBy("cluster", "_main", "_b").agg(F.min("n").alias("least"), F.max("n").alias("most"), *ends)
    # what is in the largest component needs no meeting with its like
    left = block.filter("not _main").select([F.col(c).alias(f"l{c}") for c in block.columns])
    right = block.select([F.col(c).alias(f"r{c}") for c in block.columns])
    slack = (den - num) / den + 1e-9
    meet = (F.col("lcluster") == F.col("rcluster")) & (F.col("r_main") | (F.col("r_b") >= F.col("l_b")))
    meet &= (F.col("lmost") * den >= F.col("rleast") * num) & (F.col("rmost") * den >= F.col("lleast") * num)
    for k in range(LEADERS):
        meet &= (F.col(f"llow{k}") - F.col(f"rhigh{k}") <= slack) & (F.col(f"rlow{k}") - F.col(f"lhigh{k}") <= slack)
    pairs = stage(left.join(right, meet).select(F.col("lcluster").alias("cluster"), F.col("l_b").alias("i"), F.col("r_main").alias("side"), F.col("r_b").alias("j")), "block_pairs")
    as_left = placed.filter("not _main").join(pairs.withColumnRenamed("i", "_b"), ["cluster", "_b"]).select("cluster", F.col("_b").alias("i"), "side", "j", "node", "n", "shared")
    same = (F.col("side") == F.lit(False)) & (F.col("j") == F.col("i"))
    as_right = placed.join(pairs.filter(~same).withColumnsRenamed({"side": "_main", "j": "_b"}), ["cluster", "_main", "_b"]).select("cluster", "i", F.col("_main").alias("side"), F.col("_b").alias("j"), "node", "n", "shared")
    last = as_left.unionByName(as_right).groupBy("cluster", "i", "side", "j").applyInArrow(tidy(walk), "a long, b long")
    return links.unionByName(near).unionByName(last)


def _walker(num: int, den: int):
    """A grouped function: links of the sets of one table, by the tree walk."""

    def walk(table):
        node, size = table.column("node").to_pylist(), table.column("n").to_pylist()
        order = sorted(range(len(node)), key=node.__getitem__)
        sets = [unpack(table.column("shared")[i].as_py())[0] for i in order]
        links = link_sets(sets, [size[i] for i in order], num, den)
        name = [node[i] for i in order]
        return pa.table({"a": pa.array([name[i] for i, _ in links], pa.int64()), "b": pa.array([name[j] for _, j in links], pa.int64())})

    return walk
