"""Removal of byte strings that also start in a document of smaller id.

Suffixes are ordered only through their first ``length`` bytes, by passes over digits of
eight bytes from the left; equal groups after the last pass are exactly the repeated
windows. Ordering all windows would move fifty times the text, so four things keep the
work small:

* Every window elects the 20-byte gram of least hash inside it. Equal windows elect
  the same gram, so only windows whose gram occurs in two documents can repeat; a
  first exchange of 32-bit gram codes finds these grams.
* Consecutive windows that elect one gram travel as one context of at most 80 bytes.
* A stretch that repeats itself (blanks, dashes) travels as one period of windows.
* Equal contexts, compared byte by byte, of one part of the documents are settled there:
  one copy is sent, that of the least id. A passage of a third of all documents costs
  one context a part. Where the contexts meet, equal ones are settled again, and only
  the windows of different ones are ordered.

Hashes only choose what is compared; what is removed is equal in its bytes.

Documents are dealt to parts by a hash of their id, once; the three steps that need
texts read the same exchange.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.llm.blobs import byte_values, gather, mix, pack, tidy, unpack
from kmfold.staging import MOST_PARTITIONS, pieces_for, ship_package

LENGTH, GRAM = 50, 20
ELECT = LENGTH - GRAM + 1
PART_BYTES, EXCHANGE_BYTES, BUCKET_BYTES = 1 << 20, 4 << 20, 1 << 20
INDEX = np.uint64((1 << 24) - 1)
SLICE = 1 << 20
VALUES = byte_values()
LAST_ID = np.int64(2**63 - 1)
#: Places of the digits of a window, and of the words of a context (clipped to its end).
DIGIT = 8
DIGITS = (*range(0, LENGTH - DIGIT, DIGIT), LENGTH - DIGIT)
WORDS = np.arange(0, LENGTH + ELECT - 1, DIGIT)


def gram_codes(buf: np.ndarray) -> np.ndarray:
    """A 64-bit code of the ``GRAM`` bytes that start at each position."""
    if len(buf) < GRAM:
        return np.zeros(0, np.uint64)
    one = VALUES[buf]

    def double(h: np.ndarray, step: int, factor: int) -> np.ndarray:
        return h[:-step] * np.uint64(factor) + h[step:]

    two = double(one, 1, 0x9FB21C651E98DF25)
    four = double(two, 2, 0xC2B2AE3D27D4EB4F)
    eight = double(four, 4, 0x165667B19E3779F9)
    sixteen = double(eight, 8, 0x27D4EB2F165667C5)
    n = len(buf) - GRAM + 1
    return mix(sixteen[:n] * np.uint64(0xFF51AFD7ED558CCD) + four[16 : 16 + n])


def digits(buf: np.ndarray) -> np.ndarray:
    """The eight bytes that start at each position as one number, in the order of the bytes."""
    if len(buf) < DIGIT:
        return np.zeros(0, np.uint64)
    two = (buf[:-1].astype(np.uint64) << np.uint64(8)) | buf[1:]
    four = (two[:-2] << np.uint64(16)) | two[2:]
    return (four[:-4] << np.uint64(32)) | four[4:]


def context_words(number: np.ndarray, at: np.ndarray, width: np.ndarray) -> np.ndarray:
    """All bytes of contexts of at most 80 bytes, as ten numbers each (the last ones overlap)."""
    return number[at[:, None] + np.minimum(WORDS[None, :], width[:, None] - DIGIT)]


def settle_equal(same: np.ndarray, words: np.ndarray, width: np.ndarray, total: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Which contexts have an equal one of smaller id. ``same`` is a hash, the bytes decide."""
    order = np.lexsort((ids, same))
    if not len(order):
        return np.zeros(0, bool)
    ordered = same[order]
    head = np.append(True, ordered[1:] != ordered[:-1])
    first = order[np.maximum.accumulate(np.where(head, np.arange(len(order)), 0))]
    equal = (width[order] == width[first]) & (total[order] == total[first]) & (words[order] == words[first]).all(axis=1)
    out = np.zeros(len(order), bool)
    out[order] = equal & (ids[order] > ids[first])
    return out


class Part:
    """The documents of a part in a fixed order, as one buffer of bytes."""

    def __init__(self, table: pa.Table):
        ids = [LAST_ID if d is None else d for d in table.column("doc_id").to_pylist()]
        texts = [(t or "").encode("utf-8", "surrogatepass") for t in table.column("text").to_pylist()]
        self.order = order = sorted(range(len(ids)), key=lambda i: (ids[i], texts[i]))
        self.ids = np.array([ids[i] for i in order], np.int64)
        self.null = [table.column("doc_id")[i].as_py() is None for i in order]
        self.texts = [texts[i] for i in order]
        self.size = np.fromiter(map(len, self.texts), np.int64, len(order))
        self.start = np.cumsum(self.size) - self.size

    def slices(self):
        """Runs of documents that start within ``SLICE`` bytes and end within ``INDEX`` (one document at least)."""
        i, ends = 0, self.start + self.size
        while i < len(self.ids):
            stop = min(np.searchsorted(self.start, self.start[i] + SLICE), np.searchsorted(ends, self.start[i] + int(INDEX), "right"))
            stop = max(i + 1, int(stop))
            yield i, stop
            i = stop

    def runs(self):
        """Windows that elect one gram: document, first window in it, number of windows, period, gram code; and the bytes.

        The period is 0, or that of a stretch whose windows repeat themselves.
        """
        for i, stop in self.slices():
            for lo, hi, base, buf in self._cuts(i, stop):
                yield self._runs_of(lo, hi, base, buf)

    def _cuts(self, i: int, stop: int):
        # a text above 2^24 bytes is alone and cut with an overlap of LENGTH - 1: every window is whole in one cut
        if self.size[i:stop].sum() <= int(INDEX):
            yield i, stop, 0, np.frombuffer(b"".join(self.texts[i:stop]), np.uint8)
            return
        whole = np.frombuffer(self.texts[i], np.uint8)
        for at in range(0, len(whole) - LENGTH + 1, SLICE):
            yield i, stop, at, whole[at : at + SLICE + LENGTH - 1]

    def _runs_of(self, lo: int, hi: int, base: int, buf: np.ndarray):
        sizes = self.size[lo:hi] if hi - lo > 1 else np.array([len(buf)])
        starts = np.cumsum(sizes) - sizes
        codes = gram_codes(buf)
        n = len(buf) - LENGTH + 1
        if n < 1:
            return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, np.uint64), buf, codes, np.zeros(0, np.int64))
        key = (codes & ~INDEX) | np.arange(len(codes), dtype=np.uint64)
        for step in (1, 2, 4, 8):
            key = np.minimum(key[:-step], key[step:])
        key = np.minimum(key[: len(key) - (ELECT - 16)], key[ELECT - 16 :])
        elected = (key[:n] & INDEX).astype(np.int64)
        inside = np.zeros(n + 1, np.int32)
        long = sizes >= LENGTH
        np.add.at(inside, starts[long], 1)
        np.add.at(inside, (starts + sizes - LENGTH + 1)[long], -1)
        valid = np.cumsum(inside[:-1]) > 0
        new = np.empty(n, bool)
        new[0] = True
        new[1:] = (elected[1:] != elected[:-1]) | (valid[1:] != valid[:-1])
        period = np.zeros(n, np.int64)
        for a, z, step in self._periodic(np.flatnonzero(new), n, valid, elected, codes, buf):
            new[a + 1 : z] = False
            new[a] = True
            if z < n:
                new[z] = True
            period[a] = step
        first = np.flatnonzero(new)
        count = np.diff(np.append(first, n))
        keep = valid[first]
        first, count = first[keep], count[keep]
        doc = np.searchsorted(starts, first, "right") - 1
        # an empty document shares its start with the next one: the last of equal starts is the right one
        return lo + doc, base + first - starts[doc], count, period[first], codes[elected[first]], buf, codes, first

    @staticmethod
    def _periodic(first, n, valid, elected, codes, buf):
        """Stretches of windows ``a`` to ``z`` that repeat every ``step``, found where windows in a row elect one code."""
        code = codes[elected[first]]
        joined = np.append(False, (code[1:] == code[:-1]) & valid[first[1:]] & valid[first[:-1]])
        heads = np.flatnonzero(~joined)
        for i, j in zip(heads.tolist(), np.append(heads[1:], len(first)).tolist()):
            if j - i < 3:
                continue
            a, z = int(first[i]), int(first[j]) if j < len(first) else n
            step = int(elected[first[i + 1]] - elected[first[i]])
            if not 0 < step <= ELECT or z - a < 3 * step:
                continue
            end = z + LENGTH - 1
            differ = np.flatnonzero(buf[a : end - step] != buf[a + step : end])
            edges = np.concatenate([[-1], differ, [end - step - a]])
            k = int(np.diff(edges).argmax())
            start, stop = int(edges[k]) + 1, int(edges[k + 1])  # bytes start to stop + step repeat
            windows = stop + step - start - LENGTH + 1
            if windows >= 3 * step:
                yield a + start, a + start + windows, step


def bucket_and_code(codes: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    f = mix(codes + np.uint64(1))
    return ((f >> np.uint64(33)) % np.uint64(buckets)).astype(np.int64), (f & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def offered_grams(table: pa.Table, buckets: int) -> list[tuple[int, bytes]]:
    """Codes of the elected grams of a part by bucket, with a flag for those of two documents."""
    part = Part(table)
    keys, docs = [], []
    for doc, _, _, _, codes, *_ in part.runs():
        b, c = bucket_and_code(codes, buckets)
        keys.append((b.astype(np.uint64) << np.uint64(32)) | c)
        docs.append(part.ids[doc])
    if not keys:
        return []
    key, doc = np.concatenate(keys), np.concatenate(docs)
    order = np.argsort(key, kind="stable")
    key, doc = key[order], doc[order]
    first = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    if not len(first):
        return []
    several = np.minimum.reduceat(doc, first) != np.maximum.reduceat(doc, first)
    key = key[first]
    bucket = (key >> np.uint64(32)).astype(np.int64)
    cuts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
    code = (key & np.uint64(0xFFFFFFFF)).astype(np.uint32)
    return [(int(bucket[a]), pack(code[a:z], several[a:z].astype(np.uint8))) for a, z in zip(cuts, np.append(cuts[1:], len(key)))]


def repeated_grams(cells: list[bytes]) -> list[bytes | None]:
    """For each part's cell of a bucket, its codes that occur in two documents."""
    parts = [unpack(c) for c in cells]
    code = np.concatenate([p[0] for p in parts])
    flag = np.concatenate([p[1] for p in parts]).astype(bool)
    order = np.argsort(code, kind="stable")
    ordered = code[order]
    same = ordered[1:] == ordered[:-1]
    hit = np.zeros(len(code), bool)
    hit[order[1:]] |= same
    hit[order[:-1]] |= same
    hit |= flag
    out, at = [], 0
    for p in parts:
        mine = p[0][hit[at : at + len(p[0])]]
        at += len(p[0])
        out.append(pack(mine) if len(mine) else None)
    return out


def merge_spans(doc: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Overlapping or touching spans of a document as one."""
    if not len(doc):
        return doc, start, stop
    order = np.lexsort((start, doc))
    doc, start, stop = doc[order], start[order], stop[order]
    # running maximum inside each document: shift documents apart so that one accumulate serves all
    gap = int(stop.max()) + 1
    reach = np.maximum.accumulate(stop + doc * gap)
    new = np.append(True, (doc[1:] != doc[:-1]) | (start[1:] + doc[1:] * gap > reach[:-1]))
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(doc)) - 1
    return doc[first], start[first], reach[last] - doc[last] * gap


def contexts(table: pa.Table, replies: list[tuple[int, bytes]], buckets: int):
    """Contexts to send by bucket, and spans settled inside the part.

    Yields ``(bucket, cell)`` with document row, id, first window, windows and bytes,
    then ``(None, cell)`` with the settled spans.
    """
    part = Part(table)
    wanted = np.sort(np.concatenate([(np.uint64(b) << np.uint64(32)) | unpack(c)[0].astype(np.uint64) for b, c in replies])) if replies else np.zeros(0, np.uint64)
    held = []
    for doc, first, total, period, codes, buf, grams, at in part.runs():
        b, c = bucket_and_code(codes, buckets)
        key = (b.astype(np.uint64) << np.uint64(32)) | c
        place = np.searchsorted(wanted, key)
        found = (wanted[np.minimum(place, len(wanted) - 1)] == key) if len(wanted) else np.zeros(len(key), bool)
        doc, first, total, period, b, at = doc[found], first[found], total[found], period[found], b[found], at[found]
        count = np.where(period > 0, period, total)
        words = context_words(digits(buf), at, count + LENGTH - 1)
        held.append((doc, first, total, count, b, context_codes(grams, at, count, total), words, at, [buf]))
    if not held:
        return
    doc, first, total, count, bucket, same, words, at = (np.concatenate([h[k] for h in held]) for k in range(8))
    source = np.repeat(np.arange(len(held)), [len(h[0]) for h in held])
    ids = part.ids[doc]
    settled = settle_equal(same, words, count, total, ids)
    d, s, e = merge_spans(doc[settled], first[settled], (first + total + LENGTH - 1)[settled])
    if len(d):
        yield None, pack(d, s, e)
    out = np.flatnonzero(~settled)
    out = out[np.argsort(bucket[out], kind="stable")]
    cuts = np.flatnonzero(np.append(True, np.diff(bucket[out]) != 0)) if len(out) else np.zeros(0, np.int64)
    for a, z in zip(cuts, np.append(cuts[1:], len(out))):
        rows = out[a:z]
        raw = np.concatenate([held[source[r]][8][0][at[r] : at[r] + count[r] + LENGTH - 1] for r in rows])
        yield int(bucket[rows[0]]), pack(doc[rows].astype(np.int32), ids[rows], first[rows], count[rows].astype(np.uint8), total[rows], raw)


def context_codes(grams: np.ndarray, at: np.ndarray, count: np.ndarray, total: np.ndarray) -> np.ndarray:
    """A hash of each context by its first and last window."""

    def window_code(p):
        return mix(grams[p] * np.uint64(3) + mix(grams[p + GRAM] * np.uint64(5) + grams[p + LENGTH - GRAM]))

    return mix(window_code(at) + np.uint64(7) * window_code(at + count - 1) + mix(count.astype(np.uint64) + (total.astype(np.uint64) << np.uint64(8))))


def radix_groups(number: np.ndarray, at: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Which windows equal one of a smaller id.

    ``at`` are their places in the buffer of ``number`` (eight bytes at each place). Each
    pass orders every group by its next digit, parts it where digits differ, and leaves
    out the groups that one document alone has.
    """
    dup = np.zeros(len(at), bool)
    alive = np.arange(len(at))
    group = np.zeros(len(at), np.int64)
    least = ids
    for place in DIGITS:
        if not len(alive):
            return dup
        digit = number[at[alive] + place]
        order = np.lexsort((digit, group)) if group[-1] else np.argsort(digit, kind="stable")
        alive, group, digit = alive[order], group[order], digit[order]
        first = np.flatnonzero(np.append(True, (group[1:] != group[:-1]) | (digit[1:] != digit[:-1])))
        sizes = np.diff(np.append(first, len(alive)))
        least, most = np.minimum.reduceat(ids[alive], first), np.maximum.reduceat(ids[alive], first)
        two = least != most
        keep = np.repeat(two, sizes)
        least = np.repeat(least, sizes)[keep]
        alive, group = alive[keep], np.repeat(np.arange(int(two.sum())), sizes[two])
    dup[alive] = ids[alive] > least
    return dup


def settle(cells: list[tuple[int, bytes]]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Spans to remove by part, from the contexts of one bucket."""
    doc, ids, first, count, total, raw = gather([c for _, c in cells])
    sizes = [len(gather([c])[0]) for _, c in cells]
    part = np.repeat([p for p, _ in cells], sizes)
    doc, count = doc.astype(np.int64), count.astype(np.int64)
    width = count + LENGTH - 1
    begin = np.cumsum(width) - width
    codes, number = gram_codes(raw), digits(raw)
    whole = settle_equal(context_codes(codes, begin, count, total), context_words(number, begin, width), count, total, ids)
    left = np.flatnonzero(~whole)
    windows = int(count[left].sum())
    owner = np.repeat(left, count[left])
    inner = np.arange(windows) - np.repeat(np.cumsum(count[left]) - count[left], count[left])
    at = begin[owner] + inner
    dup = np.zeros(windows, bool)
    # windows that start alike are in one lane: some MB at a time
    ways = 1 << max(0, (windows >> 20).bit_length())
    lane = codes[at] & np.uint64(ways - 1)
    for k in range(ways):
        mine = np.flatnonzero(lane == np.uint64(k))
        dup[mine] = radix_groups(number, at[mine], ids[owner[mine]])
    new = dup.copy()
    new[1:] &= ~(dup[:-1] & (owner[1:] == owner[:-1]))
    start = np.flatnonzero(new)
    ends = dup.copy()
    ends[:-1] &= ~(dup[1:] & (owner[1:] == owner[:-1]))
    stop = np.flatnonzero(ends)
    where = owner[start]
    a, z = first[where] + inner[start], first[where] + inner[stop] + LENGTH
    # a period stands for all its repetitions: less than a window apart, so their spans are one
    more = (total > count)[where]
    step, most = count[where], total[where] - 1
    last = inner[stop] + (most - inner[stop]) // step * step
    # where the last, cut repetition holds a part of the run only, the run ends with it
    last = np.where((most - inner[start]) // step > (most - inner[stop]) // step, most, last)
    z = np.where(more, first[where] + last + LENGTH, z)
    gone = np.flatnonzero(whole)
    where, a, z = np.concatenate([where, gone]), np.concatenate([a, first[gone]]), np.concatenate([z, first[gone] + total[gone] + LENGTH - 1])
    return {int(p): (doc[where[m]], a[m], z[m]) for p in np.unique(part[where]) for m in [part[where] == p]}


def removed_spans(table: pa.Table, cells: list[bytes]):
    """The part, and for each of its documents the removed spans (merged, in order)."""
    part = Part(table)
    if cells:
        doc, start, stop = merge_spans(*gather(cells))
    else:
        doc = start = stop = np.zeros(0, np.int64)
    lo, hi = np.searchsorted(doc, np.arange(len(part.ids)), "left"), np.searchsorted(doc, np.arange(len(part.ids)), "right")
    return part, [(start[a:z].tolist(), stop[a:z].tolist()) for a, z in zip(lo, hi)]


def keep_bytes(raw: bytes, starts: list[int], stops: list[int]) -> bytes:
    """What is left of ``raw`` without the spans."""
    if not starts:
        return raw
    return b"".join(raw[a:b] for a, b in zip([0, *stops], [*starts, len(raw)]))


def _cells(table: pa.Table, *names: str) -> list[tuple]:
    return list(zip(*(table.column(n).to_pylist() for n in names)))


def with_spans(docs: DataFrame, finish, schema: str, columns: list[str]) -> DataFrame:
    """Find the spans of all documents and let ``finish(table, part, spans)`` make the result of each part.

    ``columns`` (doc_id and text among them) are what ``finish`` sees of the documents.
    """
    ship_package(docs.sparkSession)
    known = docs.select("doc_id", "text")
    parts = pieces_for(known, PART_BYTES)
    buckets = pieces_for(known, BUCKET_BYTES)
    n = pieces_for(known, EXCHANGE_BYTES, most=MOST_PARTITIONS)
    dealt = docs.select(*columns).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int")).repartition(n, "part")

    def offer(table):
        rows = offered_grams(table, buckets)
        part = table.column("part")[0].as_py()
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "part": pa.array([part] * len(rows), pa.int32()), "cell": pa.array([r[1] for r in rows], pa.binary())})

    def answer(table):
        cells = _cells(table, "part", "cell")
        bucket = table.column("bucket")[0].as_py()
        rows = [(p, c) for (p, _), c in zip(cells, repeated_grams([c for _, c in cells])) if c is not None]
        return pa.table({"part": pa.array([r[0] for r in rows], pa.int32()), "bucket": pa.array([bucket] * len(rows), pa.int32()), "cell": pa.array([r[1] for r in rows], pa.binary())})

    def collect(left, right):
        rows = []
        if left.num_rows:
            part = left.column("part")[0].as_py()
            for b, cell in contexts(left, _cells(right, "bucket", "cell"), buckets):
                rows.append((part % buckets if b is None else b, part, b is None, cell))
        return pa.table({"bucket": pa.array([r[0] for r in rows], pa.int32()), "part": pa.array([r[1] for r in rows], pa.int32()), "settled": pa.array([r[2] for r in rows], pa.bool_()), "cell": pa.array([r[3] for r in rows], pa.binary())})

    def order(table):
        rows = _cells(table, "part", "settled", "cell")
        out = [(p, c) for p, done, c in rows if done]
        open_rows = [(p, c) for p, done, c in rows if not done]
        if open_rows:
            out += [(p, pack(*spans)) for p, spans in settle(open_rows).items()]
        return pa.table({"part": pa.array([r[0] for r in out], pa.int32()), "cell": pa.array([r[1] for r in out], pa.binary())})

    def end(left, right):
        if not left.num_rows:
            return pa.table({f.name: pa.array([], f.type) for f in finish_schema})
        return finish(left, *removed_spans(left, right.column("cell").to_pylist()))

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    finish_schema = list(to_arrow_schema(StructType.fromDDL(schema)))
    # all three steps read the same columns, so that Spark reuses one exchange of the texts
    offered = dealt.groupBy("part").applyInArrow(tidy(offer), "bucket int, part int, cell binary")
    answered = offered.groupBy("bucket").applyInArrow(tidy(answer), "part int, bucket int, cell binary")
    sent = dealt.groupBy("part").cogroup(answered.groupBy("part")).applyInArrow(tidy(collect), "bucket int, part int, settled boolean, cell binary")
    spans = sent.groupBy("bucket").applyInArrow(tidy(order), "part int, cell binary")
    return dealt.groupBy("part").cogroup(spans.groupBy("part")).applyInArrow(tidy(end), schema)


def dedup_digests(docs: DataFrame) -> DataFrame:
    """What is removed of each document, and a digest of what is kept.

    A null text counts as empty; texts under ``LENGTH`` bytes lose nothing; rows of
    one id are not removed for each other; a null id counts as the largest long. Other
    columns are ignored; an empty table gives an empty result.
    """

    def finish(table, part, spans):
        kept = [keep_bytes(t, a, z) for t, (a, z) in zip(part.texts, spans)]
        ids = [None if null else int(d) for d, null in zip(part.ids, part.null)]
        return pa.table(
            {
                "doc_id": pa.array(ids, pa.int64()),
                "n_bytes": pa.array(part.size, pa.int64()),
                "n_removed": pa.array([len(t) - len(k) for t, k in zip(part.texts, kept)], pa.int64()),
                "n_spans": pa.array([len(a) for a, _ in spans], pa.int64()),
                "kept_sha256": pa.array([hashlib.sha256(k).hexdigest() for k in kept]),
            }
        )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return with_spans(rows, finish, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string", ["doc_id", "text"])
