"""Suffix dedup, fingerprints, n-gram links: brute force on a tricky fixture and on given documents."""

import hashlib
import re

import numpy as np
import pytest

from kmfold.llm import blobs, components, fingerprints, ngramjoin, suffixdedup
from kmfold.sources.points import table


def brute_dedup(docs):
    seen, out = {}, {}
    for d, t in sorted(docs, key=lambda r: r[0]):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - 49):
            w = b[i : i + 50]
            if seen.setdefault(w, d) < d:
                gone[i : i + 50] = b"\1" * 50
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[d] = (len(b), sum(gone), sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1])), hashlib.sha256(kept).hexdigest())
    return out


def small_parts(monkeypatch):
    for m in (suffixdedup, ngramjoin):
        # five parts, four buckets and three partitions, whatever the estimate
        monkeypatch.setattr(m, "pieces_for", lambda df, size, least=1, most=0: {1: 5, 2: 4, 3: 3}[size])
        monkeypatch.setattr(m, "PART_BYTES", 1)
        monkeypatch.setattr(m, "BUCKET_BYTES", 2)
        monkeypatch.setattr(m, "EXCHANGE_BYTES", 3)


@pytest.mark.parametrize("many", [False, True])
def test_dedup_on_tricky_texts(tricky, rows, monkeypatch, many):
    if many:
        small_parts(monkeypatch)
    want = brute_dedup(rows)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffixdedup.dedup_digests(tricky).collect()}
    assert got == want


def test_dedup_of_repeated_and_null_ids(repeated, empty):
    got = suffixdedup.dedup_digests(repeated).collect()
    removed = sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_removed"]) for r in got)
    # rows of one id leave one another alone; the null id is larger than all others
    assert removed == [(-1, 0), (-1, 62), (2, 0), (5, 0), (5, 0), (5, 0)]
    assert suffixdedup.dedup_digests(empty).count() == 0


PERIODIC = ["-" * 400, "x" + "-" * 300 + "y", " " * 900, "ab" * 200, "ab" * 333 + "a", "q" + "ab" * 60 + "zz" + "ab" * 150, ("=" * 79 + "\n") * 9, "t" + ("=" * 79 + "\n") * 6 + "end of it", "abcabd" * 90, "dabcab" * 40 + "c", ("0123456789abcdefghijklmnopqrst" * 20), "5" + "0123456789abcdefghijklmnopqrst" * 9, ("0123456789abcdefghijklmnopqrstu" * 12), ("0123456789abcdefghijklmnopqrstuv" * 12) * 2]


@pytest.mark.parametrize("parts", [1, 2, 5])
def test_stretches_that_repeat_themselves(monkeypatch, parts):
    """Blanks, dashed lines and periods up to 32 bytes, equal, longer, shorter and shifted."""
    rng = np.random.default_rng(1)
    texts = list(PERIODIC)
    for _ in range(60):
        t = str(rng.choice(PERIODIC))
        a = int(rng.integers(0, len(t) - 50))
        texts.append("".join(rng.choice(list("klmn"), rng.integers(0, 40))) + t[a : a + int(rng.integers(50, 500))] + "".join(rng.choice(list("opq-"), rng.integers(0, 60))))
    docs = [(i + 1, t) for i, t in enumerate(texts)]
    assert dedup_by_kernels(docs, parts) == brute_dedup(docs)


def test_a_repeating_stretch_is_sent_once():
    import pyarrow as pa

    for text in (" " * 200_000, ("-" * 30) * 5000):
        table = pa.table({"doc_id": [1], "text": [text]})
        offered = suffixdedup.offered_grams(table, 1)
        sent = [c for b, c in suffixdedup.contexts(table, [(0, blobs.pack(blobs.unpack(offered[0][1])[0]))], 1) if b is not None]
        assert sum(len(blobs.unpack(c)[5]) for c in sent) < 1000


def test_equal_hashes_are_not_taken_for_equal_bytes(monkeypatch):
    """With a hash that tells nothing apart the bytes still decide."""
    rng = np.random.default_rng(9)
    base = "".join(rng.choice(list("abcdefgh"), 600))
    docs = [(1, base), (2, base[100:400] + "x" + base[401:]), (3, "z" * 30 + base[:300]), (4, base)]
    monkeypatch.setattr(suffixdedup, "gram_codes", lambda buf: np.zeros(max(0, len(buf) - suffixdedup.GRAM + 1), np.uint64))
    for parts in (1, 3):
        assert dedup_by_kernels(docs, parts) == brute_dedup(docs)


def test_long_texts_in_one_table(spark):
    """Two megabytes: several slices and buckets, on a real exchange."""
    rng = np.random.default_rng(4)
    words = np.array(["".join(w) for w in rng.choice(list("abcdefghijklmnopqrstuvwxyz"), (3000, 6))])

    def text(n):
        return " ".join(words[rng.integers(0, 3000, n)])

    long = text(250_000)
    docs = [(1, text(50)), (2, long), (3, text(400) + long[900_000:1_100_000] + " " * 5000), (4, long[:300] + text(20) + " " * 7000)]
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffixdedup.dedup_digests(spark.createDataFrame(docs, "doc_id bigint, text string")).collect()}
    assert got == brute_dedup(docs)


def dedup_by_kernels(docs, parts):
    """The steps of the operator over tables in memory, with one bucket."""
    import pyarrow as pa

    tables = [pa.table({"doc_id": [d for d, _ in docs[k::parts]], "text": [t for _, t in docs[k::parts]]}) for k in range(parts)]
    offered = [suffixdedup.offered_grams(t, 1) for t in tables]
    told = suffixdedup.repeated_grams([o[0][1] for o in offered])
    cells, sent = {k: [] for k in range(parts)}, []
    for k, t in enumerate(tables):
        for bucket, cell in suffixdedup.contexts(t, [(0, told[k])] if told[k] else [], 1):
            if bucket is None:
                cells[k].append(cell)
            else:
                sent.append((k, cell))
    if sent:
        for k, spans in suffixdedup.settle(sent).items():
            cells[k].append(blobs.pack(*spans))
    got = {}
    for k, t in enumerate(tables):
        part, spans = suffixdedup.removed_spans(t, cells[k])
        for d, raw, (a, z) in zip(part.ids.tolist(), part.texts, spans):
            kept = suffixdedup.keep_bytes(raw, a, z)
            got[d] = (len(raw), len(raw) - len(kept), len(a), hashlib.sha256(kept).hexdigest())
    return got


@pytest.mark.parametrize("parts", [1, 2])
def test_a_text_longer_than_the_index_behind_a_short_one(monkeypatch, parts):
    import pyarrow as pa

    monkeypatch.setattr(suffixdedup, "SLICE", 200)
    monkeypatch.setattr(suffixdedup, "INDEX", np.uint64((1 << 10) - 1))
    rng = np.random.default_rng(0)

    def text(n):
        return bytes(rng.integers(97, 123, n, dtype=np.uint8)).decode()

    long = text(6000)
    docs = [(1, text(80)), (2, text(120)), (3, long), (4, text(30)), (5, long[1100:2900] + text(60) + long[4000:5999]), (6, text(900)), (7, text(60) + long[3000:3100])]
    tables = [pa.table({"doc_id": [d for d, _ in docs[k::parts]], "text": [t for _, t in docs[k::parts]]}) for k in range(parts)]
    assert all(len(run[5]) <= 1023 for t in tables for run in suffixdedup.Part(t).runs())
    assert dedup_by_kernels(docs, parts) == brute_dedup(docs)


def test_merge_spans():
    d, a, z = suffixdedup.merge_spans(np.array([1, 0, 0, 1, 0]), np.array([5, 0, 10, 7, 4]), np.array([9, 5, 12, 8, 9]))
    assert d.tolist() == [0, 0, 1] and a.tolist() == [0, 10, 5] and z.tolist() == [9, 12, 9]


def brute_links(docs, n, num, den):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for _, t in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low))
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set()))
    up = list(range(len(docs)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if sets[i] and sets[j] and den * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j]):
                up[find(i)] = find(j)
    groups = {}
    for i, (d, _) in enumerate(docs):
        groups.setdefault(find(i), []).append(d)
    return {d: (len(sets[i]), min(groups[find(i)])) for i, (d, _) in enumerate(docs)}


@pytest.mark.parametrize(("n", "num", "block"), [(4, 85, 1024), (5, 80, 1024), (2, 40, 1024), (4, 85, 3), (1, 50, 5)])
def test_links_on_tricky_texts(tricky, rows, monkeypatch, n, num, block):
    small_parts(monkeypatch)
    monkeypatch.setattr(ngramjoin, "BLOCK", block)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngramjoin.ngram_components(tricky, n, num, 100).collect()}
    assert got == brute_links(rows, n, num, 100)


def test_a_cluster_of_many_blocks(spark, monkeypatch):
    """A tight group, a chain beside it, and sets that only share a prefix, in blocks of four."""
    rng = np.random.default_rng(8)
    base = [f"w{i}" for i in range(120)]
    docs = []
    for i in range(40):
        words = list(base)
        for k in rng.choice(120, 1 + i % 4, replace=False):
            words[k] = f"x{i}y{k}"
        docs.append((i, " ".join(words)))
    for i in range(30):
        docs.append((100 + i, " ".join(base[3 * i :] + [f"z{k}" for k in range(3 * i)])))
    for i in range(15):
        docs.append((200 + i, " ".join(base[:30] + [f"q{i}r{k}" for k in range(60 + 5 * i)])))
    small_parts(monkeypatch)
    monkeypatch.setattr(ngramjoin, "BLOCK", 4)
    df = spark.createDataFrame(docs, "doc_id bigint, text string").repartition(3)
    for n, num in ((1, 85), (1, 97), (2, 70)):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngramjoin.ngram_components(df, n, num, 100).collect()}
        assert got == brute_links(docs, n, num, 100)


def test_sets_of_one_key_are_told_apart_by_the_other(monkeypatch):
    import pyarrow as pa

    table = pa.table({"doc_id": [1, 2, 3], "text": ["a b c d e", "f g h i j", "a b c d e"]})
    sets = ngramjoin.Sets(table, 4)
    assert len(sets.distinct) == 2 and sets.key1[0] == sets.key1[2] != sets.key1[1] and sets.key2[0] == sets.key2[2] != sets.key2[1]


def test_rows_that_stay(spark, repeated, empty):
    a, b = "one two three four five six seven eight nine ten eleven twelve", "another text with some other words in it than the first has"
    rows = [(2, a, "x"), (5, a, "y"), (5, b, "z"), (None, a + " and", "n"), (7, a, "y"), (9, "", "e"), (9, "", "e"), (9, None, "f"), (11, b, "late"), (12, "alone " * 3, "r"), (12, "alone " * 3, "s")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    got = sorted((r["doc_id"], r["text"] or "-") for r in ngramjoin.first_of_each_group(df).collect())
    assert got == sorted([(2, a), (5, b), (9, "-"), (9, "-"), (9, "-"), (12, "alone " * 3)], key=lambda r: (r[0], r[1]))
    kept = [(r["doc_id"], r["text"]) for r in ngramjoin.first_of_each_group(repeated).collect()]
    assert len(kept) == 3 and (2, "another text") in kept and (None, None) in kept
    assert ngramjoin.first_of_each_group(empty).count() == 0


def test_links_of_repeated_ids_and_empty_tables(repeated, empty):
    got = sorted((r["doc_id"] or 0, r["n_shingles"], r["component_id"]) for r in ngramjoin.ngram_components(repeated).collect() if r["doc_id"] is not None)
    assert got == [(2, 1, 2), (5, 1, 2), (5, 9, 5), (5, 9, 5)]
    assert ngramjoin.ngram_components(empty).count() == 0


def test_tree_walk_against_all_pairs():
    rng = np.random.default_rng(3)
    for trial in range(30):
        base = rng.choice(2000, 60, replace=False)
        sets = []
        for _ in range(25):
            keep = base[rng.random(60) < rng.choice([0.6, 0.9, 0.97])]
            sets.append(np.unique(np.concatenate([keep, rng.integers(0, 3000, rng.integers(0, 12))])).astype(np.uint64))
        num = int(rng.choice([50, 70, 85]))
        f = ngramjoin.Forest(25)
        for i, j in ngramjoin.link_sets(sets, [len(s) for s in sets], num, 100):
            f.join(i, j)
        g = ngramjoin.Forest(25)
        for i in range(25):
            for j in range(i):
                c = len(np.intersect1d(sets[i], sets[j]))
                if 100 * c >= num * (len(sets[i]) + len(sets[j]) - c):
                    g.join(i, j)
        assert [f.find(i) for i in range(25)] == [g.find(i) for i in range(25)], trial


def test_components_of_long_paths(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 105), (105, 103)] + [(7, 7)]
    df = spark.createDataFrame(edges, "a bigint, b bigint")
    got = {r["node"]: r["component"] for r in components.components(df).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 103: 100, 105: 100}
    assert components.components(df.limit(0)).count() == 0


def shingles(t):
    w = t.lower().split()
    return {" ".join(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({" ".join(w)} if w else set())


def test_fingerprints_estimate_likeness(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", "text")
    rows = [(r["doc_id"], r["text"] or "") for r in docs.orderBy("doc_id").collect()]
    told = {r["doc_id"]: r for r in fingerprints.fingerprint_documents(docs).collect()}
    off = []
    for i, (d, t) in enumerate(rows):
        nxt, half = rows[i - 1][1], len(t) // 2
        edited = t[: len(t) - half] + nxt[:half]
        r = told[d]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        for name, other in (("near_edited", edited), ("near_next", nxt)):
            a, b = shingles(t), shingles(other)
            off.append(r[name] - (len(a & b) / len(a | b) if a | b else 1.0))
    assert abs(np.mean(off)) < 0.02 and np.std(off) < 0.05


def test_fingerprints_of_tricky_texts(tricky, repeated, empty, rows):
    told = {r["doc_id"]: r for r in fingerprints.fingerprint_documents(tricky).collect()}
    assert len(told) == len(rows)
    by_text = {}
    for d, t in rows:
        by_text.setdefault(t or "", set()).add(told[d]["fingerprint"])
        assert 0.0 <= told[d]["near_edited"] <= 1.0 and 0.0 <= told[d]["near_next"] <= 1.0
        assert told[d]["fingerprint"] == "" if not (t or "").split() else len(told[d]["fingerprint"]) == 256
    assert all(len(v) == 1 for v in by_text.values())
    assert fingerprints.fingerprint_documents(repeated).count() == 6
    assert fingerprints.fingerprint_documents(empty).count() == 0


def test_fingerprint_plan_is_native(tricky):
    plan = fingerprints.fingerprint_documents(tricky)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_blobs_round_trip():
    a, b = np.arange(5, dtype=np.uint32), np.zeros(0)
    x, y = blobs.unpack(blobs.pack(a, b))
    assert (x == a).all() and len(y) == 0 and x.dtype == a.dtype
