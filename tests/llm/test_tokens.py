"""BPE, packing and token files against the libraries."""

import base64
import hashlib
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from kmfold.llm import encoding, packing, tokenfiles

RANKS, JSON = P.path("byte_bpe_50k.tiktoken"), P.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def bpe():
    return encoding.codec(RANKS, P.PATTERN)


@pytest.fixture(scope="module")
def reference():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("reference", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


@pytest.fixture(scope="module")
def library():
    t = Tokenizer.from_file(JSON)
    t.encode_special_tokens = True
    return t


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=300))
def test_bpe_on_any_text(bpe, reference, text):
    ids = bpe.encode_batch([text])[0]
    assert np.frombuffer(ids, "<u4").tolist() == reference.encode_ordinary(text)
    assert bpe.decode(ids) == text.encode("utf-8", "surrogatepass")


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="abcdefgh", min_size=150, max_size=900))
def test_bpe_on_long_pieces(bpe, reference, text):
    assert np.frombuffer(bpe.encode_batch([text])[0], "<u4").tolist() == reference.encode_ordinary(text)


def test_bpe_query_rows(tricky, rows, reference, empty):
    got = {r["doc_id"]: r for r in encoding.round_trip_digests(tricky, RANKS, P.PATTERN).collect()}
    for d, t in rows:
        ids = np.array(reference.encode_ordinary(t or ""), "<u4").tobytes()
        assert got[d]["n_tokens"] == len(ids) // 4 and got[d]["ids_sha256"] == hashlib.sha256(ids).hexdigest()
        assert got[d]["decoded_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
    assert encoding.round_trip_digests(empty, RANKS, P.PATTERN).count() == 0


def test_encode_then_decode_tables(tricky, rows):
    back = encoding.decode_documents(encoding.encode_documents(tricky, RANKS, P.PATTERN), RANKS, P.PATTERN)
    assert {r["doc_id"]: bytes(r["decoded"]) for r in back.collect()} == {d: (t or "").encode() for d, t in rows}


def test_memo_is_bounded(reference, monkeypatch):
    monkeypatch.setattr(encoding, "MEMO_PIECES", 10)
    own = encoding.BpeCodec.from_file(RANKS, P.PATTERN)
    for k in range(5):
        text = " ".join(f"word{k}x{i}" for i in range(50))
        assert np.frombuffer(own.encode_batch([text])[0], "<u4").tolist() == reference.encode_ordinary(text)
        assert len(own.memo) <= 10 or len(own.memo) == 0


@settings(max_examples=100, deadline=None)
@given(st.text(max_size=200))
def test_engine_gives_the_library_ids(library, text):
    tok = tokenfiles.tokenizer(JSON)
    assert tok.engine is not None
    assert tok.encode([text])[0].tolist() == library.encode(text, add_special_tokens=False).ids


def test_engine_gives_the_library_ids_on_documents(spark, sf, library):
    from kmfold.sources.points import table

    texts = [r["text"] or "" for r in table(spark, sf, "documents").select("text").collect()] + ["<|endoftext|> is text"]
    assert [a.tolist() for a in tokenfiles.tokenizer(JSON).encode(texts)] == [e.ids for e in library.encode_batch(texts, add_special_tokens=False)]


ADDED = [(1, "x <|endoftext|> y"), (2, "<|endoftext|><|endoftext|> two\n"), (3, "plain <|endoftext| text"), (4, "end<|endoftext|>")]


def test_added_tokens_have_their_ids(spark):
    plain = Tokenizer.from_file(JSON)
    want = {d: plain.encode(t, add_special_tokens=False).ids for d, t in ADDED}
    assert want[1] == [87, 220, 50256, 331]
    got = tokenfiles.tokenizer(JSON, spell_added=False).encode([t for _, t in ADDED])
    assert [g.tolist() for g in got] == list(want.values())
    docs, start = spark.createDataFrame(ADDED, "doc_id bigint, text string"), 0
    files = {r["doc_id"]: r for r in tokenfiles.token_file_digests(docs, JSON).collect()}
    packed = {r["doc_id"]: r for r in packing.pack_documents(docs, JSON).collect()}
    for d, ids in want.items():
        crc = zlib.crc32(np.array([*ids, 0], "<u4").tobytes())
        assert (files[d]["start"], files[d]["n_tokens"], files[d]["ids_crc32"]) == (start, len(ids) + 1, crc)
        assert (packed[d]["length"], packed[d]["ids_crc32"]) == (len(ids) + 1, crc)
        start += len(ids) + 1


@pytest.fixture(scope="module")
def unchanged():
    return Tokenizer.from_file(JSON)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.sampled_from(["<|endoftext|>", "<|", "|>", " ", "a", "b's", "\n", "é", "12"]), max_size=12).map("".join))
def test_engine_gives_the_ids_of_an_unchanged_library(unchanged, text):
    assert tokenfiles.tokenizer(JSON, spell_added=False).encode([text])[0].tolist() == unchanged.encode(text, add_special_tokens=False).ids


def test_other_files_run_in_the_library():
    tok = tokenfiles.JsonTokenizer(P.path("word_bpe_49k.json"))
    assert tok.engine is None and len(tok.encode(["some words"])[0]) > 0


def all_ids(rows, library):
    return {d: [*library.encode(t or "", add_special_tokens=False).ids, 0] for d, t in rows}


def test_token_files(tricky, rows, library, empty, repeated, monkeypatch):
    monkeypatch.setattr(tokenfiles, "CHUNK_IDS", 3000)
    ids, start = all_ids(rows, library), 0
    got = {r["doc_id"]: r for r in tokenfiles.token_file_digests(tricky, JSON).collect()}
    for d in sorted(ids):
        raw = np.array(ids[d], "<u4").tobytes()
        assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (start, len(ids[d]), zlib.crc32(raw))
        start += len(ids[d])
    assert tokenfiles.token_file_digests(empty, JSON).count() == 0
    again = sorted(r["start"] for r in tokenfiles.token_file_digests(repeated, JSON).collect())
    assert len(set(again)) == 6 and again[0] == 0


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 6), min_size=1, max_size=60), min_size=1, max_size=20))
def test_pair_replacement_round_trip(docs):
    from array import array

    ids = [array("I", d) for d in docs]
    c = tokenfiles.Chunk(tokenfiles.write_chunk(list(range(len(docs))), ids, 7))
    assert c.ids().tolist() == [x for d in docs for x in d]
    assert all(c.document(i).tolist() == d for i, d in enumerate(docs))
    assert all(c.ids_between(i, len(d) // 3, len(d)).tolist() == d[len(d) // 3 :] for i, d in enumerate(docs))
    assert c.lengths.tolist() == [len(tokenfiles.expand(np.array([7 + k]), c.rules, 7)) for k in range(len(c.rules))]


def test_pair_replacement_compresses_repeats():
    from array import array

    c = tokenfiles.write_chunk([1], [array("I", [1, 2, 3, 4] * 5000)], 50257)
    assert len(c) < 20000 * 2 / 4


def frequent_pairs(seq, ends):
    """Pairs inside documents with eight occurrences or more that do not overlap."""
    told, last = {}, {}
    for i, (a, b) in enumerate(zip(seq[:-1].tolist(), seq[1:].tolist())):
        if not ends[i] and last.get((a, b)) != i - 1:
            told[a, b], last[a, b] = told.get((a, b), 0) + 1, i
    return [p for p, n in told.items() if n >= tokenfiles.LEAST_COUNT]


@pytest.mark.parametrize("kind", ["copies", "one symbol", "few symbols"])
def test_pairs_are_replaced_until_none_is_frequent(kind):
    rng = np.random.default_rng(4)
    docs = {"copies": [rng.integers(0, 50000, 300)] * 400, "one symbol": [np.full(5000, 7), np.full(9, 7)], "few symbols": [rng.integers(0, 5, 700) for _ in range(40)]}[kind]
    flat = np.concatenate(docs).astype(np.uint32)
    ends = np.zeros(len(flat), bool)
    ends[np.cumsum([len(d) for d in docs]) - 1] = True
    seq, stop, rules = tokenfiles.replace_pairs(flat, ends, 50257)
    assert tokenfiles.expand(seq, rules, 50257).tolist() == flat.tolist()
    assert not frequent_pairs(seq, stop)
    if kind == "copies":
        assert len(seq) == 400


def test_packing(tricky, rows, library, empty, repeated):
    ids = all_ids(rows, library)
    got = packing.pack_documents(tricky, JSON).collect()
    by_doc, by_sequence = {}, {}
    for r in got:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append(r)
    assert set(by_doc) == set(ids)
    for d, parts in by_doc.items():
        at = 0
        for k, r in enumerate(sorted(parts, key=lambda r: r["piece"])):
            piece = np.array(ids[d][at : at + r["length"]], "<u4").tobytes()
            assert (r["piece"], r["start"], r["ids_crc32"]) == (k, at, zlib.crc32(piece)) and (k == 0 or r["length"] == 2048)
            at += r["length"]
        assert at == len(ids[d])
    for parts in by_sequence.values():
        at = 0
        for r in sorted(parts, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    lower = -(-sum(map(len, ids.values())) // 2048)
    assert len(by_sequence) <= lower + 1
    assert packing.pack_documents(empty, JSON).count() == 0
    assert packing.pack_documents(repeated, JSON).count() == 6


def check_plan(counts, plan, capacity=2048):
    used = np.zeros(capacity + 1, np.int64)
    for copies, config in plan:
        assert sum(n * t for n, t in config) <= capacity and copies > 0
        for n, t in config:
            used[n] += copies * t
    assert (used == counts).all()
    return sum(c for c, _ in plan)


def test_packing_plans_cover_exactly_and_stay_near_the_bound():
    rng = np.random.default_rng(1)
    for lengths in (range(1, 2048), (700, 701, 1025, 400), range(600, 1200), (2048,), (1, 2047), ()):
        counts = np.zeros(2049, np.int64)
        for n in lengths:
            counts[n] = rng.integers(1, 300)
        plan, placed = packing.solve(counts, rounds=40)
        lp, plain = check_plan(counts, plan), sum(c for c, _ in packing.greedy(counts, 2048))
        assert lp <= 1.02 * plain and placed >= 0.9 * counts.sum()


@pytest.fixture(scope="module")
def histogram():
    """Piece lengths of the documents of sf0.1."""
    import pyarrow.parquet as pq

    counts = np.zeros(2049, np.int64)
    texts = pq.read_table("/root/testdata/sf0.1/documents.parquet", columns=["text"]).column("text").to_pylist()
    for ids in tokenfiles.tokenizer(JSON, spell_added=False).encode([t or "" for t in texts]):
        counts[2048] += (len(ids) + 1) // 2048
        counts[(len(ids) + 1) % 2048] += 1
    counts[0] = 0
    return counts


@pytest.mark.parametrize("times", [1, 10])
def test_the_program_places_the_pieces_and_beats_greedy(histogram, times):
    counts = histogram * times
    plan, placed = packing.solve(counts)
    lp, plain = check_plan(counts, plan), sum(c for c, _ in packing.greedy(counts, 2048))
    assert placed >= 0.99 * counts.sum() and lp <= plain
    assert lp <= -(-int((counts * np.arange(2049)).sum()) // 2048) + max(1, 1e-4 * lp)


def test_a_small_packing_is_optimal():
    """Against all partitions of eight pieces."""
    rng = np.random.default_rng(3)
    for _ in range(20):
        pieces = rng.integers(1, 21, 8).tolist()

        def least(i, rooms):
            if i == len(pieces):
                return len(rooms)
            best = least(i + 1, [*rooms, 20 - pieces[i]])
            for k in range(len(rooms)):
                if rooms[k] >= pieces[i]:
                    best = min(best, least(i + 1, [*rooms[:k], rooms[k] - pieces[i], *rooms[k + 1 :]]))
            return best

        counts = np.bincount(pieces, minlength=21)
        assert check_plan(counts, packing.solve(counts, 20)[0], 20) <= least(0, []) + 1


def test_price_is_the_best_multiset():
    value = np.zeros(21)
    value[[3, 7, 9]] = [3.0, 7.5, 9.4]
    best = max(a * 3.0 + b * 7.5 + c * 9.4 for a in range(7) for b in range(3) for c in range(3) if 3 * a + 7 * b + 9 * c <= 20)
    assert abs(sum(value[n] * t for n, t in packing.price(value, 20)) - best) < 1e-9


def test_sequences_hold_their_pieces(spark, tricky):
    import pyspark.sql.functions as F

    placed = packing.pack_documents(tricky.filter("doc_id < 60"), JSON)
    ids = encoding.encode_documents(tricky.filter("doc_id < 60"), RANKS, P.PATTERN)
    tok = {r["doc_id"]: np.frombuffer(r["ids"], "<u4").tolist() + [0] for r in ids.collect()}
    frame = spark.createDataFrame(list(tok.items()), "doc_id bigint, ids array<bigint>")
    total = packing.sequence_rows(placed, frame).agg(F.sum(F.size("ids"))).first()[0]
    assert total == sum(map(len, tok.values()))


def test_many_symbols_expand_as_one_by_one():
    """Runs, nested rules and plain ids: the ids come back from one copy a symbol."""
    import numpy as np
    from kmfold.llm import tokenfiles

    rng = np.random.default_rng(3)
    for vocabulary in (2, 50, 50257):
        ids = np.repeat((rng.zipf(1.3, 4000) % vocabulary).astype(np.uint32), rng.integers(1, 9, 4000))
        ends = rng.random(len(ids)) < 0.01
        ends[-1] = True
        symbols, _, rules = tokenfiles.replace_pairs(ids, ends.copy(), 50257)
        lengths = tokenfiles.expansion_lengths(rules, 50257)
        assert (tokenfiles.expand_all(symbols, rules, lengths, 50257) == ids).all()
        assert (tokenfiles.expand(symbols, rules, 50257) == ids).all()
    assert len(tokenfiles.expand_all(symbols[:0], rules, lengths, 50257)) == 0
