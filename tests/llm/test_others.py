"""Language ID, sharding, URL rules, permutation index, and the corpus pipeline."""

import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from kmfold.llm import ann, langid, sharding, urlfilter
from kmfold.sources.points import table

SF = "/root/testdata/sf0.01"


def test_language_accuracy_on_held_out_rows(spark):
    docs = table(spark, SF, "documents")
    truth = {r["doc_id"]: r["lang"] for r in docs.select("doc_id", "lang").collect()}
    told = langid.identify(docs).collect()
    assert len(told) == len(truth)
    held = [r for r in told if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in told)
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in held]) > 0.95
    assert all(0 <= r["score"] <= 1 and r["lang_pred"] in {"de", "en", "es", "fr"} for r in told)


def test_labels_of_held_out_rows_are_not_used(spark):
    docs = table(spark, SF, "documents")
    lie = docs.withColumn("lang", F.when(langid.held_out(), F.lit("xx")).otherwise(F.col("lang"))).withColumn("source", F.lit("zz"))
    a = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in langid.identify(docs).collect()}
    b = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in langid.identify(lie).collect()}
    assert a == b


def test_language_of_tricky_texts(tricky, rows, empty, repeated):
    told = {r["doc_id"]: r for r in langid.identify(tricky).collect()}
    for d, t in rows:
        if not any(c.isalpha() for c in t or ""):
            assert (told[d]["lang_pred"], told[d]["score"], told[d]["rejected"]) == ("und", 0.0, True)
        else:
            assert told[d]["lang_pred"] in {"en", "de"}
    assert langid.identify(empty).count() == 0 and langid.identify(repeated).count() == 6


def test_a_long_text_is_judged_like_its_blocks():
    rng = np.random.default_rng(2)

    def prose(seed, n):
        words = np.array(["".join(w) for w in np.random.default_rng(seed).choice(list("abcdefghijklmnopqrstuvwxyz"), (4000, 7))])
        return " ".join(words[rng.integers(0, 4000, n)])

    c = langid.DictionaryClassifier({"aa": prose(1, 40_000).encode(), "bb": prose(2, 40_000).encode()})
    text = prose(1, 2_500_000)
    short, long = c.judge(text[: langid.BLOCK_BYTES]), c.judge(text)
    assert short[0] == long[0] == "aa" and not short[2] and not long[2]
    assert abs(long[1] - short[1]) < 0.1 * short[1]


def test_short_labelled_rows_are_learned_from(spark):
    words = {"de": "der hund und die katze schlafen heute nicht", "en": "the dog and the cat are asleep this morning"}
    rows = [(i, f"{words[lang]} {i}", lang) for i, lang in enumerate(["de", "en"] * 30)] + [(100, "12 - 34", "zz")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    assert set(langid.learn(docs)) == {"de", "en"}
    told = {r["doc_id"]: r for r in langid.identify(docs).collect()}
    assert all((told[d]["lang_pred"], told[d]["rejected"]) == (lang, False) for d, _, lang in rows[:-1])
    # a language with short rows only beside one with long rows
    mixed = docs.withColumn("text", F.when(F.col("lang") == "en", F.repeat("text", 8)).otherwise(F.col("text")))
    told = {r["doc_id"]: r["lang_pred"] for r in langid.identify(mixed).collect()}
    assert all(told[d] == lang for d, _, lang in rows[:-1])


def test_long_rows_are_learned_from_first(spark):
    rows = [(i, "langes wort " * 30 if i % 2 else "kurz", "de") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    assert b"kurz" not in langid.learn(docs, rows_each=5)["de"]
    everything = langid.learn(docs)["de"]
    assert b"kurz" in everything and everything.index(b"kurz") > everything.rindex(b"langes")


def test_difference_is_tight():
    rng = np.random.default_rng(0)
    sizes = rng.integers(1, 5000, 3000).tolist()
    ways = sharding.difference(sizes, 8)
    sums = np.bincount(ways, sizes, 8)
    assert sums.max() - sums.min() <= 2
    assert sharding.difference([], 8) == [] and sorted(sharding.difference([5, 5, 5], 3)) == [0, 1, 2]
    assert sharding.difference([8, 7, 6, 5, 4], 2).count(0) in (2, 3)


@pytest.mark.parametrize("law", sharding.LAWS)
def test_shards(tricky, rows, empty, repeated, law):
    got = sharding.shard_documents(tricky, 8, law).collect()
    assert len(got) == len(rows)
    text = dict(rows)
    slots = {}
    for r in got:
        raw = (text[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"]) == (len(raw) + 1, zlib.crc32(raw), law) and 0 <= r["shard"] < 8
        slots.setdefault(r["shard"], []).append(r["slot"])
        if law == "key":
            assert r["grown_shard"] in (r["shard"], 8)
        else:
            assert r["grown_shard"] is None
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    if law == "rows":
        counts = [len(s) for s in slots.values()]
        assert max(counts) - min(counts) <= 1
    if law == "bytes":
        where = {}
        for r in got:
            where.setdefault(text[r["doc_id"]] or "", set()).add(r["shard"])
        assert all(len(s) == 1 for s in where.values())
    assert sharding.shard_documents(empty, 8, law).count() == 0
    assert sharding.shard_documents(repeated, 8, law).count() == 6


def test_shards_balance_documents(spark):
    told = sharding.shard_documents(table(spark, SF, "documents")).groupBy("shard").agg(F.sum("size").alias("b")).collect()
    sums = [r["b"] for r in told]
    assert len(sums) == 8 and max(sums) - min(sums) <= 0.001 * max(sums)


def judge(url, rules):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        end = min([i for c in "/?#" if (i := rest.find(c)) >= 0], default=len(rest))
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in rest[:end])
        tail = rest[end:]
        path = tail[: min([i for c in "?#" if (i := tail.find(c)) >= 0], default=len(tail))]
    fits = [r for r in rules if host and (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    best = max(fits, key=lambda r: (len(r.text), len(r.host)), default=None)
    return host, path, best.text if best else None, best.verdict if best else "allow"


URLS = [None, "", "no scheme", "http://", "http://com/en/x", "http://a.COM/en/7?x=/es/", "http://b.example.com/en/70#f", "https://example.net/de/8/9", "https://x.example.net/de/9", "http://notcom/en/", "http://org/es/", "http://é.org/es/ü", "http://a.org/ES/", "ftp://u:p@h.com:80/en/", "http://h.com/en/", "x://y://z.com/en/7", "http://.com/en/", "http://com", "http://a\nb.com/en/\n7", "http://example.com/en/7", "http://EXAMPLE.com/en/8"]


def test_url_rules(spark):
    pages = spark.createDataFrame([(i // 2, u, "h", "r") for i, u in enumerate([*URLS, *URLS])], "page_id bigint, url string, host string, rule string")
    got = sorted((r["page_id"], r["host"], r["path"], str(r["rule"]), r["verdict"]) for r in urlfilter.judge_urls(pages).collect())
    want = sorted((i // 2, h, p, str(r), v) for i, u in enumerate([*URLS, *URLS]) for h, p, r, v in [judge(u, urlfilter.DEFAULT_RULES)])
    assert got == want
    assert urlfilter.judge_urls(pages.limit(0)).count() == 0
    assert {r["verdict"] for r in urlfilter.judge_urls(pages, [], "block").collect()} == {"block"}


def test_url_rules_say_what_the_contract_says(spark):
    want = {
        "http://a.com/en/1": ("com/en/", "block"), "http://example.com/en/70": ("example.com/en/7", "allow"), "http://a.net/de/8": ("net/de/", "allow"),
        "http://b.example.net/de/9": ("net/de/", "allow"), "http://example.net/de/80": ("example.net/de/8", "block"), "http://x.org/es/": ("org/es/", "block"),
    }
    pages = spark.createDataFrame(list(enumerate(want)), "page_id bigint, url string")
    got = {r["page_id"]: (r["rule"], r["verdict"]) for r in urlfilter.judge_urls(pages).collect()}
    assert [got[i] for i in range(len(want))] == list(want.values())


def test_url_filter_with_a_long_list(spark):
    rules = [urlfilter.Rule("block" if i % 2 else "allow", f"h{i}.com", f"/{'x' * (i % 3)}") for i in range(3000)]
    urls = [f"http://www.h{i}.com/xx/{i}" for i in range(0, 4000, 7)]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in urlfilter.judge_urls(pages, rules).collect()}
    by_host = {r.host: [r] for r in rules}
    for i, u in enumerate(urls):
        assert got[i] == judge(u, by_host.get(u.split("/")[2].removeprefix("www."), []))


def test_bloom_has_no_false_negatives(spark):
    keys = [f"k{i}/p" for i in range(500)]
    b = urlfilter.BlockedBloom(keys)
    df = spark.createDataFrame([(k,) for k in keys + [f"other{i}" for i in range(2000)]], "k string")
    hits = df.crossJoin(b.row(spark)).filter(b.might_hold(F.col("k"), F.col("_bloom"))).select("k").collect()
    got = {r["k"] for r in hits}
    assert set(keys) <= got and len(got) < 500 + 100


def test_a_long_list_still_filters(spark):
    """A hundred thousand keys: 24 bits each, few false hits."""
    b = urlfilter.BlockedBloom([f"k{i}/p" for i in range(100_000)])
    assert b.blocks * 256 >= 24 * 100_000
    df = spark.range(20_000).select(F.concat(F.lit("other"), F.col("id")).alias("k"))
    assert df.crossJoin(b.row(spark)).filter(b.might_hold(F.col("k"), F.col("_bloom"))).count() < 400


def exact(x, ids, q, n):
    s = x @ x[q]
    s[q] = -np.inf
    return [ids[i] for i in np.lexsort((ids, -s))[:n] if np.isfinite(s[i])]


def test_recall_against_brute_force(spark):
    e = table(spark, "/root/testdata/sf0.1", "embeddings")
    rows = e.select("vec_id", "embedding").collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float)
    got = {}
    for r in ann.search(e).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append(r["vec_id"])
    at = {v: i for i, v in enumerate(ids)}
    assert set(got) == {i for i in ids.tolist() if i % 20 == 0}
    assert np.mean([len(set(exact(x, ids, at[q], 20)) & set(v)) / 20 for q, v in got.items()]) >= 0.9


def recall_of(found, rows, least_share=20):
    ids, x = np.array([i for i, _ in rows]), np.array([v for _, v in rows], float)
    at, got = {v: i for i, v in enumerate(ids.tolist())}, {}
    for r in found.orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert set(got) == {i for i in ids.tolist() if i % 20 == 0}
    for q, v in got.items():
        assert len(v) == 20 and len({i for i, _ in v}) == 20 and [s for _, s in v] == sorted((s for _, s in v), reverse=True)
        assert all(abs(s - x[at[q]] @ x[at[i]]) < 1e-9 for i, s in v)
    return np.mean([len(set(exact(x, ids, at[q], 20)) & {i for i, _ in v}) / 20 for q, v in got.items()])


@pytest.mark.parametrize("kind", ["even", "clustered", "lengths differ"])
def test_recall_over_split_lists(spark, monkeypatch, kind):
    """Lists and their queries in several parts; vectors of any length rank by inner product."""
    monkeypatch.setattr(ann, "LIST_ROWS", 100)
    monkeypatch.setattr(ann, "QUERY_ROWS", 10)
    rng = np.random.default_rng(6)
    x = rng.standard_normal((3000, 24))
    if kind == "clustered":
        x += 4 * rng.standard_normal((30, 24))[rng.integers(0, 30, 3000)]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    if kind == "lengths differ":
        x *= rng.uniform(0.5, 2.0, (3000, 1))
    rows = [(i, v) for i, v in enumerate(x.tolist())]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").repartition(3)
    assert recall_of(ann.search(df), rows) >= 0.9


def test_vectors_of_another_length_and_repeated_queries(spark):
    rng = np.random.default_rng(1)
    rows = [(i, rng.standard_normal(8).tolist()) for i in range(1, 60)] + [(100, [1.0] * 9)]
    rows += [(0, [1.0] + [0.0] * 7), (0, [0.0] * 7 + [1.0])]
    found = ann.search(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")).collect()
    mine = [r for r in found if r["query_id"] == 0]
    assert len(mine) == 40 and sorted(r["rank"] for r in mine) == sorted([*range(1, 21)] * 2) and {r["query_id"] for r in found} == {0, 20, 40}
    vectors = dict(rows[:59])
    for place in (0, 7):
        want = sorted(vectors, key=lambda i: (-vectors[i][place], i))[:20]
        scores = [vectors[i][place] for i in want]
        told = [r for r in mine if abs(r["score"] - vectors[r["vec_id"]][place]) < 1e-12]
        assert set(want) <= {r["vec_id"] for r in told} and scores[0] == max(r["score"] for r in told)


def test_vectors_that_take_no_part(spark):
    rows = [(0, [1.0, 0.0]), (20, [0.5, 0.5]), (1, None), (2, [0.0, 0.0]), (3, [float("nan"), 1.0]), (4, [None, 1.0]), (5, [float("inf"), 0.0]), (6, [2.0, 0.0]), (7, [2.0, 0.0]), (40, [0.0, 0.0]), (8, [])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").withColumn("rank", F.lit(1))
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in ann.search(df).collect())
    assert got == [(0, 1, 6, 2.0), (0, 2, 7, 2.0), (0, 3, 20, 0.5), (20, 1, 6, 1.0), (20, 2, 7, 1.0), (20, 3, 0, 0.5)]
    assert ann.search(df.limit(0)).count() == 0


def test_footrule_by_inverted_files():
    rng = np.random.default_rng(0)
    orders = np.array([rng.permutation(20)[:6] for _ in range(50)], np.int16)
    f = ann.InvertedFiles(orders, 20)
    q = orders[7]
    rank = {int(p): i for i, p in enumerate(q)}
    for i, o in enumerate(orders):
        mine = {int(p): k for k, p in enumerate(o)}
        want = sum(abs(rank.get(p, 6) - mine.get(p, 6)) for p in set(rank) | set(mine))
        assert f.footrule(q)[i] == want


def plain(df):
    """Rows as a multiset."""
    from collections import Counter

    return Counter((r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"]) for r in df.collect())


def brute_stage(name, rows, dictionaries):
    """A stage on a list of rows, without Spark and without the operator's search."""
    from test_texts import brute_links

    big = 2**63 - 1
    if name == "language":
        c = langid.DictionaryClassifier(dictionaries)
        return [r for r in rows if not c.judge(r[1])[2]]
    if name == "near_copies":
        place = brute_links([(i, r[1]) for i, r in enumerate(rows)], 5, 80, 100)
        groups = {}
        for i, r in enumerate(rows):
            groups.setdefault(place[i][1] if place[i][0] else ("alone", i), []).append(r)
        return [min(g, key=lambda r: big if r[0] is None else r[0]) for g in groups.values()]
    seen = {}
    for r in sorted(rows, key=lambda r: big if r[0] is None else r[0]):
        raw = (r[1] or "").encode()
        for i in range(len(raw) - 49):
            seen.setdefault(raw[i : i + 50], big if r[0] is None else r[0])
    out = []
    for r in rows:
        raw, mine = (r[1] or "").encode(), big if r[0] is None else r[0]
        gone = bytearray(len(raw))
        for i in range(len(raw) - 49):
            if seen[raw[i : i + 50]] < mine:
                gone[i : i + 50] = b"\1" * 50
        left = bytes(x for x, g in zip(raw, gone) if not g).decode("utf-8", "ignore")
        out.append(r if r[1] is None else (r[0], left, r[2], r[3], len(left)))
    return out


EXTRA = "a document that others copy word for word and that is longer than fifty bytes by some more words to be sure"


@pytest.mark.parametrize("kind", ["tricky", "repeated ids", "empty"])
def test_pipeline_stages_against_brute_force(spark, request, kind):
    from collections import Counter

    import corpus_pipeline as c

    from kmfold.staging import stage

    docs = request.getfixturevalue({"tricky": "tricky", "repeated ids": "repeated", "empty": "empty"}[kind]).select(*c.COLUMNS)
    if kind == "repeated ids":
        more = [(7, EXTRA, "en", "s", 1), (8, EXTRA, "en", "s", 2), (8, "an unrelated second row of the same id with words of its own and enough of them", "en", "s", 3), (9, EXTRA + " and a tail", "de", "s", 4), (9, EXTRA + " and a tail", "de", "s", 4), (None, "yet " + EXTRA, None, None, None)]
        docs = docs.unionByName(spark.createDataFrame(more, "doc_id bigint, text string, lang string, source string, n_chars bigint"))
    for name, step in c.STAGES[:-1]:
        before, docs = docs, stage(step(spark, docs, SF), name)
        assert docs.columns == c.COLUMNS
        rows = list(plain(before).elements())
        want = Counter(brute_stage(name, rows, langid.learn(before)))
        got = plain(docs)
        if name == "near_copies":  # of rows of one id and one group any one may stay
            assert Counter(r[0] for r in got.elements()) == Counter(r[0] for r in want.elements()) and not got - plain(before)
        else:
            assert got == want, name
    out = c.STAGES[-1][1](spark, docs, SF).collect()
    from test_tokens import JSON, Tokenizer

    library, total = Tokenizer.from_file(JSON), Counter()
    for r in docs.collect():
        total[r["doc_id"]] += len(library.encode(r["text"] or "", add_special_tokens=False).ids) + 1
    placed = Counter()
    for r in out:
        placed[r["doc_id"]] += r["length"]
    assert placed == total


def test_language_of_short_and_very_long_texts(spark):
    """Held-out texts cut to 40 characters, and joined to one and to twenty million."""
    docs = table(spark, "/root/testdata/sf0.1", "documents")
    dictionaries = langid.learn(docs)
    c = langid.DictionaryClassifier(dictionaries)
    rows = docs.filter(langid.held_out() & F.col("lang").isNotNull() & (F.length("text") > 100)).select("text", "lang").collect()
    assert np.mean([c.judge(r["text"][:40])[0] == r["lang"] for r in rows[:800]]) > 0.98
    for lang in dictionaries:
        own = " ".join(r["text"] for r in rows if r["lang"] == lang)
        for n in (1_000_000, 20_000_000):
            told = c.judge((own * (n // len(own) + 1))[:n])
            assert told[0] == lang and not told[2] and told[1] > 0.01, (lang, n, told)


def test_pipeline_keeps_clean_documents(spark):
    import corpus_pipeline as c

    docs = table(spark, SF, "documents")
    kept = c.identify_language(spark, docs, SF)
    assert kept.count() >= 0.99 * docs.count()
