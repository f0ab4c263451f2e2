"""Document fingerprints: one-permutation minwise hashing with packed low-order bits.

Every word shingle is hashed once. The top bits of the hash choose one of 256 bins,
the least hash of a bin represents it. An empty bin takes the value of the first
non-empty bin in a pseudo-random order of all bins that is its own (densification
whose probes do not depend on the document). The four lowest bits of each value are
packed into sixteen longs. Likeness is the share of equal values, corrected for the
one in sixteen that agree by chance.

DataFrame functions only. Texts move once, to ranges of the id, so that each row can
see the row before it; fingerprints are computed behind that exchange.
"""

from __future__ import annotations

from functools import reduce

import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kmfold.numbering import bucket_of, range_bounds
from kmfold.staging import pieces_for

BINS, BIN_BITS, LOW_BITS, SHINGLE = 256, 8, 4, 5
A_LONG = 64 // LOW_BITS
PROBES = 8
#: Several ranges share a partition, so that their sizes even out.
RANGE_BYTES, RANGES_A_PARTITION = 1 << 20, 4
#: Fixed value: the lowest bit of every four.
NIBBLE_LOW = 0x1111111111111111


def probe_table() -> list[list[int]]:
    """The first bins that each empty bin asks; those it has not asked follow in the order of a hash."""
    table = []
    for b in range(BINS):
        asked, k = [], 0
        while len(asked) < PROBES:
            x = xxhash.xxh64_intdigest(f"{b} {k}".encode()) % BINS
            k += 1
            if x != b and x not in asked:
                asked.append(x)
        table.append(asked)
    return table


def with_fingerprint(df: DataFrame, text: str, out: str, shingle: int = SHINGLE) -> DataFrame:
    """Add ``out``: sixteen longs for the words of ``text``; an empty array where it has none.

    Words are runs between white space, lower-cased. A text of fewer words than
    ``shingle`` is one shingle as a whole.
    """
    w, h, s, m, p = (f"_{out}_{x}" for x in ("words", "hashes", "sorted", "least", "place"))
    plain = F.trim(F.regexp_replace(F.lower(F.col(text)), r"\s+", " "))
    df = df.withColumn(w, F.when(plain == "", F.array().cast("array<string>")).otherwise(F.split(plain, " ")))
    df = df.withColumn(h, F.transform(w, lambda x: F.xxhash64(x)))
    n = F.size(h)
    some = F.transform(F.sequence(F.lit(1), n - (shingle - 1)), lambda i: F.xxhash64(*[F.element_at(F.col(h), i + k) for k in range(shingle)]))
    hashes = F.when(n == 0, F.array().cast("array<bigint>")).when(n < shingle, F.array(F.xxhash64(F.col(h), n))).otherwise(some)
    df = df.withColumn(s, F.sort_array(hashes))

    def bin_of(x: Column) -> Column:
        return F.shiftright(x, 64 - BIN_BITS) + BINS // 2  # bins ascend in the order of the sorted hashes

    df = df.withColumn(m, F.filter(s, lambda x, i: (i == 0) | (bin_of(x) != bin_of(F.get(F.col(s), i - 1)))))
    bins = F.transform(m, lambda x: bin_of(x).cast("int"))
    df = df.withColumn(f"{p}_b", bins)

    def bit(x: Column) -> Column:
        return F.call_function("shiftleft", F.lit(1).cast("bigint"), x.bitwiseAND(F.lit(63)))

    # which bins are held, as bits; the place of a held bin among the least hashes is the count of bits up to it
    def bits_of(k: int) -> Column:
        return F.aggregate(f"{p}_b", F.lit(0).cast("bigint"), lambda a, x: F.when(F.shiftright(x, 6) == k, a.bitwiseOR(bit(x))).otherwise(a))

    words = [bits_of(k) for k in range(BINS // 64)]
    df = df.withColumn(f"{p}_w", F.array(*words))
    held = [F.bit_count(F.get(F.col(f"{p}_w"), F.lit(k))) for k in range(BINS // 64)]
    df = df.withColumn(f"{p}_c", F.array(F.lit(0), *[reduce(lambda u, v: u + v, held[: k + 1]) for k in range(len(held) - 1)]))

    def place_of(b: Column) -> Column:
        word = F.get(F.col(f"{p}_w"), F.shiftright(b, 6))
        upto = F.get(F.col(f"{p}_c"), F.shiftright(b, 6)) + F.bit_count(word.bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.lit(-1).cast("bigint"), b.bitwiseAND(F.lit(63)))))) + 1
        return F.when(word.bitwiseAND(bit(b)) != 0, upto).otherwise(F.lit(0))

    df = df.withColumn(p, F.transform(F.sequence(F.lit(0), F.lit(BINS - 1)), place_of))
    probes = F.array(*[F.array(*[F.lit(x) for x in row]) for row in probe_table()])

    def value(place: Column, b: Column) -> Column:
        hit = F.get(F.filter(F.get(probes, b), lambda x: F.get(F.col(p), x) > 0), F.lit(0))
        near = F.element_at(F.col(m), F.get(F.col(p), hit))
        far = F.array_min(F.transform(F.col(m), lambda x: F.struct(F.xxhash64(b, bin_of(x)).alias("o"), x.alias("v"))))["v"]
        return F.when(place > 0, F.element_at(F.col(m), F.greatest(place, F.lit(1)))).otherwise(F.coalesce(near, far)).bitwiseAND(F.lit((1 << LOW_BITS) - 1))

    df = df.withColumn(f"{p}_v", F.transform(p, value))
    longs = [F.aggregate(F.slice(f"{p}_v", A_LONG * k + 1, A_LONG), F.lit(0).cast("bigint"), lambda a, x: F.shiftleft(a, LOW_BITS).bitwiseOR(x)) for k in range(BINS // A_LONG)]
    df = df.withColumn(out, F.when(F.size(m) > 0, F.array(*longs)).otherwise(F.array().cast("array<bigint>")))
    return df.drop(w, h, s, m, p, f"{p}_b", f"{p}_w", f"{p}_c", f"{p}_v")


def fingerprint_text(packed: Column) -> Column:
    """The packed longs as lower-case hexadecimal digits, one for each bin; empty for no words."""
    return F.lower(F.array_join(F.transform(packed, lambda x: F.lpad(F.hex(x), A_LONG, "0")), ""))


def likeness(a: Column, b: Column) -> Column:
    """Estimated share of common shingles, 0 to 1; two texts without words are alike."""

    def equal(x: Column, y: Column) -> Column:
        d = x.bitwiseXOR(y)
        d = d.bitwiseOR(F.shiftrightunsigned(d, 1))
        d = d.bitwiseOR(F.shiftrightunsigned(d, 2))
        return A_LONG - F.bit_count(d.bitwiseAND(F.lit(NIBBLE_LOW)))

    same = reduce(lambda u, v: u + v, [equal(F.get(a, F.lit(k)), F.get(b, F.lit(k))) for k in range(BINS // A_LONG)])
    chance = 1.0 / (1 << LOW_BITS)
    estimate = (same.cast("double") / BINS - chance) / (1.0 - chance)
    return F.when((F.size(a) == 0) & (F.size(b) == 0), 1.0).when((F.size(a) == 0) | (F.size(b) == 0), 0.0).otherwise(F.greatest(F.lit(0.0), estimate))


def edited_texts(docs: DataFrame, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """doc_id, text, packed, and text and fingerprint of the next document in descending order.

    After the document of least id comes that of the greatest. Rows of one id follow
    one another by text; a null id counts as the least of all.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("_o", F.coalesce("doc_id", F.lit(-(2**63))))
    n = pieces_for(docs.select("doc_id", "text"), range_bytes, most=1 << 16)  # their bounds stand in the plan
    bounds = range_bounds(rows, "_o", n)
    rows = rows.withColumn("_range", bucket_of(F.col("_o"), bounds))
    last = sorted((r["_range"], r["o"]) for r in rows.groupBy("_range").agg(F.max("_o").alias("o")).collect())  # one row a range
    spark = docs.sparkSession
    before = spark.createDataFrame([(last[i - 1][1], last[i][0]) for i in range(len(last))], "_o long, _to int")
    # one narrow row a range: bounded by the number of ranges
    guests = rows.select("_o", "doc_id", "text").join(F.broadcast(before), "_o")
    guests = guests.groupBy("_to").agg(F.max(F.struct("_o", "doc_id", "text")).alias("g"))
    guests = guests.select("g.doc_id", "g.text", "g._o", F.col("_to").alias("_range"), F.lit(0).alias("_home"))
    both = rows.withColumn("_home", F.lit(1)).unionByName(guests).repartition(-(-max(1, len(last)) // RANGES_A_PARTITION), "_range")
    both = with_fingerprint(both, "text", "packed")
    w = Window.partitionBy("_range").orderBy("_home", "_o", "text")
    seen = both.withColumn("next_text", F.lag("text").over(w)).withColumn("next_packed", F.lag("packed").over(w))
    return seen.filter("_home = 1").select("doc_id", "text", "packed", "next_text", "next_packed")


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness.

    The last half of the code points (rounded down) is replaced by the first as many
    of the next document. A null text counts as empty; texts without words have the
    empty fingerprint; repeated ids are separate rows; other columns are ignored; an
    empty table gives an empty result.
    """
    rows = edited_texts(docs)
    n = F.char_length("text").cast("int")
    half = F.floor(n / 2).cast("int")
    rows = rows.withColumn("edited", F.concat(F.substr(F.col("text"), F.lit(1), n - half), F.substr(F.col("next_text"), F.lit(1), half)))
    rows = with_fingerprint(rows, "edited", "edited_packed")
    return rows.select(
        "doc_id",
        n.cast("long").alias("n_chars"),
        F.sha2(F.encode("edited", "utf-8"), 256).alias("edited_sha256"),
        fingerprint_text(F.col("packed")).alias("fingerprint"),
        fingerprint_text(F.col("edited_packed")).alias("edited_fingerprint"),
        likeness(F.col("packed"), F.col("edited_packed")).alias("near_edited"),
        likeness(F.col("packed"), F.col("next_packed")).alias("near_next"),
    )
