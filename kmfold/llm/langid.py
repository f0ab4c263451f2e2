"""Language identification by compression with per-language dictionaries.

A bounded, documented sample of labelled rows gives each language a raw-content
dictionary. A text is compressed with every dictionary; the smallest result names
the language. The margin to the second smallest is the confidence, and narrow
margins are rejected. Long texts are compressed in blocks and their sizes added, so
that the dictionaries count as much at the end of a text as at its start.
"""

from __future__ import annotations

import re

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kmfold.llm.encoding import slices
from kmfold.staging import ship_package

UNKNOWN = "und"
DICTIONARY_BYTES = 400_000
SAMPLE_ROWS = 800
SAMPLE_CHARS = 2_000
LONG_CHARS = 200
LEAST_DICTIONARY = 8
LEAST_MARGIN = 0.001
LEVEL = 5
#: A run of zeros ends every block, so that none is stored raw and small sizes can be compared.
FILLER = bytes(512)
#: A text is judged in equal blocks of at most so many bytes, the size that the compressors are made for.
BLOCK_BYTES = 1 << 16
#: Below so many bytes sizes differ by too little to reject anything.
JUDGED_BYTES = 32
LETTER = re.compile(r"[^\W\d_]")
#: The same for a column.
ANY_LETTER = r"[\p{L}\p{Nl}\p{No}]"
NOT_LETTERS = re.compile(r"[\W\d_]+")


def letters_only(text: str) -> bytes:
    return NOT_LETTERS.sub(" ", text).lower().encode("utf-8", "ignore")


def held_out():
    """Rows whose crc32 of the id's digits leaves 1 modulo 3 are never learned from."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))


def learn(docs: DataFrame, rows_each: int = SAMPLE_ROWS, chars_each: int = SAMPLE_CHARS, dictionary_bytes: int = DICTIONARY_BYTES) -> dict[str, bytes]:
    """Dictionary of each language from at most ``rows_each`` rows of it, of ``chars_each`` characters.

    The sample is the rows of least id hash, so it does not depend on the
    partitioning; rows of ``LONG_CHARS`` characters come first, and shorter ones fill
    up where a language has too few. Rows without a language, an id or a letter are
    not learned from.
    """
    rows = docs.filter(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).filter(F.col("text").rlike(ANY_LETTER))
    sample = rows.select("lang", F.xxhash64("doc_id").alias("h"), (F.length("text") < LONG_CHARS).alias("short"), F.substring("text", 1, chars_each).alias("text"))
    per_lang = sample.groupBy("lang").agg(F.count("*").alias("n"), F.count_if(~F.col("short")).alias("long")).collect()  # one row a language
    if not per_lang:
        return {}
    # a threshold on the hash keeps the candidates few, so that no language is ordered as a whole
    cuts = {r["lang"]: int(-(2**63) + 4.0 * rows_each / r["long"] * (2**64 - 1)) for r in per_lang if r["long"] > 4 * rows_each}
    whole = [r["lang"] for r in per_lang if r["lang"] not in cuts]
    texts = _least(sample, whole, cuts, rows_each)
    few = [r["lang"] for r in per_lang if r["lang"] in cuts and len(texts.get(r["lang"], [])) < rows_each]
    if few:  # hashes are even: almost never
        texts |= _least(sample, few, {}, rows_each)
    # a compressor ignores a dictionary below LEAST_DICTIONARY bytes
    return {lang: b" ".join(map(letters_only, held))[:dictionary_bytes].rjust(LEAST_DICTIONARY) for lang, held in texts.items()}


def _least(sample: DataFrame, whole: list[str], cuts: dict[str, int], rows_each: int) -> dict[str, list[str]]:
    """The first ``rows_each`` texts of all languages in one scan: of whole ones, and of those with a cut below it."""
    lang, h = F.col("lang"), F.col("h")
    wanted = lang.isin(whole)
    for name, cut in cuts.items():
        wanted = wanted | ((lang == name) & ~F.col("short") & (h <= F.lit(cut)))
    # each task keeps its first rows of every language before the exchange
    first = Window.partitionBy("lang").orderBy("short", "h", "text")
    rows = sample.filter(wanted).withColumn("at", F.row_number().over(first)).filter(F.col("at") <= rows_each)
    texts: dict[str, list[str]] = {}
    for r in rows.orderBy("lang", "at").collect():  # languages * rows_each
        texts.setdefault(r["lang"], []).append(r["text"])
    return texts


class DictionaryClassifier:
    """Compressors of all languages, in the order of their names."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = LEVEL):
        self.langs = sorted(dictionaries)
        self.packers = [self._packer(dictionaries[name], level) for name in self.langs]

    @staticmethod
    def _packer(dictionary: bytes, level: int) -> zstandard.ZstdCompressor:
        d = zstandard.ZstdCompressionDict(dictionary, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        # tables sized for the dictionary and short texts, not for the level's largest window
        params = zstandard.ZstdCompressionParameters.from_level(level, source_size=BLOCK_BYTES, dict_size=len(dictionary), write_content_size=False, write_dict_id=False)
        d.precompute_compress(compression_params=params)
        return zstandard.ZstdCompressor(dict_data=d, compression_params=params)

    def judge(self, text: str | None, least_margin: float = LEAST_MARGIN) -> tuple[str, float, bool]:
        """Language, margin (0 to 1) and rejection; ``und``, 0 and rejected for a text without a letter."""
        if not text or not self.langs or not LETTER.search(text):
            return UNKNOWN, 0.0, True
        raw = letters_only(text)
        judged = len(raw) >= JUDGED_BYTES
        n = -(-len(raw) // BLOCK_BYTES)
        cuts = [len(raw) * i // n for i in range(n + 1)]
        blocks = [raw[a:z] + FILLER for a, z in zip(cuts, cuts[1:])]
        sizes = [sum(len(p.compress(b)) for b in blocks) for p in self.packers]
        best = min(range(len(sizes)), key=sizes.__getitem__)
        if len(sizes) == 1:
            return self.langs[0], 1.0, False
        second = min(s for i, s in enumerate(sizes) if i != best)
        margin = (second - sizes[best]) / second
        return self.langs[best], margin, judged and margin < least_margin


_classifiers: dict[int, DictionaryClassifier] = {}


def predict(docs: DataFrame, dictionaries: dict[str, bytes], least_margin: float = LEAST_MARGIN, keep: list[str] | None = None) -> DataFrame:
    """Add lang_pred, score and rejected to ``keep`` (default doc_id) of every row.

    A null text or one without a letter is ``und`` with score 0 and rejected; so is
    no learned language at all. A text of ``JUDGED_BYTES`` or more whose margin is
    below ``least_margin`` keeps its language and is rejected. Rows are never dropped; repeated ids stay; an
    empty table gives an empty result.
    """
    spark = docs.sparkSession
    ship_package(spark)
    keep = keep or ["doc_id"]
    shared = spark.sparkContext.broadcast(dictionaries)  # languages * dictionary_bytes, whatever the input
    schema = docs.select(*keep).schema

    def run(batches):
        key = shared.id if hasattr(shared, "id") else id(shared)
        if key not in _classifiers:
            _classifiers.clear()
            _classifiers[key] = DictionaryClassifier(shared.value)
        c = _classifiers[key]
        for whole in batches:
            for b in slices(whole, 8 << 20, whole.num_columns - 1):
                got = [c.judge(t, least_margin) for t in b.column(b.num_columns - 1).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [b.column(i) for i in range(len(keep))]
                    + [pa.array([g[0] for g in got]), pa.array([float(g[1]) for g in got]), pa.array([g[2] for g in got], pa.bool_())],
                    [*keep, "lang_pred", "score", "rejected"],
                )

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema) + ", lang_pred string, score double, rejected boolean"
    return docs.select(*keep, F.col("text").alias("_text")).mapInArrow(run, ddl)


def identify(docs: DataFrame, least_margin: float = LEAST_MARGIN) -> DataFrame:
    """Learn from the rows that are not held out and predict every row.

    Nulls, empty texts, repeated ids and empty tables: as ``learn`` and ``predict`` say.
    """
    dictionaries = learn(docs)
    told = predict(docs.withColumn("held_out", held_out()), dictionaries, least_margin, ["doc_id", "held_out"])
    return told.select(F.col("doc_id").cast("long").alias("doc_id"), "held_out", "lang_pred", "score", "rejected")
