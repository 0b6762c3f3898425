"""Quality rules: base counts, then divergence from language references. DataFrame functions only, no shuffle.

A text's histogram over seven character classes and its histogram over the commonest words of each language (and
"other") are held against references by Jensen-Shannon divergence, whose square root is the distance, in bits from 0
to 1. The nearest language counts. A text is rejected if its characters are further than ``char_limit`` from every
language, or its words further than ``word_limit``, where it is long enough for the histogram to mean something:
``min_chars`` and ``min_words``. Common words are known for four languages in Latin letters; texts in other scripts are held
against characters alone.

Defined cases: a null text is an empty one, has zero counts and fails the base rule (fewer than 20 words); repeated
rows are judged each; whole texts are read, in memory proportional to the longest; only named columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import WORD, table

SYMBOLS = "#*$%&|<>"
WINDOW = 8
MIN_WORDS, MIN_CHARS = 60, 600
CHAR_LIMIT, WORD_LIMIT = 0.19, 0.31

#: Shares of lower case, upper case, digits, blanks, sentence marks, symbols and letters beyond ASCII.
CHARACTERS = {
    "de": (0.79, 0.030, 0.002, 0.145, 0.020, 0.001, 0.030),
    "en": (0.80, 0.025, 0.002, 0.155, 0.020, 0.001, 0.001),
    "es": (0.77, 0.025, 0.002, 0.155, 0.020, 0.001, 0.040),
    "fr": (0.76, 0.025, 0.002, 0.155, 0.020, 0.001, 0.060),
    "ru": (0.005, 0.002, 0.003, 0.150, 0.025, 0.001, 0.814),
    "zh": (0.010, 0.006, 0.010, 0.010, 0.014, 0.001, 0.949),
}
#: Least share of a-z from which a text is held against the common words, which are all of languages written so.
LATIN = 0.5
#: The ten commonest words of each language and their shares of running text.
COMMON = {
    "de": {"der": 0.035, "die": 0.035, "und": 0.030, "in": 0.020, "den": 0.014, "von": 0.012, "zu": 0.012, "das": 0.011, "mit": 0.010, "sich": 0.009},
    "en": {"the": 0.060, "of": 0.032, "and": 0.028, "to": 0.026, "a": 0.022, "in": 0.020, "is": 0.010, "that": 0.010, "for": 0.009, "it": 0.009},
    "es": {"de": 0.060, "la": 0.038, "que": 0.030, "el": 0.028, "en": 0.026, "y": 0.025, "a": 0.020, "los": 0.017, "se": 0.011, "un": 0.010},
    "fr": {"de": 0.050, "la": 0.030, "le": 0.025, "et": 0.024, "les": 0.020, "des": 0.018, "en": 0.015, "un": 0.012, "du": 0.012, "une": 0.010},
}


def divergence(p: Column, q: list[float]) -> Column:
    """Jensen-Shannon distance of two histograms, arrays that each sum to 1."""
    part = lambda x, y: F.when(x > 0, x * F.log2(2 * x / (x + y))).otherwise(F.lit(0.0))
    terms = F.zip_with(p, F.array(*(F.lit(float(x)) for x in q)), lambda a, b: part(a, b) + part(b, a))
    return F.sqrt(F.greatest(F.lit(0.0), F.aggregate(terms, F.lit(0.0), lambda s, x: s + x) / 2))


def _with_next(distance: int):
    return lambda h, i: F.xxhash64(h, F.get("hs", i + distance))


def _less(text: str, pattern: str) -> Column:
    """Characters of ``text`` in runs that match."""
    return F.length(text) - F.length(F.regexp_replace(text, pattern, ""))


def _variants() -> list[str]:
    """The common words as they stand in a text: in three cases, alone or before a mark."""
    words = sorted({w for ref in COMMON.values() for w in ref})
    return [x + mark for w in words for x in dict.fromkeys((w, w.capitalize(), w.upper())) for mark in ("", *".,;:!?")]


def measured(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id with all base counts, the two distances and those to each language.

    A text is scanned in full three times: for its words, its lines, and for what is left without a-z, from which all
    other character counts are taken.
    """
    d = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"), F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    d = d.withColumn("n_chars_", F.length("t")).withColumn("rest", F.regexp_replace("t", "[a-z]+", "")).withColumn("ws", F.regexp_extract_all("t", F.lit(WORD), F.lit(0)))
    d = d.withColumn("n_words", F.size("ws").cast("long")).withColumn("lines", F.filter(F.split("t", "\n"), lambda x: x.rlike(WORD))).drop("t")
    d = d.withColumn("n_dup_lines", (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long")).drop("lines")
    # ---- words in windows that come twice: hashes first, places only for the texts that repeat any
    # a window's hash is made of those of its halves, down to words
    d = d.withColumn("hs", F.transform("ws", lambda w: F.xxhash64(w)))
    for half in (1, 2, 4):
        d = d.withColumn("hs", F.transform("hs", _with_next(half)))
    d = d.withColumn("hs", F.when(F.col("n_words") > WINDOW, F.slice("hs", 1, F.greatest(F.lit(0), F.size("ws") - WINDOW + 1))))
    known = F.filter("ws", lambda w: w.isin(_variants()))
    d = d.withColumn("common", F.lower(F.concat(F.lit(" "), F.regexp_replace(F.array_join(known, "  "), "[.,;:!?]", ""), F.lit(" ")))).drop("ws")
    d = d.withColumn("sorted", F.when(F.size(F.array_distinct("hs")) < F.size("hs"), F.expr("sort_array(transform(hs, (h, i) -> struct(h, i)))"))).drop("hs")
    twice = F.expr("sort_array(transform(filter(sorted, (x, i) -> (i > 0 AND sorted[i - 1].h = x.h) OR (i + 1 < size(sorted) AND sorted[i + 1].h = x.h)), x -> x.i))")
    covered = F.aggregate(twice, F.struct(F.lit(0).alias("n"), F.lit(0).alias("end")), lambda a, i: F.struct((a["n"] + i + WINDOW - F.greatest(i, a["end"])).alias("n"), (i + WINDOW).alias("end")), lambda a: a["n"])
    d = d.withColumn("n_repeat_words", F.when(F.col("sorted").isNull(), 0).otherwise(covered).cast("long")).drop("sorted")
    # ---- histograms, as arrays, so that each is made once
    upper, digits, blanks, marks, symbols = (_less("rest", p) for p in ("[A-Z]+", "[0-9]+", r"[\x20\x09-\x0D]+", r"[.,;:!?'\"()-]+", f"[{SYMBOLS}]+"))
    beyond = _less("rest", r"[^\x00-\x7F]+")
    d = d.withColumn("h", F.array(F.col("n_chars_") - F.length("rest"), upper, digits, blanks, marks, beyond, symbols)).drop("rest")
    d = d.withColumn("n_symbols", F.col("h")[6].cast("long")).withColumn("word_chars", (F.col("n_chars_") - F.col("h")[3]).cast("long"))
    vocabulary = sorted({w for ref in COMMON.values() for w in ref})
    count = lambda w: (F.octet_length("common") - F.octet_length(F.replace(F.col("common"), F.lit(f" {w} "), F.lit("")))) / (len(w.encode()) + 2)
    d = d.withColumn("k", F.array(*(count(w) for w in vocabulary))).drop("common")
    total = F.greatest(F.col("n_chars_"), F.lit(1))
    classes = [F.col("h")[i] for i in range(6)]
    other = F.col("n_chars_") - sum(classes[1:], classes[0])
    d = d.withColumn("p", F.array(*(x / total for x in (*classes[:5], other, classes[5]))))
    words = F.greatest(F.col("n_words"), F.lit(1))
    d = d.withColumn("char_distance", F.least(*(divergence(F.col("p"), [x / sum(ref) for x in ref]) for ref in CHARACTERS.values())))
    distances = []
    for ref in COMMON.values():
        shares = [F.col("k")[vocabulary.index(w)] / words for w in ref]
        distances.append(divergence(F.array(*shares, F.greatest(F.lit(1.0) - sum(shares[1:], shares[0]), F.lit(0.0))), [*ref.values(), 1 - sum(ref.values())]))
    return d.withColumn("word_distance", F.least(*distances))


OUT = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "char_distance", "word_distance")


def _judged(docs: DataFrame, columns: tuple[str, ...], doc_id: str = "doc_id", text: str = "text", char_limit: float = CHAR_LIMIT, word_limit: float = WORD_LIMIT, min_words: int = MIN_WORDS, min_chars: int = MIN_CHARS) -> DataFrame:
    """``measured`` with base_failed and kept; distances are null below the minimum lengths.

    The rows pass through a generator, below which no filter is pushed: pushed down, a filter on the verdict would be
    expanded into every expression that it stands on, several times over.
    """
    m = measured(docs, doc_id, text)
    m = m.withColumn("base_failed", (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words")))
    m = m.withColumn("char_distance", F.when(F.col("n_chars_") >= min_chars, F.col("char_distance")))
    m = m.withColumn("word_distance", F.when((F.col("n_words") >= min_words) & (F.col("p")[0] >= LATIN), F.col("word_distance")))
    far = (F.coalesce(F.col("char_distance"), F.lit(0.0)) > char_limit) | (F.coalesce(F.col("word_distance"), F.lit(0.0)) > word_limit)
    m = m.withColumn("kept", ~F.col("base_failed") & ~far)
    return m.select(F.explode(F.array(F.struct(*columns))).alias("x")).select("x.*")


def judge(docs: DataFrame, **options) -> DataFrame:
    """doc_id, the base counts, base_failed, kept, and both distances."""
    return _judged(docs, OUT, **options)


def good_documents(docs: DataFrame, **options) -> DataFrame:
    """The rows that are kept, with all their columns: a stage of a pipeline."""
    return _judged(docs, ("kept", "row"), **options).where("kept").select("row.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"))
