"""Toxicity by two class-conditional Kneser-Ney models.

A bigram model of toxic texts and one of ordinary texts are counted from labelled rows. Both discount their counts and back
off to how many different words a word follows in their class, and from there to the same number over all documents,
labelled or not, so that a word that is rare in one class is smoothed by what the whole corpus knows of it. A text's evidence
is the difference of the two log-likelihoods, normalised by its length, of words alone and of what their histories add;
differences below a margin are chance and count as none. Pairs count however seldom they were seen. A logistic curve turns
evidence into a score from 0 to 1.

All counts are distributed aggregates over all rows, whatever their number, and grow with them. Rows whose crc32(doc_id as
text) mod 5 is 0 are never learned from. Of the others a third, by hash, is kept from the counts: of it at most ``sample``
rows of each class choose the margin and the curve; only their sums of evidence go to the driver. The differences that are
beyond the least margin are the model. Up to ``MODEL_ROWS`` of them every worker gets them all; beyond, the model is dealt
into parts by hash, and many texts at a time ask each part at once for the values of their words and pairs, with the same
scores.

Defined cases: a null or empty text, or one without letters, scores the base value of the curve at evidence 0; null
labels are not learned from, and of several labels for one id the largest counts; of several texts for one id all are
learned from; with one class missing from the labels every score is 0; repeated rows are scored each; an empty table gives
no rows; only named columns are read.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import materialize, ship, table, tidy

#: Rows of each class that choose the margin and the curve, at most.
SAMPLE = 3000
#: Least differences of log-likelihoods to choose from.
MARGINS = (1.0, 1.5, 2.0, 2.5, 3.0, 4.0)
#: Differences that are broadcast, 12 bytes each, and labelled ids likewise; beyond, both sides shuffle.
MODEL_ROWS, LABEL_ROWS = 4_000_000, 4_000_000
#: Entries that a counting task holds before it hands them on.
HELD = 150_000
#: Where the model is dealt out: tokens whose values a task asks for at once; parts of the words and of the pairs, at least,
#: and differences of a part, about; bits of the filter of what the model has, as a power of two (a fixed 16 MB).
ASKED_AT, MODEL_PARTS, PART_ROWS, FILTER_BITS = 500_000, 64, 2_000_000, 27
#: How often a pair must have been seen, unless ``differences`` is asked for all, which is what scores are made of.
LEAST_PAIR = 2
WORDS = re.compile(r"[^\W\d_]+").findall


def held_out(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


class Hashes(dict):
    """64-bit keys of words, as signed numbers."""

    def __missing__(self, word: str) -> int:
        if len(self) >= HELD:
            self.clear()
        self[word] = out = key_of(word)
        return out


def key_of(word: str) -> int:
    import xxhash

    h = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def keys_of(text: str | None, hashes: Hashes) -> np.ndarray:
    words = WORDS((text or "").lower())
    return np.fromiter(map(hashes.__getitem__, words), np.int64, len(words))


def pair_keys(keys: np.ndarray) -> np.ndarray:
    """Of each word and the one before it."""
    u = keys.astype(np.uint64)
    x = (u[:-1] * np.uint64(0x9E3779B97F4A7C15)) ^ (u[1:] + np.uint64(0x632BE59BD9B4E019))
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return (x ^ (x >> np.uint64(29))).astype(np.int64)


def discounts(n: list[int]) -> tuple[float, float, float]:
    """What is taken off a count of 1, 2 and 3 or more, from how many counts are 1, 2, 3 and 4. Where that says too little,
    0.75 is taken off any."""
    if not all(n):
        return (0.75, 0.75, 0.75)
    y = n[0] / (n[0] + 2 * n[1])
    return tuple(min(max(k - (k + 1) * y * n[k] / n[k - 1], 0.05), k - 0.01) for k in (1, 2, 3))


def _off(c: Column, d: tuple[float, float, float]) -> Column:
    return F.when(c == 0, 0.0).when(c == 1, d[0]).when(c == 2, d[1]).otherwise(d[2])


def pair_counts(docs: DataFrame) -> DataFrame:
    """h, w, c1, c0: how often a word stands after another in toxic and in ordinary texts. ``docs``: __text, __toxic. Tasks
    add up what they see before it shuffles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = Hashes()
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def out() -> pa.RecordBatch:
            h, w, y = (np.concatenate([x[k] for x in held]) for k in range(3))
            order = np.lexsort((w, h))
            h, w, y = h[order], w[order], y[order]
            first = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (w[1:] != w[:-1])]))
            c1 = np.add.reduceat(y, first)
            n = np.diff(np.append(first, len(h)))
            return pa.RecordBatch.from_arrays([pa.array(h[first]), pa.array(w[first]), pa.array(c1), pa.array(n - c1)], names=["h", "w", "c1", "c0"])

        for batch in batches:
            for text, toxic in zip(batch["__text"], batch["__toxic"].to_pylist(), strict=True):
                k = keys_of(text.as_py(), hashes)
                if len(k) > 1:
                    held.append((k[:-1], k[1:], np.full(len(k) - 1, toxic, np.int64)))
                    size += len(k)
            if size > 5 * HELD:
                yield out()
                held, size = [], 0
        if held:
            yield out()

    parts = docs.mapInArrow(run, "h long, w long, c1 long, c0 long")
    return parts.groupBy("h", "w").agg(F.sum("c1").alias("c1"), F.sum("c0").alias("c0"))


def shared_counts(docs: DataFrame, text: str = "text") -> DataFrame:
    """w, s: 1 and how many different words, counted up to two, each word of any document follows. Models are not made of
    these but of ``continuations``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = Hashes()
        held: list[np.ndarray] = []
        size = 0

        def out() -> pa.RecordBatch:
            w, lo, hi = (np.concatenate([x[k] for x in held]) for k in range(3))
            order = np.argsort(w, kind="stable")
            w, lo, hi = w[order], lo[order], hi[order]
            first = np.flatnonzero(np.concatenate([[True], w[1:] != w[:-1]]))
            return pa.RecordBatch.from_arrays([pa.array(w[first]), pa.array(np.minimum.reduceat(lo, first)), pa.array(np.maximum.reduceat(hi, first))], names=["w", "lo", "hi"])

        top, low = np.iinfo(np.int64).max, np.iinfo(np.int64).min
        for batch in batches:
            for x in batch["__text"]:
                k = keys_of(x.as_py(), hashes)
                if len(k):
                    held.append(np.array([k, np.append(top, k[:-1]), np.append(low, k[:-1])]))
                    size += len(k)
                if size > 5 * HELD:
                    yield out()
                    held, size = [], 0
        if held:
            yield out()

    found = docs.select(F.col(text).alias("__text")).mapInArrow(run, "w long, lo long, hi long")
    found = found.groupBy("w").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    # one that only begins texts follows none; two different ends are two words
    return found.select("w", F.when(F.col("lo") > F.col("hi"), 1).when(F.col("lo") == F.col("hi"), 2).otherwise(3).alias("s"))


#: Parts that different pairs are dealt into by their word, and tokens that a task looks at before it hands pairs on.
PARTS, LOOKED_AT = 256, 3_000_000


#: Histories that are sent as numbers of two bytes, the most frequent; others are sent whole. It changes only what moves.
COMMON = 1 << 16
NONE = np.empty(0, np.int64)


def part_of(w: np.ndarray) -> np.ndarray:
    return (w.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64) % PARTS


class Vocabulary:
    """Hashes, each once, in order of their parts, so that the words of a part have numbers in a row."""

    def __init__(self, hashes: np.ndarray):
        """``number``: the place of each of ``hashes``."""
        known, at = np.unique(hashes, return_inverse=True)
        part = part_of(known)
        order = np.argsort(part, kind="stable")
        place = np.empty(len(known), np.int32)
        place[order] = np.arange(len(known), dtype=np.int32)
        self.hashes, self.number = known[order], place[at]
        self.starts = np.searchsorted(part[order], np.arange(PARTS + 1))


def packed_numbers(pairs: np.ndarray, known: Vocabulary, common: np.ndarray = NONE) -> list[tuple[int, bytes]]:
    """Different pairs by part of the word, each part's as one binary: the words and histories of the part once, then for
    each pair the place of its history, in order of words. Histories among ``common``, which is sorted, go as places in it.
    ``pairs``: number of the word times the size of the vocabulary, plus number of its history; it is sorted in place."""
    import zlib

    pairs.sort()
    if len(pairs):
        new = np.empty(len(pairs), bool)
        new[0] = True
        np.not_equal(pairs[1:], pairs[:-1], out=new[1:])
        pairs = pairs[new]
    v = len(known.hashes)
    cuts = np.searchsorted(pairs, known.starts * v)
    out = []
    for part in np.flatnonzero(cuts[1:] > cuts[:-1]):
        w, h = np.divmod(pairs[cuts[part]:cuts[part + 1]], v)
        words, of, n = np.unique(w, return_inverse=True, return_counts=True)
        numbers, at = np.unique(h, return_inverse=True)
        histories = known.hashes[numbers]
        place = np.searchsorted(common, histories)
        hit = np.zeros(len(histories), bool) if not len(common) else common[np.minimum(place, len(common) - 1)] == histories
        # those that are common first
        order = np.argsort(~hit, kind="stable")
        moved = np.empty(len(histories), np.int64)
        moved[order] = np.arange(len(histories))
        at = np.sort(of * len(histories) + moved[at]) % len(histories)
        rest = histories[~hit]
        head = np.array([len(words), len(rest), len(w), len(histories) - len(rest)], np.int64)
        # places in planes of bytes, which pack better than whole numbers
        planes = at.astype("<u4").view(np.uint8).reshape(-1, 4).T.copy()
        places = place[hit].astype("<u2").view(np.uint8).reshape(-1, 2).T.copy()
        body = n.astype("<u4").tobytes() + planes.tobytes() + places.tobytes()
        out.append((int(part), head.tobytes() + known.hashes[words].tobytes() + rest.tobytes() + zlib.compress(body, 1)))
    return out


def packed_pairs(h: np.ndarray, w: np.ndarray, common: np.ndarray = NONE) -> list[tuple[int, bytes]]:
    """The same of hashes."""
    known = Vocabulary(np.concatenate([w, h]))
    return packed_numbers(known.number[:len(w)].astype(np.int64) * len(known.hashes) + known.number[len(w):], known, common)


class Codes(dict):
    """Numbers of words in the order they are met, and their keys. A word that was forgotten gets one more."""

    def __init__(self):
        self.keys_ = array("q")

    def __missing__(self, word: str) -> int:
        if len(self) >= HELD:
            self.clear()
        self[word] = out = len(self.keys_)
        self.keys_.append(key_of(word))
        return out


class Pairs:
    """Texts as numbers of four bytes a word, until their different pairs are handed on."""

    def __init__(self):
        self.codes, self.texts, self.size = Codes(), [], 0

    def add(self, text: str | None) -> None:
        words = WORDS((text or "").lower())
        if words:
            self.texts.append(np.fromiter(map(self.codes.__getitem__, words), np.int32, len(words)))
            self.size += len(words)

    def handed_on(self, common: np.ndarray = NONE) -> tuple[list[tuple[int, bytes]], list[tuple[int, bytes]]]:
        """Packed pairs, and the words that begin a text, both by part. Nothing is held afterwards."""
        known, texts, n = Vocabulary(np.array(self.codes.keys_, np.int64)), self.texts, self.size - len(self.texts)
        self.__init__()
        begin = known.hashes[np.unique(known.number[[int(t[0]) for t in texts]])]
        pairs, at, v = np.empty(n, np.int64), 0, len(known.hashes)
        while texts:
            k = known.number[texts.pop()]
            now = pairs[at:at + len(k) - 1]
            np.multiply(k[1:], v, out=now, dtype=np.int64)
            now += k[:-1]
            at += len(now)
        part = part_of(begin)
        return packed_numbers(pairs, known, common), [(int(p), begin[part == p].tobytes()) for p in np.unique(part)]


def unpacked_pairs(data: bytes, common: np.ndarray = NONE) -> tuple[np.ndarray, np.ndarray]:
    """Histories and words."""
    import zlib

    v, k, m, c = np.frombuffer(data, np.int64, 4)
    words, rest = np.frombuffer(data, np.int64, v, 32), np.frombuffer(data, np.int64, k, 32 + 8 * v)
    body = zlib.decompress(data[32 + 8 * (v + k):])
    n = np.frombuffer(body, "<u4", v)
    at = np.frombuffer(body, np.uint8, 4 * m, 4 * v).reshape(4, m).T.copy().view("<u4").ravel()
    known = np.concatenate([common[np.frombuffer(body, np.uint8, 2 * c, 4 * (v + m)).reshape(2, c).T.copy().view("<u2").ravel()], rest])
    return known[at], np.repeat(words, n)


def common_histories(pairs: DataFrame) -> np.ndarray:
    """The histories with the most pairs among those counted, sorted."""
    most = pairs.groupBy("h").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "h").limit(COMMON)
    return np.sort(most.select("h").toArrow()["h"].to_numpy())


def continuations(docs: DataFrame, text: str = "text", common: np.ndarray = NONE) -> DataFrame:
    """w, s: 1 and how many different words each word of any document follows, all of them. Tasks hand on different pairs,
    packed; all pairs of a word come to one part, which counts them. Counts are the same with any ``common``."""
    shared = docs.sparkSession.sparkContext.broadcast(common)  # 512 KB at most

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = Pairs()

        def out() -> pa.RecordBatch:
            rows, begin = held.handed_on(shared.value)
            # words that begin a text go as words without a history
            return pa.RecordBatch.from_arrays([pa.array([p for p, _ in [*rows, *begin]], pa.int32()), pa.array([True] * len(rows) + [False] * len(begin)), pa.array([d for _, d in [*rows, *begin]], pa.binary())], names=["part", "pair", "data"])

        for batch in batches:
            for x in batch["__text"]:
                held.add(x.as_py())
                if held.size > LOOKED_AT:
                    yield out()
        if held.size:
            yield out()

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, h, w, begin, size = None, [], [], [], 0

        def merged() -> None:
            nonlocal h, w, size
            a, b = np.concatenate(h), np.concatenate(w)
            order = np.lexsort((a, b))
            a, b = a[order], b[order]
            new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]) if len(a) else np.empty(0, bool)
            h, w, size = [a[new]], [b[new]], 0

        def out() -> pa.RecordBatch:
            merged()
            words, n = np.unique(w[0], return_counts=True)
            bare = np.setdiff1d(np.concatenate(begin), words)
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([words, bare])), pa.array(np.concatenate([1 + n, np.ones(len(bare), np.int64)]))], names=["w", "s"])

        empty = np.empty(0, np.int64)
        for batch in batches:
            for part, pair, data in zip(batch["part"].to_pylist(), batch["pair"].to_pylist(), batch["data"], strict=True):
                if part != now:
                    if now is not None:
                        yield out()
                    now, h, w, begin, size = part, [empty], [empty], [empty], 0
                if pair:
                    a, b = unpacked_pairs(data.as_py(), shared.value)
                    h.append(a)
                    w.append(b)
                    size += len(a)
                    if size > 2_000_000:
                        merged()
                else:
                    begin.append(np.frombuffer(data.as_py(), np.int64))
        if now is not None:
            yield out()

    found = docs.select(F.col(text).alias("__text")).mapInArrow(pairs, "part int, pair boolean, data binary")
    return found.repartition(PARTS, "part").sortWithinPartitions("part").mapInArrow(counted, "w long, s long")


def differences(pairs: DataFrame, shared: DataFrame, least: float = MARGINS[0], seen: int = LEAST_PAIR) -> DataFrame | None:
    """h, w, value of all log-likelihood differences beyond ``least``, those of words alone (``h`` null) and what histories
    add, of pairs that were ``seen`` so often. None where a class has no pair."""
    count = lambda c: [F.count_if(F.col(c) == k).alias(f"{c}_{k}") for k in (1, 2, 3, 4)]
    follows = materialize(pairs.groupBy("w").agg(F.count_if(F.col("c1") > 0).alias("f1"), F.count_if(F.col("c0") > 0).alias("f0")))
    a = pairs.agg(*count("c1"), *count("c0")).collect()[0]
    b = follows.agg(*count("f1"), *count("f0"), *(F.sum(f).alias(f) for f in ("f1", "f0")), *(F.count_if(F.col(f) > 0).alias(f"n_{f}") for f in ("f1", "f0"))).collect()[0]
    if not b["f1"] or not b["f0"]:
        return None
    z = shared.agg(F.sum("s")).collect()[0][0] + 1.0  # 1 for any word that is not in the corpus
    words = follows.join(shared, "w", "left")
    left, word = {}, {}
    for c in "10":
        n = [b[f"f{c}_{k}"] for k in (1, 2, 3, 4)]
        d = discounts(n)
        left[c] = d[0] * n[0] + d[1] * n[1] + d[2] * (b[f"n_f{c}"] - n[0] - n[1])
        f = F.col(f"f{c}")
        word[c] = ((f - _off(f, d)) + left[c] * F.coalesce("s", F.lit(1)) / z) / b[f"f{c}"]
    # an unknown word says nothing
    unknown = float(np.log(left["1"] / b["f1"]) - np.log(left["0"] / b["f0"]))
    words = words.select("w", word["1"].alias("p1"), word["0"].alias("p0")).withColumn("alone", F.log("p1") - F.log("p0") - F.lit(unknown))
    off = {c: _off(F.col(f"c{c}"), discounts([a[f"c{c}_{k}"] for k in (1, 2, 3, 4)])) for c in "10"}
    histories = pairs.groupBy("h").agg(*(F.sum(f"c{c}").alias(f"u{c}") for c in "10"), *(F.sum(off[c]).alias(f"l{c}") for c in "10"))
    known = pairs.where(F.col("c1") + F.col("c0") >= seen).join(histories, "h").join(words, "w")
    p = {c: F.when(F.col(f"u{c}") > 0, (F.col(f"c{c}") - off[c] + F.col(f"l{c}") * F.col(f"p{c}")) / F.col(f"u{c}")).otherwise(F.col(f"p{c}")) for c in "10"}
    more = known.select("h", "w", (F.log(p["1"]) - F.log(p["0"]) - F.col("alone")).alias("value"))
    alone = words.select(F.lit(None).cast("long").alias("h"), "w", F.col("alone").alias("value"))
    return alone.unionByName(more).where(F.abs("value") > least)


@dataclass
class Model:
    """Sorted keys of words and of pairs, and their differences."""

    words: np.ndarray
    word_values: np.ndarray
    pairs: np.ndarray
    pair_values: np.ndarray

    def evidence(self, texts: list[np.ndarray], margins: tuple[float, ...]) -> np.ndarray:
        """A row for each text: for each margin the sums of differences beyond it, of words alone and of what histories add."""
        keys, of = np.concatenate([NONE, *texts]), np.repeat(np.arange(len(texts)), [len(k) for k in texts])
        inside = of[1:] == of[:-1]
        found = [(of, _found(self.words, self.word_values, keys)), (of[1:][inside], _found(self.pairs, self.pair_values, pair_keys(keys)[inside] if len(keys) > 1 else NONE))]
        return np.stack([np.bincount(at, np.where(np.abs(v) > m, v, 0).astype(np.float64), len(texts)) for m in margins for at, v in found], axis=1)


def _found(known: np.ndarray, values: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The value of each key, 0 of unknown ones. Keys are looked up in their order, each once, so that neighbours in the
    model are read together."""
    if not len(known) or not len(keys):
        return np.zeros(len(keys), np.float32)
    asked, where = np.unique(keys, return_inverse=True)
    at = np.minimum(np.searchsorted(known, asked), len(known) - 1)
    return np.where(known[at] == asked, values[at], np.float32(0))[where]


def keyed(rows: DataFrame) -> DataFrame:
    """alone, key, value of differences, in 12 bytes and a bit each, as tasks make the keys of pairs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h, w = batch["h"], batch["w"].to_numpy()
            alone = h.is_null().to_numpy(zero_copy_only=False)
            key = np.where(alone, w, pair_keys_of(h.fill_null(0).to_numpy(), w)) if len(w) else w
            yield pa.RecordBatch.from_arrays([pa.array(alone), pa.array(key), batch["value"]], names=["alone", "key", "value"])

    return rows.select("h", "w", F.col("value").cast("float").alias("value")).mapInArrow(run, "alone boolean, key long, value float")


def collected(rows: DataFrame) -> Model:
    """The differences on the driver, whose number has been checked."""
    found = keyed(rows)
    parts = []
    for alone in (True, False):
        t = found.where(F.col("alone") == alone).select("key", "value").toArrow()
        key, value = t["key"].to_numpy(), t["value"].to_numpy()
        del t
        order = np.argsort(key)
        parts += [key[order], value[order]]
    return Model(*parts)


def _planes(x: np.ndarray) -> bytes:
    """Numbers in planes of bytes, which pack better than whole numbers."""
    return x.view(np.uint8).reshape(len(x), -1).T.tobytes()


def _of_planes(data: bytes, kind: str, n: int, at: int) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.frombuffer(data, np.uint8, size * n, at).reshape(size, n).T.copy().view(kind).ravel()


def model_filter(found: DataFrame) -> np.ndarray:
    """Bitmap of the leading bits of all keys: what isn't marked is not in the model."""
    at = F.shiftrightunsigned("key", 64 - FILTER_BITS)
    words = found.select(F.shiftright(at, 15).cast("int").alias("word"), at.bitwiseAND(F.lit((1 << 15) - 1)).alias("bit"))
    with tidy(found.sparkSession):
        t = words.groupBy("word").agg(F.bitmap_construct_agg("bit").alias("held")).toArrow()
    out = np.zeros((1 << max(FILTER_BITS - 15, 0), 1 << 12), np.uint8)
    for word, held in zip(t["word"].to_pylist(), t["held"], strict=True):
        out[word] = np.frombuffer(held.as_py(), np.uint8)
    return out.ravel()


def asked_of(texts: list[np.ndarray], held: np.ndarray, parts: int) -> list[tuple[int, bytes]]:
    """What the words and pairs of texts ask of each part of the model: every key once, and the texts that have it, as often
    as they do. Parts of pairs come first, then as many of words. Nothing is asked that the filter knows to be missing."""
    import zlib

    keys, of = np.concatenate([NONE, *texts]), np.repeat(np.arange(len(texts), dtype=np.uint32), [len(k) for k in texts])
    inside = of[1:] == of[:-1]
    out = []
    for first, which in ((0, lambda: (pair_keys(keys)[inside], of[1:][inside])), (parts, lambda: (keys, of))):
        k, d = which()
        at = (k.view(np.uint64) >> np.uint64(64 - FILTER_BITS)).astype(np.int64)
        hit = (held[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)
        k, d = k[hit], d[hit]
        part = k.view(np.uint64) % np.uint64(parts)
        order = np.lexsort((d, k, part))
        k, d = k[order], d[order]
        cuts = np.searchsorted(part[order], np.arange(parts + 1, dtype=np.uint64))
        for p in np.flatnonzero(cuts[1:] > cuts[:-1]):
            some = slice(cuts[p], cuts[p + 1])
            known, n = np.unique(k[some], return_counts=True)
            head = np.array([len(known), len(k[some])], np.int64)
            out.append((first + int(p), head.tobytes() + known.tobytes() + zlib.compress(_planes(n.astype("<u4")) + _planes(d[some]), 1)))
    return out


def answered(data: bytes, known: np.ndarray, values: np.ndarray, margins: tuple[float, ...]) -> bytes | None:
    """For each text that asked, the sums of differences beyond each margin; None where the part has none."""
    import zlib

    m, n = (int(x) for x in np.frombuffer(data, np.int64, 2))
    body = zlib.decompress(data[16 + 8 * m:])
    v = np.repeat(_found(known, values, np.frombuffer(data, np.int64, m, 16)), _of_planes(body, "<u4", m, 0))
    some = v != 0
    v, (texts, at) = v[some], np.unique(_of_planes(body, "<u4", n, 4 * m)[some], return_inverse=True)
    if not len(texts):
        return None
    sums = [np.bincount(at, np.where(np.abs(v) > x, v, 0).astype(np.float64), len(texts)) for x in margins]
    return np.array([len(texts)], np.int64).tobytes() + zlib.compress(_planes(texts) + b"".join(_planes(x) for x in sums), 1)


def dealt_sums(docs: DataFrame, model: DataFrame, rows: int, margins: tuple[float, ...]) -> DataFrame:
    """__digest, __n, __e of ``docs`` (__digest, __text) by a model of any size: alone, key and value, ``rows`` in all. A task
    asks for many texts at once; each part of the model answers with sums for those texts, and the sums of all parts meet by
    what was asked at once. The rows of ``docs`` must come in the same order whenever they are read."""
    parts = max(MODEL_PARTS, -(-rows // PART_ROWS))
    model = model.where(F.abs("value") > min(margins))
    held = docs.sparkSession.sparkContext.broadcast(model_filter(model))
    names = ["part", "chunk", "data"]

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The model, by its parts; chunk -1."""
        found, size = [], 0

        def out() -> pa.RecordBatch:
            alone, key, value = (np.concatenate([x[i] for x in found]) for i in range(3))
            part = (key.view(np.uint64) % np.uint64(parts)).astype(np.int64) + parts * alone
            order = np.argsort(part, kind="stable")
            cuts = np.searchsorted(part[order], np.arange(2 * parts + 1))
            some = np.flatnonzero(cuts[1:] > cuts[:-1])
            key, value = key[order], value[order]
            data = [key[cuts[p]:cuts[p + 1]].tobytes() + value[cuts[p]:cuts[p + 1]].tobytes() for p in some]
            return pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([-1] * len(some), pa.int64()), pa.array(data, pa.binary())], names=names)

        for batch in batches:
            found.append((batch["alone"].to_numpy(zero_copy_only=False), batch["key"].to_numpy(), batch["value"].to_numpy()))
            size += batch.num_rows
            if size > 2 * HELD:
                yield out()
                found, size = [], 0
        if size:
            yield out()

    def asking(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        hashes, texts, digests, size = Hashes(), [], [], 0
        chunk = TaskContext.get().partitionId() << 32

        def out() -> pa.RecordBatch:
            # parts beyond those of the model only hand on which texts there are
            about = np.array([len(t) for t in texts], "<u4").tobytes() + b"".join(digests)
            asked = [*asked_of(texts, held.value, parts), (2 * parts + chunk % parts, about)]
            return pa.RecordBatch.from_arrays([pa.array([p for p, _ in asked], pa.int32()), pa.array([chunk] * len(asked), pa.int64()), pa.array([d for _, d in asked], pa.binary())], names=names)

        for batch in batches:
            for digest, text in zip(batch["__digest"], batch["__text"], strict=True):
                digests.append(digest.as_py())
                texts.append(keys_of(text.as_py(), hashes))
                size += len(texts[-1]) + 1
                if size > ASKED_AT:
                    yield out()
                    chunk, texts, digests, size = chunk + 1, [], [], 0
        if texts:
            yield out()

    def answering(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """kind 0: texts, 1: sums of pairs, 2: sums of words."""
        now, known, values, found = None, NONE, np.empty(0, np.float32), []
        for batch in batches:
            out = []
            for part, chunk, data in zip(batch["part"].to_pylist(), batch["chunk"].to_pylist(), batch["data"], strict=True):
                if part != now:
                    now, known, values, found = part, NONE, np.empty(0, np.float32), []
                data = data.as_py()
                if part >= 2 * parts:
                    out.append((chunk, 0, data))
                elif chunk < 0:
                    n = len(data) // 12
                    found.append((np.frombuffer(data, np.int64, n), np.frombuffer(data, np.float32, n, 8 * n)))
                else:
                    if found:
                        known, values = (np.concatenate([x[i] for x in found]) for i in (0, 1))
                        order, found = np.argsort(known), []
                        known, values = known[order], values[order]
                    if (sums := answered(data, known, values, margins)) is not None:
                        out.append((chunk, 1 + (part >= parts), sums))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], kind) for i, kind in enumerate((pa.int64(), pa.int32(), pa.binary()))], names=["chunk", "kind", "data"])

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zlib

        length = digests = e = None

        def out() -> pa.RecordBatch:
            sums = pa.FixedSizeListArray.from_arrays(pa.array(e.ravel()), e.shape[1]).cast(pa.list_(pa.float64()))
            return pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array(length.astype(np.int64)), sums], names=["__digest", "__n", "__e"])

        for batch in batches:
            for kind, data in zip(batch["kind"].to_pylist(), batch["data"], strict=True):
                data = data.as_py()
                if kind == 0:
                    if e is not None:
                        yield out()
                    n = len(data) // 20
                    length, digests, e = np.frombuffer(data, "<u4", n), [data[i:i + 16] for i in range(4 * n, 20 * n, 16)], np.zeros((n, 2 * len(margins)))
                else:
                    n, body = int(np.frombuffer(data, np.int64, 1)[0]), zlib.decompress(data[8:])
                    texts = _of_planes(body, "<u4", n, 0)
                    for i in range(len(margins)):
                        e[texts, 2 * i + (kind == 1)] += _of_planes(body, "<f8", n, 4 * n + 8 * n * i)
        if e is not None:
            yield out()

    kind = "part int, chunk long, data binary"
    both = model.select("alone", "key", "value").mapInArrow(dealt, kind).unionByName(docs.select("__digest", "__text").mapInArrow(asking, kind))
    found = both.repartition(2 * parts, "part").sortWithinPartitions("part", "chunk").mapInArrow(answering, "chunk long, kind int, data binary")
    return found.repartition("chunk").sortWithinPartitions("chunk", "kind").mapInArrow(summed, "__digest binary, __n long, __e array<double>")


def pair_keys_of(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    u = np.empty(2 * len(h), np.int64)
    u[::2], u[1::2] = h, w
    return pair_keys(u)[::2]


def features(a: float, b: float, n: int) -> tuple[float, ...]:
    """Evidence normalised by the length, and by its root, which is how chance adds up."""
    n = max(n, 1)
    return 1.0, a / n, a / n**0.5, b / n


def fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3, rounds: int = 50) -> np.ndarray:
    """Logistic regression by Newton steps; classes weigh the same."""
    b = np.zeros(x.shape[1])
    w = np.where(y == 1, 0.5 / max(1, (y == 1).sum()), 0.5 / max(1, (y == 0).sum()))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        g = x.T @ (w * (p - y)) + ridge * b * (np.arange(len(b)) > 0) / 100
        h = (x * (w * p * (1 - p))[:, None]).T @ x + ridge / 100 * np.eye(len(b))
        step = np.linalg.solve(h, g)
        b -= np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-7:
            break
    return b


def choose(rows: list[tuple], margins: tuple[float, ...]) -> tuple[int, np.ndarray]:
    """Which margin, and the curve. Rows: label, words, then evidence for each margin."""
    y = np.array([r[0] for r in rows])
    best = None
    for i in range(len(margins)):
        x = np.array([features(r[2 + 2 * i], r[3 + 2 * i], r[1]) for r in rows])
        curve = fit_curve(x, y)
        p = np.clip(1 / (1 + np.exp(-np.clip(x @ curve, -30, 30))), 1e-9, 1 - 1e-9)
        loss = -np.log(p[y == 1]).mean() - np.log(1 - p[y == 0]).mean()
        if best is None or loss < best[0] - 1e-3:
            best = (loss, i, curve)
    return best[1], best[2]


class Scorer:
    """Texts to evidence, with the model on every worker or dealt out."""

    def __init__(self, docs: DataFrame, rows: DataFrame, model_rows: int):
        self.rows = materialize(rows)
        self.n = self.rows.count()
        self.small = self.n <= model_rows
        self.model = docs.sparkSession.sparkContext.broadcast(collected(self.rows)) if self.small else keyed(self.rows)

    def evidence(self, docs: DataFrame, margins: tuple[float, ...], text: str = "__text") -> DataFrame:
        """The columns of ``docs`` but __text, and __n and __e (two numbers for each margin)."""
        keep = [c for c in docs.columns if c != "__text"]
        if self.small:
            model, names = self.model, [*keep, "__n", "__e"]

            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                hashes = Hashes()
                for batch in batches:
                    done, held, size, lengths = [], [], 0, []
                    for t in batch[text]:
                        held.append(keys_of(t.as_py(), hashes))
                        lengths.append(len(held[-1]))
                        size += lengths[-1]
                        if size > HELD:
                            done.append(model.value.evidence(held, margins))
                            held, size = [], 0
                    done.append(model.value.evidence(held, margins))
                    e = pa.array(list(np.concatenate(done)), pa.list_(pa.float64()))
                    yield pa.RecordBatch.from_arrays([*(batch[c] for c in keep), pa.array(lengths, pa.int64()), e], names=names)

            kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
            return docs.select(*dict.fromkeys([*keep, text])).mapInArrow(run, f"{kinds}, __n long, __e array<double>")
        # equal texts have equal evidence, so a text is known by its digest
        given = docs.withColumn("__digest", F.unhex(F.md5(F.coalesce(text, F.lit("")))))
        sums = materialize(dealt_sums(given.select("__digest", F.col(text).alias("__text")), self.model, self.n, margins))
        sums = sums.groupBy("__digest").agg(F.first("__n").alias("__n"), F.first("__e").alias("__e"))
        return given.join(sums, "__digest").select(*(given[c] for c in keep), "__n", "__e")


def _labelled(docs: DataFrame, ids: DataFrame, n: int) -> DataFrame:
    """__text, __toxic of the documents whose id is among ``ids`` (__id, __toxic)."""
    some = F.broadcast(ids) if n <= LABEL_ROWS else ids
    return docs.join(some, docs["doc_id"] == ids["__id"]).select(docs["text"].alias("__text"), ids["__toxic"])


def learned_from(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, model_rows: int = MODEL_ROWS) -> tuple[Scorer, int, np.ndarray] | None:
    """Differences, which margin, curve; None with a class missing."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy(F.col("doc_id").alias("__id")).agg(F.max(F.when(F.col("toxic") > 0, 1).otherwise(0)).alias("__toxic"))
    known = materialize(known.withColumn("__kept", F.pmod(F.xxhash64("__id"), F.lit(3)) == 2))
    n = {(r["__toxic"], r["__kept"]): r["n"] for r in known.groupBy("__toxic", "__kept").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not all(any((c, k) in n for k in (True, False)) for c in (0, 1)):
        return None
    apart = all((c, k) in n for c in (0, 1) for k in (True, False))  # with a handful of labels, all count and all choose
    total = sum(n.values())
    pairs = materialize(pair_counts(_labelled(docs, known.where("NOT __kept") if apart else known, total)))
    found = differences(pairs, materialize(continuations(docs, common=common_histories(pairs))), seen=1)
    if found is None:
        return None
    scorer = Scorer(docs, found, model_rows)
    by_hash = [F.md5(F.col("__id").cast("string")), F.col("__id")]
    some = [known.where((F.col("__toxic") == c) & (F.col("__kept") | F.lit(not apart))).orderBy(*by_hash).limit(sample) for c in (0, 1)]
    tried = _labelled(docs, some[0].unionByName(some[1]), 2 * sample)
    tried = scorer.evidence(tried if scorer.small else materialize(tried), MARGINS)
    rows = [(r["__toxic"], r["__n"], *r["__e"]) for r in tried.orderBy("__toxic", "__n", "__e").collect()]  # numbers of two samples
    if len({r[0] for r in rows}) < 2:
        return None
    return scorer, *choose(rows, MARGINS)


def _scored(docs: DataFrame, given: DataFrame, text: str, labels: DataFrame, sample: int, model_rows: int) -> DataFrame:
    """``given`` without __text, and __score, by what is learned from ``docs``."""
    ship(docs.sparkSession)
    learned = learned_from(docs.select("doc_id", "text"), labels, sample, model_rows)
    if learned is None:
        return given.drop("__text").withColumn("__score", F.lit(0.0))
    scorer, at, curve = learned
    found = scorer.evidence(given, (MARGINS[at],), text)
    length = F.greatest(F.col("__n"), F.lit(1))
    a, b = F.col("__e")[0], F.col("__e")[1]
    z = F.lit(float(curve[0])) + float(curve[1]) * a / length + float(curve[2]) * a / F.sqrt(length) + float(curve[3]) * b / length
    return found.withColumn("__score", 1 / (1 + F.exp(-F.least(F.greatest(z, F.lit(-700.0)), F.lit(700.0))))).drop("__n", "__e")


def score(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, model_rows: int = MODEL_ROWS) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted."""
    given = docs.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), F.col("text").alias("__text"))
    out = _scored(docs, given, "__text", labels, sample, model_rows)
    return out.select("doc_id", "held_out", F.col("__score").alias("score"), (F.col("__score") >= 0.5).cast("int").alias("predicted"))


def ordinary_documents(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, model_rows: int = MODEL_ROWS) -> DataFrame:
    """The rows that are not predicted toxic, with all their columns: a stage of a pipeline."""
    return _scored(docs, docs, "text", labels, sample, model_rows).where("__score < 0.5").drop("__score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
