"""Best-fit packing of token pieces into sequences, in bulk-synchronous rounds.

Documents are tokenized once and cut into pieces; only rows of a few numbers go on. A piece of full length is a sequence by
itself. The others go in phases. A phase opens sequences: one for each piece of over half the capacity, as no two of these
share one, and once these are gone, for the longest pieces as many as what is left needs at least. Then rounds follow:

1. Gaps of open sequences and pieces not yet placed are sorted by size in one order, gaps first among equals.
2. A sweep goes from large to small. Each piece takes the smallest gap before it that no piece has taken, its successor by
   size. The sweep isn't walked: a row's depth, how many gaps lie open there, is the sum of the counts of larger sizes and
   its rank within its own, and a piece meets the gap that comes right before it among the rows of its depth.
3. Ranks also settle who gets a gap that several pieces want: of equal sizes each has a depth of its own.
4. Gaps shrink by what they took, and the next round begins, until no gap holds any piece.

Where all pieces left are much smaller than a gap, the gap is dealt into several, so that a round fills it with many.
Only sums and counts go to the driver. Sizes are at most the capacity, so what is kept for each size is bounded by it; rows
of one size, however many, are dealt into parts by hash and ranked part by part. No round moves texts or ids.

Defined cases: a null or empty text is one piece, the end mark alone; a text longer than the capacity is cut into full
pieces and a rest; repeated rows are packed each; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import re
import sys
import unicodedata
import zlib
from array import array
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed.llm.common import materialize, power_of_two, ship, table
from triplefed.llm.token_count import byte_letters, tokenizer_path

CAPACITY = 4096
END_ID = 1
#: Words whose ids a task keeps. Beyond it, those go that weren't met since half as many others were.
CACHE = 600_000
#: The word pattern of the lower-casing vocabulary file, for ASCII and for any text. What most words are is
#: tried first; only the last two begin alike.
ASCII_WORDS = r"[a-z]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\sa-z0-9]+"
WORDS = r"[^\W\d_]+|\d|'(?:s|t|re|ve|m|ll|d)|(?:[^\s\w]|_)+"


#: Rows of one size that are ranked in one part.
PART_ROWS = 20_000


class WordEncoder(dict):
    """Ids of whole texts as bytes, four to an id. The library's model encodes each distinct word once; a text's ids are
    its words' ids in a row, since the vocabulary merges nothing across words.

    Words are cut here only in texts all of whose characters have been held against the library: each in several
    surroundings, once. Other texts, those with combining marks, which change their neighbours, and those with special
    strings go to the library whole.
    """

    def __init__(self, path: str, cache: int = CACHE):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.limit = max(1, cache // 2)
        self.older: dict[str, bytes] = {}
        self.letters = byte_letters()
        self.plain = str.maketrans({chr(b): self.letters[b] for b in range(128) if chr(b) != self.letters[b]})
        self.ascii_words = re.compile(ASCII_WORDS).findall
        self.words = re.compile(WORDS).findall
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        # the Greek capital whose small form hangs on the word around it
        self.odd: set[str] = {"\u03a3"}
        self.proven: set[str] = set()
        self.ascii_odd = re.compile("[" + "".join(re.escape(c) for c in map(chr, range(128)) if not self._agrees(c)) + "]" if any(not self._agrees(c) for c in map(chr, range(128))) else r"(?!)").search

    def __missing__(self, word: str) -> bytes:
        if len(self) >= self.limit:
            self.older = dict(self)
            self.clear()
        out = self.older.get(word)
        if out is None:
            if not word.isascii():
                known = "".join([self.letters[b] for b in word.encode()])
            else:  # ASCII letters and digits stand for themselves
                known = word if word.isalnum() else word.translate(self.plain)
            out = _packed([t.id for t in self.model.tokenize(known)])
        self[word] = out
        return out

    def _library(self, text: str) -> bytes:
        return _packed(self.tokenizer.encode(text, add_special_tokens=False).ids)

    def _cut(self, text: str) -> bytes:
        if text.isascii():
            return b"".join(map(self.__getitem__, self.ascii_words(text.lower())))
        return b"".join(map(self.__getitem__, self.words(unicodedata.normalize("NFC", text).lower())))

    def _agrees(self, c: str) -> bool:
        """Whether a character means the same here as to the library: alone and doubled, beside letters, digits, marks and
        blanks, and before the ends of words that are cut off after an apostrophe."""
        if unicodedata.category(c)[0] in "MC" and not c.isascii():
            return False
        text = f"{c} a{c}b{c}{c}1{c}2 {c}.{c}-\u00e9{c}\u00e9'{c}s'{c}{c} A{c}B'll{c}\n{c}"
        return self._cut(text) == self._library(text)

    def encode(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            return self._library(text)
        if text.isascii():
            return self._library(text) if self.ascii_odd(text) else self._cut(text)
        new = set(text) - self.proven
        if new:
            if self.odd.isdisjoint(new):
                for c in new:
                    (self.proven if self._agrees(c) else self.odd).add(c)
            if not self.odd.isdisjoint(new):
                return self._library(text)
        return self._cut(text)


def _packed(ids: list[int]) -> bytes:
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


_encoders: dict[tuple[str, int], WordEncoder] = {}


def encoder(path: str, cache: int = CACHE) -> WordEncoder:
    if (path, cache) not in _encoders:
        _encoders[path, cache] = WordEncoder(path, cache)
    return _encoders[path, cache]


def pieces(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", vocabulary: str = "word_bpe_49k.json", capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: each document's ids and the end mark, cut at the capacity."""
    ship(docs.sparkSession)
    kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(vocabulary if "/" in vocabulary else tokenizer_path(vocabulary))
        end, step = _packed([end_id]), 4 * capacity
        for batch in batches:
            at, piece, start, length, crc = [], [], [], [], []
            for i, x in enumerate(batch["__text"]):
                raw = e.encode(x.as_py() or "") + end
                for k, lo in enumerate(range(0, len(raw), step)):
                    part = raw[lo:lo + step]
                    at.append(i)
                    piece.append(k)
                    start.append(lo // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            yield pa.RecordBatch.from_arrays([batch["__key"].take(pa.array(at, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(doc_id).alias("__key"), F.col(text).alias("__text")).mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def _numbered(rows: DataFrame, total: int) -> DataFrame:
    """Adds ``depth``: how many gaps lie open in the sweep at a gap that is counted in, or at a piece before it takes one.
    Rows: kind (0 gap, 1 piece), size, id, unit."""
    given = rows.withColumn("part", F.pmod(F.xxhash64("id", "unit"), F.lit(power_of_two(total / PART_ROWS, 1))).cast("int"))
    parts = given.groupBy("size", "kind", "part").agg(F.count(F.lit(1)).alias("n"))
    # as many rows as there are sizes, twice the capacity at most
    sizes = parts.groupBy("size", "kind").agg(F.sum("n").alias("n"))
    larger = Window.orderBy(F.col("size").desc(), "kind").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("size", "kind", F.coalesce(F.sum(F.when(F.col("kind") == 0, F.col("n")).otherwise(-F.col("n"))).over(larger), F.lit(0)).alias("open"))
    before = Window.partitionBy("size", "kind").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = parts.select("size", "kind", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start")).join(F.broadcast(sizes), ["size", "kind"])
    rank = F.col("start") + F.row_number().over(Window.partitionBy("size", "kind", "part").orderBy("id", "unit"))
    out = given.join(starts, ["size", "kind", "part"])
    return out.withColumn("depth", F.when(F.col("kind") == 0, F.col("open") + rank).otherwise(F.col("open") - rank + 1))


def sweep(gaps: DataFrame, pieces: DataFrame, open_: int, left: int, longest: int) -> DataFrame:
    """kind, id, size, sequence: all gaps (kind 0) with their sizes, and all pieces (kind 1) with the sequence each goes to,
    null where no gap is left for it. Gaps: sequence, gap; pieces: id, size.

    A gap is dealt into units that hold the longest piece each, the last with what is over, about as many in all as
    there are pieces and gaps.
    """
    share = 1 + -(-left // max(1, open_))
    units = F.greatest(F.lit(1), F.least(F.floor(F.col("gap") / longest), F.lit(share))).cast("int")
    dealt = gaps.withColumn("units", units).select("sequence", "gap", "units", F.explode(F.sequence(F.lit(0), F.col("units") - 1)).alias("unit"))
    size = F.when(F.col("unit") < F.col("units") - 1, F.lit(longest)).otherwise(F.col("gap") - (F.col("units") - 1) * longest)
    rows = dealt.select(F.lit(0).alias("kind"), size.cast("long").alias("size"), F.col("sequence").alias("id"), "unit", F.col("gap").cast("long").alias("gap"))
    rows = rows.unionByName(pieces.select(F.lit(1).alias("kind"), "size", "id", F.lit(0).alias("unit"), F.lit(None).cast("long").alias("gap")))
    # rows of one depth are of different sizes or kinds each: twice the capacity at most
    row = Window.partitionBy("depth").orderBy(F.col("size").desc(), "kind")
    met = _numbered(rows, 2 * (open_ + left)).select("kind", "id", "size", "unit", "gap", F.lag("kind").over(row).alias("above"), F.lag("id").over(row).alias("before"))
    met = met.where("kind = 1 OR unit = 0")
    to = F.when(F.col("kind") == 0, F.col("id")).when(F.col("above") == 0, F.col("before"))
    return met.select("kind", "id", F.coalesce("gap", "size").alias("size"), to.alias("sequence"))


def _measured(left: DataFrame, gaps: DataFrame | None) -> dict:
    """Of the pieces left: number, tokens, least and greatest size, how many are large; and how many gaps hold the least."""
    one = left.agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("total"), F.min("size").alias("least"), F.max("size").alias("most"))
    if gaps is not None:
        least = left.agg(F.min("size").alias("least_"))
        one = one.crossJoin(gaps.crossJoin(F.broadcast(least)).agg(F.count_if(F.col("gap") >= F.col("least_")).alias("open")))  # one row each
    return one.collect()[0].asDict()


def _longest(pieces: DataFrame, wanted: int) -> Column:
    """Which of the pieces (id, size) are the ``wanted`` longest; of those as long as the shortest of them, those with the
    smallest hashes of their ids."""
    counts = pieces.groupBy("size").agg(F.count(F.lit(1)).alias("n")).collect()  # as many rows as sizes: the capacity at most
    for size, n in sorted(((r["size"], r["n"]) for r in counts), reverse=True):
        if n <= wanted:
            wanted -= n
            if not wanted:
                return F.col("size") >= size
            continue
        # the hash of the last one is looked for in the one of many bins that holds it
        alike, h = pieces.where(F.col("size") == size), F.xxhash64("id")
        bins = alike.groupBy(F.shiftright(h, 54).alias("bin")).agg(F.count(F.lit(1)).alias("n")).collect()  # 1024 rows
        for r in sorted(bins, key=lambda r: r["bin"]):
            if r["n"] >= wanted:
                last = alike.where(F.shiftright(h, 54) == r["bin"]).select(h.alias("h")).orderBy("h").limit(wanted).agg(F.max("h")).collect()[0][0]
                return (F.col("size") > size) | ((F.col("size") == size) & (F.xxhash64("id") <= last))
            wanted -= r["n"]
    return F.lit(True)


def best_fit(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """id, sequence, step: where each piece goes, and after which ones it came there. Pieces: id (distinct), size, at most
    the capacity. A sequence bears the id of its first piece."""
    # whatever fills a sequence, or is alone in it so far
    placed = [pieces.where(F.col("size") >= capacity).select("id", "size", F.col("id").alias("sequence"), F.lit(0).alias("step"))]
    left = materialize(pieces.where(F.col("size") < capacity).select("id", F.col("size").cast("long").alias("size")))
    gaps, step, large = None, 0, F.col("size") > capacity // 2
    now = _measured(left, None)
    while now["n"]:
        step += 1
        first = large if now["most"] > capacity // 2 else _longest(left, -(-now["total"] // capacity))
        opened = left.where(first).select("id", "size", F.col("id").alias("sequence"), F.lit(step).alias("step"))
        placed.append(opened)
        new = opened.select("sequence", (F.lit(capacity) - F.col("size")).alias("gap"))
        gaps = new if gaps is None else gaps.unionByName(new)
        left = left.where(~first)
        now = _measured(left, gaps)
        while now["n"] and now["open"]:
            step += 1
            met = materialize(sweep(gaps.where(F.col("gap") >= now["least"]), left, now["open"], now["n"], now["most"]))
            placed.append(met.where("kind = 1 AND sequence IS NOT NULL").select("id", "size", "sequence", F.lit(step).alias("step")))
            gaps = met.where("sequence IS NOT NULL").groupBy("sequence").agg(F.sum(F.when(F.col("kind") == 0, F.col("size")).otherwise(-F.col("size"))).alias("gap"))
            left = met.where("kind = 1 AND sequence IS NULL").select("id", "size")
            now = _measured(left, gaps)
    out = placed[0]
    for p in placed[1:]:
        out = out.unionByName(p)
    return out


def pack(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", vocabulary: str = "word_bpe_49k.json", capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cut = materialize(pieces(docs, doc_id, text, vocabulary, capacity, end_id).withColumn("id", F.monotonically_increasing_id()))
    places = best_fit(cut.select("id", F.col("length").alias("size")), capacity)
    # pieces of a sequence: the capacity at most
    order = Window.partitionBy("sequence").orderBy("step", "id").rowsBetween(Window.unboundedPreceding, -1)
    places = places.select("id", "sequence", F.coalesce(F.sum("size").over(order), F.lit(0)).alias("offset"))
    return cut.join(places, "id").select("doc_id", "piece", "start", "length", "ids_crc32", F.col("sequence").alias("sequence_id"), F.col("offset").cast("long").alias("offset"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
