"""Exact token counts of a byte-level BPE vocabulary, without making any token.

A text is cut into pieces by the vocabulary's own pattern. The symbols of a piece form a linked list; a heap holds its
adjacent pairs by merge rank and place. Popping the lowest live pair merges two nodes into one; the count of a piece is
its initial symbols less the merges done. Counts of pieces are kept in a table of bounded size, as pieces repeat.

Defined cases: a null or empty text has 0 bytes and 0 tokens; repeated rows are counted each; a special string inside a
text is one token, as is the library's default; texts of any length are counted whole, in memory proportional to the
longest text of a batch. Only the named columns are read.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import ship, table

#: Pieces whose counts a task keeps; the table starts anew beyond it.
CACHE = 1_000_000
LIMIT = 512
#: Fixed value: the pattern of byte-level vocabularies, as published with them.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def tokenizer_path(name: str) -> str:
    """Where the public vocabulary files lie on this machine; each executor has its own copy."""
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies: printable ones stand for themselves,
    the rest take the letters from 256 on."""
    plain = {*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)}
    out, spare = [], 256
    for b in range(256):
        if b in plain:
            out.append(chr(b))
        else:
            out.append(chr(spare))
            spare += 1
    return out


class MergeCounter(dict):
    """Token counts by piece; a missing piece is merged and kept."""

    def __init__(self, path: str, cache: int = CACHE):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        self.limit = cache
        self.letters = [vocab[c] for c in byte_letters()]
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.merges[vocab[a], vocab[b]] = (rank, vocab[a + b])
        self.split = regex.compile(PATTERN).findall
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None

    def __missing__(self, piece: str) -> int:
        if len(self) >= self.limit:
            self.clear()
        self[piece] = n = self.merged(piece.encode())
        return n

    def merged(self, raw: bytes) -> int:
        n = len(raw)
        if n < 2:
            return n
        merges = self.merges
        symbol = [self.letters[b] for b in raw]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            m = merges.get((symbol[i], symbol[i + 1]))
            if m:
                heap.append((m[0], i, m[1], symbol[i], symbol[i + 1]))
        heapq.heapify(heap)
        count = n
        while heap:
            _, i, made, left, right = heapq.heappop(heap)
            j = after[i]
            if symbol[i] != left or j >= n or symbol[j] != right:
                continue  # one of the two has been merged since
            symbol[i], symbol[j] = made, -1
            after[i] = k = after[j]
            count -= 1
            if k < n:
                before[k] = i
                m = merges.get((made, symbol[k]))
                if m:
                    heapq.heappush(heap, (m[0], i, m[1], made, symbol[k]))
            k = before[i]
            if k >= 0:
                m = merges.get((symbol[k], made))
                if m:
                    heapq.heappush(heap, (m[0], k, m[1], symbol[k], made))
        return count

    def count(self, text: str) -> int:
        if self.special is None or not self.special.search(text):
            return sum(map(self.__getitem__, self.split(text)))
        n, at = 0, 0
        for m in self.special.finditer(text):
            n += 1 + sum(map(self.__getitem__, self.split(text[at:m.start()])))
            at = m.end()
        return n + sum(map(self.__getitem__, self.split(text[at:])))


_counters: dict[tuple[str, int], MergeCounter] = {}


def counter(path: str, cache: int = CACHE) -> MergeCounter:
    """One counter for each worker process, whatever number of tasks it runs."""
    if (path, cache) not in _counters:
        _counters[path, cache] = MergeCounter(path, cache)
    return _counters[path, cache]


def count_tokens(docs: DataFrame, key: str = "doc_id", text: str = "text", vocabulary: str = "byte_bpe_50k.json", limit: int = LIMIT, cache: int = CACHE) -> DataFrame:
    """Per row: key, n_bytes, n_tokens, over_limit. One pass, no shuffle. ``vocabulary``: a file name or a path."""
    ship(docs.sparkSession)
    schema = f"{key} {docs.schema[key].dataType.simpleString()}, n_bytes long, n_tokens long, over_limit boolean"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(vocabulary if "/" in vocabulary else tokenizer_path(vocabulary), cache)
        for batch in batches:
            n_bytes, n_tokens = [], []
            for x in batch["__text"]:
                t = x.as_py() or ""
                n_bytes.append(len(t.encode()))
                n_tokens.append(c.count(t))
            yield pa.RecordBatch.from_arrays([batch["__key"], pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens], pa.bool_())], names=[key, "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col(key).alias("__key"), F.col(text).alias("__text")).mapInArrow(run, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"))
