r"""Chat formatting at the level of tokens.

Each segment of a turn is encoded by itself: its header and its end are reserved ids, its text is ordinary ids, so no
merge runs across a border and no text can make a reserved id. The loss mask is the prefix sum of +1 where a learned
segment begins and -1 where it ends.

As read back, a turn is ``### User: text </turn>`` and a newline. A backslash goes before each ``### ``, ``</turn>`` and
backslash inside a text, which makes the formatted text readable without its ids and the escape reversible. A role other
than system, user and assistant is written as ``### Role name: ``, escaped likewise and with its colons as ``\.``.

Defined cases: rows go by turn, nulls first, then role and text, so ties have one order; a null text or role is empty; a
null conversation id is an id; repeated rows are turns of their own; an empty table gives no rows. A conversation is
streamed turn by turn, so its memory is that of its longest turn.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.llm.common import ship, table
from triplefed.llm.token_count import PATTERN, tokenizer_path

#: Control strings and their reserved ids above the vocabulary (50,256 is its own end mark).
HEADERS = {"system": "### System: ", "user": "### User: ", "assistant": "### Assistant: "}
OTHER, ROLE_END, TURN_END = "### Role ", ": ", " </turn>\n"
RESERVED = {**{s: 50257 + i for i, s in enumerate(HEADERS.values())}, OTHER: 50260, ROLE_END: 50261, TURN_END: 50262}
LEARNED = "assistant"


def escape(text: str) -> str:
    return text.replace("\\", "\\\\").replace("### ", "\\### ").replace("</turn>", "\\</turn>")


def escape_role(role: str) -> str:
    return escape(role).replace(":", "\\.")


_ESCAPED = re.compile(r"\\(.)", re.S)


def unescape(text: str) -> str:
    return _ESCAPED.sub(lambda m: ":" if m[1] == "." else m[1], text)


class Codec:
    """Text to ids by the public byte-level vocabulary, and back."""

    def __init__(self, path: str):
        import base64

        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f)}
        self.encoding = tiktoken.Encoding("chat", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=RESERVED)

    def ordinary(self, text: str) -> np.ndarray:
        """Whatever the text says, no reserved id comes of it."""
        return self.encoding.encode_to_numpy(text, allowed_special=set(), disallowed_special=()).astype(np.int32)

    def turn(self, role: str, text: str) -> tuple[np.ndarray, np.ndarray]:
        header = [RESERVED[HEADERS[role]]] if role in HEADERS else [RESERVED[OTHER], *self.ordinary(escape_role(role)), RESERVED[ROLE_END]]
        body = self.ordinary(escape(text))
        ids = np.concatenate([np.array(header, np.int32), body, np.array([RESERVED[TURN_END]], np.int32)])
        steps = np.zeros(len(ids) + 1, np.int8)
        if role == LEARNED:
            steps[len(header)] += 1
            steps[len(header) + len(body)] -= 1
        return ids, np.cumsum(steps[:-1], dtype=np.int8)

    def text(self, ids) -> bytes:
        return self.encoding.decode_bytes(ids.tolist() if isinstance(ids, np.ndarray) else ids)


def _lists(parts: list[np.ndarray], kind: pa.DataType) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, parts)], dtype=np.int32)
    flat = np.concatenate(parts) if parts else np.empty(0, np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, kind))


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def parse(formatted: str) -> Iterator[tuple[str, str]]:
    """Roles and texts of a formatted text."""
    named = {v: k for k, v in HEADERS.items()}
    at = 0
    while at < len(formatted):
        for header, role in named.items():
            if formatted.startswith(header, at):
                at += len(header)
                break
        else:
            if not formatted.startswith(OTHER, at):
                raise ValueError(f"no header at {at}")
            to = formatted.index(ROLE_END, at)
            role = unescape(formatted[at + len(OTHER):to])
            at = to + len(ROLE_END)
        to = formatted.index(TURN_END, at)
        yield role, unescape(formatted[at:to])
        at = to + len(TURN_END)


def format_chat(turns: DataFrame, vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """Rows conv_id, turn, ids, loss_mask: a conversation is its rows in a row, all in one partition and in order."""
    ship(turns.sparkSession)
    kind, turn_kind = (turns.schema[c].dataType.simpleString() for c in ("conv_id", "turn"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(vocabulary if "/" in vocabulary else tokenizer_path(vocabulary))
        for batch in batches:
            made = [c.turn(r or "", t or "") for r, t in zip(batch["role"].to_pylist(), batch["text"].to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch["conv_id"], batch["turn"], _lists([m[0] for m in made], pa.int32()), _lists([m[1] for m in made], pa.int8())], names=["conv_id", "turn", "ids", "loss_mask"])

    order = [F.col("conv_id"), F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first()]
    rows = turns.select("conv_id", "turn", "role", "text").repartition("conv_id").sortWithinPartitions(*order)
    return rows.mapInArrow(run, f"conv_id {kind}, turn {turn_kind}, ids array<int>, loss_mask array<tinyint>")


def read_back(formatted: DataFrame, vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """Per conversation, decoded and parsed: conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars."""
    kind = formatted.schema["conv_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(vocabulary if "/" in vocabulary else tokenizer_path(vocabulary))
        rows: list[tuple] = []
        state = key = None

        def done() -> None:
            if state is not None:
                rows.append((state[0], state[1], state[2].hexdigest(), state[3], state[4].hexdigest(), state[5]))

        for batch in batches:
            key = batch.schema.field("conv_id").type
            ids, masks = batch["ids"], batch["loss_mask"].flatten().to_numpy()
            ends, flat = ids.offsets.to_numpy() - ids.offsets[0].as_py(), ids.flatten().to_numpy()
            for i, conv in enumerate(batch["conv_id"].to_pylist()):
                own, mask = flat[ends[i]:ends[i + 1]], masks[ends[i]:ends[i + 1]]
                if state is None or state[0] != conv:
                    done()
                    state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                text = c.text(own).decode()
                state[5] += len(text)
                for role, said in parse(text):
                    state[1] += 1
                    state[2].update(f"{role}\n{said}\n".encode())
                if mask.any():
                    learned = unescape(c.text(own[mask == 1]).decode())
                    state[3] += len(learned)
                    state[4].update(learned.encode())
            if len(rows) > 1:
                yield _rows(rows, key)
                rows = []
        done()
        if rows:
            yield _rows(rows, key)

    return formatted.select("conv_id", "ids", "loss_mask").mapInArrow(run, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def _rows(rows: list[tuple], kind: pa.DataType) -> pa.RecordBatch:
    kinds = [kind, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds, strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])


#: Fixed value: the text of both turns of conversation -7.
PROBE = "\\### Assistant: </turn> ok"


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-7, 0, "user", PROBE), (-7, 1, "assistant", PROBE)], given.schema)
    return read_back(format_chat(given.unionByName(probe)))


ORACLE = r"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
e AS (SELECT *, replace(replace(replace(text, '\', '\\'), '### ', '\### '), '</turn>', '\</turn>') AS escaped,
             CASE role WHEN 'system' THEN 12 WHEN 'user' THEN 10 WHEN 'assistant' THEN 15 END AS header FROM c),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS every,
             coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS learned,
             CAST(sum(header + length(escaped) + 9) AS BIGINT) AS formatted_chars FROM e GROUP BY conv_id)
SELECT conv_id, n_turns, sha256(every) AS turns_sha256, length(learned) AS loss_chars, sha256(learned) AS loss_sha256, formatted_chars FROM g"""
