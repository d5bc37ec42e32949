"""Chat formatting: segments are encoded apart, reserved ids spliced in, loss masks derived from prefix sums."""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm.plan import load

# The template's control strings. A turn is OPEN role MIDDLE text CLOSE.
OPEN, MIDDLE, CLOSE = "### ", ": ", "</turn>\n"
_CONTROL = re.compile(r"(?=###|</turn>)")
_ESCAPED = re.compile(r"\\(.)", re.DOTALL)


def escape(text: str) -> str:
    """No control string survives in the result; `unescape` gives the text back.

    Backslashes are doubled and every place where a control string starts, overlapping
    ones included, gets a backslash.
    """
    return _CONTROL.sub(r"\\", text.replace("\\", "\\\\"))


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


@dataclass(frozen=True)
class Vocabulary:
    """A byte-level vocabulary as (token bytes -> id) and its splitting pattern; ids from `reserved` on are free."""

    ranks: dict[bytes, int]
    pattern: str

    @property
    def reserved(self) -> int:
        return max(self.ranks.values()) + 1

    @classmethod
    def read(cls, path: str | None = None, pattern: str | None = None) -> Vocabulary:
        import public_tokenizers

        lines = Path(path or public_tokenizers.path("byte_bpe_50k.tiktoken")).read_bytes().split(b"\n")
        return cls({base64.b64decode(a): int(b) for a, b in (x.split() for x in lines if x)}, pattern or public_tokenizers.PATTERN)


def _encoder(shared):
    import tiktoken

    v = shared.value
    return tiktoken.Encoding("chat", pat_str=v.pattern, mergeable_ranks=v.ranks, special_tokens={})


def _encode(shared):
    """A turn's ids: open, role, middle, text, close; the reserved ids stand for the control strings alone."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, base = None, 0
        for batch in batches:
            if encoder is None:
                encoder, base = _encoder(shared), shared.value.reserved
            for lo in range(0, batch.num_rows, 512):
                piece = batch.slice(lo, 512)
                ids, begin, end = [], [], []
                for role, text in zip(piece.column("role").to_pylist(), piece.column("text").to_pylist(), strict=True):
                    head = [base, *encoder.encode_ordinary(escape(role)), base + 1]
                    body = encoder.encode_ordinary(escape(text))
                    ids.append([*head, *body, base + 2])
                    begin.append(len(head))
                    end.append(len(head) + len(body))
                yield pa.RecordBatch.from_arrays(
                    [piece.column("conv_id"), piece.column("turn"), piece.column("role"), pa.array(ids, pa.list_(pa.int32())), pa.array(begin, pa.int32()), pa.array(end, pa.int32())],
                    names=["conv_id", "turn", "role", "ids", "text_begin", "text_end"],
                )

    return run


def _assemble(loss_role: str):
    """Positions within the conversation from prefix sums; a conversation may go on over many batches."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, so_far, started = None, 0, False
        for batch in batches:
            conv = batch.column("conv_id")
            value = conv.fill_null(0).to_numpy()
            null = conv.is_null().to_numpy(zero_copy_only=False)
            size = np.diff(np.asarray(batch.column("ids").offsets)).astype(np.int64)
            n = len(value)
            new = np.ones(n, bool)
            new[1:] = (value[1:] != value[:-1]) | (null[1:] != null[:-1])
            if started and n:
                new[0] = current != (value[0], null[0])
            total = np.cumsum(size) - size
            head = np.maximum.accumulate(np.where(new, np.arange(n), -1))
            start = np.where(head >= 0, total - total[np.maximum(head, 0)], total + so_far)
            if n:
                started, current, so_far = True, (value[-1], null[-1]), int(start[-1] + size[-1])
            loss = np.array([r == loss_role for r in batch.column("role").to_pylist()], bool)
            begin = start + batch.column("text_begin").to_numpy()
            end = np.where(loss, start + batch.column("text_end").to_numpy(), begin)
            yield pa.RecordBatch.from_arrays(
                [conv, batch.column("turn"), batch.column("ids"), pa.array(start, pa.int64()), pa.array(begin, pa.int64()), pa.array(end, pa.int64())],
                names=["conv_id", "turn", "ids", "start", "loss_begin", "loss_end"],
            )

    return run


def format_chat(
    turns: DataFrame, vocabulary: Vocabulary, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", loss_role: str = "assistant"
) -> DataFrame:
    """Token sequences of conversations: one row a turn, in order within each partition.

    Returns conv_id, turn, ids (the turn's tokens), start (the position of the first in
    the conversation) and the mask as loss_begin and loss_end (positions of the text's
    tokens if the role is `loss_role`, else an empty range). A conversation is the
    concatenation of its rows and lies in one partition, streamed and not gathered, so
    that its length is not bounded by memory.

    Null texts and roles are empty ones. Rows without a conversation id form one
    conversation without an id. Rows without a turn come first; ties go by role, then
    text; repeated rows are turns of their own. An empty table gives no rows.
    """
    shared = turns.sparkSession.sparkContext.broadcast(vocabulary)
    rows = turns.select(
        F.col(conv_col).cast("long").alias("conv_id"),
        F.col(turn_col).cast("long").alias("turn"),
        F.coalesce(F.col(role_col).cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )
    ordered = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    encoded = ordered.mapInArrow(_encode(shared), "conv_id long, turn long, role string, ids array<int>, text_begin int, text_end int")
    return encoded.mapInArrow(_assemble(loss_role), "conv_id long, turn long, ids array<int>, start long, loss_begin long, loss_end long")


def _read_back(shared):
    """Digests of whole conversations from their tokens alone, streamed turn by turn."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, base = _encoder(shared), shared.value.reserved
        done: list[tuple] = []
        state = None

        def flush() -> pa.RecordBatch:
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            got = [pa.array(x, t) for x, t in zip(zip(*done, strict=True), kinds, strict=True)] if done else [pa.array([], t) for t in kinds]
            done.clear()
            return pa.RecordBatch.from_arrays(got, names=names)

        def close() -> None:
            done.append((state["id"], state["turns"], state["all"].hexdigest(), state["chars"], state["loss"].hexdigest(), state["formatted"]))

        for batch in batches:
            offs = np.asarray(batch.column("ids").offsets)
            flat = batch.column("ids").values.to_numpy(zero_copy_only=False)
            columns = [batch.column(c).to_pylist() for c in ("conv_id", "start", "loss_begin", "loss_end")]
            for i, (conv, start, begin, end) in enumerate(zip(*columns, strict=True)):
                if state is None or start == 0:
                    if state is not None:
                        close()
                    state = {"id": conv, "turns": 0, "all": hashlib.sha256(), "chars": 0, "loss": hashlib.sha256(), "formatted": 0}
                ids = flat[offs[i] : offs[i + 1]]
                middle, last = np.flatnonzero(ids >= base)[1:]
                role, text = (encoder.decode_bytes(ids[a:b].tolist()).decode() for a, b in ((1, middle), (middle + 1, last)))
                state["formatted"] += len(OPEN) + len(role) + len(MIDDLE) + len(text) + len(CLOSE)
                state["turns"] += 1
                state["all"].update(f"{unescape(role)}\n{unescape(text)}\n".encode())
                if end > begin:
                    said = unescape(encoder.decode_bytes(ids[begin - start : end - start].tolist()).decode())
                    state["chars"] += len(said)
                    state["loss"].update(said.encode())
            if len(done) >= 1000:
                yield flush()
        if state is not None:
            close()
        yield flush()

    return run


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    turns = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    vocabulary = Vocabulary.read()
    shared = spark.sparkContext.broadcast(vocabulary)
    return format_chat(turns, vocabulary).mapInArrow(_read_back(shared), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


ORACLE = r"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
e AS (SELECT *, replace(replace(replace(text, '\', '\\'), '###', '\###'), '</turn>', '\</turn>') AS x FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(4 + length(role) + 2 + length(x) + 8)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""
