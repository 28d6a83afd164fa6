"""Chat formatting by prefix-target expansion.

A conversation is written once, as text with marked turns. Every assistant turn is an example of its own: its context
is all that precedes it, and only its reply is trainable. As the template is a plain
concatenation, an example is a prefix of the written conversation with a span under the loss mask, so
examples are kept as offsets into it; ``example_texts`` cuts them out for a consumer that wants copies.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import lean, small_batches

#: Template: a turn is OPEN, the escaped role, HEAD, the escaped text, CLOSE.
OPEN, HEAD, CLOSE = "<turn ", ">\n", "\n</turn>\n"
_ESCAPED = re.compile(r"[\\<>#\[\]]")
_UNESCAPED = re.compile(r"\\(.)", re.S)
_TURN = re.compile(re.escape(OPEN) + r"([^\\<>]*(?:\\.[^\\<>]*)*)" + re.escape(HEAD) + r"([^\\<]*(?:\\.[^\\<]*)*)" + re.escape(CLOSE), re.S)


def escape(text: str) -> str:
    """Puts a backslash before every character that a control string needs; ``unescape`` undoes it exactly."""
    return _ESCAPED.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _UNESCAPED.sub(r"\1", text)


def write_turn(role: str, text: str) -> tuple[str, int, int]:
    """A turn as written, with the span of its (escaped) text."""
    head = OPEN + escape(role) + HEAD
    body = escape(text)
    return head + body + CLOSE, len(head), len(head) + len(body)


def read_turns(formatted: str) -> list[tuple[str, str]]:
    """Roles and texts back from the written form; raises ValueError on anything else."""
    out, at = [], 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if not m:
            raise ValueError(f"no turn at {at}")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return out


PIECES = "conv_id long, part int, turn_from long, formatted string, spans array<struct<start: long, end: long, at: long>>"


def formatted(conversations: DataFrame, role: str = "assistant", piece_chars: int = 1 << 22) -> DataFrame:
    """Conversations as written text: ``conv_id``, ``part``, ``turn_from``, ``formatted``, ``spans``.

    Turns are ordered by ``turn``, then role, then text; a null text or role counts as empty, a null turn comes first; rows with a null
    ``conv_id`` are one conversation. ``spans`` holds one entry per reply of ``role``: start and end of its escaped text within the piece and
    its offset in the whole conversation; the example's context is everything before it. A conversation longer
    than ``piece_chars`` goes on in further parts, cut between turns, so that memory is bounded by one turn and one piece.
    An empty table gives an empty result.
    """

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now: object = None
        began = False
        part = first = offset = size = 0
        pieces: list[str] = []
        spans: list[dict] = []
        done: list[tuple] = []

        def close() -> None:
            nonlocal part, first, offset, size, pieces, spans
            if pieces:
                done.append((now, part, first, "".join(pieces), spans))
                part, offset, size, pieces, spans = part + 1, offset + size, 0, [], []

        seen = 0
        for pdf in frames:
            for conv, who, text in zip(pdf["conv_id"], pdf["role"], pdf["text"]):
                conv = None if pd.isna(conv) else int(conv)
                if not began or conv != now:
                    if began:
                        close()
                    now, began, part, offset, seen = conv, True, 0, 0, 0
                    first = 0
                if size > piece_chars:
                    close()
                    first = seen
                turn, a, b = write_turn(who, text)
                if who == role:
                    spans.append({"start": size + a, "end": size + b, "at": offset + size + a})
                pieces.append(turn)
                size += len(turn)
                seen += 1
            if done:
                yield pd.DataFrame(done, columns=["conv_id", "part", "turn_from", "formatted", "spans"]).astype({"conv_id": "Int64"})
                done = []
        if began:
            close()
        if done:
            yield pd.DataFrame(done, columns=["conv_id", "part", "turn_from", "formatted", "spans"]).astype({"conv_id": "Int64"})

    small_batches(conversations.sparkSession)
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").mapInPandas(lean(work), PIECES)


def examples(written: DataFrame) -> DataFrame:
    """One row per reply: ``conv_id``, ``part``, ``example`` (from 0 within the part), ``start`` and ``end`` of the reply in the part, ``prefix_chars`` (context and
    reply), ``loss_start`` (offset of the reply in the prefix)."""
    spans = written.select("conv_id", "part", F.posexplode("spans").alias("example", "s"))
    ends = F.col("s.at") + (F.col("s.end") - F.col("s.start"))
    return spans.select("conv_id", "part", "example", F.col("s.start").alias("start"), F.col("s.end").alias("end"), ends.alias("prefix_chars"), F.col("s.at").alias("loss_start"))


def example_texts(written: DataFrame) -> DataFrame:
    """Examples cut out: ``conv_id``, ``context`` (all parts before and what precedes the reply in its own), ``reply`` (both escaped).

    Output grows with the square of a conversation's turns, and a context is one string, of 2 GB at most.
    """

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now: object = None
        began = False
        before = ""
        for pdf in frames:
            for conv, text, spans in zip(pdf["conv_id"], pdf["formatted"], pdf["spans"]):
                conv = None if pd.isna(conv) else int(conv)
                if not began or conv != now:
                    now, began, before = conv, True, ""
                for s in spans:
                    yield pd.DataFrame({"conv_id": pd.array([conv], "Int64"), "context": [before + text[: s["start"]]], "reply": [text[s["start"] : s["end"]]]})
                before += text

    ordered = written.select("conv_id", "part", "formatted", "spans").repartition("conv_id").sortWithinPartitions("conv_id", "part")
    return ordered.mapInPandas(lean(work), "conv_id long, context string, reply string")


def digests(written: DataFrame) -> DataFrame:
    """What can be read back from the written form and its examples, per conversation.

    ``n_turns``, ``turns_sha256`` (role, newline, text, newline of each turn), ``loss_chars`` and ``loss_sha256`` (unescaped replies of all
    examples), ``formatted_chars``, ``n_examples``. Each example is a row of its own; it follows the part that its reply is cut from, and its prefix
    must end where the reply does. Parts are read in order, one at a time.
    """

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now: object = None
        began = False
        state: list = []
        text = ""
        done: list[tuple] = []

        def close() -> None:
            done.append((now, state[0], state[1].hexdigest(), state[2], state[3].hexdigest(), state[4], state[5]))

        for pdf in frames:
            for conv, example, piece, start, end, prefix in zip(pdf["conv_id"], pdf["example"], pdf["formatted"], pdf["start"], pdf["end"], pdf["prefix_chars"]):
                conv = None if pd.isna(conv) else int(conv)
                if not began or conv != now:
                    if began:
                        close()
                    now, began, state = conv, True, [0, hashlib.sha256(), 0, hashlib.sha256(), 0, 0]
                if example < 0:
                    text = piece
                    for who, body in read_turns(text):
                        state[0] += 1
                        state[1].update(f"{who}\n{body}\n".encode())
                    state[4] += len(text)
                    continue
                if state[4] - len(text) + end != prefix:
                    raise ValueError(f"an example of conversation {conv} does not end with its reply")
                loss = unescape(text[int(start) : int(end)])
                state[2] += len(loss)
                state[3].update(loss.encode())
                state[5] += 1
            if done:
                yield _frame(done)
                done = []
        if began:
            close()
            yield _frame(done)

    def _frame(rows: list[tuple]) -> pd.DataFrame:
        return pd.DataFrame(rows, columns=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_examples"]).astype({"conv_id": "Int64"})

    none = F.lit(-1).cast("long")
    pieces = written.select("conv_id", "part", F.lit(-1).alias("example"), "formatted", none.alias("start"), none.alias("end"), none.alias("prefix_chars"))
    replies = examples(written).select("conv_id", "part", "example", F.lit(None).cast("string").alias("formatted"), "start", "end", "prefix_chars")
    ordered = pieces.unionByName(replies).repartition("conv_id").sortWithinPartitions("conv_id", "part", "example")
    return ordered.mapInPandas(lean(work), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_examples long")


ORACLE = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
w AS (SELECT *, 6 + 2 + 9 + length(role) + length(text) + length(regexp_replace(role || text, '[^\\<>#\[\]]', '', 'g')) AS written FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       sum(written)::BIGINT AS formatted_chars, count(*) FILTER (WHERE role = 'assistant') AS n_examples
FROM w GROUP BY conv_id
"""
