"""Chat formatting by event-sourced reconstruction.

A log holds events (conv_id, seq, turn, kind, role, text). Kinds: `open` starts a turn's message with its role, `delta`
appends a streamed piece, `edit` replaces the message, `regenerate` empties it so that later pieces replace it,
`retract` takes the turn away. The log is partitioned by conversation, sorted by (turn, seq) and folded as a stream:
only one message is held at a time, never a conversation, and what leaves is one segment of output per message.

Template: `<|turn|>role NEWLINE text <|end|> NEWLINE`. Escaping: every backslash is doubled, and a backslash is put behind
the first character of each control string, so none survives inside a text; reading drops each such backslash.

Defined results: a null text or role is empty; a null turn sorts first; events with equal (turn, seq) fold in order
of kind rank, role and text; rows repeated in a table of turns are separate messages, in order of role and text; an empty table
gives no rows; other columns are not read, so their names cannot clash.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

#: Strings that mark structure in this template or in common ones, so none may pass through unescaped.
CONTROL = ("<|turn|>", "<|end|>", "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
TURN, END = CONTROL[:2]
KINDS = {"open": 0, "regenerate": 1, "edit": 2, "delta": 3, "retract": 4}


def escaped(text: str) -> str:
    text = text.replace("\\", "\\\\")
    for mark in CONTROL:
        text = text.replace(mark, mark[0] + "\\" + mark[1:])
    return text


def unescaped(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.S)


def header(role: str) -> str:
    return f"{TURN}{escaped(role).replace(chr(10), chr(92) + chr(10))}\n"


def rendered(role: str, text: str) -> tuple[str, int, int]:
    """One message of output, and where its text starts and ends in it."""
    head, body = header(role), escaped(text)
    return f"{head}{body}{END}\n", len(head), len(head) + len(body)


def parsed(segment: str) -> tuple[str, str]:
    """Role and text read back from one message of output."""
    head = re.match(r"(?:\\.|[^\\\n])*\n", segment[len(TURN) :], flags=re.S)[0]
    return unescaped(head[:-1]), unescaped(segment[len(TURN) + len(head) : -len(END) - 1])


def events_of_turns(turns: DataFrame) -> DataFrame:
    """A table of finished turns as a log that would have made it.

    An assistant's turn is opened, streams a draft (40 characters of it), is regenerated and streams its text in two pieces; any
    other turn is opened, streams such a draft and is then edited to the whole. Rows that repeat a (conv_id, turn) are separate messages, numbered in
    order of role and text, and their events follow each other.
    """
    row = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    message = F.row_number().over(Window.partitionBy("conv_id", "turn").orderBy("role", "text")).cast("long")
    head, tail = F.expr("substring(text, 1, int(length(text) / 2))"), F.expr("substring(text, int(length(text) / 2) + 1)")
    event = lambda kind, text: F.struct(F.lit(kind).alias("kind"), text.cast("string").alias("text"))
    nothing = F.lit(None)
    streamed = F.array(event("open", nothing), event("delta", F.substring("text", 1, 40)), event("regenerate", nothing), event("delta", head), event("delta", tail))
    edited = F.array(event("open", nothing), event("delta", F.substring("text", 1, 40)), event("edit", F.col("text")))
    events = row.withColumn("_m", message).select("conv_id", "turn", "role", "_m", F.posexplode(F.when(F.col("role") == "assistant", streamed).otherwise(edited)).alias("_k", "_e"))
    return events.select("conv_id", "turn", (F.col("_m") * 8 + F.col("_k")).alias("seq"), F.col("_e.kind").alias("kind"), "role", F.col("_e.text").alias("text"))


def _folded(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """(conv_id, turn, role, text) of each message left after its events; rows come sorted."""
    key, role, parts, alive = None, "", [], False
    for batch in batches:
        for conv, turn, kind, who, text in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "turn", "kind", "role", "text")), strict=True):
            if kind == "open" or (conv, turn) != key:
                if alive:
                    yield *key, role, "".join(parts)
                key, role, parts, alive = (conv, turn), who or "", [], True
            if kind == "retract":
                alive = False
            elif kind == "regenerate":
                parts, alive = [], True
            elif kind == "edit":
                parts = [text or ""]
            else:
                parts.append(text or "")
    if alive:
        yield *key, role, "".join(parts)


def format_log(log: DataFrame, learn_role: str = "assistant") -> DataFrame:
    """Segments in order of place: conv_id, turn, place, role, segment, and the span of the loss mask in code points."""
    rank = F.create_map(*[x for k, v in KINDS.items() for x in (F.lit(k), F.lit(v))])[F.col("kind")]
    ordered = log.select("conv_id", "turn", "seq", "kind", "role", "text", rank.alias("_rank")).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "seq", "_rank", "role", "text")

    def render(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size, last, place = [], 0, object(), 0
        for conv, turn, role, text in _folded(batches):
            place = 0 if conv != last else place + 1
            last = conv
            segment, start, end = rendered(role, text)
            rows.append((conv, turn, place, role, segment, start if role == learn_role else None, end if role == learn_role else None))
            size += len(segment)
            if size > 4 << 20:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), SEGMENT_TYPES, strict=True)], SEGMENT_NAMES)
                rows, size = [], 0
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), SEGMENT_TYPES, strict=True)], SEGMENT_NAMES)

    return ordered.mapInArrow(render, SEGMENT_SCHEMA)


SEGMENT_SCHEMA = "conv_id long, turn long, place long, role string, segment string, mask_from long, mask_to long"
SEGMENT_NAMES = ["conv_id", "turn", "place", "role", "segment", "mask_from", "mask_to"]
SEGMENT_TYPES = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64()]


def joined(segments: DataFrame) -> DataFrame:
    """Whole strings, for conversations known to fit a cell: conv_id, formatted."""
    rows = F.sort_array(F.collect_list(F.struct("place", "segment")))
    return segments.groupBy("conv_id").agg(F.array_join(F.transform(rows, lambda r: r["segment"]), "").alias("formatted"))


def read_back(segments: DataFrame) -> DataFrame:
    """Digests of what the output says: each segment is parsed, and hashes run over the stream of a conversation.

    format_log's output is already partitioned by conversation and in order, so this adds no shuffle.
    """

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, last, state = [], object(), None

        def done() -> None:
            out.append((last, state[0], state[1].hexdigest(), state[2], state[3].hexdigest(), state[4]))

        for batch in batches:
            for conv, segment, start, end in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "segment", "mask_from", "mask_to")), strict=True):
                if state is None or conv != last:
                    if state:
                        done()
                    last, state = conv, [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                role, text = parsed(segment)
                state[0] += 1
                state[1].update(f"{role}\n{text}\n".encode())
                state[4] += len(segment)
                if start is not None:
                    masked = unescaped(segment[start:end])
                    state[2] += len(masked)
                    state[3].update(masked.encode())
            if len(out) > 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)
                out.clear()
        if state:
            done()
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)

    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    return segments.mapInArrow(digest, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op4_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return read_back(format_log(events_of_turns(turns.unionByName(extra))))


def _sql_escape(column: str) -> str:
    out = f"replace({column}, '\\', '\\\\')"
    for mark in CONTROL:
        out = f"replace({out}, '{mark}', '{mark[0]}\\{mark[1:]}')"
    return out


SQL = f"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn NULLS FIRST, role, text)) AS loss_sha256,
  CAST(sum(length('{TURN}') + length(replace({_sql_escape("role")}, chr(10), '\\' || chr(10))) + 1 + length({_sql_escape("text")}) + length('{END}') + 1) AS BIGINT) AS formatted_chars
FROM rows GROUP BY conv_id
"""
