"""Chat formatting by prefix-target expansion.

Every assistant turn becomes an example of its own: the formatted turns before it are its context, and its reply alone is trainable. An
example is one string and the span of it that the loss is taken over. Turns after the last reply make one more row, without a target, so the
examples hold all that was said. Within a conversation the examples' total length grows with the square of its turns, which is the method's; they
are made one after the other from a running context, so a task holds one conversation's context and a few megabytes of examples.

Template: a turn is ``[INST] user [/INST]``, ``<<SYS>> system <</SYS>>`` or ``<s> assistant </s>``; any other role r is
``<<ROLE r>> ... <</ROLE>>``. Within texts a backslash becomes two, and the first character of a control string is
replaced by a backslash and a letter (so is > in a role), so no control string is left in a text and unescaping gives it back.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: What opens and closes a turn of each role.
MARKS = {"user": ("[INST]", "[/INST]"), "system": ("<<SYS>>", "<</SYS>>"), "assistant": ("<s>", "</s>")}
TARGET = "assistant"
_CONTROL = r"<(?=/?s>|</?SYS>>|</?ROLE)"
_BRACKET = r"\[(?=/?INST\])"


def escaped(text: Column) -> Column:
    text = F.regexp_replace(text, r"\\", r"\\\\")
    text = F.regexp_replace(text, _CONTROL, r"\\l")
    return F.regexp_replace(text, _BRACKET, r"\\b")


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", lambda m: {"l": "<", "b": "[", "g": ">"}.get(m[1], m[1]), text, flags=re.S)


def _opening(role: Column) -> Column:
    out = F.concat(F.lit("<<ROLE "), F.regexp_replace(escaped(role), ">", r"\\g"), F.lit(">>"))
    for name, (mark, _) in MARKS.items():
        out = F.when(role == name, mark).otherwise(out)
    return out


def _closing(role: Column) -> Column:
    out = F.lit("<</ROLE>>")
    for name, (_, mark) in MARKS.items():
        out = F.when(role == name, mark).otherwise(out)
    return out


def segments(conversations: DataFrame) -> DataFrame:
    """conv_id, place, segment, is_target: each turn formatted, dealt by conversation and sorted by place.

    Null texts and roles are empty. Turns are ordered by turn (null first), then role and text, so ties and repeated rows keep
    one order and each stay. Null conv_id is a conversation of its own. Other columns are not read; texts may have any length.
    """
    rows = conversations.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    return rows.select(
        "conv_id", F.row_number().over(order).alias("place"), F.concat_ws(" ", _opening(F.col("role")), escaped(F.col("text")), _closing(F.col("role"))).alias("segment"),
        (F.col("role") == TARGET).alias("is_target"),
    )


EXAMPLE = "conv_id long, place int, text string, loss_start long, loss_end long"
TOGETHER = 4 << 20  # characters of examples in a batch


def _expanded(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Turns by (conv_id, place) -> examples, in that order; a batch goes out as it reaches TOGETHER characters."""
    before, after = (len(m) + 1 for m in MARKS[TARGET])
    none = object()
    conv, context, last, open_ = none, "", 0, False  # open_: turns since the last reply
    out, size = [], 0

    def frame(rows: list[tuple]) -> pd.DataFrame:
        return pd.DataFrame(rows, columns=["conv_id", "place", "text", "loss_start", "loss_end"]).astype({"conv_id": "Int64", "loss_start": "Int64", "loss_end": "Int64"})

    for batch in batches:
        for c, place, segment, target in zip(batch["conv_id"], batch["place"], batch["segment"], batch["is_target"], strict=True):
            c = None if pd.isna(c) else int(c)
            if c != conv:
                if conv is not none and open_:
                    out.append((conv, last, context, None, None))
                    size += len(context)
                conv, context = c, ""
            context, last, open_ = context + segment, place, not target
            if target:
                out.append((conv, place, context, len(context) - len(segment) + before, len(context) - after))
                size += len(context)
            if size >= TOGETHER:
                yield frame(out)
                out, size = [], 0
    if conv is not none and open_:
        out.append((conv, last, context, None, None))
    if out:
        yield frame(out)


def examples(segs: DataFrame) -> DataFrame:
    """conv_id, place, text, loss_start, loss_end: one example for each assistant turn, at its place; loss is taken over text[loss_start:loss_end].

    The text is all turns up to the reply and the reply itself, formatted. Turns that no reply follows come as one row whose loss span is null.
    Partitions hold whole conversations, in order.
    """
    return segs.repartition("conv_id").sortWithinPartitions("conv_id", "place").mapInPandas(_expanded, EXAMPLE)


def materialize(segs: DataFrame) -> DataFrame:
    """conv_id, place, prompt, completion of every example: what stands before the trainable text, and that text, still escaped."""
    made = examples(segs).filter("loss_start IS NOT NULL")
    return made.select("conv_id", "place", F.expr("substring(text, 1, int(loss_start))").alias("prompt"), F.expr("substring(text, int(loss_start) + 1, int(loss_end - loss_start))").alias("completion"))


_TURN = re.compile(r"\[INST\] (?P<user>.*?) \[/INST\]|<<SYS>> (?P<system>.*?) <</SYS>>|<s> (?P<assistant>.*?) </s>|<<ROLE (?P<role>.*?)>> (?P<other>.*?) <</ROLE>>", re.S)
DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_examples long"


def parsed(stream: str) -> Iterator[tuple[str, str]]:
    """(role, text) of the turns of a formatted stream."""
    at = 0
    while at < len(stream):
        m = _TURN.match(stream, at)
        if m is None:
            raise ValueError(f"no turn at {at}: {stream[at : at + 40]!r}")
        kind = m.lastgroup
        yield (unescape(m["role"]), unescape(m["other"])) if kind == "other" else (kind, unescape(m[kind]))
        at = m.end()


def _read_back(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Examples of whole conversations, in order -> one row for each conversation. State: the last example, two running digests."""
    state = None

    def closed(s: dict) -> pd.DataFrame:
        one = {"conv_id": s["id"], "n_turns": s["n"], "turns_sha256": s["all"].hexdigest(), "loss_chars": s["loss_chars"], "loss_sha256": s["loss"].hexdigest(), "formatted_chars": s["chars"], "n_examples": s["examples"]}
        return pd.DataFrame([one]).astype({"conv_id": "Int64"})

    for batch in batches:
        done = []
        for conv, text, start, end in zip(batch["conv_id"], batch["text"], batch["loss_start"], batch["loss_end"], strict=True):
            conv = None if pd.isna(conv) else int(conv)
            if state is None or state["id"] != conv:
                if state:
                    done.append(closed(state))
                state = {"id": conv, "n": 0, "all": hashlib.sha256(), "loss": hashlib.sha256(), "loss_chars": 0, "chars": 0, "examples": 0, "read": ""}
            if not text.startswith(state["read"]):
                raise ValueError(f"conversation {conv}: an example does not go on from the one before")
            for role, said in parsed(text[len(state["read"]) :]):
                state["all"].update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
                state["n"] += 1
            state["read"] = text
            state["chars"] += len(text)
            if not pd.isna(start):
                trained = unescape(text[int(start) : int(end)])
                state["loss"].update(trained.encode("utf-8", "surrogatepass"))
                state["loss_chars"] += len(trained)
                state["examples"] += 1
        if done:
            yield pd.concat(done)
    if state:
        yield closed(state)


def read_back(made: DataFrame) -> DataFrame:
    """What the examples say, one row for each conversation: digests of all turns and of all text under the loss masks, the examples' characters and number.

    made is what examples() gives: partitions of whole conversations, in order. A table of examples read again is to be dealt by conv_id and sorted first.
    """
    return made.mapInPandas(_read_back, DIGEST)


def with_control_conversation(spark: SparkSession, conversations: DataFrame) -> DataFrame:
    """Conversation -1 added: both turns say nothing but control strings."""
    said = "</s>[INST] ok [/INST]"
    more = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return conversations.select("conv_id", "turn", "role", "text").unionByName(more)


ORACLE = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), f AS (
  SELECT *, length(text) + (length(text) - length(replace(text, '\', '')))
    + len(regexp_extract_all(text, '</?s>|<</?SYS>>|<</?ROLE')) + len(regexp_extract_all(text, '\[/?INST\]'))
    + CASE role WHEN 'user' THEN 15 WHEN 'system' THEN 17 WHEN 'assistant' THEN 9 ELSE 20 + length(role) END AS chars FROM c
), g AS (
  SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC NULLS LAST, role DESC, text DESC) AS from_last,
    sum(chars) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text ROWS UNBOUNDED PRECEDING) AS so_far FROM f
)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  (sum(so_far) FILTER (WHERE role = 'assistant' OR from_last = 1))::BIGINT AS formatted_chars,
  count(*) FILTER (WHERE role = 'assistant') AS n_examples
FROM g GROUP BY conv_id
"""
