"""Chat formatting with typed content parts.

A turn's content is a list of parts: text, image, audio or document. A visitor walks the parts in order and
flattens them into one string in which every part that is no text is a placeholder ``<|kind:number|>``; it
records the reference behind each placeholder and how many tokens it will expand to. A turn is written as

    [INST]<|role|>content[/INST]      for every role but the assistant
    <|assistant|>content</s>          for the assistant, with content under the loss mask

and the first turn of a conversation is preceded by ``<s>``. Control strings inside texts are escaped by one
backslash behind their first character (and one more where backslashes stand there already), so that the
output can be parsed back into exactly the texts that went in.

Turns are dealt by ranges of (conv_id, turn, role, text) and stream through their task in that order, a batch at a
time, each giving one row: a conversation of any length is spread over tasks, and none is held whole. Where a
conversation goes on in the next task, its count of turns goes on too. Only a digest over all turns of a
conversation, which is a chain, is made by one task, again streaming. Null text is empty, null role is the empty role, null conv_id is a conversation of its own, null turns come
first. Rows that repeat are turns that repeat. An empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import id_as_string, id_back, written

ASSISTANT, START = "assistant", "<s>"
PARTS = "array<struct<kind:string,text:string,ref:string,width:int,height:int,seconds:double,pages:int>>"
SEGMENT = "conv_id {id}, place long, turn {turn}, segment string, loss_start int, loss_end int, attachments array<struct<number:int,kind:string,ref:string,tokens:long>>, expanded_tokens long"

#: control strings: <s> </s> <|...|> [INST] [/INST]
_ESCAPE = re.compile(r"(<\\*)(?=/?s>|\|)|(\[\\*)(?=/?INST\])")
_UNESCAPE = re.compile(r"(<\\*)\\(?=/?s>|\|)|(\[\\*)\\(?=/?INST\])")
_SEGMENT = re.compile(r"(?:<s>)?(?:(\[INST\])<\|(.*?)\|>(.*)\[/INST\]|<\|assistant\|>(.*)</s>)", re.S)


def escaped(text: str) -> str:
    return _ESCAPE.sub(lambda m: m[0] + "\\", text)


def unescaped(text: str) -> str:
    return _UNESCAPE.sub(lambda m: m[1] or m[2], text)


def role_written(role: str) -> str:
    return role.replace("%", "%25").replace("|", "%7C").replace("<", "%3C").replace("[", "%5B")


def role_read(role: str) -> str:
    return role.replace("%5B", "[").replace("%3C", "<").replace("%7C", "|").replace("%25", "%")


@dataclass
class Flattened:
    """What the visitor has written so far."""

    text: list[str] = field(default_factory=list)
    attachments: list[dict] = field(default_factory=list)


class PartVisitor:
    """Dispatches on a part's kind. Subclasses may add kinds as ``visit_<kind>``."""

    def __init__(self, patch: int = 28, tokens_per_second: float = 12.5, tokens_per_page: int = 800):
        self.patch, self.tokens_per_second, self.tokens_per_page = patch, tokens_per_second, tokens_per_page

    def flatten(self, parts) -> Flattened:
        out = Flattened()
        for part in parts:
            visit = getattr(self, f"visit_{part['kind']}", None)
            if visit is None:
                raise ValueError(f"no such kind of part: {part['kind']}")
            visit(part, out)
        return out

    def visit_text(self, part, out: Flattened) -> None:
        out.text.append(escaped(part["text"] or ""))

    def visit_image(self, part, out: Flattened) -> None:
        rows, columns = (max(1, math.ceil((part.get(k) or self.patch) / self.patch)) for k in ("height", "width"))
        self._attach(part, rows * columns, out)

    def visit_audio(self, part, out: Flattened) -> None:
        self._attach(part, max(1, math.ceil((part.get("seconds") or 0) * self.tokens_per_second)), out)

    def visit_document(self, part, out: Flattened) -> None:
        self._attach(part, max(1, part.get("pages") or 1) * self.tokens_per_page, out)

    @staticmethod
    def _attach(part, tokens: int, out: Flattened) -> None:
        number = len(out.attachments)
        out.text.append(f"<|{part['kind']}:{number}|>")
        out.attachments.append({"number": number, "kind": part["kind"], "ref": part.get("ref"), "tokens": tokens})


def write_segment(role: str, flat: Flattened, first: bool) -> tuple[str, int, int]:
    """The segment, and where the loss mask lies in it (empty but for the assistant)."""
    head, text = START * first, "".join(flat.text)
    if role == ASSISTANT:
        head += f"<|{ASSISTANT}|>"
        return f"{head}{text}</s>", len(head), len(head) + len(text)
    return f"{head}[INST]<|{role_written(role)}|>{text}[/INST]", 0, 0


def read_segment(segment: str) -> tuple[str, str]:
    """Role and text, as they went in; placeholders stay."""
    m = _SEGMENT.fullmatch(segment)
    if m is None:
        raise ValueError("not a segment")
    return (role_read(m[2]), unescaped(m[3])) if m[1] else (ASSISTANT, unescaped(m[4]))


def format_conversations(turns: DataFrame, content: str = "text", visitor: PartVisitor | None = None) -> DataFrame:
    """A segment row per row of ``turns(conv_id, turn, role, <content>)``; ``content`` is a string or PARTS."""
    visitor = visitor or PartVisitor()
    plain = turns.schema[content].dataType.simpleString() in ("string", "void")
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.col(content).alias("content"))
    said = F.coalesce("content", F.lit("")) if plain else F.coalesce(F.to_json("content"), F.lit(""))
    order = [F.col("conv_id"), F.col("turn"), F.col("role"), F.substring(said, 1, 32)]
    dealt = rows.repartitionByRange(*order).sortWithinPartitions(*order, said)

    def write(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        last, place, task = object(), 0, TaskContext.get().partitionId()
        for frame in frames:
            out = []
            for conv, turn, role, parts in zip(frame["conv_id"], frame["turn"], frame["role"], frame["content"], strict=True):
                place = place + 1 if conv == last else 0
                last = conv
                flat = visitor.flatten([{"kind": "text", "text": parts}] if plain else ([] if parts is None else parts))
                segment, start, end = write_segment(role, flat, place == 0)
                tokens = sum(x["tokens"] for x in flat.attachments)
                out.append((task, conv, place, turn, segment, start, end, flat.attachments, tokens))
            yield pd.DataFrame(out, columns=["task", "conv_id", "place", "turn", "segment", "loss_start", "loss_end", "attachments", "expanded_tokens"])

    ids = [id_as_string(turns, "conv_id"), id_as_string(turns, "turn"), "role", "content"]
    made = written(dealt.select(*ids).mapInPandas(write, f"task int, {SEGMENT.format(id='string', turn='string')}"), "segments")
    whole = continued(made)
    return whole.select(id_back(turns, "conv_id"), "place", id_back(turns, "turn"), "segment", "loss_start", "loss_end", "attachments", "expanded_tokens")


def continued(made: DataFrame) -> DataFrame:
    """Segments whose places go on where a conversation reaches over several tasks.

    Tasks hold neighbouring ranges, so at most one conversation goes on from one task to the next: the table of
    what came before has at most a row per task.
    """
    each = made.groupBy("conv_id", "task").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("conv_id").orderBy("task").rowsBetween(Window.unboundedPreceding, -1))
    bases = each.withColumn("base", before).where("base is not null").select(F.col("conv_id").alias("_conv"), F.col("task").alias("_task"), "base")
    joined = made.join(F.broadcast(bases), made["conv_id"].eqNullSafe(F.col("_conv")) & (made["task"] == F.col("_task")), "left")
    moved = F.col("base").isNotNull() & (F.col("place") == 0)  # written as a first turn, which it is not
    cut = F.when(moved, len(START)).otherwise(0)
    return (
        joined.withColumn("segment", F.when(moved, F.substring("segment", len(START) + 1, 2**31 - 1)).otherwise(F.col("segment")))
        .withColumn("loss_start", F.when(F.col("loss_end") > 0, F.col("loss_start") - cut).otherwise(0))
        .withColumn("loss_end", F.when(F.col("loss_end") > 0, F.col("loss_end") - cut).otherwise(0))
        .withColumn("place", F.col("place") + F.coalesce("base", F.lit(0)))
        .drop("_conv", "_task", "base", "task")
    )


def conversation_digests(segments: DataFrame) -> DataFrame:
    """Parses segments back: conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars."""

    def read(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
        state = None  # of the conversation at hand
        for frame in frames:
            out = []
            for conv, segment, start, end in zip(frame["conv_id"], frame["segment"], frame["loss_start"], frame["loss_end"], strict=True):
                if state is None or state[0] != conv:
                    if state:
                        out.append((state[0], state[1], state[2].hexdigest(), state[3], state[4].hexdigest(), state[5]))
                    state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                role, text = read_segment(segment)
                state[1] += 1
                state[2].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
                masked = unescaped(segment[start:end])
                state[3] += len(masked)
                state[4].update(masked.encode("utf-8", "surrogatepass"))
                state[5] += len(segment)
            if out:
                yield pd.DataFrame(out, columns=names)
        if state:
            yield pd.DataFrame([(state[0], state[1], state[2].hexdigest(), state[3], state[4].hexdigest(), state[5])], columns=names)

    schema = "conv_id string, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    rows = segments.select(id_as_string(segments, "conv_id"), "place", "segment", "loss_start", "loss_end")
    found = rows.repartition("conv_id").sortWithinPartitions("conv_id", "place").mapInPandas(read, schema)
    return found.withColumn("conv_id", id_back(segments, "conv_id"))


def format_and_read_back(turns: DataFrame) -> DataFrame:
    """Writes the segments to the shared folder, reads them again and digests what was read."""
    return conversation_digests(written(format_conversations(turns), "chat"))
