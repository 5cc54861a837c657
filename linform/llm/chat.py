"""Chat formatting by event-sourced reconstruction.

A log of events is dealt by conversation and folded into final messages, which are then rendered. Kinds:

* start: a message begins (again), with a role and the text so far;
* delta: text is added to the message;
* edit: the text of the message is replaced;
* regenerate: the message and all after it in the conversation are withdrawn (a start may follow).

The fold streams. First events are read backwards, when what an edit or regeneration makes void is already
known, so only the least withdrawn message and the edited messages are kept in memory; the live events are then
read forwards and joined message by message. A message has to fit in memory, a conversation does not.

The template marks turns with control strings; "<", backslashes, "|" in a text is written with one backslash
more, so no text holds a control string and reading takes one off. The loss mask covers assistant texts only.

`events_of` turns rows into such a log. Some of its messages (chosen by hash) have a history first: a draft that an
edit replaces, or a draft that is regenerated. The fold takes the history out again, so the final messages are those of
the rows.

Nulls in roles or texts count as empty; null conversation ids form one conversation, null turns come first.
Rows that repeat a turn become messages of their own, ordered by a hash of role and text. Extra columns are not read.
An empty log gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The control strings of the template.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
_ESCAPE, _UNESCAPE = re.compile(r"<(\\*)\|"), re.compile(r"<\\(\\*)\|")
_TURN = re.compile(re.escape(OPEN) + r"([^\n]*)\n(.*?)" + re.escape(CLOSE) + r"\n", re.DOTALL)
#: Longest text of a delta made from a row; one in so many messages is edited, and one in so many regenerated.
DELTA, HISTORY = 2_000, 4
#: What names a message in a log made from rows.
NAMES = ("message", "tie", "copy")
EVENT = "conv_id long, message long, part long, tie long, copy long, kind string, role string, text string"


def escape(text: str) -> str:
    return _ESCAPE.sub(r"<\\\1|", text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"<\1|", text)


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def render(role: str, text: str) -> tuple[str, int, int]:
    """The written turn, and where its loss mask begins and ends (code points)."""
    head, body = f"{OPEN}{escape_role(role)}\n", escape(text)
    masked = len(body) if role == "assistant" else 0
    return f"{head}{body}{CLOSE}\n", len(head), len(head) + masked


def read_turns(written: str) -> list[tuple[str, str]]:
    """(role, text) of the turns in a written conversation or part of one; an error if it is anything else."""
    out, at = [], 0
    while at < len(written):
        found = _TURN.match(written, at)
        if not found:
            raise ValueError("not a written conversation")
        out.append((unescape_role(found[1]), unescape(found[2])))
        at = found.end()
    return out


def events_of(turns: DataFrame, history: int = HISTORY) -> DataFrame:
    """Rows by turn -> a log: a start for each row and deltas with its text, for some after a history (0: for none)."""
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("message"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.groupBy(*rows.columns).agg(F.count("*").alias("n"))
    rows = rows.withColumn("tie", F.xxhash64("role", "text")).withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "n")))
    lot = F.pmod(F.xxhash64(F.lit("history"), "tie", "message"), F.lit(max(1, history)))
    draft = F.concat(F.lit("draft: "), F.substring(F.reverse("text"), 1, 200))
    begun = F.array(_event("start", F.col("role"), ""), _event("delta", None, draft))
    edited = F.concat(begun, F.array(_event("edit", None, ""), _event("edit", None, F.substring("text", 1, DELTA))))
    regenerated = F.concat(begun, F.array(_event("edit", None, "no"), _event("regenerate", None, None), _event("start", F.col("role"), F.substring("text", 1, DELTA))))
    plain = F.array(_event("start", F.col("role"), F.substring("text", 1, DELTA)))
    first = F.when(F.lit(history > 0) & (lot == 0), edited).when(F.lit(history > 1) & (lot == 1), regenerated).otherwise(plain)
    pieces = F.ceil(F.length("text") / DELTA)
    rest = F.transform(F.sequence(F.lit(1).cast("long"), F.greatest(pieces, F.lit(1).cast("long"))), lambda i: _event("delta", None, F.substring("text", (i * DELTA + 1).cast("int"), F.lit(DELTA))))
    events = F.concat(first, F.filter(rest, lambda e: e["text"] != ""))
    return rows.select("conv_id", "message", "tie", "copy", F.posexplode(events).alias("part", "e")).select("conv_id", "message", F.col("part").cast("long").alias("part"), "tie", "copy", "e.kind", "e.role", "e.text")


def _event(kind: str, role: Column | None, text) -> Column:
    as_text = text if isinstance(text, Column) else F.lit(text)
    return F.struct(F.lit(kind).alias("kind"), (F.lit(None) if role is None else role).cast("string").alias("role"), as_text.cast("string").alias("text"))


def live_events(log: DataFrame, seq: list[str], names: tuple[str, ...] = ("message",)) -> DataFrame:
    """The events that later edits and regenerations leave, dealt by conversation. seq: columns of the log's order;
    names: columns that name a message, in the order of messages (nulls first)."""
    columns = log.columns
    at = {c: i for i, c in enumerate(columns)}
    dealt = log.repartition("conv_id").sortWithinPartitions("conv_id", *(F.desc(c) for c in seq))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, cut, edited = object(), None, set()
        for batch in batches:
            convs, kinds = (batch.column(at[c]).to_pylist() for c in ("conv_id", "kind"))
            places = zip(*([-(1 << 63) if m is None else m for m in batch.column(at[c]).to_pylist()] for c in names), strict=True)
            keep = []
            for c, place, kind in zip(convs, places, kinds, strict=True):
                if c != conv:
                    conv, cut, edited = c, None, set()
                void = (cut is not None and place >= cut) or (place in edited and kind in ("delta", "edit"))
                if kind == "regenerate":
                    cut = place if cut is None else min(cut, place)
                    edited = {e for e in edited if e < cut}
                    void = True
                elif kind == "edit" and not void:
                    edited.add(place)
                elif kind == "start":
                    edited.discard(place)  # what came before the start goes when the message begins again
                keep.append(not void)
            yield batch.filter(pa.array(keep))

    return dealt.mapInArrow(run, log.schema)


def fold(log: DataFrame, seq: list[str] | None = None, names: tuple[str, ...] | None = None) -> DataFrame:
    """A log -> (conv_id, turn, written, loss_start, loss_end): final messages in order, numbered from 0, rendered.

    seq: columns that order the events of a conversation; events of one message are taken in that order. names:
    columns that name a message. Without both, the log is one made by events_of.
    """
    names = names or (("message",) if seq else NAMES)
    seq = seq or [*NAMES, "part"]
    live = live_events(log, seq, names).sortWithinPartitions("conv_id", *dict.fromkeys([*names, *seq]))
    at = {c: i for i, c in enumerate(live.columns)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, turn, told, role, pieces = object(), 0, None, None, []
        for batch in batches:
            out = []
            places = zip(*(batch.column(at[c]).to_pylist() for c in names), strict=True)
            for place, c, kind, new_role, text in zip(places, *(batch.column(at[x]).to_pylist() for x in ("conv_id", "kind", "role", "text")), strict=True):
                if (c != conv or (kind == "start" and place != told)) and role is not None:
                    out.append((conv, turn, *render(role, "".join(pieces))))
                    turn, role, pieces = turn + 1, None, []
                if c != conv:
                    conv, turn, role, pieces = c, 0, None, []
                if kind == "start":  # of a message that began before: it begins again
                    told, role, pieces = place, new_role or "", [text or ""]
                elif kind == "edit":
                    pieces = [text or ""]
                else:
                    pieces.append(text or "")
            if out:
                yield _batch(out)
        if role is not None:
            yield _batch([(conv, turn, *render(role, "".join(pieces)))])

    return live.mapInArrow(run, "conv_id long, turn long, written string, loss_start long, loss_end long")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = [*zip(*rows, strict=True)]
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["conv_id", "turn", "written", "loss_start", "loss_end"])


def digest(written: DataFrame) -> DataFrame:
    """Read rendered messages back: (conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars)."""
    dealt = written.repartition("conv_id").sortWithinPartitions("conv_id", "turn")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, state = object(), None

        def closed() -> tuple:
            n, turns, chars, loss, length = state
            return conv, n, turns.hexdigest(), chars, loss.hexdigest(), length

        def told(rows: list[tuple]) -> pa.RecordBatch:
            columns = [*zip(*rows, strict=True)]
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

        for batch in batches:
            out = []
            for c, text, start, end in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3, 4)), strict=True):
                if state is None or c != conv:
                    if state is not None:
                        out.append(closed())
                    conv, state = c, [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                for role, body in read_turns(text):
                    state[0] += 1
                    state[1].update(f"{role}\n{body}\n".encode("utf-8", "surrogatepass"))
                masked = unescape(text[start:end])
                state[2] += len(masked)
                state[3].update(masked.encode("utf-8", "surrogatepass"))
                state[4] += len(text)
            if out:
                yield told(out)
        if state is not None:
            yield told([closed()])

    asked = dealt.select("conv_id", "turn", "written", "loss_start", "loss_end")
    return asked.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
