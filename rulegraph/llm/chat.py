"""Chat formatting by incremental black-box rendering.

A template is any function from a list of messages to a string. Successive turn
prefixes are rendered and consecutive outputs compared: the new characters are the
turn's span, and a prefix that does not begin with the one before shows a template
that rewrites history. Nothing is assumed about how the template marks turns.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shuffle_partitions, tidied

#: Strings that the built-in template uses to mark turns (fixed values).
CONTROL = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "[ROLE]", "[/ROLE]")
_CONTROL = re.compile("|".join(re.escape(c) for c in CONTROL))
_TOKEN = re.compile(r"\\(.)|" + "|".join(re.escape(c) for c in CONTROL), re.S)

Messages = list[tuple[str, str]]


def escape(text: str) -> str:
    """Doubles backslashes and breaks each control string by one after its first character."""
    return _CONTROL.sub(lambda m: m[0][0] + "\\" + m[0][1:], text.replace("\\", "\\\\"))


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.S)


def instruct_template(messages: Messages) -> str:
    """Turns as ``<s>[INST]user[/INST]``, ``assistant</s>``, ``<s><<SYS>>system<</SYS>>``; other roles by name."""
    out = []
    for role, text in messages:
        body = escape(text)
        if role == "user":
            out.append(f"<s>[INST]{body}[/INST]")
        elif role == "assistant":
            out.append(f"{body}</s>")
        elif role == "system":
            out.append(f"<s><<SYS>>{body}<</SYS>>")
        else:
            out.append(f"<s>[ROLE]{escape(role)}[/ROLE]{body}</s>")
    return "".join(out)


def instruct_parse(rendered: str) -> Messages:
    """The messages of a rendering of :func:`instruct_template`."""
    messages: Messages = []
    mode, held, role, at = "assistant", [], "", 0
    for m in _TOKEN.finditer(rendered):
        held.append(rendered[at : m.start()])
        at = m.end()
        if m[0][0] == "\\":
            held.append(m[1])
            continue
        body, c = "".join(held), m[0]
        if c in ("[INST]", "<<SYS>>", "[ROLE]"):
            mode, held = {"[INST]": "user", "<<SYS>>": "system", "[ROLE]": "role"}[c], []
        elif c == "[/ROLE]":
            role, mode, held = body, "other", []
        elif c != "<s>":
            messages.append((role if mode == "other" else mode, body))
            mode, held = "assistant", []
        else:
            held = []
    return messages


class HistoryRewritten(ValueError):
    """A template changed the text of earlier turns."""


#: Stands for a turn's text when its place is looked for (a private code point).
PROBE = "\ue000"


def turn_spans(messages: Messages, template: Callable[[Messages], str], window: int = 64, role: str = "assistant") -> tuple[str, list[tuple[int, int]], list[tuple[int, int]]]:
    """The rendering, each turn's span in it, and the spans of the texts of ``role``: found by comparing renderings only.

    One rule for every length: a turn is rendered after its context, the first turn and the
    ``window`` turns before it (all turns before, where there are no more), and what the rendering
    adds to that of the context is the turn's piece. The rendering of all turns must be the
    pieces joined; where it is not, the template looks further back, and whole prefixes are rendered instead.
    A prefix that does not begin with the one before raises :class:`HistoryRewritten`.

    The text's place inside a piece is where a probe stands that is rendered in its stead.
    """

    def piece(before: str, after: str, n: int) -> str:
        if not after.startswith(before):
            raise HistoryRewritten(f"turn {n} changes the text before it")
        return after[len(before) :]

    def cut(contexts) -> tuple[list[str], list[tuple[int, int] | None]]:
        pieces, bodies = [], []
        for n, (context, shown) in enumerate(contexts):
            who, _ = messages[n]
            own = piece(shown, template([*context, messages[n]]), n)
            pieces.append(own)
            bodies.append(_place(own, piece(shown, template([*context, (who, PROBE)]), n)) if who == role else None)
        return pieces, bodies

    def near():
        for n in range(len(messages)):
            context = messages[:n] if n <= window + 1 else [messages[0], *messages[n - window : n]]
            yield context, template(context) if context else ""

    def whole():
        for n in range(len(messages)):
            yield messages[:n], template(messages[:n]) if n else ""

    rendered = template(messages) if messages else ""
    pieces, bodies = cut(near())
    if "".join(pieces) != rendered:
        pieces, bodies = cut(whole())
        if "".join(pieces) != rendered:
            raise HistoryRewritten("the whole is not its turns")
    spans, loss, at = [], [], 0
    for own, body in zip(pieces, bodies, strict=True):
        spans.append((at, at + len(own)))
        if body is not None:
            loss.append((at + body[0], at + body[1]))
        at += len(own)
    return rendered, spans, loss


def _place(own: str, probed: str) -> tuple[int, int]:
    """Where a turn's text lies in its piece, given the piece with a probe in place of the text.

    A template that renders other text around different texts, or no probe, has its whole piece under the mask.
    """
    before, found, after = probed.partition(PROBE)
    if found and own.startswith(before) and own.endswith(after) and len(own) >= len(before) + len(after):
        return len(before), len(own) - len(after)
    return 0, len(own)


_OUT = pa.schema([("conv_id", pa.int64()), ("formatted", pa.string()), ("turn_spans", pa.list_(pa.list_(pa.int64()))), ("loss_spans", pa.list_(pa.list_(pa.int64()))), ("rewritten", pa.bool_())])
_DDL = "conv_id long, formatted string, turn_spans array<array<long>>, loss_spans array<array<long>>, rewritten boolean"


def format_chats(conversations: DataFrame, template: Callable[[Messages], str] = instruct_template, batch_rows: int = 256) -> DataFrame:
    """One row for each conversation (conv_id, turn, role, text): its rendering with spans.

    Turns are ordered by turn, then role and text (repeated turns stay, each as a turn of
    its own); a null text is empty, a null role the empty name; a null conv_id is one
    conversation. A template that rewrites history gives a row with ``rewritten`` true and
    no spans. A conversation is the unit of rendering and is held by one task, as its
    output is one string; turns arrive sorted and other conversations stream by.
    """

    def render(batches):
        held, key, out = [], None, []

        def done():
            try:
                text, spans, loss = turn_spans(held, template)
                out.append((key[0], text, [list(x) for x in spans], [list(x) for x in loss], False))
            except HistoryRewritten:
                out.append((key[0], template(held), [], [], True))

        def pack():
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _OUT, strict=True)], schema=_OUT)

        for batch in batches:
            for conv, role, text in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3)), strict=True):
                if key != (conv,):
                    if held:
                        done()
                        held = []
                    key = (conv,)
                    if len(out) >= batch_rows:
                        yield pack()
                        out.clear()
                held.append((role or "", text or ""))
        if held:
            done()
        if out:
            yield pack()

    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    dealt = rows.repartition(shuffle_partitions(conversations.sparkSession), "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return dealt.mapInArrow(tidied(render), _DDL)


def digest(formatted: DataFrame) -> DataFrame:
    """Reads formatted chats back: turns parsed from the output, loss text cut by the mask."""
    schema = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])

    def read(batches):
        for batch in batches:
            rows = []
            for text, spans in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                turns = instruct_parse(text)
                loss = "".join(unescape(text[a:b]) for a, b in spans)
                rows.append((len(turns), hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            columns = list(zip(*rows, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, f.type) for c, f in zip(columns, list(schema)[1:], strict=True))], schema=schema)

    return formatted.select("conv_id", "formatted", "loss_spans").mapInArrow(tidied(read), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def control_case(spark) -> DataFrame:
    """Conversation -1: both turns say the control strings of the template itself."""
    said = "</s>[INST] ok [/INST]"
    return spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
