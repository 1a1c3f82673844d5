"""Chat formatting by prefix-target expansion.

Every assistant turn becomes one example: its text is the conversation up to and
with that turn, and only that reply is trainable. Turns behind the last reply stand in
one more row, the whole conversation, that trains nothing. So the examples of a
conversation are quadratic in its turns, as the method wants. An example of more than
CONTEXT characters comes in several rows, cut between turns: ``context_chars`` says how
many characters of this example stand in its rows before, and the last row trains.
``materialize_examples`` joins them to one text.

A turn is ``<|role|>\\n`` text ``<|end|>\\n``. Control strings inside roles and
texts are broken by a backslash after their first character, and backslashes are
doubled, which one left to right pass undoes.

Defined results: rows of a conversation go by turn, then role, then text, nulls
first; a null text or role is empty; repeated rows are turns of their own;
a null conv_id is a conversation of its own; a conversation without assistant
turns has a row that trains nothing; other columns are ignored. Rows of a conversation are
streamed through one task, which holds CONTEXT characters and a turn of it; what is
longer lies in a file of that task.
"""

from __future__ import annotations

import hashlib
import re
import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Strings that common chat templates treat as control.
CONTROL = ("<|", "|>", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
_FIRST = re.compile(r"[\\" + re.escape("".join(sorted({c[0] for c in CONTROL}))) + "]")
_TURN = re.compile(r"<\|([^|]*(?:\|(?!>)[^|]*)*)\|>\n(.*?)<\|end\|>\n", re.S)
CONTEXT = 1 << 22

EXAMPLES = "conv_id long, example long, trains boolean, text string, context_chars long, loss_start long, loss_end long"
DIGESTS = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def escape(text: str) -> str:
    """A backslash after every character that may begin a control string, so that none is left; backslashes double."""
    return _FIRST.sub(lambda m: f"{m[0]}\\", text)


def unescape(text: str) -> str:
    return re.sub(r"\\(\\?)", r"\1", text)


def _rows(batches: Iterator[pa.RecordBatch], *names: str) -> Iterator[tuple]:
    for batch in batches:
        yield from zip(*(batch.column(n).to_pylist() for n in names), strict=True)


def _batches(rows: Iterator[tuple], schema: pa.Schema, most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += sum(len(x) for x in row if isinstance(x, str)) + 64
        if size > most:
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)


_EXAMPLES = pa.schema([("conv_id", pa.int64()), ("example", pa.int64()), ("trains", pa.bool_()), ("text", pa.string()), ("context_chars", pa.int64()), ("loss_start", pa.int64()), ("loss_end", pa.int64())])
_DIGESTS = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])


def _expand(rows: Iterator[tuple], context: int) -> Iterator[tuple]:
    now, number, held, size, filed, fresh = object(), 0, [], 0, [], False
    with tempfile.TemporaryFile() as file:

        def example(trains: bool, *marks: int | None) -> Iterator[tuple]:
            before = 0
            file.seek(0)
            for length in filed:
                text = file.read(length).decode()
                yield now, number, False, text, before, None, None
                before += len(text)
            if held:
                yield now, number, trains, "".join(held), before, *marks

        for conv, role, text in rows:
            if conv != now:
                if fresh:
                    yield from example(False, None, None)
                now, number, held, size, filed, fresh = conv, 0, [], 0, [], False
                file.truncate(0)
            head, body = f"<|{escape(role or '')}|>\n", escape(text or "")
            held.append(f"{head}{body}<|end|>\n")
            size, fresh = size + len(held[-1]), True
            if role == "assistant":
                start = size - len(held[-1]) + len(head)
                yield from example(True, start, start + len(body))
                number, fresh = number + 1, False
            if size > context:
                file.seek(0, 2)
                filed.append(file.write("".join(held).encode()))
                held, size = [], 0
        if fresh:
            yield from example(False, None, None)


def format_chat(conversations: DataFrame, context: int = CONTEXT) -> DataFrame:
    """Examples (see EXAMPLES), those of a conversation in order in one partition; loss_start and loss_end are places in the row's text."""
    turns = conversations.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), F.col("role"), F.col("text"))
    ordered = turns.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return ordered.mapInArrow(lambda batches: _batches(_expand(_rows(batches, "conv_id", "role", "text"), context), _EXAMPLES), EXAMPLES)


def _digest(rows: Iterator[tuple]) -> Iterator[tuple]:
    now, state, read, seen = object(), None, 0, 0

    def out():
        n, turns, chars, loss, total = state
        return now, n, turns.hexdigest(), chars, loss.hexdigest(), total

    for conv, trains, text, before, start, end in rows:
        if conv != now:
            if state:
                yield out()
            now, state, read = conv, [0, hashlib.sha256(), 0, hashlib.sha256(), 0], 0
        seen = (seen if before else 0) + len(text)
        if before + len(text) > read:
            for m in _TURN.finditer(text, max(read - before, 0)):  # the turns that the examples before did not have
                state[0] += 1
                state[1].update(f"{unescape(m[1])}\n{unescape(m[2])}\n".encode())
            read = before + len(text)
        if trains:
            reply = unescape(text[start:end])
            state[2] += len(reply)
            state[3].update(reply.encode())
            state[4] += seen
    if state:
        yield out()


def digests(examples: DataFrame, ordered: bool = False) -> DataFrame:
    """What the examples say, read back: turns, trainable text, characters of all examples. ``ordered``: they are as ``format_chat`` gives them."""
    if not ordered:
        examples = examples.repartition("conv_id").sortWithinPartitions("conv_id", "example", "context_chars")
    return examples.mapInArrow(lambda batches: _batches(_digest(_rows(batches, "conv_id", "trains", "text", "context_chars", "loss_start", "loss_end")), _DIGESTS), DIGESTS)


def materialize_examples(examples: DataFrame) -> DataFrame:
    """conv_id, example, text (context and reply), loss_start and loss_end in it, of every example that trains."""
    rows = F.sort_array(F.collect_list(F.struct("context_chars", "text", "trains", "loss_start", "loss_end")))
    full = examples.groupBy("conv_id", "example").agg(rows.alias("_rows")).withColumn("_last", F.element_at("_rows", -1)).where("_last.trains")
    shift = F.col("_last.context_chars")
    return full.select("conv_id", "example", F.concat_ws("", "_rows.text").alias("text"), (shift + F.col("_last.loss_start")).alias("loss_start"), (shift + F.col("_last.loss_end")).alias("loss_end"))
