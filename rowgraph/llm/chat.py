"""Chat formatting with a grammar round trip.

Template: each turn is ``<|im_start|>ROLE\\nTEXT<|im_end|>\\n``.  A deterministic parser reads the rendered text back.
Where what it recovers differs from the source, the control strings inside the text are escaped, one level more each
time, until it is identical; the level is written into the turn's head, so reading back undoes it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The control strings of the template.
START = "<|im_start|>"
END = "<|im_end|>"
ESCAPE = "<|esc|>"
#: Role whose text is under the loss mask.
LEARNED = "assistant"


class BadMarkup(ValueError):
    pass


def escape(text: str) -> str:
    """The text without any control string; ``unescape`` gives it back.

    Every ``<|`` becomes ``<`` + backslash + ``|``, and backslashes that stand between ``<`` and ``|`` grow by one.
    """
    out, at = [], 0
    while (k := text.find("<", at)) >= 0:
        stop = k + 1
        while text[stop : stop + 1] == "\\":
            stop += 1
        out.append(text[at:stop])
        if text[stop : stop + 1] == "|":
            out.append("\\")
        at = stop
    out.append(text[at:])
    return "".join(out)


def unescape(text: str) -> str:
    out, at = [], 0
    while (k := text.find("<\\", at)) >= 0:
        stop = k + 1
        while text[stop : stop + 1] == "\\":
            stop += 1
        out.append(text[at : stop - 1] if text[stop : stop + 1] == "|" else text[at:stop])
        at = stop
    out.append(text[at:])
    return "".join(out)


def render(role: str, text: str) -> str:
    """One turn, escaped only where the plain form doesn't read back as itself."""
    plain = f"{START}{role}\n{text}{END}\n"
    if _reads_as(plain, role, text):
        return plain
    safe = f"{START}{ESCAPE}{escape(role).replace(chr(10), '<' + chr(92) + 'n')}\n{escape(text)}{END}\n"
    if not _reads_as(safe, role, text):
        safe = f"{START}{ESCAPE * 2}{role.encode().hex()}\n{text.encode().hex()}{END}\n"
        if not _reads_as(safe, role, text):
            raise BadMarkup("a turn that can't be formatted")
    return safe


def _reads_as(markup: str, role: str, text: str) -> bool:
    try:
        return [(r, t) for r, t, _, _ in parse(markup)] == [(role, text)]
    except (BadMarkup, ValueError):
        return False


def parse(markup: str) -> Iterator[tuple[str, str, int, int]]:
    """(role, text, start, end) of each turn; start and end bound the text as it stands in the markup.

    Deterministic: the head ends at the first newline, the text at the first control string, which must be END.
    """
    at = 0
    while at < len(markup):
        if not markup.startswith(START, at):
            raise BadMarkup(f"no turn starts at {at}")
        head = at + len(START)
        level = 0
        while level < 2 and markup.startswith(ESCAPE, head):
            level, head = level + 1, head + len(ESCAPE)
        line = markup.find("\n", head)
        stop = markup.find(END, line + 1)
        if line < 0 or stop < 0 or not markup.startswith(END + "\n", stop):
            raise BadMarkup(f"the turn at {at} doesn't end")
        role, text = markup[head:line], markup[line + 1 : stop]
        if START in text or START in role or END in role or ESCAPE in role:
            raise BadMarkup(f"a control string within the turn at {at}")
        if level == 1:
            role, text = unescape(role.replace("<\\n", "\n")), unescape(text)
        elif level == 2:
            role, text = bytes.fromhex(role).decode(), bytes.fromhex(text).decode()
        yield role, text, line + 1, stop
        at = stop + len(END) + 1


def format_turns(rows: DataFrame) -> DataFrame:
    """conv_id, turn, role, text and ``markup``, the rendered turn, for each row (null role or text: empty).

    Turns are rendered and proved where they lie; nothing is gathered.
    """
    kinds = dict(rows.dtypes)
    rows = rows.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))

    def run(batches):
        for batch in batches:
            made = [render(r, t) for r, t in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, pa.string())], names=[*batch.schema.names, "markup"])

    return rows.mapInArrow(run, f"conv_id {kinds['conv_id']}, turn {kinds['turn']}, role string, text string, markup string")


class _Reader:
    """Digests of one conversation, fed with its markup turn by turn."""

    def __init__(self, conv_id):
        self.conv_id = conv_id
        self.turns, self.loss = hashlib.sha256(), hashlib.sha256()
        self.n_turns = self.loss_chars = self.chars = 0

    def feed(self, markup: str) -> None:
        self.chars += len(markup)
        for role, text, _, _ in parse(markup):
            self.n_turns += 1
            self.turns.update(f"{role}\n{text}\n".encode())
            if role == LEARNED:
                self.loss.update(text.encode())
                self.loss_chars += len(text)

    def row(self) -> tuple:
        return self.conv_id, self.n_turns, self.turns.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars


_OUT = [("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())]


def read_back(formatted: DataFrame) -> DataFrame:
    """One row per conversation, recovered by the parser from the markup alone.

    Conversations are streamed: rows come sorted by conversation and turn (nulls first; ties by markup), and a
    conversation of any length is read turn by turn without being held.  A null conv_id is a conversation.
    """
    schema = pa.schema(_OUT)
    placed = formatted.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "markup")
    placed = placed.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "markup").select("conv_id", "markup")

    def run(batches: Iterable[pa.RecordBatch]):
        current, done = None, []
        for batch in batches:
            for conv_id, markup in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if current is None or current.conv_id != conv_id:
                    if current is not None:
                        done.append(current.row())
                    current = _Reader(conv_id)
                current.feed(markup)
            if len(done) > 1000:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*done, strict=True), _OUT, strict=True)], schema=schema)
                done = []
        if current is not None:
            done.append(current.row())
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*done, strict=True), _OUT, strict=True)], schema=schema)

    return placed.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def loss_spans(markup: str) -> list[tuple[int, int]]:
    """Stretches of a formatted conversation on which the loss is taken."""
    return [(start, end) for role, _, start, end in parse(markup) if role == LEARNED]


def chat_digests(conversations: DataFrame) -> DataFrame:
    """Formats all turns, reads the output back and gives its digests per conversation."""
    return read_back(format_turns(conversations))
