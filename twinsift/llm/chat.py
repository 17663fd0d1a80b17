"""Chat formatting by incremental black-box rendering.

A template is any function from a list of (role, text) turns to a string. The
renderer is called on successive prefixes; each output must begin with the one
before, and what it adds is the span of the new turn. Where it does not, the
template rewrites history: this is reported, and the text is the template's output for the
whole conversation, in which every turn's own text is looked for anew. The part of a
span that is the turn's own text is found by rendering the turn twice more with
one-letter probes: what both probes share on the left and on the right is the
frame. So the loss mask needs no knowledge of the template. What is told of a conversation is parsed from its finished text, in a step that sees nothing else.

The prefixes are whole ones, so work grows with the square of a conversation's turns and a
conversation is held in memory. Only a template that is declared history-free (attribute
`history_free`: what a turn adds depends on that turn alone, as in `instruct_template`) is, beyond WINDOW turns, rendered
over a sliding window of turns, so the work for each turn is bounded; at the end of each window the first turn
of the next one is rendered in both and must add the same text.

Defined cases: a null text is empty, a null role is the empty role; turns go by
(turn, role, text), null first, and repeated rows are separate turns; rows with
a null conv_id form one conversation; an empty table gives an empty one;
further columns are ignored. A conversation is a stream of its sorted rows and one row of output, so a task holds the text of
one conversation (2 GB at most) besides one batch. After a rewrite, a turn that the final text lacks or shows more than once has no span.
"""

import hashlib
import os.path
import re
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value

by_value(__name__)

WINDOW = 24
Turn = tuple[str, str]

# The control strings of this template, and the character that escapes them.
FRAMES = {"user": ("<s>[INST] ", " [/INST]"), "assistant": (" ", "</s>"), "system": ("<<SYS>>\n", "\n<</SYS>>\n")}
OTHER = ("[ROLE]", "[/ROLE]", "[/END]")
CONTROLS = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", *OTHER)
_TO_ESCAPE = re.compile("|".join(map(re.escape, ("\\", *CONTROLS))))
_ESCAPED = re.compile(r"\\(" + _TO_ESCAPE.pattern + ")")


def escape(text: str) -> str:
    return _TO_ESCAPE.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def instruct_template(turns: list[Turn]) -> str:
    """[INST]-style text in which every turn, of whatever role, can be told apart and read back."""
    out = []
    for role, text in turns:
        if role in FRAMES:
            before, after = FRAMES[role]
            mark = "[ROLE][/ROLE]" if role == "assistant" else ""
            out += [mark, before, escape(text), after]
        else:
            out += [OTHER[0], "=", escape(role), OTHER[1], escape(text), OTHER[2]]
    return "".join(out)


instruct_template.history_free = True

_TOKENS = re.compile(_ESCAPED.pattern + "|(?P<mark>" + "|".join(map(re.escape, CONTROLS)) + ")")
_OPENS = {"<s>": ("user", "[INST] ", " [/INST]"), "<<SYS>>": ("system", "\n", "\n<</SYS>>\n")}


def parse_instruct(text: str) -> list[Turn]:
    """The turns that instruct_template was given, from its output alone."""
    marks = [(m.start(), m["mark"]) for m in _TOKENS.finditer(text) if m["mark"]]
    turns, k, at = [], 0, 0

    def upto(end: str, begin: int) -> str:
        nonlocal k, at
        word = end.strip()
        while marks[k][1] != word or marks[k][0] < begin:
            k += 1
        stop = marks[k][0] - (len(end) - len(end.lstrip()))
        at, k = stop + len(end), k + 1
        return unescape(text[begin:stop])

    while at < len(text):
        start, mark = marks[k]
        if start != at:
            raise ValueError(f"no turn begins at {at}")
        k += 1
        if mark in _OPENS:
            role, rest, end = _OPENS[mark]
            begin = at + len(mark) + len(rest)
        elif text.startswith("[ROLE]=", at):
            role = upto("[/ROLE]", at + 7)
            begin, end = at, "[/END]"
        else:
            role, begin, end = "assistant", at + len("[ROLE][/ROLE] "), "</s>"
        turns.append((role, upto(end, begin)))
    return turns


def _shared(a: str, b: str) -> int:
    return len(os.path.commonprefix([a, b]))


class Spans:
    """Feeds turns one after another to a black-box template and tells what each adds."""

    def __init__(self, render: Callable[[list[Turn]], str], window: int = WINDOW, probes: tuple[str, str] = ("a", "b")):
        self.render, self.probes = render, probes
        self.window = window if getattr(render, "history_free", False) else None
        self.turns: list[Turn] = []
        self.out = render([])
        self.opening, self.rewrites = self.out, 0

    def add(self, role: str, text: str) -> tuple[str, int, int]:
        """The text that this turn adds, and where its own (rendered) text begins and ends in it."""
        if self.window and len(self.turns) >= self.window:
            self.turns = self.turns[-(self.window // 2) :]
            short = self.render(self.turns)
            self.rewrites += self.render([*self.turns, (role, text)])[len(short) :] != self.render([*self.turns[1:], (role, text)])[len(self.render(self.turns[1:])) :]
            self.out = short
        after = self.render([*self.turns, (role, text)])
        same = _shared(self.out, after)
        if same < len(self.out):
            self.rewrites += 1
        added = after[same:]
        one, two = (self.render([*self.turns, (role, p)])[same:] for p in self.probes)
        head = _shared(one, two)
        tail = _shared(one[:head:-1], two[:head:-1])
        self.turns.append((role, text))
        self.out = after
        return added, min(head, len(added)), max(min(head, len(added)), len(added) - tail)

    def place(self, k: int) -> tuple[int, int] | None:
        """Where the text of turn k is in the output for all turns; None if it is not there, or not in one place."""
        role = self.turns[k][0]
        one, two = (self.render([*self.turns[:k], (role, p), *self.turns[k + 1 :]]) for p in self.probes)
        head = _shared(one, two)
        tail = _shared(one[:head:-1], two[:head:-1])
        if one == two or head + tail + 1 != len(one) or not one[:head] == self.out[:head] or head + tail > len(self.out) or not self.out.endswith(one[len(one) - tail :]):
            return None
        return head, len(self.out) - tail


def _grouped(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple]:
    for batch in batches:
        yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)


_MADE = "conv_id long, formatted string, loss_spans array<array<long>>, rewrites long"
_READ = _MADE + ", n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
ROWS_OUT, CHARS_OUT = 2000, 4 << 20  # conversations, and their characters, in a batch that is handed on


def _handed_on(rows: Iterable[tuple], schema: str, chars: int) -> Iterator[pa.RecordBatch]:
    """Rows as batches of bounded size; chars is the place of the long text in a row."""
    types = {"long": pa.int64(), "string": pa.string(), "array<array<long>>": pa.list_(pa.list_(pa.int64()))}
    fields = pa.schema([(name, types[kind]) for name, kind in (c.split() for c in schema.split(", "))])
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[chars])
        if len(held) >= ROWS_OUT or size >= CHARS_OUT:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), fields.types, strict=True)], schema=fields)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), fields.types, strict=True)], schema=fields)


def render_conversations(turns: DataFrame, render: Callable[[list[Turn]], str] = instruct_template) -> DataFrame:
    """conv_id, formatted, loss_spans (code points, begin and end of each assistant text), rewrites: one row per conversation."""

    def finished(conv, spans: Spans, pieces: list[str], marked: list[list[int]]) -> tuple:
        if spans.window is None:  # the output for all turns is what counts; after a rewrite every turn is looked for anew
            text = spans.out
            if spans.rewrites:
                marked = [list(at) for at in (spans.place(k) for k, (role, _) in enumerate(spans.turns) if role == "assistant") if at]
        else:
            text = "".join(pieces)
        return conv, text, marked, spans.rewrites

    def conversations(batches):
        now = None
        for conv, role, text in _grouped(batches):
            if now is None or now[0] != conv:
                if now:
                    yield finished(*now)
                spans = Spans(render)
                now, length = (conv, spans, [spans.opening], []), len(spans.opening)
            added, begin, end = spans.add(role or "", text or "")
            if role == "assistant":
                now[3].append([length + begin, length + end])
            length += len(added)
            if spans.window:
                now[2].append(added)
        if now:
            yield finished(*now)

    rows = turns.select(turns["conv_id"].cast("long"), turns["turn"], turns["role"], turns["text"])
    rows = rows.repartition(F.col("conv_id")).sortWithinPartitions("conv_id", "turn", "role", "text")
    return rows.select("conv_id", "role", "text").mapInArrow(lambda batches: _handed_on(conversations(batches), _MADE, 1), _MADE)


def read_back(made: DataFrame, parse: Callable[[str], list[Turn]] = parse_instruct, read: Callable[[str], str] = unescape) -> DataFrame:
    """What the finished texts say: turns that parsing finds in them, and what stands under the loss mask; input as render_conversations gives it."""

    def conversations(batches):
        for conv, text, marked, rewrites in _grouped(batches):
            turns, loss, n, chars = hashlib.sha256(), hashlib.sha256(), 0, 0
            for role, said in parse(text):
                n += 1
                turns.update(f"{role}\n{said}\n".encode())
            for begin, end in marked:
                body = read(text[begin:end])
                loss.update(body.encode())
                chars += len(body)
            yield conv, text, marked, rewrites, n, turns.hexdigest(), chars, loss.hexdigest(), len(text)

    return made.select("conv_id", "formatted", "loss_spans", "rewrites").mapInArrow(lambda batches: _handed_on(conversations(batches), _READ, 1), _READ)


def format_conversations(turns: DataFrame, render: Callable[[list[Turn]], str] = instruct_template, parse: Callable[[str], list[Turn]] = parse_instruct, read: Callable[[str], str] = unescape, keep: bool = True) -> DataFrame:
    """One row per conversation: its text, the code-point spans under the loss mask, and digests read back from that text alone.

    keep=False leaves the text and the spans out of the result after they have been read."""
    done = read_back(render_conversations(turns, render), parse, read)
    return done if keep else done.withColumn("formatted", F.lit(None).cast("string")).withColumn("loss_spans", F.lit(None).cast("array<array<long>>"))
