"""Chat formatting into windows under a token budget.

Turns are written as ``<|im_start|>role\\ntext<|im_end|>\\n``.  Prefix sums of turn tokens choose spans of whole
turns: a window holds the system turn, up to ``history`` earlier turns that fit, repeated as context, and
new turns up to the budget.  A turn that fits the budget but not beside the system turn gets a window without
it; a system turn over the budget is an ordinary turn, as no window can hold it.  The loss mask covers the
assistant texts of new turns only, so a repeated target is masked.  A single turn over the budget gets a window
beside the system turn only, whole, without history.

Control strings inside texts are escaped reversibly: every ``<``, backslashes, ``|`` run in a text gains one
backslash, so no written text can hold ``<|``; reading back removes it.  In roles backslashes and line ends are
escaped too.

Rows are sorted by conversation and turn and streamed: a window is emitted as soon as it is full and only the
current window is held, however long a conversation is.

Edge cases: null texts and roles are empty; null turns sort first; rows with the same turn keep role and text
order; repeated rows are turns of their own; a null conv_id is a conversation of its own; a conversation without
assistant turns has empty loss; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
import re
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>"
_CONTROL, _ESCAPED, _ROLE = re.compile(r"<(\\*)\|"), re.compile(r"<\\(\\*)\|"), re.compile(r"\\(.)")
WINDOW = "conv_id {kind}, window int, first_turn long, n_new int, n_context int, n_tokens long, text string, loss array<struct<start:int,end:int>>"


def escape(text: str) -> str:
    return _CONTROL.sub(r"<\\\1|", text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"<\1|", text)


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return _ROLE.sub(lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def write_turn(role: str, text: str) -> tuple[str, int, int]:
    """Written turn, and where its text starts and ends in it."""
    head = f"{START}{escape_role(role)}\n"
    body = escape(text)
    return f"{head}{body}{END}\n", len(head), len(head) + len(body)


def read_turns(written: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a window."""
    out, at = [], 0
    while at < len(written):
        line = written.index("\n", at)
        stop = written.index(END + "\n", line + 1)
        out.append((unescape_role(written[at + len(START) : line]), unescape(written[line + 1 : stop])))
        at = stop + len(END) + 1
    return out


class Windows:
    """Windows of one conversation, from its turns in order."""

    def __init__(self, budget: int, history: int, count):
        self.budget, self.history, self.count = budget, history, count
        self.system = None
        self.beside = True  # the current window holds the system turn, if there is one
        self.turns: list = []  # (number, tokens, role, text, is new)
        self.prefix = [0]  # token sums over self.turns
        self.number = self.windows = 0

    def add(self, role: str, text: str, tokens: int | None = None):
        """Yields the window that this turn does not fit into, if any; ``tokens``: of the written turn, if known."""
        tokens = self.count(write_turn(role, text)[0]) if tokens is None else tokens
        if role == "system" and not self.number and tokens <= self.budget:
            self.system = (0, tokens, role, text, True)
            self.number += 1
            return
        most = self.system[1] if self.system else 0
        beside = most + tokens <= self.budget or tokens > self.budget  # a turn over the budget is over it anyway
        full = (most if self.beside else 0) + self.prefix[-1] + tokens > self.budget
        begun = any(t[4] for t in self.turns) or self.system and self.system[4] and not beside
        if begun and (full or beside and not self.beside):
            yield self.window()
            self.beside = beside
            room = self.budget - (most if beside else 0) - tokens
            # the earliest start whose suffix fits, by the prefix sums
            n = len(self.turns)
            start = max(n - self.history, 0)
            while start < n and self.prefix[n] - self.prefix[start] > room:
                start += 1
            self._restart([(*t[:4], False) for t in self.turns[start:]])
        self.turns.append((self.number, tokens, role, text, True))
        self.prefix.append(self.prefix[-1] + tokens)
        self.number += 1

    def _restart(self, turns: list) -> None:
        self.turns, self.prefix = turns, [0]
        for t in turns:
            self.prefix.append(self.prefix[-1] + t[1])

    def window(self) -> tuple:
        parts, loss, at, tokens = [], [], 0, 0
        shown = ([self.system] if self.system and self.beside else []) + self.turns
        for number, n, role, text, new in shown:
            written, a, b = write_turn(role, text)
            if new and role == "assistant":
                loss.append({"start": at + a, "end": at + b})
            parts.append(written)
            at += len(written)
            tokens += n
        fresh = [t for t in shown if t[4]]
        out = (self.windows, fresh[0][0], len(fresh), len(shown) - len(fresh), tokens, "".join(parts), loss)
        self.windows += 1
        if self.system:
            self.system = (*self.system[:4], False)
        return out

    def rest(self):
        if any(t[4] for t in self.turns) or self.system and self.system[4]:
            yield self.window()


def format_windows(turns: DataFrame, tokenizer: str, budget: int = 1024, history: int = 4) -> DataFrame:
    """One row per window of each conversation; columns as in ``WINDOW``.  ``tokenizer``: its JSON text."""
    shared = turns.sparkSession.sparkContext.broadcast(tokenizer)
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    names = ["conv_id", "window", "first_turn", "n_new", "n_context", "n_tokens", "text", "loss"]
    types = [pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))]

    def run(batches):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer

        tok = Tokenizer.from_str(shared.value)
        tok.encode_special_tokens = True
        none = object()
        held, now, kind = None, none, None

        def batch(out: list) -> pa.RecordBatch:
            cols = [pa.array([r[0] for r in out], kind), *(pa.array([r[i + 1] for r in out], t) for i, t in enumerate(types))]
            return pa.RecordBatch.from_arrays(cols, names=names)

        def counted():
            """Rows with the tokens of their written turns, counted some at a time."""
            for b in batches:
                rows = list(zip(*(c.to_pylist() for c in b.columns), strict=True))
                for i in range(0, len(rows), 256):
                    some = rows[i : i + 256]
                    found = tok.encode_batch_fast([write_turn(role, text)[0] for _, _, role, text in some], add_special_tokens=False)
                    yield from ((b.schema.field(0).type, conv, role, text, len(e)) for (conv, _, role, text), e in zip(some, found, strict=True))

        out, size = [], 0
        for kind, conv, role, text, tokens in counted():
            if conv != now or now is none:
                if held:
                    out += [(now, *w) for w in held.rest()]
                held, now = Windows(budget, history, None), conv
            out += [(now, *w) for w in held.add(role, text, tokens)]
            size += len(text)
            if size > 1 << 22:
                yield batch(out)
                out, size = [], 0
        if held:
            out += [(now, *w) for w in held.rest()]
        if out:
            yield batch(out)

    return rows.mapInArrow(run, WINDOW.format(kind=turns.schema["conv_id"].dataType.simpleString()))


def read_back(windows: DataFrame) -> DataFrame:
    """Digests of each conversation read from its windows alone."""
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    kind = windows.schema["conv_id"].dataType.simpleString()
    rows = windows.repartition("conv_id").sortWithinPartitions("conv_id", "window").select("conv_id", "n_context", "text", "loss")

    def run(batches):
        def all_rows():
            for b in batches:
                yield from zip(*(c.to_pylist() for c in b.columns), strict=True)

        out = []
        for conv, mine in groupby(all_rows(), key=lambda r: r[0]):
            turns, loss = hashlib.sha256(), hashlib.sha256()
            n = chars = total = 0
            for _, context, text, spans in mine:
                read = read_turns(text)
                for role, body in read[context:]:  # context stands before the new turns
                    turns.update(f"{role}\n{body}\n".encode())
                    n += 1
                for s in spans:
                    body = unescape(text[s["start"] : s["end"]])
                    loss.update(body.encode())
                    chars += len(body)
                total += len(text)
            out.append((conv, n, turns.hexdigest(), chars, loss.hexdigest(), total))
        types = [windows_type, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(types)], names=names)

    from pyspark.sql.pandas.types import to_arrow_type

    windows_type = to_arrow_type(windows.schema["conv_id"].dataType)
    return rows.mapInArrow(run, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
