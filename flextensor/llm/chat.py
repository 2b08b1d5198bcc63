"""Chat formatting by incremental black-box rendering.

A template is a function from a list of (role, text) turns to one string. Nothing is known about it: the formatter
renders successive prefixes of a conversation and compares consecutive outputs. Where an output begins with the one
before, the rest is the new turn's span; where it doesn't, the template rewrites history, which is reported together
with the turn, and the span is taken from the first difference on. Every prefix of every conversation is rendered and
compared, whatever its length; the templates here remember the turns they have rendered, up to a bounded number of
characters, so that a further prefix costs its joining and one comparison of memory.

The template ``marked`` starts each turn with a control string and escapes whatever looks like one in texts and
roles: backslashes double and a backslash goes behind the first character of a control string. Reading back undoes both.

Defined results: null texts and roles are empty; turns are ordered by turn (nulls first), role, text; repeated rows are
turns of their own; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Turns = list[tuple[str, str]]
# fixed values: control strings of common chat templates
CONTROL = re.compile(r"<\||\|>|</?s>|\[/?INST\]|<</?SYS>>|<(?:bos|eos|start_of_turn|end_of_turn)>")
STARTS = re.compile(rf"(?={CONTROL.pattern})(.)")
TURN = re.compile(r"<\|turn\|>(.*?)<\|text\|>(.*?)<\|end\|>", re.S)
REMEMBERED_CHARS = 1 << 24


def escape(text: str) -> str:
    if "\\" in text:
        text = text.replace("\\", "\\\\")
    return STARTS.sub(r"\1\\", text)


def unescape(text: str) -> str:
    return re.sub(r"\\(\\?)", r"\1", text) if "\\" in text else text


def remembered(render: Callable[[tuple[str, str]], str], most: int = REMEMBERED_CHARS) -> Callable[[tuple[str, str]], str]:
    """``render`` of single turns, its results kept up to ``most`` characters."""
    known: dict[tuple[str, str], str] = {}
    held = 0

    def piece(turn: tuple[str, str]) -> str:
        nonlocal held
        out = known.get(turn)
        if out is None:
            out = render(turn)
            held += len(out) + len(turn[1])
            if held > most:
                known.clear()
                held = len(out) + len(turn[1])
            known[turn] = out
        return out

    return piece


_marked_turn = remembered(lambda turn: f"<|turn|>{escape(turn[0])}<|text|>{escape(turn[1])}<|end|>")


def marked(turns: Turns) -> str:
    return "".join(map(_marked_turn, turns))


def bracketed(turns: Turns) -> str:
    """Users in brackets; a system text joins the first user turn."""
    out, system = [], ""
    for role, text in turns:
        if role == "system":
            system = f"<<SYS>>{escape(text)}<</SYS>>"
        elif role == "user":
            out.append(f"<s>[INST]{system}{escape(text)}[/INST]")
            system = ""
        else:
            out.append(f"{escape(text)}</s>")
    return "".join(out)


def last_answer_only(turns: Turns) -> str:
    """Drops the text of every assistant turn but the last: a template that rewrites history."""
    last = max((i for i, (r, _) in enumerate(turns) if r == "assistant"), default=-1)
    return "".join(f"<|turn|>{escape(r)}<|text|>{escape(t) if r != 'assistant' or i == last else ''}<|end|>" for i, (r, t) in enumerate(turns))


def locate(turns: Turns, template: Callable[[Turns], str]) -> tuple[str, list[tuple[int, int]], list[int]]:
    """(output, span of each turn, turns at which history was rewritten)"""
    old, spans, rewritten = "", [], []
    for k in range(len(turns)):
        new = template(turns[: k + 1])
        if new.startswith(old):
            start = len(old)
        else:
            rewritten.append(k)
            low, high = 0, min(len(old), len(new))
            while low < high:  # the longest common prefix
                mid = (low + high + 1) // 2
                low, high = (mid, high) if old[:mid] == new[:mid] else (low, mid - 1)
            start = low
            spans = [(min(a, start), min(b, start)) for a, b in spans]
        spans.append((start, len(new)))
        old = new
    return old, spans, rewritten


def read_back(output: str) -> Turns:
    return [(unescape(m[1]), unescape(m[2])) for m in TURN.finditer(output)]


def read_span(output: str, start: int, end: int) -> tuple[str, str]:
    m = TURN.fullmatch(output, start, end)
    if m is None:
        raise ValueError(f"no turn at {start}")
    return unescape(m[1]), unescape(m[2])


def _conversations(frames: Iterator[pd.DataFrame]) -> Iterator[tuple[int, Turns]]:
    """Whole conversations from rows sorted by conversation and turn."""
    key, turns, some = None, [], False
    for pdf in frames:
        for c, role, text in zip(pdf["conv_id"].astype(object), pdf["role"], pdf["text"], strict=True):
            c = None if pd.isna(c) else int(c)
            if some and c != key:
                yield key, turns
                turns = []
            key, some = c, True
            turns.append((role or "", text or ""))
    if some:
        yield key, turns


def _sorted(convs: DataFrame) -> DataFrame:
    return convs.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "role", "text").repartition("conv_id").sortWithinPartitions("conv_id", F.col("turn").asc_nulls_first(), "role", "text").select("conv_id", "role", "text")


def format_chats(convs: DataFrame, template: Callable[[Turns], str] = marked) -> DataFrame:
    """(conv_id, formatted, spans, assistant, rewritten): the output, (start, end) of each turn and whether it is the assistant's, and where history changed."""

    def run(frames):
        for c, turns in _conversations(frames):
            out, spans, rewritten = locate(turns, template)
            yield pd.DataFrame({"conv_id": pd.Series([c], dtype="Int64"), "formatted": [out], "spans": [[list(s) for s in spans]], "assistant": [[r == "assistant" for r, _ in turns]], "rewritten": [rewritten]})

    return _sorted(convs).mapInPandas(run, "conv_id long, formatted string, spans array<array<int>>, assistant array<boolean>, rewritten array<int>")


def chat_digests(convs: DataFrame) -> DataFrame:
    """What the formatted conversations hold, read back from the output alone."""

    def digest(out: str, spans: list[tuple[int, int]]) -> tuple:
        all_, loss, n_loss = hashlib.sha256(), hashlib.sha256(), 0
        for a, b in spans:
            role, text = read_span(out, a, b)
            all_.update(f"{role}\n{text}\n".encode())
            if role == "assistant":
                loss.update(text.encode())
                n_loss += len(text)
        return len(spans), all_.hexdigest(), n_loss, loss.hexdigest(), len(out)

    def run(frames):
        rows = []
        for c, turns in _conversations(frames):
            out, spans, rewritten = locate(turns, marked)
            rows.append((c, *digest(out, spans), bool(rewritten)))
            if len(rows) == 500:
                yield frame(rows)
                rows = []
        if rows:
            yield frame(rows)

    def frame(rows):
        pdf = pd.DataFrame(rows, columns=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "rewrites_history"])
        return pdf.astype({"conv_id": "Int64"})

    return _sorted(convs).mapInPandas(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, rewrites_history boolean")
