"""Chat formatting in budgeted windows.

A turn is written as <|role|>, its text with control strings escaped, and <|end|>. A conversation that exceeds the budget becomes
several windows of whole turns: prefix sums of the turns' tokens give the longest span that fits; each window repeats a leading system
turn and, up to a limit, the turns before it. Assistant texts carry the loss, each in one window only: repeated ones are masked.
A single turn larger than the budget has a window of its own.

Escaping: `<`, `[`, `]`, `|` and backslash of a text or role become a backslash and a letter, so no control string of this
template or another stands in it; undone letter by letter. The mask is a list of character ranges of the formatted window.

Rows stream through in the order of conversation and turn, one turn at a time with the turns of the open window; windows are rows of
their own, so a conversation of any length takes bounded memory, and its digests are taken along the way.

Results for odd input: a null text or role is empty; a null turn comes first; rows of equal conversation and turn are ordered by
role and text, and all are kept; a null conv_id is one conversation; an empty table gives no row; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import hot_share, mapped

BUDGET = 1024
HISTORY = 256
#: Tokens that the marks of a turn are taken to cost.
MARKS = 4
CONTROL = re.compile(r"[<\[\]|\\]")
ESCAPED = re.compile(r"\\([lbdps])")
LETTER = {"<": "l", "[": "b", "]": "d", "|": "p", "\\": "s"}
SIGN = {v: k for k, v in LETTER.items()}
TURN = re.compile(r"<\|([^<|]*)\|>([^<]*)<\|end\|>")
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"


def escape(text: str) -> str:
    return CONTROL.sub(lambda m: "\\" + LETTER[m[0]], text)


def unescape(text: str) -> str:
    return ESCAPED.sub(lambda m: SIGN[m[1]], text)


def token_counter(path: str = VOCABULARY):
    """Numbers of byte-pair tokens of texts."""
    import base64

    import public_tokenizers
    import tiktoken

    with open(path, "rb") as file:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in file if line.strip())}
    coder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda texts: [len(x) for x in coder.encode_ordinary_batch(texts, num_threads=1)]


def windows(turns: Iterator[tuple[str, str, int]], budget: int = BUDGET, history: int = HISTORY) -> Iterator[list[tuple[str, str, bool]]]:
    """Windows of (role, text, repeated), from (role, text, tokens) in order. Holds the turns of one window and its history."""
    system: tuple[str, str, int] | None = None
    past: list[tuple[str, str, int]] = []
    open_: list[tuple[str, str, int]] = []
    total, lead, first = 0, 0, True

    def close() -> list[tuple[str, str, bool]]:
        head = [(*system[:2], True)] if system and not begins else []
        return head + [(r, t, True) for r, t, _ in past] + [(r, t, False) for r, t, _ in open_]

    begins = True  # whether the open window begins the conversation
    for turn in turns:
        if first:
            first = False
            if turn[0] == "system":
                system = turn
        if open_ and total + turn[2] > budget:
            yield close()
            # The longest run of last turns whose prefix sums differ by no more than the limit.
            before, total, past = [x for x in past + open_ if x is not system], 0, []
            lead = system[2] if system else 0
            room = min(history, max(0, budget - lead - turn[2]))
            for old in reversed(before):
                if total + old[2] > room:
                    break
                past.insert(0, old)
                total += old[2]
            total += lead
            open_, begins = [], False
        open_.append(turn)
        total += turn[2]
    if open_:
        yield close()


def render(window: list[tuple[str, str, bool]]) -> tuple[str, list[tuple[int, int]], int]:
    """The formatted text, the character ranges under the loss, and the number of leading repeated turns."""
    parts, mask, at = [], [], 0
    for role, text, repeated in window:
        head, body = f"<|{escape(role)}|>", escape(text)
        parts += [head, body, "<|end|>"]
        if role == "assistant" and not repeated:
            mask.append((at + len(head), at + len(head) + len(body)))
        at += len(head) + len(body) + len("<|end|>")
    return "".join(parts), mask, sum(1 for w in window if w[2])


def parse(text: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a formatted window."""
    out, at = [], 0
    while at < len(text):
        m = TURN.match(text, at)
        if not m:
            raise ValueError("not a formatted window")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return out


def ordered(conversations: DataFrame) -> DataFrame:
    role, text = F.coalesce(F.col("role"), F.lit("")), F.coalesce(F.col("text"), F.lit(""))
    rows = conversations.select("conv_id", "turn", role.alias("role"), text.alias("text"))
    return rows.repartition(hot_share(conversations.sparkSession), "conv_id").sortWithinPartitions(F.col("conv_id").asc_nulls_first(), F.col("turn").asc_nulls_first(), "role", "text")


def formatted(conversations: DataFrame, budget: int = BUDGET, history: int = HISTORY, vocabulary: str = VOCABULARY) -> DataFrame:
    """conv_id, window (0, 1, ...), text, mask (ranges a, b) and repeated (leading turns that an earlier window has)."""
    kind = conversations.schema["conv_id"].dataType.simpleString()

    def run(batches):
        count = token_counter(vocabulary)

        def turns():
            for batch in batches:
                for k in range(0, batch.num_rows, 1000):
                    part = batch.slice(k, 1000)
                    texts = part.column(3).to_pylist()
                    yield from zip(part.column(0).to_pylist(), part.column(2).to_pylist(), texts, (n + MARKS for n in count(texts)), strict=True)

        source = turns()
        ahead = next(source, None)
        while ahead is not None:
            conv = ahead[0]

            def own():
                nonlocal ahead
                while ahead is not None and ahead[0] == conv:  # noqa: B023
                    now, ahead = ahead, next(source, None)
                    yield now[1:]

            for k, window in enumerate(windows(own(), budget, history)):
                yield conv, k, *render(window)

    def batches_of(batches):
        from itertools import islice

        rows = run(batches)
        names = ["conv_id", "window", "text", "mask", "repeated"]
        while part := list(islice(rows, 500)):
            conv, k, text, mask, repeated = zip(*part, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(conv, pa.int64() if kind == "bigint" else None), pa.array(k, pa.int64()), pa.array(text), pa.array([[{"a": a, "b": b} for a, b in m] for m in mask], pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))), pa.array(repeated, pa.int64())], names=names)

    return mapped(ordered(conversations), batches_of, f"conv_id {kind}, window bigint, text string, mask array<struct<a:bigint,b:bigint>>, repeated bigint")


def report(windows_: DataFrame) -> DataFrame:
    """Per conversation, read back from its windows: conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, n_windows."""
    kind = windows_.schema["conv_id"].dataType.simpleString()
    rows = windows_.repartition(hot_share(windows_.sparkSession), "conv_id").sortWithinPartitions(F.col("conv_id").asc_nulls_first(), "window")

    def run(batches):
        now, done = None, []

        def result():
            return (now[0], now[1], now[2].hexdigest(), now[3], now[4].hexdigest(), now[5], now[6])

        def table():
            return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*done, strict=True), (pa.int64() if kind == "bigint" else None, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64()), strict=True)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_windows"])

        for batch in batches:
            for conv, text, mask, repeated in zip(*(batch.column(batch.schema.names.index(n)) for n in ("conv_id", "text", "mask", "repeated")), strict=True):
                conv, text = conv.as_py(), text.as_py()
                if now is None or now[0] != conv:
                    if now is not None:
                        done.append(result())
                        if len(done) == 1000:
                            yield table()
                            done.clear()
                    now = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0, 0]
                for role, body in parse(text)[repeated.as_py() :]:
                    now[1] += 1
                    now[2].update(f"{role}\n{body}\n".encode())
                for r in mask.as_py():
                    loss = unescape(text[r["a"] : r["b"]])
                    now[3] += len(loss)
                    now[4].update(loss.encode())
                now[5] += len(text)
                now[6] += 1
        if now is not None:
            done.append(result())
        if done:
            yield table()

    return mapped(rows, run, f"conv_id {kind}, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint, n_windows bigint")
