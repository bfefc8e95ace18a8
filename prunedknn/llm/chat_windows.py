"""Chat formatting in budgeted windows.

A conversation's turns are read in order. Running sums of turn tokens place window ends
between turns; each window holds the leading system turn, a limited tail of turns that an
earlier window had, and fresh turns up to the budget. Only fresh assistant texts are under
the loss mask, so each is learnt once. Rows are dealt by conversation and sorted; a task
streams through them and holds one window, however long the conversation.

Control strings inside texts are broken by a backslash after their first character, and
backslashes are doubled: what is read back is the text, and no text can close a turn.

Edge cases: null texts and roles are empty; rows with a null conversation id form one
conversation; null turns come first, ties go by role and text; a turn longer than the budget
has a window of its own; repeated rows are turns each; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BUDGET, HISTORY = 1024, 256
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
#: Control strings of this template and of other common ones.
CONTROLS = (
    OPEN, CLOSE, "<|endoftext|>", "<|begin_of_text|>", "<|end_of_text|>", "<|start_header_id|>", "<|end_header_id|>", "<|eot_id|>",
    "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|user|>", "<|assistant|>", "<|system|>", "<start_of_turn>", "<end_of_turn>",
)
_BREAK = re.compile(r"\\|" + "|".join(f"(?<={re.escape(c[0])})(?={re.escape(c[1:])})" for c in CONTROLS))
_MEND = re.compile(r"\\(\\?)")
_LINE = "␤"


def escape(text: str) -> str:
    return _BREAK.sub(lambda m: "\\\\" if m[0] else "\\", text)


def unescape(text: str) -> str:
    return _MEND.sub(r"\1", text)


def escape_role(role: str) -> str:
    return escape(role).replace("\n", "\\" + _LINE)


def unescape_role(role: str) -> str:
    return _MEND.sub(lambda m: m[1], re.sub(rf"(?<!\\)((?:\\\\)*)\\{_LINE}", lambda m: m[1] + "\n", role))


_WINDOWS = pa.schema(
    [("conv_id", pa.int64()), ("window", pa.int32()), ("formatted", pa.string()), ("repeated", pa.int32()), ("n_tokens", pa.int64()),
     ("loss", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))]
)
WINDOW_TYPE = "conv_id long, window int, formatted string, repeated int, n_tokens long, loss array<struct<start: long, end: long>>"


class _Conversation:
    def __init__(self, conv_id, budget: int, history: int):
        self.conv_id, self.budget, self.history = conv_id, budget, history
        self.system: tuple | None = None
        self.repeated: list[tuple] = []
        self.fresh: list[tuple] = []
        self.tokens = self.made = self.seen = 0

    def add(self, role: str, text: str, tokens: int) -> dict | None:
        """The window that ends before this turn, if one does."""
        out, turn = None, (role, text, tokens)
        self.seen += 1
        if self.fresh and self.tokens + tokens > self.budget:
            out = self.window()
            kept, size = [], 0
            for old in reversed(self.repeated + self.fresh):  # whole turns from the end, while they fit
                size += old[2]
                if size > self.history or size + tokens > self.budget or old is self.system:
                    break
                kept.insert(0, old)
            self.repeated, self.fresh = kept, []
            self.tokens = sum(t[2] for t in kept) + (self.system[2] if self.system else 0)
        if self.seen == 1 and role == "system":
            self.system = turn
        self.fresh.append(turn)
        self.tokens += tokens
        return out

    def window(self) -> dict:
        lead = [self.system] if self.system and self.made else []
        text, loss = [], []
        at = 0
        for k, (role, said, _) in enumerate([*lead, *self.repeated, *self.fresh]):
            head, body = f"{OPEN}{escape_role(role)}\n", escape(said)
            if k >= len(lead) + len(self.repeated) and role == "assistant":
                loss.append({"start": at + len(head), "end": at + len(head) + len(body)})
            text.append(head + body + CLOSE + "\n")
            at += len(text[-1])
        out = {
            "conv_id": self.conv_id, "window": self.made, "formatted": "".join(text), "repeated": len(lead) + len(self.repeated),
            "n_tokens": self.tokens, "loss": loss,
        }
        self.made += 1
        return out


def _format(ranks, pattern: str, budget: int, history: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import tiktoken

        count = tiktoken.Encoding("count", pat_str=pattern, mergeable_ranks=ranks.value, special_tokens={}).encode_ordinary
        now: _Conversation | None = None
        for batch in batches:
            out = []
            for conv_id, role, text in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if now is None or now.conv_id != conv_id:
                    if now is not None:
                        out.append(now.window())
                    now = _Conversation(conv_id, budget, history)
                role, text = role or "", text or ""
                done = now.add(role, text, len(count(f"{OPEN}{role}\n{escape(text)}{CLOSE}\n")))
                if done:
                    out.append(done)
                if len(out) >= 2000:
                    yield pa.RecordBatch.from_pylist(out, schema=_WINDOWS)
                    out = []
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=_WINDOWS)
        if now is not None:
            yield pa.RecordBatch.from_pylist([now.window()], schema=_WINDOWS)

    return run


def windows(turns: DataFrame, vocabulary: str, pattern: str, budget: int = BUDGET, history: int = HISTORY) -> DataFrame:
    """Windows of (conv_id, turn, role, text): formatted text, repeated leading turns, loss spans in
    characters. A task's rows come by conversation and window, in order."""
    from .bpe_words import load_ranks

    sent = turns.sparkSession.sparkContext.broadcast(load_ranks(vocabulary))  # as large as the vocabulary
    return (
        turns.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "role", "text").repartition("conv_id")
        .sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")
        .mapInArrow(_format(sent, pattern, budget, history), WINDOW_TYPE)
    )


def read_turns(formatted: str) -> list[tuple[str, str]]:
    """The turns of a window, as they were before formatting."""
    out = []
    for part in formatted.split(CLOSE + "\n")[:-1]:
        role, _, text = part.removeprefix(OPEN).partition("\n")
        out.append((unescape_role(role), unescape(text)))
    return out


_DIGEST = pa.schema(
    [("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()),
     ("formatted_chars", pa.int64())]
)
DIGEST_TYPE = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def _read_back(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    now = None

    def row() -> dict:
        conv_id, n, said, chars, loss, size = now
        return {"conv_id": conv_id, "n_turns": n, "turns_sha256": said.hexdigest(), "loss_chars": chars, "loss_sha256": loss.hexdigest(), "formatted_chars": size}

    for batch in batches:
        out = []
        for conv_id, number, formatted, repeated, _, loss in zip(*[c.to_pylist() for c in batch.columns], strict=True):
            if number == 0:
                if now is not None:
                    out.append(row())
                now = [conv_id, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
            for role, text in read_turns(formatted)[repeated:]:
                now[1] += 1
                now[2].update(f"{role}\n{text}\n".encode())
            for span in loss:
                text = unescape(formatted[span["start"] : span["end"]])
                now[3] += len(text)
                now[4].update(text.encode())
            now[5] += len(formatted)
        if out:
            yield pa.RecordBatch.from_pylist(out, schema=_DIGEST)
    if now is not None:
        yield pa.RecordBatch.from_pylist([row()], schema=_DIGEST)


def digests(made: DataFrame) -> DataFrame:
    """What the windows hold, read back from their formatted texts; made: the result of windows()."""
    return made.mapInArrow(_read_back, DIGEST_TYPE)
