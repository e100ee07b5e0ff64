"""Chat formatting with a grammar round trip.

A conversation is rendered turn by turn; a deterministic parser reads the rendered text back, piece by piece, and each
recovered turn is compared with its source. A turn that does not come back as it was is rendered again with its control
strings escaped. Rendering, parsing and digests stream over turns sorted by conversation, so a conversation of any length
takes the memory of one turn.

Grammar: turn = "<|im_start|>" role "\\n" text "<|im_end|>\\n". Escape: every "<", backslashes, "|" in a role or text gets one
backslash more, in a role also before "n|"; a line break in a role becomes "<n|"; so no rendered role or text holds "<|", and
removing one backslash restores it.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>\n"
RESULT = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_escaped long"


def escape(text: str) -> str:
    return re.sub(r"<(\\*)\|", r"<\1\\|", text)


def unescape(text: str) -> str:
    return re.sub(r"<(\\*)\\\|", r"<\1|", text)


def escape_role(role: str) -> str:
    return re.sub(r"<(\\*)(n?)\|", r"<\1\\\2|", role).replace("\n", "<n|")


def unescape_role(role: str) -> str:
    return re.sub(r"<(\\*)\\(n?)\|", r"<\1\2|", role.replace("<n|", "\n"))


def render(role: str, text: str, escaped: bool) -> str:
    return f"{START}{escape_role(role) if escaped else role}\n{escape(text) if escaped else text}{END}"


def parse(rendered: str) -> list[tuple[str, str, int, int]] | None:
    """Turns of a rendered text with the place of each text in it (role, text, start, end); None if it isn't of the grammar."""
    turns, at = [], 0
    while at < len(rendered):
        line = rendered.find("\n", at)
        end = rendered.find(END, at)
        if not rendered.startswith(START, at) or line < 0 or end < line:
            return None
        role, text = rendered[at + len(START) : line], rendered[line + 1 : end]
        if "<|" in role or "<|" in text:
            return None
        turns.append((unescape_role(role), unescape(text), line + 1, end))
        at = end + len(END)
    return turns


def formatted(role: str, text: str) -> tuple[str, tuple[str, str, int, int], bool]:
    """A turn as rendered text, as read back from it, and whether it needed escapes."""
    for escaped in (False, True):
        out = render(role, text, escaped)
        back = parse(out)
        if back is not None and len(back) == 1 and back[0][:2] == (role, text):
            return out, back[0], escaped
    raise AssertionError("an escaped turn must come back")


def format_turns(rows: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Adds rendered, loss_start, loss_end (empty span: no loss) and escaped to turns (conv_id, turn, role, text)."""
    for part in rows:
        made = [(out, back, esc) for out, back, esc in (formatted(r or "", t or "") for r, t in zip(part.role, part.text, strict=True))]
        learnt = [b[0] == "assistant" for _, b, _ in made]
        yield part[["conv_id", "turn"]].assign(rendered=[m[0] for m in made], loss_start=[m[1][2] if k else 0 for m, k in zip(made, learnt, strict=True)], loss_end=[m[1][3] if k else 0 for m, k in zip(made, learnt, strict=True)], escaped=[m[2] for m in made])


def _digests(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    none = object()
    conv, state, out = none, None, []

    def close():
        n, turns, chars, loss, size, escaped = state
        out.append((None if conv is None else int(conv), n, turns.hexdigest(), chars, loss.hexdigest(), size, escaped))

    for part in parts:
        for c, shown, a, b, esc in zip(part.conv_id, part.rendered, part.loss_start, part.loss_end, part.escaped, strict=True):
            c = None if pd.isna(c) else c
            if c != conv or conv is none:
                if conv is not none:
                    close()
                conv, state = c, [0, hashlib.sha256(), 0, hashlib.sha256(), 0, 0]
            for role, text, _, _ in parse(shown):
                state[0] += 1
                state[1].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
            learnt = unescape(shown[a:b])
            state[2] += len(learnt)
            state[3].update(learnt.encode("utf-8", "surrogatepass"))
            state[4] += len(shown)
            state[5] += bool(esc)
        if out:
            yield pd.DataFrame(out, columns=RESULT.replace(" long", "").replace(" string", "").split(", "))
            out.clear()
    if conv is not none:
        close()
        yield pd.DataFrame(out, columns=RESULT.replace(" long", "").replace(" string", "").split(", "))


def rendered_turns(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, rendered, loss_start, loss_end, escaped: the formatted text turn by turn, with its loss mask.

    Null texts and roles are empty; null turns come first; rows that tie on turn go by role, then text; repeated rows are turns
    of their own; a null conv_id is one conversation; other columns are ignored. An empty table gives no row.
    """
    return conversations.select(F.col("conv_id").cast("string"), F.col("turn").cast("string"), "role", "text").mapInPandas(format_turns, "conv_id string, turn string, rendered string, loss_start long, loss_end long, escaped boolean")


def digests(conversations: DataFrame) -> DataFrame:
    """Per conversation what the rendered turns say when read back; see rendered_turns for odd rows."""
    rows = conversations.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").withColumns({c: F.col(c).cast("string") for c in ("conv_id", "turn")}).mapInPandas(format_turns, "conv_id string, turn string, rendered string, loss_start long, loss_end long, escaped boolean").mapInPandas(_digests, RESULT)
