"""Chat formatting with offset-aligned loss masks.

A conversation is rendered as one string, encoded once, and the token offsets are intersected with the sorted spans
of the turns by binary search. The three marks are tokens of their own, so no token crosses the border of a text.
Texts and roles can't forge a mark: each `<`, any backslashes and `|` in them get one backslash more, which reading
takes away again.

Defined cases: a null text or role is empty; rows sort by turn (null first), then role, then text; repeated rows are
turns of their own; a row with null conv_id belongs to no other and is a conversation by itself; other columns are
ignored; an empty table gives no rows. The tokenizer's file is a parameter, read on every executor.
"""

from __future__ import annotations

import hashlib
import os
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The marks of the template.
OPEN, MIDDLE, CLOSE = "<|im_start|>", "<|im_sep|>", "<|im_end|>"
TOKENIZER = "/opt/tokenizers/byte_bpe_50k.json"
ENCODE_CHARS = 1 << 20

FORMATTED = "conv_id long, formatted string, token_ids array<int>, token_starts array<int>, token_ends array<int>, loss_mask array<boolean>"
DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_tokens long, n_loss_tokens long"

_TURN = re.compile(re.escape(OPEN) + "(.*?)" + re.escape(MIDDLE) + "(.*?)" + re.escape(CLOSE), re.S)


def escape(text: str) -> str:
    return re.sub(r"<(\\*)\|", r"<\1\\|", text)


def unescape(text: str) -> str:
    return re.sub(r"<\\(\\*)\|", r"<\1|", text)


def render(turns: list[tuple[str, str]]) -> str:
    return "".join(f"{OPEN}{escape(role)}{MIDDLE}{escape(text)}{CLOSE}" for role, text in turns)


def spans(formatted: str) -> list[tuple[str, int, int]]:
    """(role, start, end of the escaped text) of each turn, in order."""
    return [(unescape(m[1]), m.start(2), m.end(2)) for m in _TURN.finditer(formatted)]


@lru_cache(maxsize=2)
def tokenizer(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import AddedToken, Tokenizer

    if not os.path.exists(path):
        raise FileNotFoundError(f"no tokenizer at {path}: give format_conversations() the path of one as `path`")
    t = Tokenizer.from_file(path)
    t.add_special_tokens([AddedToken(x, normalized=False, special=True) for x in (OPEN, MIDDLE, CLOSE)])
    # the stock step after encoding trims blanks from offsets, which would leave them out of the mask
    from tokenizers.processors import ByteLevel

    t.post_processor = ByteLevel(trim_offsets=False)
    return t


def token_mask(starts: np.ndarray, ends: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For sorted, disjoint spans [lo, hi): whether each token overlaps one, and the first that it overlaps."""
    k = np.searchsorted(hi, starts, "right")
    inside = np.minimum(k, max(len(lo) - 1, 0))
    hit = (k < len(lo)) & (ends > starts)
    if len(lo):
        hit &= lo[inside] < ends
    return hit, inside


def _formatter(path: str, loss_roles: tuple[str, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(path)
        for batch in batches:
            ids = batch.column(0).to_pylist()
            held, chars = [], 0
            for i, conv in enumerate(ids):
                formatted = render([(t["role"], t["text"]) for t in batch.column(1)[i].as_py()])
                held.append((conv, formatted))
                chars += len(formatted)
                if chars >= ENCODE_CHARS or i == len(ids) - 1:
                    yield encode(tok, held)
                    held, chars = [], 0

    def encode(tok, held: list[tuple[int | None, str]]) -> pa.RecordBatch:
        out = []
        for (_, formatted), e in zip(held, tok.encode_batch([x for _, x in held], add_special_tokens=False), strict=True):
            at = np.array(e.offsets, np.int32).reshape(-1, 2)
            wanted = [(a, z) for role, a, z in spans(formatted) if role in loss_roles and z > a]
            lo, hi = np.array(wanted, np.int64).reshape(-1, 2).T
            out.append((np.array(e.ids, np.int32), at[:, 0], at[:, 1], token_mask(at[:, 0], at[:, 1], lo, hi)[0]))
        cols = [pa.array([x[k] for x in out], pa.list_(t)) for k, t in enumerate((pa.int32(), pa.int32(), pa.int32(), pa.bool_()))]
        return pa.RecordBatch.from_arrays([pa.array([c for c, _ in held], pa.int64()), pa.array([f for _, f in held], pa.string()), *cols], [c.split()[0] for c in FORMATTED.split(", ")])

    return run


def format_conversations(turns: DataFrame, path: str = TOKENIZER, loss_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """One row per conversation with its text, tokens and loss mask. A conversation is one output row, so its turns
    meet in one task; there is one shuffle. Rows without conv_id aren't shuffled."""
    row = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), row.alias("row"))
    grouped = rows.where("conv_id is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list("row")).alias("turns"))
    grouped = grouped.unionByName(rows.where("conv_id is null").select("conv_id", F.array("row").alias("turns")))
    return grouped.mapInArrow(_formatter(path, tuple(loss_roles)), FORMATTED)


def masked_text(formatted: str, starts: np.ndarray, ends: np.ndarray, mask: np.ndarray) -> list[str]:
    """The text under the mask for each span that has some, unescaped. Tokens that share a character count it once."""
    turns = spans(formatted)
    lo, hi = np.array([x[1:] for x in turns], np.int64).reshape(-1, 2).T
    keep = hi > lo
    lo, hi = lo[keep], hi[keep]
    s, e = starts[mask].astype(np.int64), ends[mask].astype(np.int64)
    _, which = token_mask(s, e, lo, hi)
    pieces: dict[int, list[str]] = {}
    done = 0
    for a, z, k in zip(np.maximum(s, lo[which]) if len(s) else s, np.minimum(e, hi[which]) if len(e) else e, which, strict=True):
        a = max(int(a), done)
        if z > a:
            pieces.setdefault(int(k), []).append(formatted[a:z])
            done = int(z)
    return [unescape("".join(pieces[k])) for k in sorted(pieces)]


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sha = lambda x: hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest()
    for batch in batches:
        rows = []
        for i in range(batch.num_rows):
            conv, formatted = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
            starts, ends, mask = (np.asarray(batch.column(k)[i].values.to_numpy(zero_copy_only=False)) for k in (3, 4, 5))
            turns = [(role, unescape(formatted[a:z])) for role, a, z in spans(formatted)]
            loss = "".join(masked_text(formatted, starts, ends, mask.astype(bool)))
            rows.append((conv, len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), len(formatted), len(mask), int(mask.sum())))
        names = [c.split()[0] for c in DIGEST.split(", ")]
        kinds = [pa.string() if "string" in c else pa.int64() for c in DIGEST.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names)


def digests(formatted: DataFrame) -> DataFrame:
    """What the formatted rows say when read back."""
    return formatted.mapInArrow(_digests, DIGEST)
