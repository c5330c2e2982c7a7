"""Chat formatting by columnar byte assembly.

A batch of turns becomes one byte buffer: lengths of headers, contents and
footers give cumulative offsets; headers and contents are copied to their places
by scatter indices, and the buffer is the Arrow string column as it is.  Roles and
texts are escaped as columns, too; no turn is a Python object on the way.  Only a
conversation that goes on over the end of a batch is put together from parts.  Control strings inside texts
are escaped reversibly: a backslash-like mark follows `<|` and an escaped `<|`
can be told from a real one.

Turn: `<|im_start|>role\\n` + content + `<|im_end|>\\n`.  In roles and contents `<|` becomes
`<\\|`, and `<\\` + backslashes + `|` gets one backslash more, so unescaping takes one off.

Cases: null text and null role are empty; turns are ordered by turn (nulls
first), then role, then text, and repeated rows are turns of their own; an empty
table has no conversations; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.session import arrow_rows, ship

OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"
#: bytes of one result batch: a string column has 32-bit offsets
MOST = 1 << 30
_GUARD = re.compile(r"<(\\*)\|")
_UNGUARD = re.compile(r"<(\\*)\\\|")
# a content that ends in "<" and backslashes would meet the "<" of CLOSE, never a "|": no guard is needed there


def escape(text: str) -> str:
    return _GUARD.sub(r"<\1\\|", text) if "<" in text else text


def unescape(text: str) -> str:
    return _UNGUARD.sub(r"<\1|", text) if "<" in text else text


def escape_role(role: str) -> str:
    """A role ends at a line end, so its own are marked; backslashes double to tell the two apart."""
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def _escaped(column: pa.Array) -> pa.Array:
    return pc.replace_substring_regex(column, r"<(\\*)\|", r"<\1\\|")


def _bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, bytes) of a large string column without nulls."""
    n = len(column)
    _, at, data = column.buffers()
    at = np.frombuffer(at, np.int64, n + 1, 8 * column.offset) if n else np.zeros(1, np.int64)
    return np.diff(at), np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] > at[0] else np.zeros(0, np.uint8)


def assemble(roles: pa.Array, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """One buffer of all turns: (bytes, turn offsets, content start, content end)."""
    roles, texts = roles.cast(pa.large_string()), texts.cast(pa.large_string())
    named = _escaped(pc.replace_substring(pc.replace_substring(roles, "\\", "\\\\"), "\n", "\\n"))
    heads = pc.binary_join_element_wise(pa.scalar(OPEN, pa.large_string()), named, pa.scalar("\n", pa.large_string()), pa.scalar("", pa.large_string()))
    foot = np.frombuffer(CLOSE.encode(), np.uint8)
    parts = [_bytes(heads), _bytes(_escaped(texts)), (np.full(len(roles), len(foot)), np.tile(foot, len(roles)))]
    size = np.array([p[0] for p in parts], dtype=np.int64).T  # turns x parts
    ends = np.cumsum(size.ravel()).reshape(size.shape)
    starts = ends - size
    out = np.empty(int(ends[-1, 2]) if len(ends) else 0, np.uint8)
    for k, (length, flat) in enumerate(parts):
        lead = np.cumsum(length) - length
        at = np.arange(len(flat)) + np.repeat(starts[:, k] - lead, length)
        out[at] = flat
    return out, np.append(starts[:, 0], len(out)), starts[:, 1], ends[:, 1]


def parse(formatted: str) -> list[tuple[str, str, int, int]]:
    """(role, text, first, end) of each turn, read back from a formatted conversation; offsets are of the escaped content."""
    turns, at = [], 0
    while at < len(formatted):
        if not formatted.startswith(OPEN, at):
            raise ValueError("a turn does not open here")
        end = formatted.index(CLOSE, at + len(OPEN))
        line = formatted.index("\n", at + len(OPEN))
        turns.append((unescape_role(formatted[at + len(OPEN) : line]), unescape(formatted[line + 1 : end]), line + 1, end))
        at = end + len(CLOSE)
    return turns


def format_conversations(turns: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """conv_id, formatted, n_turns, loss_starts, loss_ends (byte spans under the loss mask) of each conversation.

    Turns are dealt by conversation and sorted, and a partition streams through
    in batches; only the conversation at hand is held, which is one row of the result
    (a row of a string column has at most 2 GB, and so has a conversation).
    """
    spark = turns.sparkSession
    ship(spark)
    arrow_rows(spark, 4000)
    kind = turns.schema["conv_id"].dataType.simpleString()
    slim = turns.select(F.col("conv_id").alias("conv_id"), F.col("turn").alias("turn"), F.coalesce(F.col("role"), F.lit("")).alias("role"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    order = slim.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    ids = turns.schema["conv_id"].dataType

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_type

        key_type = to_arrow_type(ids)

        def batch(keys, data, at, n_turns, owner, first, last):
            """Conversations that lie one after the other in a buffer; spans by conversation, from its start."""
            offsets = (at - at[0]).astype(np.int32)
            text = pa.Array.from_buffers(pa.string(), len(keys), [None, pa.py_buffer(offsets), pa.py_buffer(data[at[0] : at[-1]])])
            edge = pa.array(np.searchsorted(owner, np.arange(len(keys) + 1)).astype(np.int32))
            spans = [pa.ListArray.from_arrays(edge, pa.array(x - at[owner])) for x in (first, last)]
            return pa.RecordBatch.from_arrays([keys, text, pa.array(n_turns, pa.int64()), *spans], names=["conv_id", "formatted", "n_turns", "loss_starts", "loss_ends"])

        def alone(held):
            """The one conversation that several batches gave parts of."""
            key, blocks = held
            at = np.cumsum([0, *(len(x[0]) for x in blocks)])
            first, last = (np.concatenate([x[k] + a for x, a in zip(blocks, at, strict=False)]) for k in (1, 2))
            return batch(key, np.concatenate([x[0] for x in blocks]), at[[0, -1]], [sum(x[3] for x in blocks)], np.zeros(len(first), np.int64), first, last)

        held = None
        for b in batches:
            n = len(b)
            if not n:
                continue
            keys = b.column("conv_id").cast(key_type)
            data, turn_at, cs, ce = assemble(b.column("role"), b.column("text"))
            loss = pc.equal(b.column("role"), loss_role).to_numpy(zero_copy_only=False)
            same = pc.equal(keys[1:], keys[:-1]).fill_null(False).to_numpy(zero_copy_only=False) | (keys[1:].is_null().to_numpy(zero_copy_only=False) & keys[:-1].is_null().to_numpy(zero_copy_only=False))
            cuts = np.concatenate([[0], np.flatnonzero(~same) + 1, [n]])

            def part(lo, hi):
                m, base = np.flatnonzero(loss[lo:hi]) + lo, turn_at[lo]
                return data[base : turn_at[hi]], cs[m] - base, ce[m] - base, hi - lo

            lo = 0
            if held is not None and held[0][0].as_py() == keys[0].as_py():
                held[1].append(part(0, cuts[1]))
                lo = 1
            if held is not None and len(cuts) - 1 > lo:
                yield alone(held)
                held = None
            # whole conversations of this batch, as many at once as 32-bit offsets allow; the last one may go on
            while lo < len(cuts) - 2:
                hi = max(lo + 1, int(np.searchsorted(turn_at[cuts], turn_at[cuts[lo]] + MOST, side="right")) - 1)
                hi = min(hi, len(cuts) - 2)
                c = cuts[lo : hi + 1]
                m = np.flatnonzero(loss[c[0] : c[-1]]) + c[0]
                yield batch(keys.take(pa.array(c[:-1])), data, turn_at[c], np.diff(c), np.searchsorted(c, m, side="right") - 1, cs[m], ce[m])
                lo = hi
            if lo == len(cuts) - 2:
                held = (keys.slice(cuts[lo], 1), [part(cuts[lo], n)])
        if held is not None:
            yield alone(held)

    return order.mapInArrow(run, f"conv_id {kind}, formatted string, n_turns long, loss_starts array<long>, loss_ends array<long>")


def digests(formatted: DataFrame) -> DataFrame:
    """What reading each formatted conversation back gives: turns and loss text, unescaped, as digests."""
    ids = formatted.schema["conv_id"].dataType

    def run(batches):
        for b in batches:
            cols: list[list] = [[] for _ in range(5)]
            for text, starts, ends in zip(b.column("formatted").to_pylist(), b.column("loss_starts").to_pylist(), b.column("loss_ends").to_pylist(), strict=True):
                turns, loss, all_ = hashlib.sha256(), hashlib.sha256(), parse(text)
                for role, said, _, _ in all_:
                    turns.update(f"{role}\n{said}\n".encode())
                raw, n = text.encode(), 0
                for s, e in zip(starts, ends, strict=True):
                    said = unescape(raw[s:e].decode())
                    n += len(said)
                    loss.update(said.encode())
                for c, v in zip(cols, (len(all_), turns.hexdigest(), n, loss.hexdigest(), len(text)), strict=True):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([b.column("conv_id"), *(pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True))], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return formatted.select("conv_id", "formatted", "loss_starts", "loss_ends").mapInArrow(run, f"conv_id {ids.simpleString()}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
