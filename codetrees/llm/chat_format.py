r"""Chat formatting by columnar byte assembly.

Rows arrive dealt out by conversation and sorted by turn. For each Arrow batch the segments (conversation start, turn
header, text, turn end) get lengths, cumulative offsets and scatter indices in numpy, and all bytes are copied into one
preallocated buffer, which becomes the `formatted` column without another copy. A conversation of any length streams
through in batches; only digest states are carried over.

Template: "<s>" opens a conversation; a turn is "<|role|>\n" text "</s>\n". In texts and role names a backslash is
doubled, and one is put behind the first character of each control string, so that no control string can occur in them;
`unescape` undoes it exactly. The loss mask covers assistant texts.

Edge rules: null text is empty; null role is the empty role; null turns sort first, ties by text and role; rows of a
null conversation id form one conversation; a repeated row is a turn of its own; an empty table gives none (or just the
extra rows); extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import small_batches, tidy

# Control strings of the template.
CONTROL = ["<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|", "|>"]

ESCAPE = re.compile(rb"\\|" + b"|".join(re.escape(c[:1].encode()) + b"(?=" + re.escape(c[1:].encode()) + b")" for c in CONTROL))
UNESCAPE = re.compile(rb"\\(\\?)")
HEADER = re.compile(rb"<\|(.*?)\|>\n", re.S)
OPEN, END = b"<s>", b"</s>\n"
BLOCK = 4 << 20


def escape(b: bytes) -> bytes:
    return ESCAPE.sub(lambda m: b"\\\\" if m[0] == b"\\" else m[0] + b"\\", b)


def unescape(b: bytes) -> bytes:
    return UNESCAPE.sub(rb"\1", b) if b"\\" in b else b


def header(role: bytes) -> bytes:
    return b"<|" + escape(role) + b"|>\n"


def _scatter(out: np.ndarray, to: np.ndarray, source: np.ndarray, at: np.ndarray, lengths: np.ndarray) -> None:
    total = int(lengths.sum())
    if total:
        before = np.cumsum(lengths) - lengths
        step = np.arange(total)
        out[np.repeat(to - before, lengths) + step] = source[np.repeat(at - before, lengths) + step]


def assemble(first: np.ndarray, roles: list[bytes], data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows (escaped texts as data and offsets) to bytes: buffer, row offsets, and start and end of each text in its row."""
    names = {r: i for i, r in enumerate(dict.fromkeys(roles))}
    heads = [header(r) for r in names]
    role = np.array([names[r] for r in roles], np.int64)
    head_len = np.array([len(h) for h in heads], np.int64)
    head_at = np.cumsum(head_len) - head_len
    n = len(roles)
    lengths = np.stack([np.where(first, len(OPEN), 0), head_len[role], np.diff(off), np.full(n, len(END))], 1)
    ends = np.cumsum(lengths.ravel()).reshape(n, 4)
    starts = ends - lengths
    out = np.empty(int(ends[-1, -1]), np.uint8)
    zero = np.zeros(n, np.int64)
    for k, (source, at) in enumerate([(np.frombuffer(OPEN, np.uint8), zero), (np.frombuffer(b"".join(heads), np.uint8), head_at[role]), (data, off[:-1]), (np.frombuffer(END, np.uint8), zero)]):
        _scatter(out, starts[:, k], source, at, lengths[:, k])
    rows = np.concatenate([[0], ends[:, 3]])
    return out, rows, starts[:, 2] - rows[:-1], ends[:, 2] - rows[:-1]


def parse(formatted: bytes) -> list[tuple[bytes, bytes]]:
    """Read turns back from formatted bytes: [(role, text)]."""
    turns, at = [], len(OPEN) if formatted.startswith(OPEN) else 0
    while at < len(formatted):
        m = HEADER.match(formatted, at)
        end = formatted.index(END, m.end())
        turns.append((unescape(m[1]), unescape(formatted[m.end() : end])))
        at = end + len(END)
    return turns


def _format(batches):
    import pyarrow as pa

    from codetrees.llm.textbytes import byte_columns

    last = object()
    for b in batches:
        at = 0
        while at < b.num_rows:
            _, off = byte_columns(b.column("text").slice(at))
            size = max(1, int(np.searchsorted(off - off[0], BLOCK, "right")) - 1)
            x = b.slice(at, size)
            at += x.num_rows
            convs = x.column("conv").to_pylist()
            first = np.array([c != p for c, p in zip(convs, [last, *convs[:-1]], strict=True)])
            last = convs[-1]
            data, off = byte_columns(x.column("text"))
            data = data[off[0] : off[-1]]
            off = off - off[0]
            odd = np.flatnonzero((data == 92) | (data == 60) | (data == 91) | (data == 124))
            touched = np.unique(np.searchsorted(off, odd, "right") - 1)
            if len(touched):
                pieces, lens, raw, done = [], np.diff(off), data.tobytes(), 0
                for i in touched.tolist():
                    new = escape(raw[off[i] : off[i + 1]])
                    pieces += (raw[done : off[i]], new)
                    lens[i], done = len(new), int(off[i + 1])
                data = np.frombuffer(b"".join([*pieces, raw[done:]]), np.uint8)
                off = np.concatenate([[0], np.cumsum(lens)])
            roles = [(r or "").encode() for r in x.column("role").to_pylist()]
            out, rows, begin, end = assemble(first, roles, data, off)
            made = pa.Array.from_buffers(pa.binary(), len(roles), [None, pa.py_buffer(rows.astype(np.int32)), pa.py_buffer(out)])
            loss = np.array([r == b"assistant" for r in roles])
            yield pa.RecordBatch.from_arrays([x.column("conv"), pa.array(first), made, pa.array(np.where(loss, begin, 0)), pa.array(np.where(loss, end, 0))], names=["conv", "first", "formatted", "loss_start", "loss_end"])


def format_turns(df: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row per turn, in order within its partition: conv, first, formatted (bytes), loss_start and loss_end (byte
    span of the text under the loss mask; empty but for assistants)."""
    small_batches(df.sparkSession)
    rows = df.select(F.col(conv_col).alias("conv"), F.col(turn_col).alias("turn"), F.col(role_col).cast("string").alias("role"), F.col(text_col).cast("string").alias("text"))
    rows = rows.repartition("conv").sortWithinPartitions("conv", "turn", "text", "role")
    kind = rows.schema["conv"].dataType.simpleString()
    return rows.mapInArrow(tidy(_format), f"conv {kind}, first boolean, formatted binary, loss_start long, loss_end long")


def chars(b: bytes) -> int:
    a = np.frombuffer(b, np.uint8)
    return len(a) - int(((a & 0xC0) == 0x80).sum())


def _read_back(batches):
    import pyarrow as pa

    def fresh(conv):
        return {"conv": conv, "n": 0, "turns": hashlib.sha256(), "loss": hashlib.sha256(), "loss_chars": 0, "chars": 0}

    def row(states, kind):
        return pa.RecordBatch.from_arrays(
            [pa.array([s["conv"] for s in states], kind), pa.array([s["n"] for s in states], pa.int64()), pa.array([s["turns"].hexdigest() for s in states]), pa.array([s["loss_chars"] for s in states], pa.int64()), pa.array([s["loss"].hexdigest() for s in states]), pa.array([s["chars"] for s in states], pa.int64())],
            names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"],
        )

    state, kind = None, None
    for b in batches:
        kind, done = b.column("conv").type, []
        for conv, first, text, lo, hi in zip(*(b.column(c).to_pylist() for c in ("conv", "first", "formatted", "loss_start", "loss_end")), strict=True):
            if first:
                if state:
                    done.append(state)
                state = fresh(conv)
            for role, said in parse(text):
                state["n"] += 1
                state["turns"].update(role + b"\n" + said + b"\n")
            if hi > lo:
                masked = unescape(text[lo:hi])
                state["loss"].update(masked)
                state["loss_chars"] += chars(masked)
            state["chars"] += chars(text)
        if done:
            yield row(done, kind)
    if state:
        yield row([state], kind)


def conversation_digests(turns: DataFrame) -> DataFrame:
    """Read formatted turns back, streaming: one row per conversation."""
    kind = turns.schema["conv"].dataType.simpleString()
    return turns.mapInArrow(tidy(_read_back), f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def format_conversations(df: DataFrame, **columns) -> DataFrame:
    """One row per conversation with its whole formatted text (for conversations that fit a row): conv_id, formatted."""
    turns = format_turns(df, **columns)
    return turns.mapInArrow(tidy(_join_turns), f"conv_id {turns.schema['conv'].dataType.simpleString()}, formatted string")


def _join_turns(batches):
    import pyarrow as pa

    held, kind, conv = [], None, None
    for b in batches:
        kind, out = b.column("conv").type, []
        for c, first, text in zip(*(b.column(x).to_pylist() for x in ("conv", "first", "formatted")), strict=True):
            if first and held:
                out.append((conv, b"".join(held).decode()))
                held = []
            conv = c
            held.append(text)
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], kind), pa.array([o[1] for o in out], pa.string())], names=["conv_id", "formatted"])
    if held:
        yield pa.RecordBatch.from_arrays([pa.array([conv], kind), pa.array([b"".join(held).decode()], pa.string())], names=["conv_id", "formatted"])


def op10_chat_format(spark, sf_dir: str) -> DataFrame:
    """All conversations plus one made of control strings (id -7), formatted and read back."""
    df = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    odd = spark.range(2).select(F.lit(-7).cast(df.schema["conv_id"].dataType).alias("conv_id"), F.col("id").cast(df.schema["turn"].dataType).alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    return conversation_digests(format_turns(df.unionByName(odd)))


def op10_sql() -> str:
    count = lambda c: f"(length(text) - length(replace(text, '{c}', ''))) // {len(c)}"
    added = " + ".join(count(c) for c in ["\\", *CONTROL])
    return f"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL VALUES (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')),
     t AS (SELECT *, length(role) + length(text) + 10 + {added} AS c FROM r)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, text, role)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, text, role) FILTER (role = 'assistant'), '')) AS loss_sha256,
       (3 + sum(c))::BIGINT AS formatted_chars
FROM t GROUP BY conv_id
"""
