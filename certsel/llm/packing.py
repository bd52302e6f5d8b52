"""Vector bin packing of examples into sequences under limits on tokens, segments and loss-bearing tokens.

An example is a demand vector (tokens, 1 segment, loss tokens), each part divided by its limit.  It goes to the open
sequence whose remaining room has the largest dot product with the demand, among those where it fits.  Each partition
keeps a bounded number of sequences open, so memory does not grow with the data and no rows are shuffled.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import tidy
from .tokens import TokenIds

#: Sequence ids are the partition number shifted by this many bits plus a running number.
PARTITION_SHIFT = 40


@dataclass(frozen=True)
class Limits:
    tokens: int = 1024
    segments: int = 256
    loss_tokens: int = 1024
    open_bins: int = 32


@dataclass
class _Bin:
    room: np.ndarray
    items: list = field(default_factory=list)


class DotProductPacker:
    """place(item, tokens, loss) puts whole items into bins; take() hands out the bins closed so far."""

    def __init__(self, limits: Limits):
        self.limits, self.open, self.closed = limits, [], []
        self.cap = np.array([limits.tokens, limits.segments, limits.loss_tokens], dtype=np.int64)
        self.rooms = np.zeros((limits.open_bins, 3), dtype=np.int64)

    def best(self, demand) -> int:
        """Index of the open bin with the largest dot product of room and demand where it fits, or -1."""
        n = len(self.open)
        if not n:
            return -1
        rooms = self.rooms[:n]
        score = ((rooms / self.cap) * (demand / self.cap)).sum(axis=1)
        score[(rooms < demand).any(axis=1)] = -1.0
        at = int(score.argmax())
        return at if score[at] >= 0 else -1

    def put(self, at: int, item, demand) -> None:
        self.open[at].items.append(item)
        self.rooms[at] -= demand
        if (self.rooms[at] <= 0)[:2].any():
            self.close(at)

    def close(self, at: int) -> None:
        self.closed.append(self.open[at].items)
        last = len(self.open) - 1
        self.open[at], self.rooms[at] = self.open[last], self.rooms[last]
        self.open.pop()

    def new(self) -> int:
        """A new bin; where all places are taken, the fullest one is closed for it."""
        if len(self.open) == self.limits.open_bins:
            self.close(int(self.rooms[:, 0].argmin()))
        self.open.append(_Bin(self.cap))
        self.rooms[len(self.open) - 1] = self.cap
        return len(self.open) - 1

    def place(self, item, tokens: int, loss: int) -> None:
        demand = np.array([tokens, 1, loss], dtype=np.int64)
        at = self.best(demand)
        self.put(at if at >= 0 else self.new(), item, demand)

    def take(self, end: bool = False) -> list:
        while end and self.open:
            self.close(len(self.open) - 1)
        out, self.closed = self.closed, []
        return out


def pack_examples(df: DataFrame, id_col: str, tokens_col: str, loss_col: str, limits: Limits = Limits()) -> DataFrame:
    """Pack whole examples: (id, sequence_id, segment, offset, tokens, loss_tokens).

    Examples are never cut.  One that exceeds a limit by itself, or whose sizes are null or negative, comes back with a null
    sequence_id.  Zero-token examples take a segment.  Repeated ids are separate examples.  No rows in, no rows out.
    """

    def run(batches):
        from pyspark import TaskContext

        packer, number = DotProductPacker(limits), TaskContext.get().partitionId() << PARTITION_SHIFT

        def emit(bins):
            nonlocal number
            rows = []
            for items in bins:
                offset = 0
                for k, (key, tokens, loss) in enumerate(items):
                    rows.append((key, number, k, offset, tokens, loss))
                    offset += tokens
                number += 1
            return rows

        for b in batches:
            rows = []
            for key, tokens, loss in zip(*(c.to_pylist() for c in b.columns)):
                if None in (tokens, loss) or min(tokens, loss) < 0 or tokens > limits.tokens or loss > limits.loss_tokens:
                    rows.append((key, None, None, None, tokens, loss))
                else:
                    packer.place((key, tokens, loss), tokens, loss)
            yield _batch(rows + emit(packer.take()), kinds, b.schema.field(0).type)
        yield _batch(emit(packer.take(end=True)), kinds, None)

    kinds = ["id", "sequence_id", "segment", "offset", "tokens", "loss_tokens"]
    id_type = df.select(id_col).schema[0].dataType.simpleString()
    arrow_id = pa.string() if id_type == "string" else pa.int64() if id_type == "bigint" else pa.int32()

    def _batch(rows, names, _):
        cols = list(zip(*rows)) if rows else [[] for _ in names]
        return pa.RecordBatch.from_arrays([pa.array(list(c), arrow_id if i == 0 else pa.int64()) for i, c in enumerate(cols)], names=names)

    return df.select(F.col(id_col).alias("id"), F.col(tokens_col).cast("long").alias("tokens"), F.col(loss_col).cast("long").alias("loss")).mapInArrow(
        tidy(run), f"id {id_type}, sequence_id long, segment long, offset long, tokens long, loss_tokens long")


def token_counts(df: DataFrame, tokenizer_path: str, text_col: str = "text") -> DataFrame:
    """df with n_tokens, the number of ids of its text; null texts have none.  All other columns pass through."""
    names = [c for c in df.columns if c != "n_tokens"]

    def run(batches):
        ids = TokenIds(tokenizer_path)
        for b in batches:
            n = [len(ids.encode(t or "")) // 4 for t in b.column(names.index(text_col)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n, pa.int64())], names=[*names, "n_tokens"])

    d = df.select(*names)
    return d.mapInArrow(tidy(run), T.StructType([*d.schema.fields, T.StructField("n_tokens", T.LongType())]))


def pack_conversations(turns: DataFrame, tokenizer_path: str, limits: Limits | None = None) -> DataFrame:
    """Conversations as examples for pack_examples: all turns' tokens, of which the assistant's bear loss.

    Turns with a null conv_id are one conversation.  A conversation over a limit comes back with a null sequence_id.
    """
    t = token_counts(turns.select("conv_id", "role", "text"), tokenizer_path)
    loss = F.when(F.col("role") == "assistant", F.col("n_tokens")).otherwise(0)
    return pack_examples(t.groupBy("conv_id").agg(F.sum("n_tokens").alias("tokens"), F.sum(loss).alias("loss")), "conv_id", "tokens", "loss", limits or Limits(tokens=4096, segments=8, loss_tokens=1024))


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, segment long"


def pack_documents(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", limits: Limits = Limits(), end_id: int = 0) -> DataFrame:
    """Cut documents into pieces and pack these: one row per piece, schema PIECES.

    A document's ids are its text's ids and end_id; full runs of limits.tokens are sequences by themselves and the rest is
    placed by dot product.  Where it fits nowhere and no more bins may be opened, it is cut at the fullest bin's end.
    Only the last sequence of a partition may be partly empty.  Null and empty texts give end_id alone; null ids are
    kept; rows with the same id are separate documents with their own pieces.  No rows in, no rows out.
    """
    names = [x.split()[0] for x in PIECES.split(", ")]

    def run(batches):
        from pyspark import TaskContext

        ids, packer = TokenIds(tokenizer_path), DotProductPacker(limits)
        number = TaskContext.get().partitionId() << PARTITION_SHIFT
        end, size = np.array([end_id], dtype="<u4").tobytes(), limits.tokens

        def emit(bins):
            nonlocal number
            rows = []
            for items in bins:
                offset = 0
                for k, (doc, start, raw, total) in enumerate(items):
                    rows.append((doc, start, len(raw) // 4, zlib.crc32(raw), total, number, offset, k))
                    offset += len(raw) // 4
                number += 1
            return pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in (zip(*rows) if rows else [[] for _ in names])], names=names)

        def place(doc, start, raw, total):
            n = len(raw) // 4
            demand = np.array([n, 1, n], dtype=np.int64)
            at = packer.best(demand)
            if at < 0 and len(packer.open) == limits.open_bins:
                at = int(packer.rooms[:, 0].argmin())
                room = int(min(packer.rooms[at][0], packer.rooms[at][2]))  # an open bin has tokens and segments left
                packer.put(at, (doc, start, raw[:room * 4], total), np.array([room, 1, room], dtype=np.int64))
                return place(doc, start + room, raw[room * 4:], total)
            packer.put(at if at >= 0 else packer.new(), (doc, start, raw, total), demand)

        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(1)):
                raw = ids.encode(text.as_py() or "") + end
                total, full = len(raw) // 4, len(raw) // (4 * size) * size
                for start in range(0, full, size):
                    packer.closed.append([(doc, start, raw[start * 4:(start + size) * 4], total)])
                if total > full:
                    place(doc, full, raw[full * 4:], total)
            yield emit(packer.take())
        left = [x for items in packer.take(end=True) for x in items]
        # The bins still open are filled one after another, so that one of them at most stays partly empty.
        bins, room, slots = [[]], size, limits.segments
        for doc, start, raw, total in left:
            while raw:
                if not room or not slots:
                    bins, room, slots = [*bins, []], size, limits.segments
                cut = raw[:room * 4]
                bins[-1].append((doc, start, cut, total))
                raw, start, room, slots = raw[len(cut):], start + len(cut) // 4, room - len(cut) // 4, slots - 1
        yield emit([x for x in bins if x])

    assert limits.loss_tokens >= limits.tokens, "every token of a document bears loss"
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), PIECES)
