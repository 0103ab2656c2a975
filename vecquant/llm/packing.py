"""Hierarchical packing of token sequences into windows of several lengths.

Each document is cut into windows of the longest tier and a rest. The rest goes to the shortest
tier that holds it. Windows of a long tier that a rest leaves open are filled from the waiting
rests of shorter tiers, shortest first, which may be cut; so a window is closed only when it
is full. What is left at the end of a partition is packed into whole shorter windows, and one
last window may be padded. Within a tier, windows are dealt to step groups of one token budget.

The work is one narrow map: a partition packs what it reads, holds a bounded number of open
windows, and numbers its windows apart from all others.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.llm import bpe
from vecquant.llm.common import single_column, text_slices

#: Sequence numbers leave this many bits to a partition's own windows.
_WINDOW_BITS = 36


class _Rest:
    """What of a document is not in a closed window yet."""

    __slots__ = ("doc", "raw", "start", "total")

    def __init__(self, doc: object, raw: bytes, start: int, total: int) -> None:
        self.doc, self.raw, self.start, self.total = doc, raw, start, total

    def __len__(self) -> int:
        return len(self.raw) // 4 - self.start


class TierPacker:
    """Packs one partition's documents; rows of closed windows are taken with drain()."""

    def __init__(self, base: int, tiers: tuple[int, ...], step_tokens: int, waiting: int) -> None:
        self._tiers = tiers
        self._step_tokens = step_tokens
        self._waiting = waiting
        self._queues: dict[int, deque[_Rest]] = {t: deque() for t in tiers}
        self._next = base
        self._base = base
        self._closed = dict.fromkeys(tiers, 0)
        self._rows: list[tuple] = []

    def _write(self, parts: list[tuple[_Rest, int]], tier: int) -> None:
        group = self._closed[tier] * tier // self._step_tokens
        self._closed[tier] += 1
        offset = 0
        for rest, n in parts:
            piece = rest.raw[4 * rest.start : 4 * (rest.start + n)]
            self._rows.append((rest.doc, rest.start, n, zlib.crc32(piece), rest.total, self._next, offset, tier, self._base + group))
            rest.start += n
            offset += n
        self._next += 1

    def add(self, doc: object, raw: bytes) -> None:
        """Cut off the whole long windows of a document and queue its rest."""
        longest = self._tiers[-1]
        rest = _Rest(doc, raw, 0, len(raw) // 4)
        while len(rest) >= longest:
            self._write([(rest, longest)], longest)
        if n := len(rest):
            self._queues[next(t for t in self._tiers if n <= t)].append(rest)
        if sum(map(len, self._queues.values())) >= self._waiting:
            self.fill()

    def _filled(self, tier: int) -> list[tuple[_Rest, int]] | None:
        """Parts of one full window of the tier: its oldest rest, then shorter tiers' rests."""
        shorter = [self._queues[t] for t in self._tiers if t <= tier]
        if not self._queues[tier]:
            return None
        first = self._queues[tier].popleft()
        parts, open_ = [(first, len(first))], tier - len(first)
        while open_:
            queue = next((q for q in shorter if q), None)
            if queue is None:
                for rest, n in reversed(parts):
                    if n == len(rest):
                        self._back(rest)
                return None
            rest = queue[0]
            n = min(open_, len(rest))
            parts.append((rest, n))
            open_ -= n
            if n == len(rest):
                queue.popleft()
        return parts

    def _back(self, rest: _Rest) -> None:
        queue = self._queues[next(t for t in self._tiers if len(rest) <= t)]
        if not queue or queue[0] is not rest:
            queue.appendleft(rest)

    def _resettle(self) -> None:
        """Rests that were cut may fit a shorter tier now."""
        for tier in self._tiers[1:]:
            queue = self._queues[tier]
            for _ in range(len(queue)):
                rest = queue.popleft()
                self._queues[next(t for t in self._tiers if len(rest) <= t)].append(rest)

    def fill(self) -> None:
        """Close every window, long tiers first, that waiting rests can fill."""
        for tier in reversed(self._tiers):
            while (parts := self._filled(tier)) is not None:
                self._write(parts, tier)
        self._resettle()

    def finish(self) -> None:
        """Pack what still waits: full windows from long to short, then one padded window."""
        left = [r for t in reversed(self._tiers) for r in self._queues[t] if len(r)]
        for queue in self._queues.values():
            queue.clear()
        for tier in reversed(self._tiers):
            while sum(map(len, left)) >= tier:
                parts, open_ = [], tier
                for rest in left:
                    n = min(open_, len(rest))
                    parts.append((rest, n))
                    open_ -= n
                    if not open_:
                        break
                self._write(parts, tier)
                left = [r for r in left if len(r)]
        if left:
            self._write([(r, len(r)) for r in left], self._tiers[-1])

    def drain(self) -> list[tuple]:
        rows, self._rows = self._rows, []
        return rows


def pack_documents(
    docs: DataFrame,
    definition_path: str,
    id_column: str = "doc_id",
    text_column: str = "text",
    tiers: tuple[int, ...] = (256, 512, 1024, 2048),
    end_id: int = 1,
    step_tokens: int = 65_536,
    waiting: int = 4_096,
) -> DataFrame:
    """Pack every document (its ids, then end_id) into windows.

    A row per piece: the id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and the
    window's tier and step_group. tiers are powers of two, ascending. Every partition pads one
    window at most, to the longest tier. A null or empty text is end_id alone; repeated rows are
    documents of their own; an empty table gives no rows; other columns are ignored. Memory: at
    most `waiting` rests of less than the longest tier, and one slice of texts.
    """
    with open(definition_path, encoding="utf-8") as file:
        definition = file.read()
    shipped, vocabulary = docs.sparkSession.sparkContext.broadcast(definition), bpe.digest(definition)
    field = docs.schema[id_column].dataType.simpleString()
    names = ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "tier", "step_group"]
    end = int(end_id).to_bytes(4, "little")

    def table(rows: list[tuple], kind: pa.DataType) -> pa.RecordBatch:
        columns = list(zip(*rows, strict=True))
        arrays = [pa.array(columns[0], kind)] + [pa.array(np.array(c, dtype=np.int64)) for c in columns[1:]]
        return pa.RecordBatch.from_arrays(arrays, names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = bpe.per_worker("ranked", vocabulary, lambda: bpe.RankedEncoder(shipped.value)).encode
        base = TaskContext.get().partitionId() << _WINDOW_BITS
        packer = TierPacker(base, tiers, step_tokens, waiting)
        kind = None
        for batch, texts in text_slices(batches, "text"):
            ids = single_column(batch, "id")
            kind = ids.type
            for doc, text in zip(ids.to_pylist(), texts, strict=True):
                packer.add(doc, encode(text) + end)
            if rows := packer.drain():
                yield table(rows, kind)
        packer.fill()
        packer.finish()
        if rows := packer.drain():
            yield table(rows, kind)

    schema = f"id {field}, " + ", ".join(f"{n} long" for n in names[1:])
    rows = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text")).mapInArrow(run, schema)
    return rows.withColumnRenamed("id", id_column)


def padding_report(pieces: DataFrame, longest: int = 2048) -> DataFrame:
    """One row: windows, tokens, padded positions and their share."""
    windows = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    power = (F.col("n").bitwiseAND(F.col("n") - 1)) == 0
    size = F.when(power, F.col("n")).otherwise(F.lit(longest))
    total = windows.agg(
        F.count("*").alias("windows"), F.sum("n").alias("tokens"), F.sum(size - F.col("n")).alias("padded")
    )
    return total.withColumn("padded_share", F.col("padded") / (F.col("tokens") + F.col("padded")))
