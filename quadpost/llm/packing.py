"""Bounded-space online packing of token sequences.

Each partition reads its documents once and keeps a fixed number of open
windows. A document longer than a window is cut into full windows and a rest; a
rest goes to the open window that it fills best; when none has room, the fullest
open window is emitted and an empty one takes its place. What is open at the end
of a partition is its leftover. Leftovers travel with their ids, are dealt to
groups of partitions, and each group lays its leftovers end to end into full
windows, so at most one window of a group is padded.

Defined cases: a null text is an empty one, which is one token (the end id);
repeated rows are packed as often as they come; an empty table gives no rows;
extra columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quadpost.llm import tokens
from quadpost.llm.staging import written

WINDOW, END_ID = 2048, 1
OPEN_WINDOWS = 64
#: Partitions whose leftovers are merged in one task: at most so many times OPEN_WINDOWS windows of ids.
MERGED_PARTITIONS = 16
#: A partition numbers its windows from its own number times this.
NUMBERS = 1 << 36
_ROWS = 8192
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
STAGED = f"{PIECES}, ids binary, part int"


def _crc(ids: np.ndarray) -> int:
    return zlib.crc32(np.ascontiguousarray(ids, "<u4").tobytes())


class OpenWindows:
    """The open windows of one partition, ordered by free room."""

    def __init__(self, size: int, count: int):
        self.size, self.count = size, count
        self.rooms: list[tuple[int, int]] = []  # (free room, window number), ascending
        self.held: dict[int, list[tuple]] = {}
        self.numbers = 0

    def _new(self) -> int:
        self.numbers += 1
        return self.numbers - 1

    def full(self, piece: tuple) -> tuple[int, list[tuple]]:
        return self._new(), [piece]

    def place(self, piece: tuple, length: int) -> list[tuple[int, list[tuple]]]:
        """Puts the piece into the best fitting window; returns the windows that leave."""
        left = []
        i = bisect_left(self.rooms, (length, -1))
        if i == len(self.rooms):
            if len(self.rooms) >= self.count:
                _, n = self.rooms.pop(0)  # the fullest
                left.append((n, self.held.pop(n)))
            room, n = self.size, self._new()
            self.held[n] = []
        else:
            room, n = self.rooms.pop(i)
        self.held[n].append(piece)
        if room == length:
            left.append((n, self.held.pop(n)))
        else:
            insort(self.rooms, (room - length, n))
        return left


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    schema = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")] + [("ids", pa.binary()), ("part", pa.int32())])
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


def _pack(path: str, size: int, count: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, encode = TaskContext.get().partitionId(), tokens.encoder(path).ids
        windows, out = OpenWindows(size, count), []

        def emit(leaving: list[tuple[int, list[tuple]]]) -> None:
            for n, pieces in leaving:
                offset = 0
                for doc, start, ids, total in pieces:
                    out.append((doc, start, len(ids), _crc(ids), total, part * NUMBERS + n, offset, None, part))
                    offset += len(ids)

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.append(encode(text.as_py() or ""), np.uint32(END_ID))
                whole = len(ids) - len(ids) % size
                for start in range(0, whole, size):
                    emit([windows.full((doc, start, ids[start : start + size], len(ids)))])
                if whole < len(ids):
                    emit(windows.place((doc, whole, ids[whole:].copy(), len(ids)), len(ids) - whole))
                if len(out) >= _ROWS:
                    yield _batch(out)
                    out.clear()
        for _, n in windows.rooms:
            for doc, start, ids, total in windows.held[n]:
                out.append((doc, start, len(ids), None, total, None, None, ids.astype("<u4").tobytes(), part))
        if out:
            yield _batch(out)

    return run


def _merge(size: int):
    def run(key, table):
        group = key[0].as_py()
        table = table.sort_by([("part", "ascending"), ("doc_id", "ascending"), ("start", "ascending")])
        out, number, offset = [], 0, 0
        for doc, start, total, raw in zip(*(table.column(n).to_pylist() for n in ("doc_id", "start", "doc_tokens", "ids")), strict=True):
            ids = np.frombuffer(raw, "<u4")
            while len(ids):
                piece, ids = ids[: size - offset], ids[size - offset :]
                out.append((doc, start, len(piece), _crc(piece), total, -1 - (group * NUMBERS + number), offset))
                start, offset = start + len(piece), offset + len(piece)
                if offset == size:
                    number, offset = number + 1, 0
        names = [c.split()[0] for c in PIECES.split(", ")]
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(names, zip(*out, strict=True), strict=True)})

    return run


def pack(docs: DataFrame, path: str | None = None, size: int = WINDOW, open_windows: int = OPEN_WINDOWS) -> DataFrame:
    """One row per piece: which ids of which document stand where in which sequence."""
    staged = written(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_pack(path or tokens.default_path(), size, open_windows), STAGED), "packed")
    names = [c.split()[0] for c in PIECES.split(", ")]
    done = staged.where("ids IS NULL").select(*names)
    rest = staged.where("ids IS NOT NULL").select("doc_id", "start", "doc_tokens", "ids", "part", F.floor(F.col("part") / MERGED_PARTITIONS).cast("int").alias("group"))
    return done.unionByName(rest.groupBy("group").applyInArrow(_merge(size), PIECES))
