"""Codecs over DataFrames: one row is one bounded block, so nothing is shuffled.

Whatever filters blocks goes before these operators: a Python operator lets no
predicate through to the scan.
"""

from __future__ import annotations

from collections.abc import Iterator
from time import perf_counter_ns

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quadpost.codecs.base import Block, Codec, codec
from quadpost.schemas import BLOCK_FIELDS

#: Lists below this many postings go to variable byte codes.
SHORT_LIST = 64
_BLOCK_NAMES = [f.split()[0] for f in BLOCK_FIELDS.split(", ")]
_KINDS = {"string": pa.string(), "int": pa.int32(), "binary": pa.binary(), "bigint": pa.int64()}


def _fields(df: DataFrame, without: tuple[str, ...] = ()) -> tuple[list[str], str]:
    names = [f.name for f in df.schema if f.name not in without]
    return names, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema if f.name in names)


def _lists(column: pa.ListArray) -> Iterator[np.ndarray]:
    values, offsets = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    for a, z in zip(offsets[:-1], offsets[1:], strict=True):
        yield values[a:z]


def encode_blocks(df: DataFrame, name: str, col: str = "values", backend: str = "lanes", prefix: str = "", codecs: dict[str, Codec] | None = None, short: str | None = None) -> DataFrame:
    """``df`` without ``col`` and with the block columns of its encoded values.

    ``short`` names the codec of rows whose column ``df`` (list length) is below ``SHORT_LIST``.
    """
    keep, fields = _fields(df, (col,))
    ours, extra = (codecs or {}).get(name), [f"{prefix}{n}" for n in _BLOCK_NAMES]
    at = {n: i for i, n in enumerate(df.columns)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        main = ours or codec(name)
        brief = codec(short) if short else None
        for batch in batches:
            lengths = batch.column(at["df"]).to_pylist() if brief else None
            used = [brief if brief and lengths[i] < SHORT_LIST else main for i in range(batch.num_rows)]
            lists, made = list(_lists(batch.column(at[col]))), [None] * batch.num_rows
            for c in {id(c): c for c in used}.values():
                mine = [i for i, u in enumerate(used) if u is c]
                for i, b in zip(mine, c.encode_many([lists[i] for i in mine], backend if backend in c.backends else "lanes"), strict=True):
                    made[i] = b
            columns = [pa.array([c.name for c in used], pa.string())] + [pa.array([getattr(b, n) for b in made], _KINDS[k]) for n, k in (f.split() for f in BLOCK_FIELDS.split(", ")) if n != "codec"]
            yield pa.RecordBatch.from_arrays([batch.column(at[n]) for n in keep] + columns, keep + extra)

    more = ", ".join(f"`{prefix}{n}` {k}" for n, k in (f.split() for f in BLOCK_FIELDS.split(", ")))
    return df.mapInArrow(run, f"{fields}, {more}" if fields else more)


def decoded(names: list[str], blocks: list[Block], backend: str = "lanes", codecs: dict[str, Codec] | None = None) -> np.ndarray:
    """The values of a batch's blocks, one block after another; all blocks of one codec are decoded together."""
    if len(set(names)) == 1:
        used = (codecs or {}).get(names[0]) or codec(names[0])
        return used.decode_many(blocks, backend if backend in used.backends else "lanes").astype(np.int64)
    counts = np.array([b.n for b in blocks], np.int64)
    which, out = np.array(names), np.empty(int(counts.sum()), np.int64)
    starts = np.cumsum(counts) - counts
    for name in sorted(set(names)):
        mine = np.flatnonzero(which == name)
        n = counts[mine]
        inner = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat(starts[mine], n) + inner] = decoded([name], [blocks[i] for i in mine], backend, codecs)
    return out


def decode_blocks(df: DataFrame, col: str = "values", backend: str = "lanes", prefix: str = "", codecs: dict[str, Codec] | None = None) -> DataFrame:
    """``df`` with its block columns turned back into ``col``, an array of integers."""
    gone = tuple(f"{prefix}{n}" for n in _BLOCK_NAMES)
    keep, fields = _fields(df, gone)
    at = {n: i for i, n in enumerate(df.columns)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, *areas = (batch.column(at[f"{prefix}{n}"]).to_pylist() for n in ("codec", "n", "ctrl", "data", "exc"))
            blocks = [Block(*b) for b in zip(*areas, strict=True)]
            flat = decoded(names, blocks, backend, codecs) if names else np.zeros(0, np.int64)
            ends = pa.array(np.concatenate([[0], np.cumsum([b.n for b in blocks])]), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(at[n]) for n in keep] + [pa.ListArray.from_arrays(ends, pa.array(flat))], keep + [col])

    return df.mapInArrow(run, f"{fields}, `{col}` array<bigint>" if fields else f"`{col}` array<bigint>")


def roundtrip(df: DataFrame, name: str, col: str = "values", backend: str = "lanes") -> DataFrame:
    return decode_blocks(encode_blocks(df, name, col, backend), col, backend)


def sizes(df: DataFrame, names: list[str], col: str = "values", codecs: dict[str, Codec] | None = None) -> DataFrame:
    """Per row and codec: (codec, n, bits, ctrl_bits, data_bits, exc_bits, head_bits); codecs that cannot hold a row's values give none."""
    keep, fields = _fields(df, (col,))
    at = {n: i for i, n in enumerate(df.columns)}
    parts = ("ctrl_bits", "data_bits", "exc_bits", "head_bits")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        used = [(codecs or {}).get(n) or codec(n) for n in names]
        for batch in batches:
            rows, out = [], []
            for i, values in enumerate(_lists(batch.column(at[col]))):
                for c in used:
                    try:
                        b = c.encode(values)
                    except ValueError:
                        continue
                    rows.append(i)
                    out.append((c.name, b.n, b.bits, *(getattr(b, p) for p in parts)))
            taken = batch.select(keep).take(pa.array(rows, pa.int32()))
            columns = list(zip(*out, strict=True)) if out else [[]] * 7
            yield pa.RecordBatch.from_arrays(
                [taken.column(k) for k in range(len(keep))] + [pa.array(columns[0], pa.string()), pa.array(columns[1], pa.int64())] + [pa.array(c, pa.int64()) for c in columns[2:]],
                keep + ["codec", "n", "bits", *parts],
            )

    return df.mapInArrow(run, f"{fields}, codec string, n bigint, bits bigint, {', '.join(f'{p} bigint' for p in parts)}")


def timings(df: DataFrame, names: list[str], backends: tuple[str, ...] = ("lanes", "scalar"), col: str = "values", runs: int = 10) -> DataFrame:
    """Per codec and build: integers, encoding and decoding nanoseconds, taken inside the kernel and added up over tasks."""
    at = df.columns.index(col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: dict[tuple[str, str], list[int]] = {}
        for batch in batches:
            lists = [np.array(v) for v in _lists(batch.column(at))]
            for c in map(codec, names):
                for backend in (b for b in backends if b in c.backends):
                    held = out.setdefault((c.name, backend), [0, 0, 0])
                    for _ in range(runs):
                        began = perf_counter_ns()
                        made = [c.encode(v, backend) for v in lists]
                        between = perf_counter_ns()
                        c.decode_many(made, backend)
                        held[0] += sum(map(len, lists))
                        held[1] += between - began
                        held[2] += perf_counter_ns() - between
        rows = [(*k, *v) for k, v in out.items()]
        columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.string()), pa.array(columns[1], pa.string())] + [pa.array(c, pa.int64()) for c in columns[2:]], ["codec", "backend", "n", "encode_ns", "decode_ns"])

    made = df.mapInArrow(run, "codec string, backend string, n bigint, encode_ns bigint, decode_ns bigint")
    total = made.groupBy("codec", "backend").agg(F.sum("n").alias("n"), F.sum("encode_ns").alias("e"), F.sum("decode_ns").alias("d"))
    return total.select("codec", "backend", "n", (F.col("n") * 1000 / F.col("e")).alias("encode_mis"), (F.col("n") * 1000 / F.col("d")).alias("decode_mis"))
