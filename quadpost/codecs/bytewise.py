"""Byte-aligned classics: variable byte, group variable byte with binary descriptors, and two with unary descriptors."""

from __future__ import annotations

from functools import cache

import numpy as np

from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import U64, bitlen, ceil_div, chase, first_of, starts_of

GROUP = 4
GROUP_BYTES = 8


def _spread(values: np.ndarray, sizes: np.ndarray, bits: int) -> np.ndarray:
    """Each value's parts of ``bits`` bits, low part first."""
    ends = np.cumsum(sizes)
    inner = np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - sizes, sizes)
    return (np.repeat(values, sizes) >> (bits * inner).astype(U64) & U64((1 << bits) - 1)).astype(np.uint8)


def _gather(raw: np.ndarray, starts: np.ndarray, sizes: np.ndarray, bits: int) -> np.ndarray:
    """The values again, one part after another: few values have a second, fewer a third."""
    out, more = raw[starts].astype(U64), np.flatnonzero(sizes > 1)
    k = 1
    while len(more):
        out[more] |= raw[starts[more] + k].astype(U64) << U64(bits * k)
        k += 1
        more = more[sizes[more] > k]
    return out


def _vbyte_encode(x: np.ndarray, backend: str) -> Block:
    sizes = ceil_div(bitlen(x), 7)
    raw = _spread(x, sizes, 7)
    if len(x):
        raw[np.cumsum(sizes) - 1] |= 0x80
    return Block(len(x), data=raw.tobytes(), data_bits=8 * len(raw))


def _vbyte_together(x: np.ndarray, counts: np.ndarray) -> list[Block]:
    sizes = ceil_div(bitlen(x), 7)
    raw = _spread(x, sizes, 7)
    if len(x):
        raw[np.cumsum(sizes) - 1] |= 0x80
    ends = np.concatenate([[0], np.cumsum(sizes)])[np.cumsum(counts)]
    data, starts = raw.tobytes(), np.concatenate([[0], ends[:-1]])
    return [Block(n, data=data[a:z], data_bits=8 * (z - a)) for n, a, z in zip(counts.tolist(), starts.tolist(), ends.tolist(), strict=True)]


def _vbyte_decode(block: Block, backend: str) -> np.ndarray:
    raw = np.frombuffer(block.data, np.uint8)
    if backend == "scalar":
        out, value, shift = [], 0, 0
        for byte in raw.tolist():
            value |= (byte & 0x7F) << shift
            shift += 7
            if byte & 0x80:
                out.append(value)
                value, shift = 0, 0
        return np.array(out, U64)
    ends = np.flatnonzero(raw & 0x80)
    starts = np.concatenate([[0], ends[:-1] + 1])
    return _gather(raw & 0x7F, starts, ends - starts + 1, 7)


def _gvb_encode(x: np.ndarray, backend: str) -> Block:
    sizes = ceil_div(bitlen(x), 8)
    codes = np.concatenate([sizes - 1, np.zeros(-len(x) % GROUP, np.int64)]).reshape(-1, GROUP)
    ctrl = (codes << 2 * np.arange(GROUP)).sum(axis=1).astype(np.uint8)
    return Block(len(x), ctrl.tobytes(), _spread(x, sizes, 8).tobytes(), ctrl_bits=8 * len(ctrl), data_bits=8 * int(sizes.sum()))


@cache
def _gvb_table() -> np.ndarray:
    return (np.arange(256)[:, None] >> 2 * np.arange(GROUP) & 3) + 1


def _gvb_decode(block: Block, backend: str) -> np.ndarray:
    raw = np.frombuffer(block.data, np.uint8)
    if backend == "scalar":
        out, at, data = [], 0, block.data
        for byte in block.ctrl:
            for k in range(GROUP):
                if len(out) < block.n:
                    size = (byte >> 2 * k & 3) + 1
                    out.append(int.from_bytes(data[at : at + size], "little"))
                    at += size
        return np.array(out, U64)
    sizes = _gvb_table()[np.frombuffer(block.ctrl, np.uint8)].ravel()[: block.n]
    return _gather(raw, np.cumsum(sizes) - sizes, sizes, 8)


def _descriptors(positions: np.ndarray, count: int) -> np.ndarray:
    """One byte for each 8 data bytes, low bit first: zeros where a value ends, ones elsewhere."""
    bits = np.ones(8 * count, np.uint8)
    bits[positions] = 0
    return np.packbits(bits, bitorder="little")


def _g8cu_encode(x: np.ndarray, backend: str) -> Block:
    sizes = ceil_div(bitlen(x), 8)
    raw = _spread(x, sizes, 8)
    groups = int(ceil_div(len(raw), GROUP_BYTES))
    data = np.concatenate([raw, np.zeros(groups * GROUP_BYTES - len(raw), np.uint8)])
    ctrl = _descriptors(np.cumsum(sizes) - 1, groups)
    return Block(len(x), ctrl.tobytes(), data.tobytes(), ctrl_bits=8 * groups, data_bits=64 * groups)


def _g8iu_encode(x: np.ndarray, backend: str) -> Block:
    sizes = ceil_div(bitlen(x), 8)
    ends = np.cumsum(sizes)
    # how many values a group takes if it starts with value j
    last = np.searchsorted(ends, ends - sizes + GROUP_BYTES, side="right")
    heads = chase(last - np.arange(len(x))) if len(x) else np.zeros(0, np.int64)
    groups = len(heads)
    counts = np.diff(np.append(heads, len(x)))
    start = ends - sizes - np.repeat((ends - sizes)[heads], counts) + GROUP_BYTES * np.repeat(np.arange(groups), counts)
    data = np.zeros(groups * GROUP_BYTES, np.uint8)
    inner = np.arange(int(sizes.sum())) - np.repeat(ends - sizes, sizes)
    data[np.repeat(start, sizes) + inner] = _spread(x, sizes, 8)
    ctrl = _descriptors(start + sizes - 1, groups)
    return Block(len(x), ctrl.tobytes(), data.tobytes(), ctrl_bits=8 * groups, data_bits=64 * groups)


def _g8_decode(whole: bool):
    def run(block: Block, backend: str) -> np.ndarray:
        raw = np.frombuffer(block.data, np.uint8)
        if backend == "scalar":
            out, value, size = [], 0, 0
            for k, byte in enumerate(block.ctrl):
                if whole:
                    value, size = 0, 0
                for j in range(8):
                    value |= int(raw[8 * k + j]) << 8 * size
                    size += 1
                    if not byte >> j & 1:
                        out.append(value)
                        value, size = 0, 0
            return np.array(out, U64)
        ends = np.flatnonzero(np.unpackbits(np.frombuffer(block.ctrl, np.uint8), bitorder="little") == 0)
        starts = np.concatenate([[0], ends[:-1] + 1])
        if whole:
            starts = np.maximum(starts, ends // GROUP_BYTES * GROUP_BYTES)
        return _gather(raw, starts, ends - starts + 1, 8)

    return run


def _joined(blocks: list[Block], area: str) -> np.ndarray:
    return np.frombuffer(b"".join(getattr(b, area) for b in blocks), np.uint8)


def _counts(blocks: list[Block]) -> np.ndarray:
    return np.fromiter((b.n for b in blocks), np.int64, len(blocks))


def _vbyte_many(blocks: list[Block]) -> np.ndarray:
    return _vbyte_decode(Block(0, data=b"".join(b.data for b in blocks)), "lanes")


def _gvb_many(blocks: list[Block]) -> np.ndarray:
    held = GROUP * np.fromiter((len(b.ctrl) for b in blocks), np.int64, len(blocks))
    sizes = first_of(_gvb_table()[_joined(blocks, "ctrl")].ravel(), held, _counts(blocks))
    return _gather(_joined(blocks, "data"), starts_of(sizes), sizes, 8)


def _g8_many(whole: bool):
    def run(blocks: list[Block]) -> np.ndarray:
        """Groups never cross blocks; a block's first value starts at its first byte."""
        raw = _joined(blocks, "data")
        ends = np.flatnonzero(np.unpackbits(_joined(blocks, "ctrl"), bitorder="little") == 0)
        starts = np.concatenate([[0], ends[:-1] + 1])
        if whole:
            starts = np.maximum(starts, ends // GROUP_BYTES * GROUP_BYTES)
        else:
            starts[starts_of(_counts(blocks))] = starts_of(np.fromiter((len(b.data) for b in blocks), np.int64, len(blocks)))
        return _gather(raw, starts, ends - starts + 1, 8)

    return run


register(Codec("vbyte", _vbyte_encode, _vbyte_decode, together=_vbyte_together, backends=("lanes", "scalar"), many=_vbyte_many))
register(Codec("gvb", _gvb_encode, _gvb_decode, backends=("lanes", "scalar"), many=_gvb_many))
register(Codec("g8iu", _g8iu_encode, _g8_decode(True), backends=("lanes", "scalar"), many=_g8_many(True)))
register(Codec("g8cu", _g8cu_encode, _g8_decode(False), backends=("lanes", "scalar"), many=_g8_many(False)))
