"""The quad_length family: a length descriptor for each quad, in units of 1, 2, 4 or 8 bits.

Descriptors are stored binary (``b``), unary across bytes (``cu``) or unary within
bytes (``iu``). Unary codes are read from the high bit of each byte on: a descriptor
of d units is d - 1 ones and a zero.
"""

from __future__ import annotations

from functools import cache

import numpy as np

from quadpost.codecs import lanes
from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import U64, bitlen, ceil_div, chase, first_of, from_bytes, starts_of, to_bytes

GRANULARITIES = (1, 2, 4, 8)
# By granularity, the bits of a binary descriptor, how many share a control unit, and the unit's bytes.
BINARY_BITS = {1: 5, 2: 4, 4: 3, 8: 2}
BINARY_UNIT = {1: (3, 2), 2: (2, 1), 4: (2, 1), 8: (4, 1)}
WAYS = [(cg, ld) for ld in ("b", "cu", "iu") for cg in GRANULARITIES if ld != "iu" or cg >= 4]


def descriptors(maxima: np.ndarray, cg: int) -> np.ndarray:
    """Units that the quad's largest value needs; at least one."""
    return ceil_div(bitlen(maxima), cg)


# --- writing descriptors -------------------------------------------------------------------------------------------


def write_binary(ld: np.ndarray, cg: int) -> bytes:
    per, size = BINARY_UNIT[cg]
    fields = np.concatenate([ld - 1, np.zeros(-len(ld) % per, np.int64)]).reshape(-1, per)
    units = (fields << BINARY_BITS[cg] * np.arange(per)).sum(axis=1)
    return units.astype(f"<u{size}").tobytes()


def write_complete(ld: np.ndarray) -> bytes:
    bits = np.ones(int(ld.sum()), np.uint8)
    bits[np.cumsum(ld) - 1] = 0
    return to_bytes(bits, msb=True, fill=1)


def write_incomplete(ld: np.ndarray) -> bytes:
    ends = np.cumsum(ld)
    # how many codes a byte takes if it starts with code j
    last = np.searchsorted(ends, ends - ld + 8, side="right")
    heads = chase(last - np.arange(len(ld)))
    byte = np.repeat(np.arange(len(heads)), np.diff(np.append(heads, len(ld))))
    within = ends - np.repeat((ends - ld)[heads], np.diff(np.append(heads, len(ld))))
    bits = np.ones(8 * len(heads), np.uint8)
    bits[8 * byte + within - 1] = 0
    return to_bytes(bits, msb=True)


# --- reading descriptors -------------------------------------------------------------------------------------------


@cache
def unary_table() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each byte: how many codes end in it, their lengths, and the ones after the last of them."""
    count, lengths, tail = np.zeros(256, np.int64), np.zeros((256, 8), np.int64), np.zeros(256, np.int64)
    for byte in range(256):
        zeros = [k for k in range(8) if not byte >> (7 - k) & 1]
        count[byte] = len(zeros)
        for i, z in enumerate(zeros):
            lengths[byte, i] = z - (zeros[i - 1] if i else -1)
        tail[byte] = 7 - zeros[-1] if zeros else 8
    return count, lengths, tail


@cache
def binary_table(cg: int) -> np.ndarray:
    """For each control unit (2^15 of two bytes, else 2^8): its descriptors."""
    per, bits = BINARY_UNIT[cg][0], BINARY_BITS[cg]
    units = np.arange(1 << 15 if cg == 1 else 256)
    return (units[:, None] >> bits * np.arange(per) & (1 << bits) - 1) + 1


def read_unary(ctrl: bytes, quads: int, complete: bool, way: str = "table") -> np.ndarray:
    raw = np.frombuffer(ctrl, np.uint8)
    if way == "bits":  # positions of zeros, as counting leading bits would find them
        zeros = np.flatnonzero(from_bytes(ctrl, msb=True) == 0)
        before = np.concatenate([[-1], zeros[:-1]])
        if not complete:
            before = np.maximum(before, zeros // 8 * 8 - 1)
        return (zeros - before)[:quads]
    count, lengths, tail = unary_table()
    mine = count[raw]
    out = lengths[raw][np.arange(8) < mine[:, None]]
    if complete:  # what earlier bytes left unfinished belongs to a byte's first code
        full = np.flatnonzero(mine)
        left = np.concatenate([[0], np.cumsum(tail[raw])])
        carry = left[full] - np.concatenate([[0], left[full[:-1]]])
        out[np.cumsum(mine[full]) - mine[full]] += carry
    return out[:quads]


def read_binary(ctrl: bytes, quads: int, cg: int, way: str = "table") -> np.ndarray:
    per, size = BINARY_UNIT[cg]
    units = np.frombuffer(ctrl, f"<u{size}").astype(np.int64)
    if way == "table":
        return binary_table(cg)[units].ravel()[:quads]
    return ((units[:, None] >> BINARY_BITS[cg] * np.arange(per) & (1 << BINARY_BITS[cg]) - 1) + 1).ravel()[:quads]


# --- the codec -----------------------------------------------------------------------------------------------------


def _encode(cg: int, ld: str):
    def run(x: np.ndarray, backend: str) -> Block:
        rows = lanes.quads(x)
        units = descriptors(lanes.quad_or(x), cg) if len(x) else np.zeros(0, np.int64)
        ctrl = b"" if not len(x) else write_binary(units, cg) if ld == "b" else write_complete(units) if ld == "cu" else write_incomplete(units)
        widths = units * cg
        words = int(ceil_div(int(widths.sum()), lanes.WORD))
        data = lanes.pack(rows, lanes.offsets_of(widths), widths, words, backend)
        return Block(len(x), ctrl, data, ctrl_bits=8 * len(ctrl), data_bits=128 * words)

    return run


def read_descriptors(block: Block, cg: int, ld: str, way: str = "table") -> np.ndarray:
    quads = -(-block.n // lanes.LANES)
    return read_binary(block.ctrl, quads, cg, way) if ld == "b" else read_unary(block.ctrl, quads, ld == "cu", way)


def decode_by_unit(block: Block, cg: int, ld: str) -> np.ndarray:
    """The same values, one control unit after another (for the ablation): a unit's table entry says which descriptors end in it.

    Binary units always hold as many. Of unary codes each byte holds its own number, and a
    complete code that a byte does not end goes on in the next.
    """
    quads, out, at = -(-block.n // lanes.LANES), [], 0
    if ld == "b":
        units = binary_table(cg)[np.frombuffer(block.ctrl, f"<u{BINARY_UNIT[cg][1]}").astype(np.int64)]
    else:
        count, lengths, tail = unary_table()
        units, pending = [], 0
        for byte in block.ctrl:
            found = lengths[byte][: count[byte]].copy()
            if len(found):
                found[0] += pending
            if ld == "cu":
                pending = int(tail[byte]) + (0 if len(found) else pending)
            units.append(found)
    left = quads
    for descriptors_of_unit in units:
        widths = descriptors_of_unit[:left] * cg
        if len(widths):
            out.append(lanes.unpack(block.data, at + lanes.offsets_of(widths), widths))
            at += int(widths.sum())
            left -= len(widths)
    return np.concatenate(out).ravel()[: block.n].astype(np.uint32)


def _decode(cg: int, ld: str, way: str = "table"):
    def run(block: Block, backend: str) -> np.ndarray:
        widths = read_descriptors(block, cg, ld, way) * cg
        return lanes.unpack(block.data, lanes.offsets_of(widths), widths, backend).ravel()

    return run


def _descriptors_of_many(blocks: list[Block], quads: np.ndarray, cg: int, ld: str) -> np.ndarray:
    ctrl, sizes = b"".join(b.ctrl for b in blocks), np.fromiter((len(b.ctrl) for b in blocks), np.int64, len(blocks))
    if ld == "b":
        per, size = BINARY_UNIT[cg]
        return first_of(binary_table(cg)[np.frombuffer(ctrl, f"<u{size}").astype(np.int64)].ravel(), sizes // size * per, quads)
    if ld == "iu":
        return read_unary(ctrl, int(quads.sum()), False)
    zeros = np.flatnonzero(from_bytes(ctrl, msb=True) == 0)
    before = np.concatenate([[-1], zeros[:-1]])
    before[starts_of(quads)] = 8 * starts_of(sizes) - 1  # what fills up a block's last byte belongs to no code
    return zeros - before


def _decode_many(cg: int, ld: str):
    def run(blocks: list[Block]) -> np.ndarray:
        n = np.fromiter((b.n for b in blocks), np.int64, len(blocks))
        quads = ceil_div(n, lanes.LANES)
        return lanes.unpack_many([b.data for b in blocks], _descriptors_of_many(blocks, quads, cg, ld) * cg, quads, n)

    return run


def quad_length(cg: int, ld: str, way: str = "table") -> Codec:
    if (cg, ld) not in WAYS:
        raise ValueError(f"no quad_length codec has granularity {cg} with {ld} descriptors: a code would not fit a byte")
    return Codec(f"ql_{cg}_{ld}", _encode(cg, ld), _decode(cg, ld, way), backends=("lanes", "scalar"), many=_decode_many(cg, ld))


FAMILY = [register(quad_length(cg, ld)) for cg, ld in WAYS]


def k_gamma() -> Codec:
    """Four values under one unary length: the member of granularity 1 with complete unary descriptors."""
    return quad_length(1, "cu")
