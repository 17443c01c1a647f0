"""Bit-aligned classics: gamma, Rice and Golomb codes, and plain 32-bit storage. Codes are read from the high bit on."""

from __future__ import annotations

import numpy as np

from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import U64, bitlen, from_bytes, get_bits, low_mask, put_bits, to_bytes

HEAD_BITS = 8
#: A Rice quotient is at most so long; a larger spread raises the parameter.
MOST_QUOTIENT_BITS = 16


def _interleave(unary: np.ndarray, tails: np.ndarray, tail_bits: np.ndarray) -> np.ndarray:
    """For each value: ``unary`` ones, a zero, then its tail."""
    lengths = np.empty(2 * len(unary), np.int64)
    lengths[0::2], lengths[1::2] = unary + 1, tail_bits
    bits = np.ones(int(lengths.sum()), np.uint8)
    starts = np.cumsum(lengths) - lengths
    bits[starts[0::2] + unary] = 0
    body = put_bits(tails, tail_bits, msb=True)
    where = np.repeat(starts[1::2], tail_bits) + np.arange(len(body)) - np.repeat(np.cumsum(tail_bits) - tail_bits, tail_bits)
    bits[where] = body
    return bits


def _walk(bits: np.ndarray, n: int, tail) -> tuple[np.ndarray, np.ndarray]:
    """Start and unary length of each code; ``tail(unary, at)`` says how many bits follow its zero."""
    zeros = np.flatnonzero(bits == 0).tolist()
    starts, unary, at, z = [], [], 0, 0
    for _ in range(n):
        while zeros[z] < at:
            z += 1
        starts.append(at)
        unary.append(zeros[z] - at)
        at = zeros[z] + 1 + tail(unary[-1], zeros[z] + 1)
    return np.array(starts, np.int64), np.array(unary, np.int64)


def _gamma_encode(x: np.ndarray, backend: str) -> Block:
    more = bitlen(x) - 1
    bits = _interleave(more, x & low_mask(more), more)
    return Block(len(x), data=to_bytes(bits, msb=True), data_bits=len(bits))


def _gamma_decode(block: Block, backend: str) -> np.ndarray:
    bits = from_bytes(block.data, msb=True)
    starts, more = _walk(bits, block.n, lambda u, at: u)
    return get_bits(bits, starts + more + 1, more, msb=True) | U64(1) << more.astype(U64)


def rice_parameter(x: np.ndarray) -> int:
    """The bit length, less one, of 0.69 times the mean; in whole numbers only."""
    if not len(x):
        return 0
    share = 69 * int(x.sum()) // (100 * len(x))
    return max(share.bit_length() - 1 if share else 0, int(x.max()).bit_length() - MOST_QUOTIENT_BITS, 0)


def rice_best(x: np.ndarray) -> int:
    low = max(0, int(x.max()).bit_length() - MOST_QUOTIENT_BITS) if len(x) else 0
    return min(range(low, 32), key=lambda b: int(((x - U64(1)) >> U64(b)).sum()) + len(x) * (1 + b)) if len(x) else 0


def _rice(choose):
    def encode(x: np.ndarray, backend: str) -> Block:
        b = choose(x)
        rest = x - U64(1)
        bits = _interleave((rest >> U64(b)).astype(np.int64), rest & low_mask(b), np.full(len(x), b))
        return Block(len(x), bytes([b]), to_bytes(bits, msb=True), data_bits=len(bits), head_bits=HEAD_BITS)

    return encode


def _rice_decode(block: Block, backend: str) -> np.ndarray:
    b, bits = block.ctrl[0], from_bytes(block.data, msb=True)
    starts, q = _walk(bits, block.n, lambda u, at: b)
    return (q.astype(U64) << U64(b) | get_bits(bits, starts + q + 1, np.full(block.n, b), msb=True)) + U64(1)


def golomb_parameter(x: np.ndarray) -> int:
    return max(1, 69 * int(x.sum()) // (100 * len(x)), int(x.max()) >> MOST_QUOTIENT_BITS) if len(x) else 1


def _golomb_encode(x: np.ndarray, backend: str) -> Block:
    m = golomb_parameter(x)
    full = (m - 1).bit_length()
    short = (1 << full) - m  # so many remainders take one bit less
    q, r = np.divmod(x - U64(1), U64(m))
    brief = r < short
    bits = _interleave(q.astype(np.int64), np.where(brief, r, r + U64(short)), np.where(brief, max(full - 1, 0), full))
    return Block(len(x), m.to_bytes(4, "little"), to_bytes(bits, msb=True), data_bits=len(bits), head_bits=32)


def _golomb_decode(block: Block, backend: str) -> np.ndarray:
    m, bits = int.from_bytes(block.ctrl, "little"), from_bytes(block.data, msb=True)
    full = (m - 1).bit_length()
    short = (1 << full) - m
    if full == 0:
        starts, q = _walk(bits, block.n, lambda u, at: 0)
        return q.astype(U64) + U64(1)
    padded = np.concatenate([bits, np.zeros(full, np.uint8)])
    weights = 1 << np.arange(full - 1)[::-1]

    def tail(u: int, at: int) -> int:
        return full - 1 if int(padded[at : at + full - 1] @ weights) < short else full

    starts, q = _walk(bits, block.n, tail)
    at = starts + q + 1
    r = get_bits(padded, at, np.full(block.n, full - 1), msb=True)
    long = r >= short
    r[long] = get_bits(padded, at[long], np.full(int(long.sum()), full), msb=True) - U64(short)
    return q.astype(U64) * U64(m) + r + U64(1)


def _plain_encode(x: np.ndarray, backend: str) -> Block:
    return Block(len(x), data=x.astype("<u4").tobytes(), data_bits=32 * len(x))


register(Codec("gamma", _gamma_encode, _gamma_decode, positive=True))
register(Codec("rice", _rice(rice_parameter), _rice_decode, positive=True))
register(Codec("rice_best", _rice(rice_best), _rice_decode, positive=True))
register(Codec("golomb", _golomb_encode, _golomb_decode, positive=True))
register(Codec("uncompressed", _plain_encode, lambda b, _: np.frombuffer(b.data, "<u4"), many=lambda blocks: np.frombuffer(b"".join(b.data for b in blocks), "<u4")))
