"""Bit arithmetic in numpy that all codecs share."""

from __future__ import annotations

import numpy as np

U64 = np.uint64


def as_values(values) -> np.ndarray:
    """Unsigned 32-bit integers, held in 64 bits for shifting."""
    x = np.asarray(values, dtype=np.int64)
    if len(x) and (x.min() < 0 or x.max() > 0xFFFFFFFF):
        raise ValueError("values must be unsigned 32-bit integers")
    return x.astype(U64)


def bitlen(x: np.ndarray) -> np.ndarray:
    """Effective bits of each value; 1 for zero."""
    _, e = np.frexp(x.astype(np.float64))  # exact below 2^53
    return np.maximum(e, 1).astype(np.int64)


def ceil_div(a, b):
    return -(-a // b)


def low_mask(width: np.ndarray | int) -> np.ndarray:
    return (U64(1) << np.asarray(width, U64)) - U64(1)


def put_bits(values: np.ndarray, lengths: np.ndarray, msb: bool = False) -> np.ndarray:
    """The values' bits one after another, as an array of 0/1; low bit first unless ``msb``."""
    lengths = np.asarray(lengths, np.int64)
    total = int(lengths.sum())
    ends = np.cumsum(lengths)
    inner = np.arange(total) - np.repeat(ends - lengths, lengths)
    shift = np.repeat(lengths, lengths) - 1 - inner if msb else inner
    return ((np.repeat(np.asarray(values, U64), lengths) >> shift.astype(U64)) & U64(1)).astype(np.uint8)


def get_bits(bits: np.ndarray, starts: np.ndarray, lengths: np.ndarray, msb: bool = False) -> np.ndarray:
    """The values at ``starts`` with ``lengths`` bits (0 bits: the value 0)."""
    lengths = np.asarray(lengths, np.int64)
    out = np.zeros(len(lengths), U64)
    some = lengths > 0
    if not some.any():
        return out
    n, at = lengths[some], np.asarray(starts)[some]
    ends = np.cumsum(n)
    inner = np.arange(int(ends[-1])) - np.repeat(ends - n, n)
    weight = np.repeat(n, n) - 1 - inner if msb else inner
    out[some] = np.add.reduceat(bits[np.repeat(at, n) + inner].astype(U64) << weight.astype(U64), ends - n)
    return out


def to_bytes(bits: np.ndarray, msb: bool = False, fill: int = 0) -> bytes:
    """Bits as bytes, the last one filled up with ``fill``."""
    short = -len(bits) % 8
    if short:
        bits = np.concatenate([bits, np.full(short, fill, np.uint8)])
    return np.packbits(bits, bitorder="big" if msb else "little").tobytes()


def from_bytes(raw: bytes, msb: bool = False) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="big" if msb else "little")


def pad_to(values: np.ndarray, multiple: int) -> np.ndarray:
    short = -len(values) % multiple
    return np.concatenate([values, np.zeros(short, values.dtype)]) if short else values


def starts_of(counts: np.ndarray) -> np.ndarray:
    return np.cumsum(counts) - counts


def first_of(values: np.ndarray, held: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Of groups of ``held`` values the first ``wanted`` of each."""
    if (held == wanted).all():
        return values
    inner = np.arange(int(held.sum())) - np.repeat(starts_of(held), held)
    return values[inner < np.repeat(wanted, held)]


def chase(step: np.ndarray) -> np.ndarray:
    """Start positions of a walk over 0..len(step)-1 that moves on by step[position]."""
    out, at, n, hops = [], 0, len(step), step.tolist()
    while at < n:
        out.append(at)
        at += hops[at]
    return np.array(out, np.int64)


def greedy(need: np.ndarray, patterns: list[tuple[int, ...]]) -> tuple[np.ndarray, np.ndarray]:
    """(starts, chosen): the walk that always takes the first pattern whose slots hold what comes next.

    ``need`` has the bits that each value wants. Whether a pattern fits is known for
    all positions at once; only the walk itself goes step by step. A pattern may be
    part-filled at the end.
    """
    n = len(need)
    chosen = np.full(n, -1, np.int64)
    for k in range(len(patterns) - 1, -1, -1):
        widths = np.asarray(patterns[k], np.int64)
        padded = np.concatenate([need, np.zeros(len(widths) - 1, need.dtype)]) if n else need
        if n:
            if (widths == widths[0]).all():
                bad = np.concatenate([[0], np.cumsum(padded > widths[0])])
                fits = bad[len(widths) :] == bad[: len(bad) - len(widths)]
            else:
                fits = (np.lib.stride_tricks.sliding_window_view(padded, len(widths)) <= widths).all(axis=1)
            chosen[fits] = k
    if (chosen < 0).any():
        raise ValueError("a value is too large for every pattern of this codec")
    sizes = np.array([len(p) for p in patterns], np.int64)
    starts = chase(sizes[chosen]) if n else np.zeros(0, np.int64)
    return starts, chosen[starts]
