"""Four 32-bit lanes side by side: the data area of every 4-lane codec.

Member i of a quad goes to lane i. A lane is a row of 32-bit components, low
bits first. A value that does not fit into what is left of a component is split:
its high part fills the top of this component, its low part starts the next.
"""

from __future__ import annotations

import numpy as np

from quadpost.codecs.bits import U64, first_of, low_mask, pad_to, starts_of

LANES = 4
WORD = 32


def quads(values: np.ndarray) -> np.ndarray:
    """(m, 4) rows of four consecutive integers, the last filled up with zeros."""
    return pad_to(values, LANES).reshape(-1, LANES)


def quad_max(values: np.ndarray) -> np.ndarray:
    return quads(values).max(axis=1) if len(values) else values


def quad_or(values: np.ndarray) -> np.ndarray:
    """A stand-in for the maximum with the same number of effective bits, free of comparisons."""
    return np.bitwise_or.reduce(quads(values), axis=1) if len(values) else values


def offsets_of(widths: np.ndarray) -> np.ndarray:
    return np.cumsum(widths) - widths


def pack(rows: np.ndarray, offsets: np.ndarray, widths: np.ndarray, words: int, backend: str = "lanes") -> bytes:
    """rows (m, 4) at bit ``offsets`` of their lanes, ``widths`` bits each, as ``words`` vectors of 128 bits."""
    if backend == "scalar":
        return _pack_one_by_one(rows, offsets, widths, words)
    out = np.zeros((words + 1, LANES), U64)
    word, bit = offsets // WORD, offsets % WORD
    room = WORD - bit
    over = np.maximum(widths - room, 0)
    low = rows & low_mask(widths)[:, None]
    here = low >> over.astype(U64)[:, None] << bit.astype(U64)[:, None]
    np.add.at(out, word, here)
    split = over > 0
    if split.any():
        np.add.at(out, word[split] + 1, low[split] & low_mask(over[split])[:, None])
    return out[:words].astype("<u4").tobytes()


def unpack(data: bytes, offsets: np.ndarray, widths: np.ndarray, backend: str = "lanes") -> np.ndarray:
    """(m, 4) values again: at most two components are read for each."""
    if backend == "scalar":
        return _unpack_one_by_one(data, offsets, widths)
    return _unpack(data, offsets, widths).astype(U64)


_MASKS = ((1 << np.arange(WORD + 1, dtype=np.uint64)) - 1).astype(np.uint32)


def _unpack(data: bytes, offsets: np.ndarray, widths: np.ndarray) -> np.ndarray:
    words = np.frombuffer(data, "<u4").reshape(-1, LANES)
    word, bit = offsets >> 5, offsets & 31
    over = np.maximum(widths - (WORD - bit), 0)
    out = words[word]
    out >>= bit.astype(np.uint32)[:, None]
    out &= _MASKS[widths - over][:, None]
    split = np.flatnonzero(over)
    if len(split):
        rest = over[split]
        out[split] = out[split] << rest.astype(np.uint32)[:, None] | words[word[split] + 1] & _MASKS[rest][:, None]
    return out


def unpack_many(data: list[bytes], widths: np.ndarray, quads_of: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The first ``n`` values of each block. widths: of all blocks' quads, ``quads_of`` them a block."""
    words = np.fromiter(map(len, data), np.int64, len(data)) // (LANES * WORD // 8)
    run = offsets_of(widths)
    base = WORD * starts_of(words) - run[starts_of(quads_of)]
    return first_of(_unpack(b"".join(data), run + np.repeat(base, quads_of), widths).ravel(), LANES * quads_of, n)


def _pack_one_by_one(rows, offsets, widths, words) -> bytes:
    out = [[0] * LANES for _ in range(words + 1)]
    for row, offset, width in zip(rows.tolist(), offsets.tolist(), widths.tolist(), strict=True):
        word, bit = divmod(offset, WORD)
        over = max(0, width - (WORD - bit))
        for lane in range(LANES):
            value = row[lane] & ((1 << width) - 1)
            out[word][lane] |= value >> over << bit
            if over:
                out[word + 1][lane] |= value & ((1 << over) - 1)
    return np.array(out[:words], "<u4").reshape(-1, LANES).tobytes()


def _unpack_one_by_one(data, offsets, widths) -> np.ndarray:
    words = np.frombuffer(data, "<u4").reshape(-1, LANES).tolist()
    out = []
    for offset, width in zip(offsets.tolist(), widths.tolist(), strict=True):
        word, bit = divmod(offset, WORD)
        over = max(0, width - (WORD - bit))
        for lane in range(LANES):
            value = words[word][lane] >> bit & ((1 << (width - over)) - 1)
            if over:
                value = value << over | words[word + 1][lane] & ((1 << over) - 1)
            out.append(value)
    return np.array(out, U64).reshape(-1, LANES)
