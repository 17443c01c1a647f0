"""quad_selector: ten ways to share a 128-bit vector between quads of equal width."""

from __future__ import annotations

import numpy as np

from quadpost.codecs import lanes
from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import bitlen, ceil_div, first_of, from_bytes, greedy, put_bits, starts_of, to_bytes

# Selector number, values per lane, bits per value.
SELECTORS = ((0, 32, 1), (1, 16, 2), (2, 10, 3), (3, 8, 4), (4, 6, 5), (5, 5, 6), (6, 4, 8), (7, 3, 10), (8, 2, 16), (9, 1, 32))

NUM = np.array([n for _, n, _ in SELECTORS])
BW = np.array([b for _, _, b in SELECTORS])
PATTERNS = [(b,) * n for _, n, b in SELECTORS]
CTRL_BITS, VECTOR_BITS = 4, 128


def select(maxima: np.ndarray) -> np.ndarray:
    """The selector of each vector, from a quarter of the numbers: the quads' maxima."""
    return greedy(bitlen(maxima), PATTERNS)[1]


def _slots(selectors: np.ndarray, quads: int) -> tuple[np.ndarray, np.ndarray]:
    """Bit offset in its lane and width of every quad; each vector starts a new component."""
    num = NUM[selectors]
    vector = np.repeat(np.arange(len(selectors)), num)[:quads]
    slot = np.arange(len(vector)) - np.repeat(np.cumsum(num) - num, num)[:quads]
    width = BW[selectors][vector]
    return vector * lanes.WORD + slot * width, width


def _encode(maximum):
    def run(x: np.ndarray, backend: str) -> Block:
        rows = lanes.quads(x)
        selectors = select(maximum(x))
        offsets, widths = _slots(selectors, len(rows))
        data = lanes.pack(rows, offsets, widths, len(selectors), backend)
        ctrl = to_bytes(put_bits(selectors, np.full(len(selectors), CTRL_BITS)))
        return Block(len(x), ctrl, data, ctrl_bits=CTRL_BITS * len(selectors), data_bits=VECTOR_BITS * len(selectors))

    return run


def read_selectors(block: Block) -> np.ndarray:
    vectors = len(block.data) * 8 // VECTOR_BITS
    bits = from_bytes(block.ctrl)[: vectors * CTRL_BITS].reshape(-1, CTRL_BITS)
    return (bits << np.arange(CTRL_BITS)).sum(axis=1)


def _decode(block: Block, backend: str) -> np.ndarray:
    selectors, quads = read_selectors(block), -(-block.n // lanes.LANES)
    if backend == "scalar":
        offsets, widths = _slots(selectors, quads)
        return lanes.unpack(block.data, offsets, widths, backend).ravel()
    return _unpacked(selectors, block.data)[:quads].ravel()


def _unpacked(selectors: np.ndarray, data: bytes) -> np.ndarray:
    """The quads of all vectors; those of one selector are unpacked by that selector's own shifts and mask."""
    words = np.frombuffer(data, "<u4").reshape(-1, lanes.LANES)
    num = NUM[selectors]
    first = starts_of(num)
    out = np.zeros((int(num.sum()), lanes.LANES), np.uint32)
    for s in np.unique(selectors):
        mine = np.flatnonzero(selectors == s)
        n, width = int(NUM[s]), int(BW[s])
        shifts = np.arange(n, dtype=np.uint32) * np.uint32(width)
        got = words[mine][:, None, :] >> shifts[None, :, None] & np.uint32((1 << width) - 1)
        out[first[mine][:, None] + np.arange(n)] = got
    return out


def _decode_many(blocks: list[Block]) -> np.ndarray:
    n = np.fromiter((b.n for b in blocks), np.int64, len(blocks))
    vectors = np.fromiter((len(b.data) for b in blocks), np.int64, len(blocks)) * 8 // VECTOR_BITS
    raw = np.frombuffer(b"".join(b.ctrl for b in blocks), np.uint8)
    selectors = first_of(np.stack([raw & 15, raw >> 4], axis=1).ravel().astype(np.int64), 2 * ceil_div(vectors, 2), vectors)
    held = np.add.reduceat(NUM[selectors], starts_of(vectors))
    return first_of(_unpacked(selectors, b"".join(b.data for b in blocks)).ravel(), lanes.LANES * held, n)


QUAD_SELECTOR = register(Codec("quad_selector", _encode(lanes.quad_or), _decode, backends=("lanes", "scalar"), many=_decode_many))
#: The same with true maxima, for the ablation of the comparison-free stand-in.
QUAD_SELECTOR_MAX = Codec("quad_selector_max", _encode(lanes.quad_max), _decode, backends=("lanes", "scalar"))
