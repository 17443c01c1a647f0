"""Word-aligned classics: several values of equal or mixed widths in one word, told by a 4-bit selector."""

from __future__ import annotations

import numpy as np

from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import U64, bitlen, greedy, low_mask

SELECTOR_BITS = 4
# Fixed values: (values, bits) of each selector; the 16-way one in runs of (values, bits).
NINE = ((28, 1), (14, 2), (9, 3), (7, 4), (5, 5), (4, 7), (3, 9), (2, 14), (1, 28))
SIXTEEN = (
    ((28, 1),),
    ((7, 2), (14, 1)),
    ((7, 1), (7, 2), (7, 1)),
    ((14, 1), (7, 2)),
    ((14, 2),),
    ((1, 4), (8, 3)),
    ((1, 3), (4, 4), (3, 3)),
    ((7, 4),),
    ((4, 5), (2, 4)),
    ((2, 4), (4, 5)),
    ((3, 6), (2, 5)),
    ((2, 5), (3, 6)),
    ((4, 7),),
    ((1, 10), (2, 9)),
    ((2, 14),),
    ((1, 28),),
)
EIGHT_B = ((240, 0), (120, 0), (60, 1), (30, 2), (20, 3), (15, 4), (12, 5), (10, 6), (8, 7), (7, 8), (6, 10), (5, 12), (4, 15), (3, 20), (2, 30), (1, 60))


class _Layout:
    """Patterns of one word codec; selectors stand in the word's low bits."""

    def __init__(self, patterns: list[tuple[int, ...]], dtype: str, ones: bool):
        self.patterns, self.dtype, self.ones = patterns, dtype, ones
        self.sizes = np.array([len(p) for p in patterns], np.int64)
        self.offsets = [np.concatenate([[0], np.cumsum(p)[:-1]]).astype(np.int64) + SELECTOR_BITS for p in patterns]
        self.word_bits = 8 * np.dtype(dtype).itemsize

    def need(self, x: np.ndarray) -> np.ndarray:
        bits = bitlen(x)
        return np.where(x == 1, 0, bits) if self.ones else bits

    def encode(self, x: np.ndarray, backend: str) -> Block:
        starts, chosen = greedy(self.need(x), self.patterns)
        words = chosen.astype(U64)
        for s in np.unique(chosen):
            mine = np.flatnonzero(chosen == s)
            widths = np.asarray(self.patterns[s])
            if not widths[0]:
                continue
            padded = np.concatenate([x, np.zeros(len(widths), U64)])
            values = padded[starts[mine][:, None] + np.arange(len(widths))]
            # what stands beyond the end of the sequence belongs to no value
            inside = starts[mine][:, None] + np.arange(len(widths)) < len(x)
            words[mine] |= np.bitwise_or.reduce(np.where(inside, values, U64(0)) << self.offsets[s].astype(U64), axis=1)
        return Block(len(x), data=words.astype(self.dtype).tobytes(), ctrl_bits=SELECTOR_BITS * len(words), data_bits=(self.word_bits - SELECTOR_BITS) * len(words))

    def decode(self, block: Block, backend: str) -> np.ndarray:
        words = np.frombuffer(block.data, self.dtype).astype(U64)
        chosen = (words & U64(15)).astype(np.int64)
        sizes = self.sizes[chosen]
        first = np.cumsum(sizes) - sizes
        out = np.ones(int(sizes.sum()), U64)
        for s in np.unique(chosen):
            widths = np.asarray(self.patterns[s])
            if not widths[0]:
                continue
            mine = np.flatnonzero(chosen == s)
            out[first[mine][:, None] + np.arange(len(widths))] = words[mine][:, None] >> self.offsets[s].astype(U64) & low_mask(widths)
        return out[: block.n]


def _register(name: str, patterns: list[tuple[int, ...]], dtype: str, max_bits: int, ones: bool = False) -> None:
    layout = _Layout(patterns, dtype, ones)
    register(Codec(name, layout.encode, layout.decode, max_bits=max_bits))


_register("simple9", [(b,) * n for n, b in NINE], "<u4", 28)
_register("simple16", [tuple(b for n, b in runs for _ in range(n)) for runs in SIXTEEN], "<u4", 28)
_register("simple8b", [(b,) * n for n, b in EIGHT_B], "<u8", 32, ones=True)
