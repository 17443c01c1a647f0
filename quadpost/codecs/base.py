"""The contract of every codec, and their registry."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from quadpost.codecs.bits import as_values


@dataclass(frozen=True)
class Block:
    """One encoded sequence: three separate areas and their sizes in bits."""

    n: int
    ctrl: bytes = b""
    data: bytes = b""
    exc: bytes = b""
    ctrl_bits: int = 0
    data_bits: int = 0
    exc_bits: int = 0
    head_bits: int = 0

    @property
    def bits(self) -> int:
        return self.ctrl_bits + self.data_bits + self.exc_bits + self.head_bits


@dataclass(frozen=True)
class Codec:
    """encode(values, backend) and decode(block, backend) with plain numpy arrays.

    ``positive`` codecs cannot hold zero; ``backends`` names the builds that exist.
    ``many`` decodes a list of blocks, none of them empty, in one go; ``together`` encodes
    values that lie one sequence after another, given their counts.
    """

    name: str
    encoder: Callable[[np.ndarray, str], Block]
    decoder: Callable[[Block, str], np.ndarray]
    positive: bool = False
    max_bits: int = 32
    backends: tuple[str, ...] = ("lanes",)
    options: dict = field(default_factory=dict)
    many: Callable[[list[Block]], np.ndarray] | None = None
    together: Callable[[np.ndarray, np.ndarray], list[Block]] | None = None

    def encode(self, values, backend: str = "lanes") -> Block:
        x = as_values(values)
        if self.positive and len(x) and not x.all():
            raise ValueError(f"{self.name} holds positive integers only")
        if self.max_bits < 32 and len(x) and int(x.max()) >> self.max_bits:
            raise ValueError(f"{self.name} holds values below 2^{self.max_bits} only")
        return self.encoder(x, backend)

    def encode_many(self, lists: list[np.ndarray], backend: str = "lanes") -> list[Block]:
        """A block of each list."""
        if backend == "lanes" and self.together and not self.positive and lists:
            return self.together(as_values(np.concatenate(lists)), np.array([len(v) for v in lists], np.int64))
        return [self.encode(v, backend) for v in lists]

    def decode(self, block: Block, backend: str = "lanes") -> np.ndarray:
        if not block.n:
            return np.zeros(0, np.uint32)
        return self.decoder(block, backend)[: block.n].astype(np.uint32)

    def decode_many(self, blocks: list[Block], backend: str = "lanes") -> np.ndarray:
        """The values of all blocks, one block after another."""
        if backend == "lanes" and self.many:
            some = [b for b in blocks if b.n]
            return self.many(some).astype(np.uint32, copy=False) if some else np.zeros(0, np.uint32)
        return np.concatenate([self.decode(b, backend) for b in blocks]) if blocks else np.zeros(0, np.uint32)

    def bits(self, values) -> int:
        return self.encode(values).bits


_registry: dict[str, Codec] = {}


def register(codec: Codec) -> Codec:
    _registry[codec.name] = codec
    return codec


def codec(name: str) -> Codec:
    from quadpost import codecs  # all modules register on import

    codecs.load()
    if name not in _registry:
        raise KeyError(f"no codec {name!r}; there are {sorted(_registry)}")
    return _registry[name]


def names() -> list[str]:
    from quadpost import codecs

    codecs.load()
    return list(_registry)
