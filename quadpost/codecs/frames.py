"""Frame codecs: runs of values of one width, in plain bits or in four lanes.

Each codec is a partition (which frames), a width rule (which width, and which
values are exceptions) and a store. ``lift`` takes any of them to four lanes: the
partition and the widths are found on the quads' maxima, a quarter of the
numbers, and every quad is packed into the lanes.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np

from quadpost.codecs import lanes
from quadpost.codecs.base import Block, Codec, register
from quadpost.codecs.bits import U64, bitlen, ceil_div, from_bytes, get_bits, low_mask, pad_to, put_bits, starts_of, to_bytes

HEAD = 8
EXCEPTION_WIDTHS = (8, 16, 32)
ZETA = 0.10
PAGE = 65_536


@dataclass(frozen=True)
class Scheme:
    """frames: lengths to choose from, in integers; one length means frames of that size."""

    name: str
    frames: tuple[int, ...]
    rule: str = "max"  # max | threshold | cost
    zeta: float = ZETA
    laned: bool = False


def partition(need: np.ndarray, sizes: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, widths) of the frames that cost least: HEAD + length * width each; ties go to the longer frame.

    Positions are cells of the smallest size; the tail fills up its last cell. Costs
    come from the end, each with the running maxima of its candidate frames.
    """
    cell = sizes[0]
    cells = pad_to(need, cell).reshape(-1, cell).max(axis=1) if len(need) else need
    m = len(cells)
    options = []
    for size in sorted(sizes, reverse=True):
        k = size // cell
        if k <= m:
            top = np.lib.stride_tricks.sliding_window_view(cells, k).max(axis=1)
            options.append((k, (HEAD + size * top).tolist(), top.tolist()))
    best, pick = [0] * (m + 1), [(1, 1)] * m
    for at in range(m - 1, -1, -1):
        cost = None
        for k, costs, tops in options:
            if at + k <= m and (cost is None or costs[at] + best[at + k] < cost):
                cost, pick[at] = costs[at] + best[at + k], (k, tops[at])
        best[at] = cost
    lengths, widths, at = [], [], 0
    while at < m:
        k, top = pick[at]
        lengths.append(k * cell)
        widths.append(top)
        at += k
    return np.array(lengths, np.int64), np.array(widths, np.int64)


def _fixed(need: np.ndarray, size: int) -> np.ndarray:
    return pad_to(need, size).reshape(-1, size)


def threshold_widths(need: np.ndarray, size: int, zeta: float) -> np.ndarray:
    """For each frame the least width that leaves a share of exceptions strictly below ``zeta``."""
    counts = np.minimum(size, len(need) - size * np.arange(ceil_div(len(need), size)))
    frames = _fixed(need, size)
    over = np.stack([(frames > b).sum(axis=1) for b in range(1, 33)], axis=1)
    return (over < zeta * counts[:, None]).argmax(axis=1) + 1


def cost_widths(need: np.ndarray, size: int) -> np.ndarray:
    """For each frame the width of least cost: all values at that width, and each exception's high part and place."""
    frames = _fixed(need, size)
    counts = np.minimum(size, len(need) - size * np.arange(len(frames)))
    top = frames.max(axis=1)
    place = 8 if size <= 256 else 16
    cost = np.stack([counts * b + (frames > b).sum(axis=1) * np.maximum(top - b, 0) + (frames > b).sum(axis=1) * place for b in range(1, 33)], axis=1)
    return cost.argmin(axis=1) + 1


# --- stores --------------------------------------------------------------------------------------------------------


def _store(slots: np.ndarray, lengths: np.ndarray, widths: np.ndarray, laned: bool, backend: str) -> tuple[bytes, int]:
    """slots at their frames' widths; lengths count integers (plain) or quads (laned)."""
    each = np.repeat(widths, lengths)
    if laned:
        rows = lanes.quads(slots)
        short = int(lengths.sum()) - len(rows)
        rows = np.concatenate([rows, np.zeros((short, lanes.LANES), U64)]) if short > 0 else rows
        words = int(ceil_div(int(each.sum()), lanes.WORD))
        return lanes.pack(rows, lanes.offsets_of(each), each, words, backend), 128 * words
    bits = put_bits(np.concatenate([slots, np.zeros(len(each) - len(slots), U64)]), each)
    return to_bytes(bits), len(bits)


def _load(data: bytes, lengths: np.ndarray, widths: np.ndarray, laned: bool, backend: str) -> np.ndarray:
    each = np.repeat(widths, lengths)
    if laned:
        return lanes.unpack(data, lanes.offsets_of(each), each, backend).ravel()
    return get_bits(from_bytes(data), lanes.offsets_of(each), each)


def _fixed_lengths(units: int, size: int) -> np.ndarray:
    """The last frame may be short."""
    out = np.full(int(ceil_div(units, size)), size, np.int64)
    if len(out):
        out[-1] = units - size * (len(out) - 1)
    return out


# --- exceptions ----------------------------------------------------------------------------------------------------


def chain(flags: np.ndarray, width: int) -> np.ndarray:
    """Exception places of a frame, with forced ones where a distance less one would not fit ``width`` bits."""
    places = np.flatnonzero(flags).tolist()
    reach = 1 << min(width, 16)
    out = places[:1]
    for p in places[1:]:
        while p - out[-1] > reach:
            out.append(out[-1] + reach)
        out.append(p)
    return np.array(out, np.int64)


def _threshold_encode(s: Scheme, x: np.ndarray, backend: str) -> Block:
    size = s.frames[0]
    unit = lanes.LANES if s.laned else 1
    maxima = lanes.quad_or(x) if s.laned else x
    widths = threshold_widths(bitlen(maxima), size // unit, s.zeta) if len(x) else np.zeros(0, np.int64)
    small = size <= 256
    place = "<u1" if small else "<u2"
    need, slots = bitlen(x), x.copy()
    ctrl, exc, n_exc = [], [], 0
    for k, b in enumerate(widths.tolist()):
        a, z = k * size, min(len(x), (k + 1) * size)
        # of a flagged quad only the values that themselves exceed the width are exceptions
        places = chain(need[a:z] > b, b)
        values = x[a + places]
        code = int(np.searchsorted([8, 16, 32], int(bitlen(values).max()))) if len(places) else 0
        if len(places):
            slots[a + places[:-1]] = np.diff(places) - 1
            slots[a + places[-1]] = 0
            exc.append(values.astype(f"<u{EXCEPTION_WIDTHS[code] // 8}").tobytes())
            n_exc += len(places) * EXCEPTION_WIDTHS[code]
        ctrl.append(bytes([b - 1 | code << 6]) + np.array([places[0] if len(places) else 0, len(places) & (0xFF if small else 0xFFFF)], place).tobytes())
    lengths = _fixed_lengths(int(ceil_div(len(x), unit)), size // unit)
    data, data_bits = _store(slots, lengths, widths, s.laned, backend)
    ctrl_bytes = b"".join(ctrl)
    return Block(len(x), ctrl_bytes, data, b"".join(exc), 8 * len(ctrl_bytes), data_bits, n_exc)


def _threshold_decode(s: Scheme, block: Block, backend: str) -> np.ndarray:
    size, unit = s.frames[0], lanes.LANES if s.laned else 1
    small = size <= 256
    step, place = (3, "<u1") if small else (5, "<u2")
    raw = np.frombuffer(block.ctrl, np.uint8).reshape(-1, step)
    widths, codes = (raw[:, 0] & 63).astype(np.int64) + 1, raw[:, 0] >> 6
    heads = np.ascontiguousarray(raw[:, 1:]).view(place).astype(np.int64)
    out = _load(block.data, _fixed_lengths(int(ceil_div(block.n, unit)), size // unit), widths, s.laned, backend)
    at = 0
    for k, (code, (first, count)) in enumerate(zip(codes.tolist(), heads.tolist(), strict=True)):
        if not count:
            continue
        width = EXCEPTION_WIDTHS[code] // 8
        values = np.frombuffer(block.exc, f"<u{width}", count, at)
        at += width * count
        here = k * size + first
        for v in values.tolist():
            step_on = int(out[here]) + 1
            out[here] = v
            here += step_on
    return out


def _cost_encode(s: Scheme, x: np.ndarray, backend: str) -> Block:
    """Exceptions keep their low part in place; high parts are pooled by their width, page by page."""
    size, unit = s.frames[0], lanes.LANES if s.laned else 1
    maxima = lanes.quad_or(x) if s.laned else x
    widths = cost_widths(bitlen(maxima), size // unit) if len(x) else np.zeros(0, np.int64)
    need = bitlen(x)
    place = "<u1" if size <= 256 else "<u2"
    ctrl, pools = [], {}
    for k, b in enumerate(widths.tolist()):
        a, z = k * size, min(len(x), (k + 1) * size)
        places = np.flatnonzero(need[a:z] > b)
        more = int(need[a:z].max()) - b if len(places) else 0
        ctrl.append(bytes([b, more]) + np.array([len(places) & 0xFFFF], "<u2").tobytes() + places.astype(place).tobytes())
        if len(places):
            pools.setdefault((a // PAGE, more), []).append(x[a + places] >> U64(b))
    parts, exc_bits = [], 0
    for (_, more), highs in sorted(pools.items()):
        values = np.concatenate(highs)
        parts.append(to_bytes(put_bits(values, np.full(len(values), more))))
        exc_bits += len(values) * more
    lengths = _fixed_lengths(int(ceil_div(len(x), unit)), size // unit)
    data, data_bits = _store(x & low_mask(np.repeat(widths, np.minimum(size, len(x) - size * np.arange(len(widths))))), lengths, widths, s.laned, backend)
    ctrl_bytes = b"".join(ctrl)
    return Block(len(x), ctrl_bytes, data, b"".join(parts), 8 * len(ctrl_bytes), data_bits, exc_bits)


def _cost_decode(s: Scheme, block: Block, backend: str) -> np.ndarray:
    size, unit = s.frames[0], lanes.LANES if s.laned else 1
    width_of = np.dtype("<u1" if size <= 256 else "<u2")
    frames, at = [], 0
    while at < len(block.ctrl):
        b, more, count = block.ctrl[at], block.ctrl[at + 1], int.from_bytes(block.ctrl[at + 2 : at + 4], "little")
        places = np.frombuffer(block.ctrl, width_of, count, at + 4).astype(np.int64)
        frames.append((b, more, places))
        at += 4 + width_of.itemsize * count
    widths = np.array([b for b, _, _ in frames], np.int64)
    out = _load(block.data, _fixed_lengths(int(ceil_div(block.n, unit)), size // unit), widths, s.laned, backend)
    pools: dict[tuple[int, int], list[int]] = {}
    for k, (_, more, places) in enumerate(frames):
        if len(places):
            pools.setdefault((k * size // PAGE, more), []).append(k)
    at = 0
    for (_, more), mine in sorted(pools.items()):
        total = sum(len(frames[k][2]) for k in mine)
        size_bytes = int(ceil_div(total * more, 8))
        highs = get_bits(from_bytes(block.exc[at : at + size_bytes]), more * np.arange(total), np.full(total, more))
        at += size_bytes
        for k in mine:
            b, _, places = frames[k]
            out[k * size + places] |= highs[: len(places)] << U64(b)
            highs = highs[len(places) :]
    return out


# --- frames of fixed and of chosen lengths --------------------------------------------------------------------------


def _max_encode(s: Scheme, x: np.ndarray, backend: str) -> Block:
    unit = lanes.LANES if s.laned else 1
    need = bitlen(lanes.quad_or(x) if s.laned else x)
    sizes = tuple(f // unit for f in s.frames)
    if len(sizes) == 1:
        lengths = _fixed_lengths(len(need), sizes[0])
        widths = _fixed(need, sizes[0]).max(axis=1) if len(need) else need
        heads = widths - 1
    else:
        lengths, widths = partition(need, tuple(s.frames)) if not s.laned else _lane_partition(need, s.frames)
        codes = np.array([s.frames.index(n * unit) for n in lengths.tolist()], np.int64)
        heads = widths - 1 | codes << 5
    data, data_bits = _store(x, lengths, widths, s.laned, backend)
    return Block(len(x), heads.astype(np.uint8).tobytes(), data, ctrl_bits=HEAD * len(heads), data_bits=data_bits)


def _lane_partition(need: np.ndarray, frames: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """The same choice on quads: a frame of L integers is L / 4 quads and costs HEAD + L * width bits over all lanes."""
    cell = frames[0] // lanes.LANES
    cells = pad_to(need, cell).reshape(-1, cell).max(axis=1) if len(need) else need
    lengths, widths = partition(np.repeat(cells, frames[0]), frames)
    return lengths // lanes.LANES, widths


def _max_decode(s: Scheme, block: Block, backend: str) -> np.ndarray:
    unit = lanes.LANES if s.laned else 1
    raw = np.frombuffer(block.ctrl, np.uint8).astype(np.int64)
    widths = (raw & 31) + 1
    if len(s.frames) == 1:
        lengths = _fixed_lengths(int(ceil_div(block.n, unit)), s.frames[0] // unit)
    else:
        lengths = np.array(s.frames)[raw >> 5] // unit
    return _load(block.data, lengths, widths, s.laned, backend)


def _max_many(s: Scheme):
    """All frames of all blocks in four lanes at once."""

    def run(blocks: list[Block]) -> np.ndarray:
        n = np.fromiter((b.n for b in blocks), np.int64, len(blocks))
        frames = np.fromiter((len(b.ctrl) for b in blocks), np.int64, len(blocks))
        raw = np.frombuffer(b"".join(b.ctrl for b in blocks), np.uint8).astype(np.int64)
        quads = ceil_div(n, lanes.LANES)
        if len(s.frames) == 1:
            size = s.frames[0] // lanes.LANES
            lengths = np.full(len(raw), size, np.int64)
            lengths[np.cumsum(frames) - 1] = quads - size * (frames - 1)
        else:
            lengths = np.array(s.frames)[raw >> 5] // lanes.LANES
            quads = np.add.reduceat(lengths, starts_of(frames))
        return lanes.unpack_many([b.data for b in blocks], np.repeat((raw & 31) + 1, lengths), quads, n)

    return run


_RULES = {"max": (_max_encode, _max_decode), "threshold": (_threshold_encode, _threshold_decode), "cost": (_cost_encode, _cost_decode)}


def build(s: Scheme) -> Codec:
    if s.laned and any(f % lanes.LANES for f in s.frames):
        raise ValueError("a frame in lanes holds a multiple of four integers")
    encode, decode = _RULES[s.rule]
    return Codec(
        s.name,
        lambda x, backend: encode(s, x, backend),
        lambda block, backend: decode(s, block, backend),
        backends=("lanes", "scalar") if s.laned else ("lanes",),
        options={"scheme": s},
        many=_max_many(s) if s.laned and s.rule == "max" else None,
    )


def lift(codec: Codec, name: str, frames: tuple[int, ...] | None = None) -> Codec:
    """The four-lane form of a frame codec."""
    return build(replace(codec.options["scheme"], name=name, laned=True, frames=frames or codec.options["scheme"].frames))


PACKED_BINARY = register(build(Scheme("packed_binary", (512,))))
PFOR = register(build(Scheme("pfor", (128,), "threshold")))
FASTPFOR = register(build(Scheme("fastpfor", (512,), "cost")))
AFOR = register(build(Scheme("afor", (8, 16, 32))))
VSENCODING = register(build(Scheme("vsencoding", (4, 8, 16, 32, 64))))
register(lift(PACKED_BINARY, "quad_bp128", (128,)))
register(lift(PACKED_BINARY, "quad_packed", (512,)))
register(lift(FASTPFOR, "quad_fastpfor", (512,)))
register(lift(PFOR, "quad_pfor", (128,)))
register(lift(AFOR, "quad_afor", (32, 64, 128)))
register(lift(VSENCODING, "quad_vse", (16, 32, 64, 128, 256)))
