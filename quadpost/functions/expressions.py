"""What the codecs decide and cost, as Catalyst expressions: no value leaves the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from quadpost.codecs.quad_length import BINARY_BITS, BINARY_UNIT
from quadpost.codecs.quad_selector import CTRL_BITS, SELECTORS, VECTOR_BITS

LANES = 4


def effective_bits(x: Column) -> Column:
    """Bits of a value; 1 for zero."""
    return F.length(F.bin(x))


def _units(values: Column, size: int) -> Column:
    """The array in pieces of ``size``; the last may be shorter, an empty array has none."""
    count = F.ceil(F.size(values) / size).cast("int")
    starts = F.when(count > 0, F.sequence(F.lit(0), count - 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda k: F.slice(values, k * size + 1, F.lit(size)))


def quad_max(values: Column) -> Column:
    return F.transform(_units(values, LANES), F.array_max)


def quad_or(values: Column) -> Column:
    return F.transform(_units(values, LANES), lambda q: F.aggregate(q, F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x)))


def lane(values: Column, k: int) -> Column:
    """The members that go to lane ``k``."""
    return F.transform(_units(values, LANES), lambda q: F.coalesce(F.get(q, F.lit(k)), F.lit(0).cast("long")))


def length_descriptor(x: Column, cg: int) -> Column:
    return F.ceil(effective_bits(x) / cg)


def stored_descriptor(x: Column, cg: int, coding: str) -> Column:
    """What the control area holds: binary descriptors are stored less one."""
    return length_descriptor(x, cg) - (1 if coding == "b" else 0)


def width_of(stored: Column, cg: int, coding: str) -> Column:
    return cg * (stored + (1 if coding == "b" else 0))


def _total(values: Column, f) -> Column:
    return F.aggregate(values, F.lit(0).cast("long"), lambda a, x: a + f(x).cast("long"))


def _vectors(bits: Column) -> Column:
    return VECTOR_BITS * F.ceil(bits / 32)


def value_bits(values: Column) -> Column:
    return F.transform(values, effective_bits)


def quad_bits(bits: Column) -> Column:
    """What each quad needs, from what its values need."""
    return F.transform(_units(bits, LANES), F.array_max)


def quad_length_bits(need: Column, cg: int, coding: str) -> Column:
    """Bits of the family's members from the quads' bit lengths."""
    units = _total(need, lambda b: F.ceil(b / cg))
    if coding == "b":
        per, size = BINARY_UNIT[cg]
        ctrl = 8 * size * F.ceil(F.size(need) / per)
    elif coding == "cu":
        ctrl = 8 * F.ceil(units / 8)
    else:  # codes fill bytes greedily: carry (bytes begun, bits used in the last)
        start = F.struct(F.lit(0).cast("long").alias("bytes"), F.lit(8).cast("long").alias("used"))
        code = lambda b: F.ceil(b / cg).cast("long")
        fold = F.aggregate(
            need,
            start,
            lambda a, b: F.when(a["used"] + code(b) > 8, F.struct((a["bytes"] + 1).alias("bytes"), code(b).alias("used"))).otherwise(F.struct(a["bytes"].alias("bytes"), (a["used"] + code(b)).alias("used"))),
        )
        ctrl = 8 * fold["bytes"]
    return ctrl + _vectors(units * cg)


def selector_modes(values: Column) -> Column:
    """The selectors of quad_selector, by one fold that keeps what is still unpacked out of sight: the next free quad."""
    # an array of one element binds the needs to a name, so that they are computed once
    return F.transform(F.array(F.transform(quad_or(values), effective_bits)), _modes_of)[0]


def _modes_of(need: Column) -> Column:
    return _selection(need, F.array().cast("array<int>"), lambda modes, pick: F.concat(modes, F.array(pick)))


def _selection(need: Column, empty: Column, add) -> Column:
    """A fold over the quads' bit lengths; ``add`` takes in each selector that is chosen."""

    def step(a: Column, k: Column) -> Column:
        def at(n: int) -> Column:
            return F.slice(need, a["next"] + 1, F.lit(n))

        pick = None
        for s, n, b in reversed(SELECTORS):
            pick = F.lit(s) if pick is None else F.when(F.array_max(at(n)) <= b, F.lit(s)).otherwise(pick)
        taken = F.element_at(F.array(*[F.lit(n) for _, n, _ in SELECTORS]), pick + 1)
        return F.when(a["next"] == k, F.struct((a["next"] + taken).alias("next"), add(a["held"], pick).alias("held"))).otherwise(a)

    places = F.when(F.size(need) > 0, F.sequence(F.lit(0), F.size(need) - 1)).otherwise(F.array().cast("array<int>"))
    return F.aggregate(places, F.struct(F.lit(0).alias("next"), empty.alias("held")), step)["held"]


def size_expr(name: str, values: Column, bits: Column | None = None, need: Column | None = None) -> Column:
    """The exact bits that codec ``name`` takes for the array, without encoding it.

    ``bits`` (``value_bits``) and ``need`` (``quad_bits`` of it) are computed here unless
    given; who asks for several codecs binds them as columns once.
    """
    n = F.size(values)
    bits = value_bits(values) if bits is None else bits
    need = quad_bits(bits) if need is None else need
    if name.startswith("ql_"):
        _, cg, coding = name.split("_")
        return quad_length_bits(need, int(cg), coding)
    byte_total = _total(bits, lambda b: F.ceil(b / 8))
    if name == "gamma":
        return _total(bits, lambda b: 2 * b - 1)
    if name == "vbyte":
        return 8 * _total(bits, lambda b: F.ceil(b / 7))
    if name == "gvb":
        return 8 * F.ceil(n / LANES) + 8 * byte_total
    if name == "g8cu":
        return 72 * F.ceil(byte_total / 8)
    if name == "uncompressed":
        return (32 * n).cast("long")
    if name == "packed_binary":
        return _total(_units(bits, 512), lambda f: 8 + F.size(f) * F.array_max(f))
    if name == "quad_bp128":
        return _vectors(_total(_units(bits, 128), lambda f: F.ceil(F.size(f) / LANES) * F.array_max(f))) + 8 * F.ceil(n / 128)
    if name == "rice":
        share = F.floor(69 * _total(values, lambda x: x) / (100 * n))
        parameter = F.when(share > 0, effective_bits(share) - 1).otherwise(0)
        # bound by an array of one element, or every value would add up the array again
        return F.transform(F.array(parameter), lambda b: 8 + n * (1 + b) + _total(values, lambda x: F.floor((x - 1) / F.pow(F.lit(2), b))))[0]
    if name == "quad_selector":
        return (CTRL_BITS + VECTOR_BITS) * _selection(need, F.lit(0).cast("long"), lambda count, _: count + 1)
    raise KeyError(f"no closed form for {name}")


CLOSED = ("uncompressed", "gamma", "vbyte", "gvb", "g8cu", "packed_binary", "quad_bp128", *(f"ql_{cg}_{c}" for c in ("b", "cu") for cg in (1, 2, 4, 8)))

__all__ = ["BINARY_BITS", "CLOSED", "effective_bits", "lane", "length_descriptor", "quad_max", "quad_or", "selector_modes", "size_expr", "stored_descriptor", "width_of"]
