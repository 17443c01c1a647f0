import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from quadpost.codecs import frames, lanes, quad_length, quad_selector
from quadpost.codecs.base import codec, names
from quadpost.codecs.bits import bitlen

RNG = np.random.default_rng(1)
CASES = {
    "empty": [],
    "one": [1],
    "two": [1, 2],
    "three": [1, 2, 3],
    "five": [5, 1, 1, 1, 9],
    "eight": list(range(1, 9)),
    "zeros": [0] * 128,
    "max32": [2**32 - 1] * 5,
    "powers": [2**i for i in range(32)],
    "geometric": RNG.geometric(0.1, 512).tolist(),
    "zipf": np.minimum(RNG.zipf(1.3, 700), 2**27).tolist(),
    "ones": [1] * 300,
    "wide": RNG.integers(1, 2**32, 130).tolist(),
    "outliers": ([1] * 100 + [2**31] + [1] * 40) * 3,
    "far outliers": [1] * 9 + [1000] + [1] * 500 + [2**20],
    "straddle": [1000] * 40,
}


def fits(c, values):
    return not (c.positive and 0 in values) and not (c.max_bits < 32 and values and max(values) >> c.max_bits)


@pytest.mark.parametrize("name", names())
def test_round_trip_and_equal_builds(name):
    c = codec(name)
    for values in CASES.values():
        if not fits(c, values):
            with pytest.raises(ValueError):
                c.encode(values)
            continue
        block = c.encode(values)
        for backend in c.backends:
            assert c.decode(block, backend).tolist() == values
            assert c.encode(values, backend) == block


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(1, 2**27), max_size=150), st.sampled_from(names()))
def test_round_trip_of_any_sequence(values, name):
    c = codec(name)
    assert c.decode(c.encode(values)).tolist() == values


@pytest.mark.parametrize("name", names())
def test_blocks_decoded_together(name):
    c = codec(name)
    held = [v for v in CASES.values() if fits(c, v)] * 2
    want = [x for v in held for x in v]
    for backend in c.backends:
        assert c.decode_many([c.encode(v) for v in held], backend).tolist() == want
    assert c.decode_many([]).tolist() == [] and c.decode_many([c.encode([])]).tolist() == []


@pytest.mark.parametrize("cg, ld", quad_length.WAYS)
def test_units_one_after_another(cg, ld):
    c = quad_length.quad_length(cg, ld)
    for values in CASES.values():
        if values:
            assert quad_length.decode_by_unit(c.encode(values), cg, ld).tolist() == values


def test_lane_codecs_pad_to_whole_vectors():
    for name in names():
        if name.startswith(("quad_", "ql_")):
            assert codec(name).encode(CASES["zipf"]).data_bits % 128 == 0


def test_selector_constants():
    assert [s for s, _, _ in quad_selector.SELECTORS] == list(range(10))
    assert all(n * b <= 32 for _, n, b in quad_selector.SELECTORS)


def test_twenty_integers():
    below, above = [40, 1, 2, 63] * 5, [64, 1, 2, 3] + [40, 1, 2, 63] * 4
    assert quad_selector.read_selectors(codec("quad_selector").encode(below)).tolist() == [5]
    assert quad_selector.read_selectors(codec("quad_selector").encode(above)).tolist() == [6, 5]


def test_lane_layout_of_one_to_eight():
    block = codec("quad_selector").encode(range(1, 9))
    assert quad_selector.read_selectors(block).tolist() == [3]
    assert [hex(w) for w in np.frombuffer(block.data, "<u4")] == ["0x51", "0x62", "0x73", "0x84"]


def test_length_descriptor_of_458():
    ld = quad_length.descriptors(np.array([458], np.uint64), 2)
    assert ld.tolist() == [5] and 2 * ld[0] == 10
    assert quad_length.write_complete(ld)[0] >> 3 == 0b11110
    assert quad_length.write_binary(ld, 2)[0] & 15 == 0b0100


def test_a_control_byte_in_parts():
    count, lengths, tail = quad_length.unary_table()
    assert (count[0b10110011], lengths[0b10110011][:3].tolist(), tail[0b10110011]) == (3, [2, 3, 1], 2)


def test_binary_fields():
    assert quad_length.BINARY_BITS == {1: 5, 2: 4, 4: 3, 8: 2}
    assert {cg: per for cg, (per, _) in quad_length.BINARY_UNIT.items()} == {1: 3, 2: 2, 4: 2, 8: 4}
    assert len(quad_length.binary_table(1)) == 2**15 and len(quad_length.binary_table(2)) == 256


@pytest.mark.parametrize("cg", [1, 2])
def test_incomplete_unary_needs_wide_units(cg):
    with pytest.raises(ValueError):
        quad_length.quad_length(cg, "iu")


def test_ways_of_reading_descriptors_agree():
    values = CASES["zipf"]
    for cg, ld in quad_length.WAYS:
        c = quad_length.quad_length(cg, ld)
        block = c.encode(values)
        assert quad_length.read_descriptors(block, cg, ld).tolist() == quad_length.read_descriptors(block, cg, ld, "bits").tolist()
        assert quad_length.decode_by_unit(block, cg, ld).tolist() == values
    assert quad_length.k_gamma().encode(values) == codec("ql_1_cu").encode(values)


def test_threshold_is_strict():
    need = np.ones(20, np.int64)
    need[:2] = 9
    assert frames.threshold_widths(need, 32, 0.1).tolist() == [9]
    assert frames.threshold_widths(np.append(need, 1), 32, 0.1).tolist() == [1]


def test_partition_of_two_halves():
    lengths, widths = frames._lane_partition(np.array([1] * 16 + [8] * 16), (32, 64, 128))
    assert (lengths * 4).tolist() == [64, 64] and widths.tolist() == [1, 8]
    assert int((8 + 4 * lengths * widths).sum()) == 592


def test_partition_against_every_partition():
    for _ in range(30):
        cells = RNG.integers(1, 20, RNG.integers(1, 12))
        need = np.repeat(cells, 8)

        def least(at):
            if at == len(cells):
                return 0
            return min(8 + 8 * k * int(cells[at : at + k].max()) + least(at + k) for k in (1, 2, 4) if at + k <= len(cells))

        lengths, widths = frames.partition(need, (8, 16, 32))
        assert int((8 + lengths * widths).sum()) == least(0)


def test_selection_against_a_plain_scan():
    for _ in range(20):
        maxima = RNG.integers(1, 2 ** int(RNG.integers(2, 32)), RNG.integers(1, 80)).astype(np.uint64)
        left, expected = maxima.tolist(), []
        while left:
            for s, n, b in quad_selector.SELECTORS:
                if all(x < 1 << b for x in left[:n]):
                    expected.append(s)
                    left = left[n:]
                    break
        assert quad_selector.select(maxima).tolist() == expected


def test_exceptions_of_quads_are_rarer():
    values = np.array(CASES["outliers"], np.uint64)
    need = bitlen(lanes.quad_or(values))
    width = frames.threshold_widths(need, 32, 0.1)
    for k, b in enumerate(width):
        of_quads = (need[k * 32 : k * 32 + 32] > b).mean()
        of_values = (bitlen(values)[k * 128 : k * 128 + 128] > b).mean()
        assert of_values <= of_quads < 0.1


def test_chain_forces_exceptions():
    flags = np.zeros(128, bool)
    flags[[3, 90]] = True
    assert frames.chain(flags, 4).tolist() == [3, 19, 35, 51, 67, 83, 90]


def test_pseudo_maximum_has_the_maximums_bits():
    x = np.array([4, 8, 0, 1], np.uint64)
    assert lanes.quad_or(x).tolist() == [13] and bitlen(lanes.quad_or(x)).tolist() == bitlen(lanes.quad_max(x)).tolist()


@pytest.mark.parametrize(
    "name, least", [("vbyte", 8), ("gvb", 10), ("g8iu", 9), ("g8cu", 9), ("ql_8_iu", 8.25), ("ql_8_cu", 8.25), ("ql_8_b", 8.5), ("ql_4_cu", 4.25), ("ql_4_b", 5), ("ql_2_b", 3), ("ql_2_cu", 2.25), ("ql_1_cu", 1.25), ("gamma", 1), ("quad_selector", 132 / 128), ("quad_bp128", 1 + 8 / 128)]
)
def test_lower_bounds(name, least):
    for values in ([1] * 1024, CASES["geometric"]):
        assert codec(name).bits(values) >= least * len(values) - 1e-9


def test_unary_descriptors_cost_less_and_coarse_units_more():
    """Observed trends on gap-like data; the exact sizes of real lists are in test_core."""
    v = CASES["geometric"]
    for ld in ("b", "cu"):
        assert codec(f"ql_2_{ld}").bits(v) < codec(f"ql_4_{ld}").bits(v) < codec(f"ql_8_{ld}").bits(v)
    assert all(codec(f"ql_{cg}_cu").bits(v) <= codec(f"ql_{cg}_b").bits(v) for cg in (1, 2, 4, 8))


def test_a_lifted_frame_holds_four_frames():
    v = np.array(CASES["geometric"])
    plain = frames.build(frames.Scheme("plain32", (32,)))
    for a, b in itertools.pairwise(range(0, 513, 128)):
        assert codec("quad_bp128").encode(v[a:b]).data_bits >= plain.encode(v[a:b]).data_bits


def test_lift_needs_whole_quads():
    with pytest.raises(ValueError):
        frames.lift(frames.PACKED_BINARY, "odd", (126,))
