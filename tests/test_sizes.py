"""The SQL sizes of every codec against its encoder, and whole indexes against built ones."""

import duckdb
import numpy as np
import pytest

from quadpost.codecs.base import codec, names
from quadpost.operators import corpus
from quadpost.operators.index import build_index, index_bits, index_sizes
from quadpost.plans import registry, sql
from quadpost.plans.size_sql import BLK, FORMS
from quadpost.sources import tables
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def lists():
    rng = np.random.default_rng(7)
    out = {"ones": [1] * 700, "one": [5], "six": [1, 2, 70_000, 3, 4, 9]}
    for k, n in enumerate((64, 129, 512, 513, 1500)):
        v = rng.geometric(0.05, n)
        far = rng.random(n) < 0.04 * k  # exceptions, some of them far from the last
        out[f"list{k}"] = np.where(far, rng.integers(1 << 9, 1 << 20, n), v).tolist()
    return out


@pytest.fixture(scope="module")
def con(lists):
    con = duckdb.connect()
    con.execute("CREATE TABLE gaps (term VARCHAR, pos BIGINT, gap BIGINT)")
    for term, values in lists.items():
        con.executemany("INSERT INTO gaps VALUES (?, ?, ?)", [(term, i, int(v)) for i, v in enumerate(values)])
    return con


@pytest.mark.parametrize("name", names())
def test_sql_size_is_the_encoders(name, con, lists):
    text = f"WITH RECURSIVE {BLK.format(values='gap', source='gaps')}, {sql.ROWS.format(values='gap')}, {sql.QUADS} SELECT term, block, bits FROM {FORMS[name]}"
    got = {(t, b): int(bits) for t, b, bits in con.execute(text).fetchall()}
    want = {(t, at // 512): codec(name).encode(np.array(v[at : at + 512])).bits for t, v in lists.items() for at in range(0, len(v), 512)}
    assert got == want


@pytest.mark.parametrize("name", ["q_ratio_documents_gap", "q_ratio_quality_tf", "q_index_size", "q_sweep_quad_frames", "q_sweep_quad_afor", "q_sweep_quad_pfor", "q_family_bits", "q_relation_gaps", "q_bits_simple16"])
def test_size_query_equals_oracle(name, same):
    same(name, registry.queries(), registry.oracles())


def test_index_sizes_are_those_of_built_indexes(spark):
    found = corpus.postings(tables.collection(spark, SMALL, "documents")).cache()
    by_name = {r["codec"]: r for r in index_sizes(found, ("quad_pfor", "simple9")).collect()}
    for name, row in by_name.items():
        built = index_bits(build_index(found, name)).first()
        assert built.asDict() == {c: row[c] for c in built.asDict()}


def test_index_sizes_of_nothing(spark):
    empty = spark.createDataFrame([], "term string, doc_id bigint, tf bigint")
    assert index_sizes(empty, ("vbyte",)).collect() == []
