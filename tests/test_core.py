import numpy as np
import pytest
from pyspark.sql import functions as F

from quadpost.codecs.base import codec
from quadpost.functions import expressions as E
from quadpost.operators import blocks as B
from quadpost.operators import corpus, search
from quadpost.operators.choose import choose_codec
from quadpost.operators.index import build_index, decode_postings, index_bits, merge_segments, write_index
from quadpost.plans import registry
from quadpost.sources import tables
from quadpost.sources.shared import written
from quadpost.streaming import ingest
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def found(spark):
    return corpus.postings(tables.collection(spark, SMALL, "documents")).cache()


SAMPLE = ["q_tf", "q_dgap", "q_dataset_stats", "q_seek_asof", "q_skip_blocks", "q_selector_modes", "q_iu_ctrl_bits", "q_afor_partition", "q_pfor_width", "q_exceptions", "q_bits_cube", "q_choose_codec", "q_and_topk", "q_or_topk", "q_or_wand", "q_or_maxscore", "q_set_not", "q_win_session", "q_decode_udtf", "q_bits_udaf", "q_pages_fields", "q_rel_postings_bits", "q_dense_ids"]


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_oracle(name, same):
    same(name, registry.queries(), registry.oracles())


def test_every_oracle_has_a_query():
    assert set(registry.oracles()) <= set(registry.queries())


def test_size_expressions_equal_the_encoders(spark):
    rng = np.random.default_rng(4)
    rows = [(i, [int(x) for x in v]) for i, v in enumerate([[1], [1] * 9, rng.geometric(0.05, 300), np.minimum(rng.zipf(1.4, 513), 2**26), rng.integers(1, 2**31, 70)])]
    df = spark.createDataFrame(rows, "i int, values array<bigint>")
    names = [*E.CLOSED, "ql_4_iu", "ql_8_iu", "quad_selector", "rice"]
    got = df.select("i", *[E.size_expr(n, F.col("values")).cast("long").alias(n) for n in names]).collect()
    for row in got:
        for n in names:
            assert row[n] == codec(n).bits(rows[row["i"]][1]), n


def test_no_python_in_size_expressions(spark):
    df = spark.range(1).select(F.array(F.lit(1).cast("long")).alias("v")).select(E.size_expr("ql_1_cu", F.col("v")))
    assert "Python" not in df._jdf.queryExecution().executedPlan().toString() and "Arrow" not in df._jdf.queryExecution().executedPlan().toString()


def test_encode_decode_keep_other_columns(spark):
    df = spark.createDataFrame([(7, [1, 2, 3], "x"), (8, [], "y")], "k int, values array<bigint>, codec2 string")
    back = B.roundtrip(df, "quad_pfor").orderBy("k").collect()
    assert [(r["k"], r["values"], r["codec2"]) for r in back] == [(7, [1, 2, 3], "x"), (8, [], "y")]


def test_index_reads_back_and_prunes(spark, found, tmp_path):
    index = build_index(found, "quad_afor", size=64)
    write_index(index, str(tmp_path / "index"), 3)
    stored = spark.read.parquet(str(tmp_path / "index"))
    assert sorted(map(tuple, decode_postings(stored).collect())) == sorted((r["term"], r["doc_id"], r["tf"]) for r in found.collect())
    plan = stored.where("term = 'the' AND first_doc <= 50 AND last_doc >= 20").select("term", "g_data")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(term,the)" in plan and "LessThanOrEqual(f" in plan and "t_data" not in plan


def test_short_lists_use_variable_bytes(spark):
    rows = [("short", i, 1) for i in range(63)] + [("long", i, 1) for i in range(64)]
    index = build_index(spark.createDataFrame(rows, "term string, doc_id bigint, tf bigint"), "quad_selector")
    assert {r["term"]: r["g_codec"] for r in index.collect()} == {"short": "vbyte", "long": "quad_selector"}


def test_shards_restart_gaps(spark):
    rows = [("t", d, 1) for d in (0, 5, 99, 100, 250)]
    g = corpus.gaps(spark.createDataFrame(rows, "term string, doc_id bigint, tf bigint"), 100)
    assert sorted((r["shard"], r["pos"], r["gap"]) for r in g.collect()) == [(0, 0, 1), (0, 1, 5), (0, 2, 94), (1, 0, 1), (2, 0, 51)]
    assert sorted(r["doc_id"] for r in corpus.doc_ids(g, 100).collect()) == [0, 5, 99, 100, 250]
    assert sorted(r["doc_id"] for r in decode_postings(build_index(spark.createDataFrame(rows, "term string, doc_id bigint, tf bigint"), shard_docs=100)).collect()) == [0, 5, 99, 100, 250]


def test_dense_ids(spark):
    df = spark.createDataFrame([(x,) for x in (30, 10, 99, 20)], "k int")
    assert sorted(map(tuple, corpus.dense_doc_ids(df, "k").collect())) == [(10, 0), (20, 1), (30, 2), (99, 3)]


@pytest.mark.parametrize("adaptive", ["true", "false"])
def test_dense_ids_keep_every_wide_row(spark, adaptive):
    before = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", adaptive)
    try:
        wide = spark.range(400_000, numPartitions=32).select((F.col("id") * 7919 % 1_000_003).alias("k"), F.repeat(F.sha2(F.col("id").cast("string"), 256), 8).alias("wide"), F.lit(1).alias("_part"))
        got = corpus.dense_doc_ids(wide, "k").select("k", "dense_id").orderBy("k").toPandas()
        assert got["dense_id"].tolist() == list(range(400_000)) and got["k"].is_unique
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", before)


def test_a_cluster_must_name_its_shared_folder():
    from types import SimpleNamespace

    from quadpost.sources import shared

    conf = lambda **held: SimpleNamespace(conf=SimpleNamespace(get=lambda k, default=None: held.get(k, default)))
    with pytest.raises(ValueError):
        shared.shared_dir(conf(**{"spark.master": "local-cluster[2,1,1024]"}))
    assert shared.shared_dir(conf(**{"spark.master": "yarn", "spark.checkpoint.dir": "hdfs://x"})) == "hdfs://x"


def test_wand_skips_and_stays_exact():
    rng = np.random.default_rng(2)
    lists = [(np.sort(rng.choice(3000, n, replace=False)), rng.random(n) * w) for n, w in ((40, 5.0), (900, 1.0), (2000, 0.4))]
    total = {}
    for docs, parts in lists:
        for d, p in zip(docs.tolist(), parts.tolist(), strict=True):
            total[d] = total.get(d, 0.0) + p
    best = sorted(((s, -d) for d, s in total.items()), reverse=True)[:10]
    heap, scored = search.wand(lists, 10, 0.0)
    assert np.allclose(sorted(heap, reverse=True), best) and scored < len(total)


def test_pruning_decodes_fewer_blocks_and_stays_exact(spark):
    """A rare term with high frequencies in a few ranges beside a common one everywhere."""
    rng = np.random.default_rng(5)
    rows = [("common", d, 1) for d in range(30_000) if rng.random() < 0.6] + [("rare", int(d), 9) for d in rng.choice(2000, 200, replace=False)] + [("fill", d, 20) for d in range(30_000)]
    found = spark.createDataFrame(rows, "term string, doc_id bigint, tf bigint").cache()
    lengths = found.groupBy("doc_id").agg(F.sum("tf").alias("len"))
    searcher = search.Searcher(build_index(found, "quad_bp128").cache(), lengths.cache())
    asked = corpus.dictionary(found).where("term != 'fill'").select(F.lit(1).cast("long").alias("query_id"), "term", "df").cache()
    bounds, _, live = searcher.prune(asked)
    every, few = searcher._blocks_of(asked).count(), searcher.blocks_in(asked, live.select("query_id", "range"), bounds).count()
    assert few * 4 < every
    want = sorted(map(tuple, searcher.or_topk(asked).collect()))
    assert sorted(map(tuple, searcher.or_wand(asked).collect())) == want and sorted(map(tuple, searcher.or_maxscore(asked).collect())) == want
    top_part = searcher.parts(asked).withColumn("range", F.floor(F.col("doc_id") / search.OR_RANGE_DOCS)).groupBy("term", "range").agg(F.max("part").alias("part"))
    assert top_part.join(bounds.groupBy("term", "range").agg(F.max("bound").alias("bound")), ["term", "range"], "left").where("bound IS NULL OR part > bound + 1e-9").isEmpty()


@pytest.mark.parametrize("mode", ["or_wand", "or_maxscore"])
def test_pruning_keeps_queries_whose_best_range_is_empty(spark, mode):
    """One block spans ranges without a posting, and all its ranges have the same bound."""
    gap = search.OR_RANGE_DOCS
    found = spark.createDataFrame([("thin", 0, 1), ("thin", 9 * gap, 1)] + [("fill", d * gap, 4) for d in range(10)], "term string, doc_id bigint, tf bigint").cache()
    lengths = found.where("term = 'fill'").select("doc_id", F.lit(5).cast("long").alias("len"))
    searcher = search.Searcher(build_index(found, "quad_bp128").cache(), lengths.cache())
    words = corpus.dictionary(found)
    asked = words.where("term = 'thin'").select(F.lit(1).cast("long").alias("query_id"), "term", "df").unionByName(words.select(F.lit(2).cast("long").alias("query_id"), "term", "df")).cache()
    want = sorted(map(tuple, searcher.or_topk(asked).collect()))
    assert len(want) == 12 and sorted(map(tuple, getattr(searcher, mode)(asked).collect())) == want


@pytest.mark.parametrize("mode", ["or_maxscore", "or_wand"])
def test_or_never_makes_rows_of_queries_times_postings(spark, mode):
    """Compressed blocks and lengths go to a range's task; decoded postings are joined with nothing."""
    found = spark.createDataFrame([(t, d, 1 + d % 5) for t in "ab" for d in range(20_000) if t == "a" or d % 3], "term string, doc_id bigint, tf bigint").cache()
    searcher = search.Searcher(written(build_index(found, "quad_bp128"), "index"), written(found.groupBy("doc_id").agg(F.sum("tf").alias("len")), "lengths"))
    asked = corpus.dictionary(found).select(F.explode(F.array(*[F.lit(q).cast("long") for q in range(5)])).alias("query_id"), "term", "df").where("query_id % 2 = 0 OR term = 'b'")
    asked = written(asked, "asked")
    best = getattr(searcher, mode)(asked)
    plan = best._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "MapInArrow" not in plan and "FlatMapGroupsInPandas" not in plan
    assert sorted(map(tuple, best.collect())) == sorted(map(tuple, searcher.or_topk(asked).collect()))


def test_sharded_postings_are_dealt_once_and_give_the_same_index(spark):
    docs = spark.createDataFrame([(1, "b a b"), (1, "a c"), (7, ""), (8, None), (205, "A a, d"), (301, "c")], "doc_id bigint, text string")
    rows = corpus.sharded_postings(docs, 100)
    assert sorted(map(tuple, rows.select("term", "doc_id", "tf").collect())) == sorted(map(tuple, corpus.postings(docs).collect()))
    ours, want = build_index(rows, shard_docs=100), build_index(corpus.postings(docs), shard_docs=100)
    assert sorted(map(str, ours.collect())) == sorted(map(str, want.select(*ours.columns).collect()))
    assert sorted(map(tuple, corpus.doc_lengths(docs).collect())) == sorted(map(tuple, corpus.postings(docs).groupBy("doc_id").agg(F.sum("tf")).collect()))
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        plan = build_index(rows, shard_docs=100)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert plan.count("REPARTITION_BY_COL") == 2 and plan.count("ReusedExchange") == 1  # the reused one names what it reads


def test_short_lists_are_encoded_together_as_alone():
    lists = [np.array(v, np.int64) for v in ([1], [], [300, 2**32 - 1, 0], list(range(200)), [])]
    assert codec("vbyte").encode_many(lists) == [codec("vbyte").encode(v) for v in lists]


def test_wand_leaves_ties_of_rounded_scores_to_the_ranking():
    found, _ = search.wand([(np.arange(12), np.array([1.0] + [1.0000003] * 10 + [0.5]))], 10, 0.0)
    assert sorted(-d for _, d in found) == list(range(11))


def test_codec_choice_for_speed(spark):
    df = spark.createDataFrame([([3] * 512,)], "values array<bigint>")
    assert choose_codec(df, ("vbyte", "quad_bp128", "gamma"), "speed").first()["chosen"] == "quad_bp128"


def test_segments_that_share_documents_are_refused(spark):
    rows = [(0, "a", 1, 1), (1, "a", 1, 1)]
    with pytest.raises(ValueError):
        merge_segments(spark.createDataFrame(rows, "seg int, term string, doc_id bigint, tf bigint"))


def test_stream_builds_the_same_index(spark, found, tmp_path):
    docs = tables.collection(spark, SMALL, "documents")
    docs.repartition(4).write.parquet(str(tmp_path / "in"))
    for _ in range(2):  # a second run finds nothing new and changes nothing
        ingest.ingest(ingest.read_documents(spark, str(tmp_path / "in")), str(tmp_path / "segments"), str(tmp_path / "ck"))
    segments = ingest.read_segments(spark, str(tmp_path / "segments"))
    assert segments.select("seg").distinct().count() == 4
    assert sorted(map(tuple, decode_postings(merge_segments(segments)).collect())) == sorted((r["term"], r["doc_id"], r["tf"]) for r in found.collect())
    one = index_bits(build_index(found)).first()
    assert index_bits(merge_segments(segments)).first() == one


def test_streamed_gaps_continue_over_batches(spark, tmp_path):
    for i, docs in enumerate(([2, 5], [9, 9, 20])):
        spark.createDataFrame([("t", d) for d in docs], "term string, doc_id bigint").coalesce(1).write.parquet(str(tmp_path / f"p{i}"))
    (tmp_path / "in").mkdir()
    found = []
    for i in range(2):
        for f in (tmp_path / f"p{i}").glob("*.parquet"):
            f.rename(tmp_path / "in" / f"{i}.parquet")
        stream = spark.readStream.schema("term string, doc_id bigint").parquet(str(tmp_path / "in"))
        query = ingest.streamed_gaps(stream).writeStream.option("checkpointLocation", str(tmp_path / "ck")).outputMode("append").trigger(availableNow=True).foreachBatch(lambda df, _: found.extend(map(tuple, df.collect()))).start()
        query.awaitTermination()
    assert sorted(found) == [("t", 2, 3), ("t", 5, 3), ("t", 9, 4), ("t", 20, 11)]


def test_repeated_and_late_events_are_dropped(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:10:00"), (2, "2024-01-01 05:00:00")]
    spark.createDataFrame(rows, "id int, t string").select("id", F.col("t").cast("timestamp").alias("t")).coalesce(1).write.parquet(str(tmp_path / "in"))
    got = []
    stream = spark.readStream.schema("id int, t timestamp").parquet(str(tmp_path / "in"))
    ingest.unrepeated(stream, "id", "t").writeStream.option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).foreachBatch(lambda df, _: got.extend(r["id"] for r in df.collect())).start().awaitTermination()
    assert sorted(got) == [1, 2]


def test_exact_sizes_of_whole_lists(spark):
    """The exact bit totals of the long lists of documents at the second scale, one block per list."""
    d = "/root/testdata/sf0.01"
    g = corpus.gaps(corpus.long_lists(corpus.postings(tables.collection(spark, d, "documents"))))
    whole = corpus.blocks(g, 1 << 20).select("term", F.col("gaps").alias("values"))
    got = {r["codec"]: r["b"] for r in B.sizes(whole, ["gamma", "vbyte", "gvb", "g8cu", "quad_selector", *[f"ql_{c}_{w}" for c in (1, 2, 4, 8) for w in ("b", "cu")]]).groupBy("codec").agg(F.sum("bits").alias("b")).collect()}
    # Measured beforehand on these tables.
    assert got == {
        "gamma": 240746,
        "vbyte": 431176,
        "gvb": 540048,
        "g8cu": 496296,
        "quad_selector": 302016,
        "ql_1_b": 305632,
        "ql_1_cu": 284696,
        "ql_2_b": 314216,
        "ql_2_cu": 289952,
        "ql_4_b": 363880,
        "ql_4_cu": 328032,
        "ql_8_b": 482528,
        "ql_8_cu": 469168,
    }


def test_speeds_and_ablations(spark):
    from quadpost.plans import workloads

    rows = workloads.codec_sweep(spark, SMALL, names=["quad_selector", "vbyte"], runs=1, sampled=False).collect()
    assert {(r["codec"], r["backend"]) for r in rows} == {(c, b) for c in ("quad_selector", "vbyte") for b in ("lanes", "scalar")} and all(r["decode_mis"] > 0 for r in rows)
    assert all(r["on_mis"] > 0 for r in workloads.ablations(np.random.default_rng(0).geometric(0.1, 4096), 2))


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).columns == ["query_id", "rank", "doc_id", "score"]
    assert set(registry.queries()) <= set(entry.queries())


def test_batch_segments_merge_to_the_same_index(spark, found, tmp_path):
    from quadpost.operators.index import build_segments, write_segments

    docs = tables.collection(spark, SMALL, "documents")
    write_segments(build_segments(docs, 100_000), str(tmp_path / "s"))
    stored = spark.read.schema("term string, doc_id bigint, tf bigint, seg int").parquet(str(tmp_path / "s"))
    assert stored.select("seg").distinct().count() > 3
    assert index_bits(merge_segments(stored)).first() == index_bits(build_index(found)).first()


@pytest.mark.parametrize("kind", ["json", "csv", "orc", "text"])
def test_sources(spark, tmp_path, kind):
    rows = [(0, "alpha beta"), (1, "gamma, \"delta\"")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    path = str(tmp_path / kind)
    {"json": lambda: df.write.json(path), "csv": lambda: df.write.option("header", "true").option("escape", "\"").csv(path), "orc": lambda: df.write.orc(path), "text": lambda: df.select("text").write.text(path)}[kind]()
    got = sorted(map(tuple, tables.read_texts(spark, path, kind).collect()))
    assert [i for i, _ in got] == [0, 1] and got[0] == rows[0]
