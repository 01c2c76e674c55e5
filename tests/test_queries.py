"""Queries against their oracles at the smallest scale, and the physical plans that scale rests on."""

import datetime
import decimal
import math
import re

import pytest
from pyspark.sql import functions as F

from treepack import registry

registry.load_all()
PICKED = (
    "byte_histogram byte_histogram_rel huffman_lengths canonical_codes nbh_bu_roundtrip nbh_td_roundtrip ans_roundtrip base_table11 wire_right_counts wire_corrupt_rows node_skew_report "
    "pivot_rel_bitmaps pivot_rel_decode_bu pivot_rel_decode_td nbh_roundtrip_events nbh_roundtrip_lineitem puc_bitmaps lz_roundtrip cd_positions cd_histogram cd_rank probe_vectorised "
    "join_range_row_blocks join_asof_codebook join_interval_events agg_cube_bytes win_sessionize set_except_all sub_lateral udf_roundtrip udtf_symbols src_datasource_treepack st_tumbling_hist st_late_drop degenerate_streams"
).split()


def plain(v):
    if isinstance(v, float | decimal.Decimal):
        return "nan" if math.isnan(v) else float(f"{float(v):.9g}")
    if isinstance(v, bytes | bytearray):
        return bytes(v).hex()
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    if isinstance(v, list | tuple):
        return tuple(plain(x) for x in v)
    return v


@pytest.mark.parametrize("name", PICKED)
def test_query_equals_oracle(spark, duck, sf, name):
    df = registry.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted(repr(tuple(plain(v) for v in r)) for r in df.select(*cols).collect())
    want = duck.sql(registry.ORACLES[name])
    assert sorted(want.columns) == cols
    quoted = ", ".join(f'"{c}"' for c in cols)
    assert got == sorted(repr(tuple(plain(v) for v in r)) for r in duck.sql(f"SELECT {quoted} FROM ({registry.ORACLES[name]})").fetchall())


def plan(df) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_encoding_shuffles_nothing_and_prunes_columns(spark, sf):
    from treepack.operators import stats
    from treepack.operators.blocks import encode_blocks
    from treepack.sources.streams import build_stream, to_blocks
    from treepack.sources.tables import staged

    values = build_stream(spark, sf, "doc_en")
    books = staged(stats.codebooks(stats.byte_histogram(values)))
    text = plan(encode_blocks(to_blocks(values), books))
    assert "BroadcastHashJoin" in text and "Exchange hashpartitioning" not in text
    assert "ReadSchema: struct<doc_id:bigint,text:string,lang:string>" in text and "EqualTo(lang,en)" in text


def test_block_sink_prunes_folders_and_pushes_filters(spark, sf):
    text = plan(registry.QUERIES["src_blocks"](spark, sf))
    assert "PartitionFilters: [isnotnull(stream_id" in text and "EqualTo(block_no,0)" in text


@pytest.mark.parametrize(("name", "operator"), [("join_shuffle_hash", "ShuffledHashJoin"), ("join_sort_merge", "SortMergeJoin"), ("probe_spark", "BroadcastHashJoin"), ("sort_limit_offset", "TakeOrderedAndProject"), ("agg_cube_bytes", "Expand"), ("topk_symbols_per_lang", "WindowGroupLimit")])
def test_physical_operator(spark, sf, name, operator):
    assert operator in plan(registry.QUERIES[name](spark, sf))


def test_data_source_sees_filters(spark, sf, tmp_path):
    from treepack.sources import datasource
    from treepack.sources.streams import build_stream, to_blocks

    datasource.register(spark)
    rows = to_blocks(build_stream(spark, sf, "doc_en")).select("stream_id", "value_id", "block_no", "raw")
    rows.write.format("treepack").mode("append").save(f"{tmp_path}/t")
    first = spark.read.format("treepack").load(f"{tmp_path}/t").where("block_no = 1")
    assert first.count() == rows.where("block_no = 1").count() > 0


def test_state_of_a_block_builder_survives_a_restart(spark, sf, tmp_path):
    from treepack.streaming import ops

    src = f"{tmp_path}/in"
    schema = "k string, v string"
    stream = lambda: ops.block_builder(spark.readStream.schema(schema).parquet(src), "k", "v", 10).writeStream.option("checkpointLocation", f"{tmp_path}/c").format("parquet").option("path", f"{tmp_path}/out").trigger(availableNow=True).start().awaitTermination(60)
    for part in ("abcdef", "ghijkl"):
        spark.createDataFrame([("x", part)], schema).write.mode("append").parquet(src)
        stream()
    out = spark.read.parquet(f"{tmp_path}/out").collect()
    assert [(r.block_no, bytes(r.raw)) for r in out] == [(0, b"abcdefghij")]


def test_every_query_but_reports_has_an_oracle():
    assert len(registry.QUERIES) > 220
    assert len(registry.ORACLES) > 200


def test_table_of_a_bitmap_rounds_halves_like_its_sql(spark, duck):
    from treepack.plans.selective import choose_table
    from treepack.queries.codec import table_id

    rows = [(n, r) for n in (8, 40, 200, 1000, 5000) for r in range(n + 1)]
    got = [x[0] for x in spark.createDataFrame(rows, "n long, n_right long").select(table_id(F.col("n"), F.col("n_right"))).collect()]
    sql = "least(greatest(floor(100 * greatest(r, n - r) / n + 0.5), 50), 99)::BIGINT - 49"
    want = [duck.sql(f"SELECT {sql} FROM (SELECT {n}::BIGINT AS n, unnest(range({n + 1})) AS r)").fetchall() for n in (8, 40, 200, 1000, 5000)]
    assert got == choose_table(*zip(*rows, strict=True))[0].tolist() == [x[0] for w in want for x in w]


def test_relational_decoders_shuffle_no_row_per_bit(spark, sf):
    for name in ("pivot_rel_decode_td", "pivot_rel_decode_bu"):
        text = plan(registry.QUERIES[name](spark, sf))
        assert "Window" not in text and "SortMergeJoin" not in text and "Exchange hashpartitioning" not in text


def test_relational_forms_take_repeated_ids_empty_and_multi_block_values(spark):
    from treepack.operators import relational, stats
    from treepack.sources.streams import to_blocks

    texts = [(1, b"abracadabra" * 900), (1, b"abracadabra" * 900), (2, b""), (3, b"z"), (4, bytes(range(256)) * 70)]
    values = spark.createDataFrame([("s", k, bytearray(t)) for k, t in texts], "stream_id string, value_id long, raw binary")
    codes = stats.canonical_codes(stats.code_lengths(stats.codebooks(stats.byte_histogram(values), max_len=15, floor=4096)))
    pivoted = relational.pivot(to_blocks(values), codes)
    want = sorted((v, at // 8192, at % 8192, x) for v, t in texts for at, x in enumerate(t))
    for decode in (relational.decode_topdown, relational.decode_bottomup):
        assert sorted((r.value_id, r.block_no, r.pos, r.sym) for r in decode(pivoted, codes).collect()) == want
    code = {r.sym: r.code for r in codes.collect()}
    bits: dict = {}
    for v, block, _, x in want:
        for d, c in enumerate(code[x]):
            bits[v, block, code[x][:d]] = bits.get((v, block, code[x][:d]), "") + c
    got = relational.bitmaps(relational.pivot(relational.interleaved(to_blocks(values)), codes)).collect()
    assert len(got) == len(bits) and {(r.value_id, r.block_no, r.prefix): r.bitmap for r in got} == bits


def test_ratios_build_their_streams_once(spark, sf):
    from treepack.queries.measures import ratios

    assert "documents.parquet" not in plan(ratios(spark, sf, ("doc_de",)))


@pytest.mark.parametrize("name", "ans_gate_examples ans_static_vs_custom ans_two_cursors ans_xor_marker".split())
def test_examples_on_events_equal_their_oracles(spark, duck, sf, name):
    test_query_equals_oracle(spark, duck, sf, name)


@pytest.mark.parametrize("name", "ans_gate_examples ans_static_vs_custom ans_two_cursors ans_xor_marker bench_golomb bench_kernels_bu bench_kernels_td bench_tans_cursors bench_td_grid".split())
def test_measures_read_a_given_table(spark, sf, name):
    df = registry.QUERIES[name](spark, sf)
    assert "events.parquet" in plan(df) and df.count() > 0


def test_codec_reports_keep_no_results_of_other_queries(spark, sf):
    from treepack.queries import measures

    for like, names in (("encode", {"doc_es"}), ("naive top-down|classic table", {"doc_es", "doc_fr"})):
        df = measures.codec_rates(spark, sf, sorted(names), like=like)
        assert "documents.parquet" in plan(df)
        rows = df.collect()
        assert {r.stream_id for r in rows} == names and all(re.search(like, r.what) for r in rows)
    assert not hasattr(measures, "_MEASURED")
