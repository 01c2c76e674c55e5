"""Relational operators around the codec: joins, aggregates, windows, sorting, sets, subqueries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.queries import sql
from treepack.queries.both import both
from treepack.queries.common import codes_of, hist_of
from treepack.registry import query
from treepack.sources.streams import build_stream
from treepack.sources.tables import load, small

# --- projection and filters ------------------------------------------------------

query("proj_stream_bytes", "2.17", "SELECT doc_id, strlen(text)::BIGINT AS n_bytes, length(text)::BIGINT AS chars, strlen(text) / length(text) AS bytes_per_char FROM documents WHERE length(text) > 0")(
    lambda spark, d: load(spark, d, "documents").where("length(text) > 0").select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.length("text").cast("long").alias("chars"), (F.octet_length("text") / F.length("text")).alias("bytes_per_char"))
)
both("filter_langs", "2.17", "SELECT doc_id, lang, n_chars FROM {documents} WHERE lang IN ('de', 'fr') AND n_chars BETWEEN 500 AND 5000")
both("filter_like", "2.17", "SELECT p_partkey, p_name FROM {part} WHERE p_name LIKE '%e%' AND p_type LIKE '%R%'")
both("filter_null_safe", "2.17", "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 0", "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality <=> NULL OR l.quality = 0")
both("filter_between_in", "2.17", "SELECT o_orderkey, o_orderpriority FROM {orders} WHERE o_totalprice BETWEEN 1000 AND 100000 AND o_orderstatus IN ('O', 'P')")

# --- joins -----------------------------------------------------------------------


@query("join_broadcast_codes", "2.17", f"WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_fr'])}), {sql.codes(sql.hist('SELECT * FROM src'))} SELECT value_id, sum(len)::BIGINT AS bits FROM src JOIN codes USING (stream_id, sym) GROUP BY value_id")
def join_broadcast_codes(spark, d):
    """Code bits of each document: its byte counts meet the broadcast code table."""
    values = build_stream(spark, d, "doc_fr")
    codes = codes_of(stats.codebooks(stats.byte_histogram(values), max_len=15, floor=4096)).drop("stream_id")
    per_doc = stats.byte_histogram(values, ("value_id",))
    return per_doc.join(small(codes), "sym").groupBy("value_id").agg(F.sum(F.col("cnt") * F.col("len")).alias("bits"))


_LO = "SELECT o_orderstatus, count(*)::BIGINT AS rows_, sum(strlen(l_returnflag))::BIGINT AS flag_bytes FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus"


def _lineitem_orders(hint: str):
    def run(spark, d):
        o = load(spark, d, "orders").select("o_orderkey", "o_orderstatus").hint(hint)
        j = load(spark, d, "lineitem").select("l_orderkey", "l_returnflag").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
        return j.groupBy("o_orderstatus").agg(F.count("*").alias("rows_"), F.sum(F.octet_length("l_returnflag")).alias("flag_bytes"))

    return run


query("join_shuffle_hash", "2.17", _LO)(_lineitem_orders("shuffle_hash"))
query("join_sort_merge", "2.17", _LO)(_lineitem_orders("merge"))


@query("join_theta_prefix", "2.17", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_es'])))}, p AS (SELECT DISTINCT left(code, x.d) AS prefix FROM codes, unnest(range(len)) AS x(d)) SELECT prefix, sum(cnt)::BIGINT AS weight FROM p JOIN codes ON starts_with(code, prefix) JOIN hist USING (stream_id, sym) GROUP BY prefix")
def join_theta_prefix(spark, d):
    """Weight of each tree node: the codes that start with its prefix; both sides have at most 256 codes' prefixes."""
    hist = hist_of(spark, d, ["doc_es"])
    codes = codes_of(stats.codebooks(hist, max_len=15, floor=4096)).join(hist, ["stream_id", "sym"]).select("code", "len", "cnt")
    prefixes = codes.select(F.explode(F.transform(F.sequence(F.lit(0), F.col("len") - 1), lambda k: F.col("code").substr(F.lit(1), k))).alias("prefix")).distinct()
    return small(prefixes).join(codes, F.expr("startswith(code, prefix)")).groupBy("prefix").agg(F.sum("cnt").alias("weight"))


@query("join_range_row_blocks", "2.17", "WITH o AS (SELECT doc_id, source, strlen(text) AS n, sum(strlen(text)) OVER (PARTITION BY source ORDER BY doc_id) - strlen(text) AS b FROM documents WHERE strlen(text) > 0), k AS (SELECT source, unnest(range(((max(b + n) + 8191) // 8192)::BIGINT)) AS block FROM o GROUP BY source) SELECT doc_id, count(*)::BIGINT AS blocks FROM o JOIN k ON o.source = k.source AND b < (block + 1) * 8192 AND b + n > block * 8192 GROUP BY doc_id")
def join_range_row_blocks(spark, d):
    """Blocks that each document's byte range touches, by source: ranges become the block numbers they cover, and the join is an equality."""
    docs = load(spark, d, "documents").where("octet_length(text) > 0").select("doc_id", "source", F.octet_length("text").cast("long").alias("n"))
    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    docs = docs.withColumn("b", F.coalesce(F.sum("n").over(w), F.lit(0)))
    touched = docs.select("doc_id", "source", F.explode(F.expr("sequence(b div 8192, (b + n - 1) div 8192)")).alias("block"))
    blocks = docs.groupBy("source").agg(F.max(F.expr("(b + n - 1) div 8192")).alias("last")).select("source", F.explode(F.expr("sequence(0L, last)")).alias("block"))
    return touched.join(blocks, ["source", "block"]).groupBy("doc_id").agg(F.count("*").alias("blocks"))


@query("join_asof_codebook", "2.17", "SELECT e.event_id, v.version FROM events e ASOF JOIN (SELECT date_trunc('day', ts) AS valid_from, count(*)::BIGINT AS version FROM events WHERE event_type = 'error' GROUP BY 1) v ON e.ts >= v.valid_from")
def join_asof_codebook(spark, d):
    """The latest daily version at each event: versions are as few as days, so each goes to the days it holds for, and days are joined."""
    e = load(spark, d, "events")
    v = e.where("event_type = 'error'").groupBy(F.date_trunc("day", "ts").alias("valid_from")).agg(F.count("*").alias("version"))
    span = v.withColumn("until", F.lead("valid_from").over(Window.orderBy("valid_from")))  # one row a day
    last = e.agg(F.max(F.date_trunc("day", "ts")).alias("last"))
    days = span.crossJoin(F.broadcast(last)).select("version", F.explode(F.expr("sequence(to_date(valid_from), to_date(coalesce(until - interval 1 day, last)), interval 1 day)")).alias("day"))
    return e.select("event_id", F.to_date("ts").alias("day")).join(small(days), "day").select("event_id", "version")


@query("join_interval_events", "2.17", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def join_interval_events(spark, d):
    """Pairs of one user within ten minutes: equality on user and ten-minute slot, each event also in the slot before its own."""
    e = load(spark, d, "events").select("user_id", "event_id", "ts", F.expr("unix_micros(cast(ts as timestamp)) div 600000000").alias("slot"))
    a = e.select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("t1"), F.explode(F.array("slot", F.col("slot") + 1)).alias("slot"))
    b = e.select("user_id", F.col("event_id").alias("second_id"), F.col("ts").alias("t2"), "slot")
    return a.join(b, ["user_id", "slot"]).where("t2 > t1 and t2 <= t1 + interval 10 minutes").select("first_id", "second_id")


query("join_semi_labeled", "2.17", "SELECT doc_id, lang FROM documents SEMI JOIN labels USING (doc_id)")(lambda spark, d: load(spark, d, "documents").join(load(spark, d, "labels"), "doc_id", "left_semi").select("doc_id", "lang"))


def _alphabet(lang: str) -> str:
    return f"SELECT DISTINCT sym FROM ({sql.rows([f'doc_{lang}'])})"


def _alpha(spark, d, lang):
    return hist_of(spark, d, [f"doc_{lang}"]).select("sym", "cnt")


query("join_anti_uncoded", "2.17", f"SELECT sym FROM ({_alphabet('fr')}) ANTI JOIN ({_alphabet('en')}) e USING (sym)")(lambda spark, d: _alpha(spark, d, "fr").join(_alpha(spark, d, "en"), "sym", "left_anti").select("sym"))
_CNT = {x: f"(SELECT sym, count(*)::BIGINT AS {x} FROM ({sql.rows([f'doc_{x}'])}) GROUP BY sym)" for x in ("de", "es")}
for _how, _name in (("left", "join_left_outer"), ("right", "join_right_outer"), ("full", "join_full_alphabets")):
    query(_name, "2.17", f"SELECT sym, de, es FROM {_CNT['de']} a {_how.upper()} JOIN {_CNT['es']} b USING (sym)")(
        lambda spark, d, h=_how: _alpha(spark, d, "de").withColumnRenamed("cnt", "de").join(_alpha(spark, d, "es").withColumnRenamed("cnt", "es"), "sym", h).select("sym", "de", "es")
    )


@query("join_cross_gates", "2.17", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_es'])))}, {sql.NODES} SELECT g.s AS min_skew, count(*) FILTER (WHERE greatest(n_right / n, 1 - n_right / n) > g.s)::BIGINT AS nodes FROM nodes_, (VALUES (0.55), (0.625), (0.75), (0.9)) g(s) GROUP BY g.s".replace("(VALUES (0.55)", "(VALUES (0.55::DOUBLE)"))
def join_cross_gates(spark, d):
    """Nodes that pass each of four gates: a few hundred nodes by a grid of four, a product of two small sides."""
    from treepack.plans.selective import skew_report

    hist = hist_of(spark, d, ["doc_es"])
    nodes = skew_report(hist, codes_of(stats.codebooks(hist, max_len=15, floor=4096)))
    grid = spark.createDataFrame([(x,) for x in (0.55, 0.625, 0.75, 0.9)], "min_skew double")
    return nodes.crossJoin(F.broadcast(grid)).groupBy("min_skew").agg(F.count_if(F.col("skew") > F.col("min_skew")).alias("nodes"))


both("join_self_delta", "2.17", "SELECT a.l_orderkey, a.l_linenumber, a.l_partkey, b.l_partkey AS next_part, a.l_suppkey, b.l_suppkey AS next_supp FROM {lineitem} a JOIN {lineitem} b ON a.l_orderkey = b.l_orderkey AND b.l_linenumber = a.l_linenumber + 1")
both("join_multi_star", "2.17", "SELECT r_name, count(*) AS lines, sum(l_quantity) AS quantity FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name")

# --- aggregates ------------------------------------------------------------------

query("agg_hist_lang", "2.17", " UNION ALL ".join(f"SELECT '{x}' AS lang, sym, count(*)::BIGINT AS cnt FROM ({sql.rows([f'doc_{x}'])}) GROUP BY sym" for x in ("en", "de", "fr", "es")))(
    lambda spark, d: stats.byte_histogram(load(spark, d, "documents").where("text is not null").select("lang", F.col("text").cast("binary").alias("raw")), ("lang",))
)


@query("agg_sort_based", "2.17", "SELECT o_custkey, string_agg(o_orderstatus, '' ORDER BY o_orderkey) AS statuses FROM orders GROUP BY o_custkey")
def agg_sort_based(spark, d):
    g = load(spark, d, "orders").groupBy("o_custkey").agg(F.array_sort(F.collect_list(F.struct("o_orderkey", "o_orderstatus"))).alias("r"))
    return g.select("o_custkey", F.array_join(F.transform("r", lambda x: x["o_orderstatus"]), "").alias("statuses"))


query("agg_alphabet", "2.17", "SELECT stream_id, count(DISTINCT sym)::BIGINT AS symbols, count(DISTINCT sym % 16)::BIGINT AS low_nibbles FROM (" + sql.rows(["doc_de", "doc_es"]) + ") GROUP BY stream_id")(
    lambda spark, d: hist_of(spark, d, ["doc_de", "doc_es"]).groupBy("stream_id").agg(F.count_distinct("sym").alias("symbols"), F.count_distinct(F.col("sym") % 16).alias("low_nibbles"))
)
query("agg_approx_distinct", "2.17", "SELECT count(DISTINCT user_id)::BIGINT AS users, true AS close FROM events")(
    lambda spark, d: load(spark, d, "events").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("about")).select("users", (F.abs(F.col("about") - F.col("users")) <= 0.05 * F.col("users")).alias("close"))
)
_BYTES = "SELECT lang, source, sum(strlen(text))::BIGINT AS n_bytes, grouping({g})::INT AS g FROM documents GROUP BY {w}"


def _grouped(kind: str):
    def run(spark, d):
        docs = load(spark, d, "documents").withColumn("n", F.octet_length("text"))
        return getattr(docs, kind)("lang", "source").agg(F.sum("n").alias("n_bytes"), F.grouping_id().cast("int").alias("g"))

    return run


query("agg_rollup_bytes", "2.17", _BYTES.format(g="lang, source", w="ROLLUP (lang, source)"))(_grouped("rollup"))
query("agg_cube_bytes", "2.17", _BYTES.format(g="lang, source", w="CUBE (lang, source)"))(_grouped("cube"))
both("agg_grouping_sets", "2.17", "SELECT lang, source, count(*) AS docs FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())")
both("agg_percentile_blocks", "2.17", "SELECT lang, quantile_cont(strlen(text), 0.5) AS median, quantile_cont(strlen(text), 0.9) AS p90 FROM {documents} WHERE lang IS NOT NULL GROUP BY lang", "SELECT lang, percentile(octet_length(text), 0.5) AS median, percentile(octet_length(text), 0.9) AS p90 FROM {documents} WHERE lang IS NOT NULL GROUP BY lang")


@query("agg_best_codec", "2.17", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_de', 'doc_fr'])))}, s AS (SELECT stream_id, 'raw' AS codec, sum(cnt)::BIGINT AS n_bytes FROM hist GROUP BY 1 UNION ALL SELECT stream_id, 'huffman', 128 + (sum(cnt * len)::BIGINT + 7) // 8 FROM hist JOIN codes USING (stream_id, sym) GROUP BY 1 UNION ALL SELECT stream_id, 'fixed', (sum(cnt)::BIGINT * ceil(log2(count(*)))::BIGINT + 7) // 8 FROM hist GROUP BY 1) SELECT stream_id, arg_min(codec, n_bytes) AS best, min(n_bytes) AS n_bytes FROM s GROUP BY 1")
def agg_best_codec(spark, d):
    """The smallest of raw, fixed-width and Huffman by their size formulas."""
    hist = hist_of(spark, d, ["doc_de", "doc_fr"])
    lens = stats.code_lengths(stats.codebooks(hist, max_len=15, floor=4096))
    raw = hist.groupBy("stream_id").agg(F.sum("cnt").alias("n"), F.count("*").alias("k"))
    coded = hist.join(lens, ["stream_id", "sym"]).groupBy("stream_id").agg(F.sum(F.col("cnt") * F.col("len")).alias("bits"))
    rows = raw.join(coded, "stream_id").select("stream_id", F.expr("stack(3, 'raw', n, 'huffman', 128 + (bits + 7) div 8, 'fixed', (n * cast(ceil(log2(k)) as long) + 7) div 8) as (codec, n_bytes)"))
    return rows.groupBy("stream_id").agg(F.min_by("codec", "n_bytes").alias("best"), F.min("n_bytes").alias("n_bytes"))


_TEN = (32, 97, 101, 105, 110, 111, 114, 115, 116, 117)


@query("agg_pivot_symbols", "2.17", "SELECT sym, " + ", ".join(f"count(*) FILTER (WHERE stream_id = 'doc_{x}')::BIGINT AS {x}" for x in ("en", "de", "fr", "es")) + f" FROM ({sql.rows(['doc_en', 'doc_de', 'doc_fr', 'doc_es'])}) WHERE sym IN {_TEN} GROUP BY sym")
def agg_pivot_symbols(spark, d):
    h = hist_of(spark, d, ["doc_en", "doc_de", "doc_fr", "doc_es"]).where(F.col("sym").isin(*_TEN)).withColumn("lang", F.substring("stream_id", 5, 2))
    return h.groupBy("sym").pivot("lang", ["en", "de", "fr", "es"]).agg(F.sum("cnt"))


both("agg_popcount", "2.17", "SELECT event_type, sum(bit_count(user_id))::BIGINT AS ones, bit_and(user_id) AS all_, bit_or(user_id) AS any_, bit_xor(user_id) AS odd FROM {events} GROUP BY event_type", "SELECT event_type, sum(bit_count(user_id)) AS ones, bit_and(user_id) AS all_, bit_or(user_id) AS any_, bit_xor(user_id) AS odd FROM {events} GROUP BY event_type")
both("agg_having_filter", "2.17", "SELECT user_id, count(*) FILTER (WHERE event_type = 'error') AS errors, count_if(value > 50)::BIGINT AS high FROM {events} GROUP BY user_id HAVING count(*) > 3", "SELECT user_id, count(*) FILTER (WHERE event_type = 'error') AS errors, count_if(value > 50) AS high FROM {events} GROUP BY user_id HAVING count(*) > 3")


@query("agg_bitmap_distinct", "2.17", "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY event_type")
def agg_bitmap_distinct(spark, d):
    """Distinct users by bitmaps of 32768 bits, a bucket of ids each."""
    part = load(spark, d, "events").groupBy("event_type", F.bitmap_bucket_number("user_id").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("user_id")).alias("bits"))
    return part.groupBy("event_type").agg(F.sum(F.bitmap_count("bits")).alias("users"))


both("agg_stats", "2.17", "SELECT lang, round(stddev(n_chars), 3) AS sd, round(var_pop(n_chars), 2) AS var, round(corr(n_chars, doc_id), 6) AS corr, round(covar_samp(n_chars, doc_id), 2) AS cov FROM {documents} GROUP BY lang")

# --- windows ---------------------------------------------------------------------

query("win_node_index", "2.17", f"SELECT value_id, pos::INT AS pos, (row_number() OVER (PARTITION BY value_id, sym % 2 ORDER BY pos) - 1)::INT AS idx FROM ({sql.rows(['doc_es'])})")(
    lambda spark, d: build_stream(spark, d, "doc_es").where("octet_length(raw) > 0").select("value_id", F.hex("raw").alias("h"), F.explode(F.expr("sequence(0, octet_length(raw) - 1)")).alias("pos"))
    .withColumn("bit", F.conv(F.expr("substring(h, 2 * pos + 1, 2)"), 16, 10).cast("int") % 2)
    .select("value_id", "pos", (F.row_number().over(Window.partitionBy("value_id", "bit").orderBy("pos")) - 1).alias("idx"))
)


@query("win_rank_symbols", "2.17", f"SELECT stream_id, sym, row_number() OVER w AS rn, rank() OVER r AS rk, dense_rank() OVER r AS dr FROM ({sql.hist(sql.rows(['doc_de', 'doc_es']))}) WINDOW w AS (PARTITION BY stream_id ORDER BY cnt DESC, sym), r AS (PARTITION BY stream_id ORDER BY cnt DESC)")
def win_rank_symbols(spark, d):
    w = Window.partitionBy("stream_id").orderBy(F.desc("cnt"))
    return hist_of(spark, d, ["doc_de", "doc_es"]).select("stream_id", "sym", F.row_number().over(Window.partitionBy("stream_id").orderBy(F.desc("cnt"), "sym")).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


both("win_delta", "2.17", "SELECT event_id, user_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("win_offsets", "2.17", "SELECT doc_id, source, sum(strlen(text)) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)::BIGINT AS end_ FROM {documents}", "SELECT doc_id, source, sum(octet_length(text)) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING) AS end_ FROM {documents}")
both("win_moving_skew", "2.17", "SELECT event_id, round(avg(CASE WHEN event_type = 'error' THEN 1.0::DOUBLE ELSE 0.0 END) OVER (PARTITION BY user_id % 10 ORDER BY event_id ROWS BETWEEN 100 PRECEDING AND CURRENT ROW), 9) AS share, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS last_hour FROM {events}", "SELECT event_id, round(avg(CASE WHEN event_type = 'error' THEN 1.0D ELSE 0.0D END) OVER (PARTITION BY user_id % 10 ORDER BY event_id ROWS BETWEEN 100 PRECEDING AND CURRENT ROW), 9) AS share, count(*) OVER (PARTITION BY user_id ORDER BY cast(ts AS timestamp) RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS last_hour FROM {events}")
both("win_ntile", "2.17", "SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS quarter FROM {documents}")
both("win_first_last", "2.17", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_, last_value(event_id) OVER w AS last_ FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("win_cume_dist", "2.17", "SELECT doc_id, round(cume_dist() OVER w, 9) AS cd, round(percent_rank() OVER w, 9) AS pr FROM {documents} WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")
both("win_sessionize", "2.17", "SELECT event_id, sum(new_) OVER (PARTITION BY user_id ORDER BY ts, event_id)::BIGINT AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new_ FROM {events})")

# --- order, limits ----------------------------------------------------------------


@query("topk_nodes", "2.17", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_es'])))}, {sql.NODES} SELECT prefix, n FROM nodes_ ORDER BY n DESC, prefix LIMIT 10")
def topk_nodes(spark, d):
    from treepack.plans.selective import skew_report

    hist = hist_of(spark, d, ["doc_es"])
    return skew_report(hist, codes_of(stats.codebooks(hist, max_len=15, floor=4096))).select("prefix", "n").orderBy(F.desc("n"), "prefix").limit(10)


@query("topk_symbols_per_lang", "2.17", f"SELECT stream_id, sym, cnt FROM ({sql.hist(sql.rows(['doc_de', 'doc_es', 'doc_fr']))}) QUALIFY row_number() OVER (PARTITION BY stream_id ORDER BY cnt DESC, sym) <= 5")
def topk_symbols_per_lang(spark, d):
    w = Window.partitionBy("stream_id").orderBy(F.desc("cnt"), "sym")
    return hist_of(spark, d, ["doc_de", "doc_es", "doc_fr"]).withColumn("k", F.row_number().over(w)).where("k <= 5").drop("k")


both("sort_limit_offset", "2.17", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")
both("sort_nulls", "2.17", "SELECT doc_id, quality FROM (SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id) ORDER BY quality NULLS FIRST, doc_id LIMIT 50")

# --- sets -------------------------------------------------------------------------

query("set_union_streams", "2.17", f"SELECT sym FROM ({_alphabet('de')}) UNION ALL SELECT sym FROM ({_alphabet('es')})")(lambda spark, d: _alpha(spark, d, "de").select("sym").unionByName(_alpha(spark, d, "es").select("sym")))
query("set_union_distinct", "2.17", f"SELECT sym FROM ({_alphabet('de')}) UNION SELECT sym FROM ({_alphabet('es')})")(lambda spark, d: _alpha(spark, d, "de").select("sym").unionByName(_alpha(spark, d, "es").select("sym")).distinct())
query("set_intersect_alphabet", "2.17", f"SELECT sym FROM ({_alphabet('de')}) INTERSECT SELECT sym FROM ({_alphabet('es')})")(lambda spark, d: _alpha(spark, d, "de").select("sym").intersect(_alpha(spark, d, "es").select("sym")))
query("set_except_alphabet", "2.17", f"SELECT sym FROM ({_alphabet('de')}) EXCEPT SELECT sym FROM ({_alphabet('es')})")(lambda spark, d: _alpha(spark, d, "de").select("sym").subtract(_alpha(spark, d, "es").select("sym")))
both("set_intersect_all", "2.17", "SELECT event_type, user_id % 5 AS u FROM {events} WHERE event_id % 2 = 0 INTERSECT ALL SELECT event_type, user_id % 5 FROM {events} WHERE event_id % 2 = 1")
both("set_except_all", "2.17", "SELECT event_type, user_id % 5 AS u FROM {events} EXCEPT ALL SELECT event_type, user_id % 5 FROM {events} WHERE event_id % 2 = 1")

# --- subqueries --------------------------------------------------------------------

both("sub_scalar", "2.17", "SELECT doc_id FROM {documents} WHERE n_chars > (SELECT avg(n_chars) FROM {documents})")
both("sub_in", "2.17", "SELECT doc_id FROM {documents} WHERE doc_id IN (SELECT doc_id FROM {labels} WHERE quality = 1)")
both("sub_exists", "2.17", "SELECT o_orderkey FROM {orders} o WHERE EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)")
both("sub_lateral", "2.17", "SELECT n_name, t.c_name, t.c_acctbal FROM {nation} n, LATERAL (SELECT c_name, c_acctbal FROM {customer} c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_name LIMIT 1) t")
both(
    "cte_recursive_prefixes", "2.17",
    "WITH RECURSIVE p(word, prefix) AS (SELECT n_name, n_name FROM {nation} UNION ALL SELECT word, left(prefix, length(prefix) - 1) FROM p WHERE length(prefix) > 1) SELECT word, prefix FROM p",
)
both("cte_with", "2.17", "WITH big AS (SELECT source, sum(n_chars) AS chars FROM {documents} GROUP BY source), top AS (SELECT * FROM big WHERE chars > (SELECT avg(chars) FROM big)) SELECT d.source, count(*) AS docs FROM {documents} d JOIN top t ON d.source = t.source GROUP BY d.source")
