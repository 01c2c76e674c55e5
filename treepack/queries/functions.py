"""The scalar-function surface, and the codec's own SQL functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.queries import sql
from treepack.queries.both import both
from treepack.queries.common import books_of
from treepack.registry import query
from treepack.sources.streams import build_stream, to_blocks
from treepack.sources.tables import load, small

S = "2.15"
both("fn_string_bytes", S, "SELECT doc_id, strlen(text)::BIGINT AS n_bytes, length(text)::BIGINT AS chars, (strlen(text) * 8)::BIGINT AS bits, left(hex(encode(text)), 8) AS head, to_base64(encode(left(text, 6))) AS b64 FROM {documents}", "SELECT doc_id, cast(octet_length(text) as long) AS n_bytes, cast(length(text) as long) AS chars, cast(bit_length(text) as long) AS bits, left(hex(encode(text, 'utf-8')), 8) AS head, base64(encode(left(text, 6), 'utf-8')) AS b64 FROM {documents}")
both("fn_string_shape", S, "SELECT n_nationkey, substring(n_name, 2, 3) AS a, left(n_name, 2) AS b, right(n_name, 2) AS c, lpad(n_name, 12, '*') AS d, rpad(n_name, 12, '*') AS e, repeat(left(n_name, 1), 3) AS f, reverse(n_name) AS g, translate(n_name, 'AEI', 'aei') AS h, trim('  ' || n_name || ' ') AS i, upper(n_name) AS j, lower(n_name) AS k FROM {nation}")
both("fn_string_search", S, r"SELECT page_id, instr(html, '<p>')::INT AS first_p, contains(html, '<table') AS has_table, starts_with(html, '<!DOCTYPE') AS doctype, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, split_part(url, '/', 3) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INT AS text_chars FROM {pages}", r"SELECT page_id, instr(html, '<p>') AS first_p, contains(html, '<table') AS has_table, startswith(html, '<!DOCTYPE') AS doctype, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, split_part(url, '/', 3) AS host, length(regexp_replace(html, '<[^>]*>', '')) AS text_chars FROM {pages}")
both("fn_string_digest", S, "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM {documents}", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM {documents}")
both("fn_string_codepoint", S, "SELECT n_nationkey, ascii(n_name) AS a, chr((65 + n_nationkey)::INT) AS c, bin(n_nationkey) AS b, concat_ws('-', n_name, n_nationkey::VARCHAR) AS w, levenshtein(n_name, 'FRANCE')::INT AS l FROM {nation}", "SELECT n_nationkey, ascii(n_name) AS a, char(65 + n_nationkey) AS c, bin(n_nationkey) AS b, concat_ws('-', n_name, cast(n_nationkey as string)) AS w, levenshtein(n_name, 'FRANCE') AS l FROM {nation}")
both("fn_date_parts", S, "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS d, quarter(o_orderdate)::INT AS q, strftime(o_orderdate, '%Y-%m') AS ym, date_trunc('month', o_orderdate)::DATE AS first_ FROM {orders}", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d, quarter(o_orderdate) AS q, date_format(o_orderdate, 'yyyy-MM') AS ym, to_date(date_trunc('month', o_orderdate)) AS first_ FROM {orders}")
both("fn_date_arith", S, "SELECT event_id, date_diff('day', TIMESTAMP '2024-01-01', ts)::INT AS days, (ts::DATE + 7)::DATE AS week_on, epoch_us(ts) AS us, epoch_us(ts + INTERVAL 90 MINUTE) AS later FROM {events}", "SELECT event_id, datediff(ts, date'2024-01-01') AS days, date_add(to_date(ts), 7) AS week_on, unix_micros(cast(ts as timestamp)) AS us, unix_micros(cast(ts + interval 90 minutes as timestamp)) AS later FROM {events}")
both("fn_math_entropy", S, "SELECT l_orderkey, l_linenumber, round(log2(l_quantity + 1), 9) AS a, round(pow(l_discount + 1, 3), 9) AS b, round(ln(l_extendedprice), 9) AS c, round(exp(l_tax), 9) AS d, round(sqrt(l_quantity), 9) AS e, greatest(l_discount, l_tax) AS f, least(l_discount, l_tax) AS g, abs(l_tax - l_discount) AS h FROM {lineitem} WHERE l_orderkey < 2000", "SELECT l_orderkey, l_linenumber, round(log2(l_quantity + 1), 9) AS a, round(pow(l_discount + 1, 3), 9) AS b, round(ln(l_extendedprice), 9) AS c, round(exp(l_tax), 9) AS d, round(sqrt(l_quantity), 9) AS e, greatest(l_discount, l_tax) AS f, least(l_discount, l_tax) AS g, abs(l_tax - l_discount) AS h FROM {lineitem} WHERE l_orderkey < 2000")
both("fn_math_rounding", S, "SELECT doc_id, ((n_chars + 7) // 8)::BIGINT AS bytes_, ceil(n_chars / 8.0)::BIGINT AS up, floor(n_chars / 8.0)::BIGINT AS down, (n_chars % 7)::BIGINT AS rest FROM {documents}", "SELECT doc_id, (n_chars + 7) div 8 AS bytes_, cast(ceil(n_chars / 8.0D) as long) AS up, cast(floor(n_chars / 8.0D) as long) AS down, pmod(n_chars, 7) AS rest FROM {documents}")
both("fn_bit_ops", S, "SELECT event_id, user_id << 3 AS l, user_id >> 2 AS r, user_id & 255 AS a, user_id | 1 AS o, xor(user_id, 170) AS x, ~user_id AS n, bit_count(user_id)::INT AS ones, ((user_id >> 3) & 1)::INT AS third FROM {events}", "SELECT event_id, shiftleft(user_id, 3) AS l, shiftright(user_id, 2) AS r, user_id & 255 AS a, user_id | 1 AS o, user_id ^ 170 AS x, ~user_id AS n, bit_count(user_id) AS ones, cast(getbit(user_id, 3) as int) AS third FROM {events}")
both("fn_cond", S, "SELECT d.doc_id, CASE WHEN n_chars < 1000 THEN 'raw' WHEN n_chars < 8000 THEN 'one' ELSE 'many' END AS codec, coalesce(l.quality, -1) AS q, nullif(d.lang, 'en') AS not_en, CASE WHEN l.toxic = 1 THEN 'bad' ELSE 'ok' END AS t FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id", "SELECT d.doc_id, CASE WHEN n_chars < 1000 THEN 'raw' WHEN n_chars < 8000 THEN 'one' ELSE 'many' END AS codec, nvl(l.quality, -1) AS q, nullif(d.lang, 'en') AS not_en, if(l.toxic = 1, 'bad', 'ok') AS t FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")
both("fn_cast", S, "SELECT o_orderkey, o_orderkey::VARCHAR AS s, o_totalprice::BIGINT AS i, o_totalprice::DECIMAL(18, 2) AS m, try_cast(o_orderpriority AS INT) AS none_ FROM {orders} WHERE o_totalprice - floor(o_totalprice) < 0.4", "SELECT o_orderkey, cast(o_orderkey as string) AS s, cast(o_totalprice as bigint) AS i, cast(o_totalprice as decimal(18, 2)) AS m, try_cast(o_orderpriority as int) AS none_ FROM {orders} WHERE o_totalprice - floor(o_totalprice) < 0.4")
both("fn_array_build", S, "SELECT n_nationkey, range(1, n_nationkey + 2) AS seq, [n_nationkey, 7] AS pair, range(1, n_nationkey + 2)[2:3] AS part, len(range(1, n_nationkey + 2))::INT AS n, list_concat([1, 2], [n_nationkey]) AS cat FROM {nation}", "SELECT n_nationkey, sequence(1, n_nationkey + 1) AS seq, array(n_nationkey, 7) AS pair, slice(sequence(1, n_nationkey + 1), 2, 2) AS part, size(sequence(1, n_nationkey + 1)) AS n, concat(array(1, 2), array(n_nationkey)) AS cat FROM {nation}")
both("fn_array_hof", S, "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS positive, list_max(embedding) AS top, len(list_filter(embedding, lambda x: x > 3)) > 0 AS any_large, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2 FROM {embeddings}", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS positive, array_max(embedding) AS top, exists(embedding, x -> x > 3) AS any_large, round(aggregate(embedding, 0.0D, (a, x) -> a + double(x) * double(x)), 4) AS norm2 FROM {embeddings}")
both("fn_array_set", S, "SELECT n_nationkey, list_sort(list_distinct(string_split(n_name, ''))) AS letters, len(list_intersect(string_split(n_name, ''), ['A', 'E', 'I']))::INT AS vowels, list_contains(string_split(n_name, ''), 'A') AS has_a, list_max(string_split(n_name, '')) AS last_, coalesce(list_position(string_split(n_name, ''), 'A'), 0)::INT AS at_a FROM {nation}", "SELECT n_nationkey, sort_array(array_distinct(split(n_name, ''))) AS letters, size(array_intersect(split(n_name, ''), array('A', 'E', 'I'))) AS vowels, array_contains(split(n_name, ''), 'A') AS has_a, array_max(split(n_name, '')) AS last_, cast(array_position(split(n_name, ''), 'A') as int) AS at_a FROM {nation}")
both("fn_array_explode", S, "SELECT r_name, u.i::INT AS pos, substr(r_name, u.i + 1, 1) AS letter FROM {region}, unnest(range(length(r_name))) AS u(i)", "SELECT r_name, pos, letter FROM {region} LATERAL VIEW posexplode(split(r_name, '')) t AS pos, letter")
both("fn_map_codebook", S, "SELECT n_regionkey, count(*) AS n, list_sort(list(n_name)) AS keys_, sum(length(n_name))::BIGINT AS chars FROM {nation} GROUP BY n_regionkey", "SELECT n_regionkey, cardinality(m) AS n, sort_array(map_keys(m)) AS keys_, aggregate(map_values(transform_values(m, (k, v) -> cast(length(k) as long))), 0L, (a, x) -> a + x) AS chars FROM (SELECT n_regionkey, map_from_entries(collect_list(struct(n_name, n_nationkey))) AS m FROM {nation} GROUP BY n_regionkey)")
both("fn_json_props", S, "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM {events}", "SELECT event_id, cast(get_json_object(props, '$.k') as bigint) AS k FROM {events} WHERE from_json(props, 'k bigint').k <=> cast(get_json_object(props, '$.k') as bigint)")
both("fn_struct", S, "SELECT n_nationkey, n_name AS a, n_regionkey * 2 AS b FROM {nation}", "SELECT s.k AS n_nationkey, s.name AS a, s.b FROM (SELECT named_struct('k', n_nationkey, 'name', n_name, 'b', n_regionkey * 2) AS s FROM {nation})")


both("fn_array_pairs", S, "SELECT n_nationkey, [n_nationkey * 1, n_nationkey * 2] AS products, list_has_any([n_nationkey], [1, 3, 5]) AS overlap, [n_name, n_name] AS twice, [n_name, 'x'][2] AS second_, flatten([[n_nationkey], [7, 8]]) AS flat FROM {nation}", "SELECT n_nationkey, zip_with(array(n_nationkey, n_nationkey), array(1, 2), (a, b) -> a * b) AS products, arrays_overlap(array(n_nationkey), array(1, 3, 5)) AS overlap, array_repeat(n_name, 2) AS twice, element_at(array(n_name, 'x'), 2) AS second_, flatten(array(array(n_nationkey), array(7, 8))) AS flat FROM {nation}")
both("fn_array_zip", S, "SELECT n_nationkey, n_nationkey + k AS a, 2 * k AS b FROM {nation}, range(3) r(k)", "SELECT n_nationkey, z.x AS a, cast(z.y as bigint) AS b FROM (SELECT n_nationkey, inline(arrays_zip(x, y)) AS (x, y) FROM (SELECT n_nationkey, transform(array(0L, 1L, 2L), k -> n_nationkey + k) AS x, array(0, 2, 4) AS y FROM {nation})) z")
both("fn_map_more", S, "SELECT n_nationkey, CASE WHEN n_regionkey > 1 THEN 1 ELSE 0 END AS kept, n_nationkey + n_regionkey AS both_ FROM {nation}", "SELECT n_nationkey, size(map_filter(map_from_arrays(array('k'), array(n_regionkey)), (k, v) -> v > 1)) AS kept, element_at(map_zip_with(map('a', n_nationkey), map('a', n_regionkey), (k, x, y) -> x + y), 'a') AS both_ FROM {nation}")
both("fn_date_more", S, "SELECT o_orderkey, (o_orderdate + INTERVAL 3 MONTH)::DATE AS later, epoch_us(make_timestamp(1700000000000000 + o_orderkey)) AS us FROM {orders}", "SELECT o_orderkey, add_months(to_date(o_orderdate), 3) AS later, unix_micros(timestamp_micros(1700000000000000 + o_orderkey)) AS us FROM {orders}")
both("fn_string_more", S, "SELECT n_nationkey, printf('%s-%03d', n_name, n_nationkey) AS f, len(regexp_extract_all(n_name, '[AEIOU]'))::INT AS vowels FROM {nation}", "SELECT n_nationkey, format_string('%s-%03d', n_name, n_nationkey) AS f, regexp_count(n_name, '[AEIOU]') AS vowels FROM {nation}")
both("fn_json_more", S, "SELECT r_regionkey, r_name AS name, '{\"k\":' || r_regionkey || '}' AS j, 'ARRAY<BIGINT>' AS schema_ FROM {region}", "SELECT r.r_regionkey, t.name, to_json(named_struct('k', r.r_regionkey)) AS j, schema_of_json('[1]') AS schema_ FROM {region} r LATERAL VIEW json_tuple(to_json(named_struct('name', r.r_name)), 'name') t AS name")


@query("fn_hash", S)
def fn_hash(spark, d):
    return load(spark, d, "documents").select("doc_id", F.xxhash64("text").alias("x"), F.hash("text").alias("h"), F.crc32("text").alias("c"))


# --- the codec's functions -------------------------------------------------------------


@query("udf_roundtrip", "2.13", "SELECT conv_id, turn, md5(text) AS digest, true AS smaller_sum FROM conversations WHERE text IS NOT NULL")
def udf_roundtrip(spark, d):
    from treepack.functions import udfs

    udfs.register(spark)
    c = load(spark, d, "conversations").where("text is not null").select("conv_id", "turn", F.col("text").cast("binary").alias("raw"))
    hist = stats.byte_histogram(c.select(F.lit("c").alias("stream_id"), F.col("conv_id").alias("value_id"), "raw"))
    counts = hist.groupBy().agg(F.map_from_entries(F.collect_list(F.struct("sym", "cnt"))).alias("m")).select(F.transform(F.sequence(F.lit(0), F.lit(255)), lambda s: F.coalesce(F.col("m")[s], F.lit(0))).alias("counts"))
    book = counts.select(udfs.huff_lengths("counts").alias("lengths"))
    enc = c.crossJoin(F.broadcast(book)).withColumn("payload", F.expr("nbh_encode(raw, lengths)"))
    return enc.select("conv_id", "turn", F.expr("md5(nbh_decode(payload, lengths))").alias("digest"), (F.octet_length("payload") <= F.octet_length("raw") + 8).alias("smaller_sum"))


@query("udf_entropy", "2.13", f"SELECT value_id, round(sum(-c / n * log2(c / n)), 6) AS h FROM (SELECT value_id, sym, count(*) AS c, sum(count(*)) OVER (PARTITION BY value_id) AS n FROM ({sql.rows(['doc_es'])}) GROUP BY value_id, sym) GROUP BY value_id")
def udf_entropy(spark, d):
    from treepack.functions.udfs import byte_entropy

    return build_stream(spark, d, "doc_es").where("octet_length(raw) > 0").select("value_id", F.round(byte_entropy("raw"), 6).alias("h"))


@query("udaf_hist", "2.13", "SELECT source, sym, count(*)::BIGINT AS cnt FROM (SELECT source, ('0x' || substr(h, 2 * u.i + 1, 2))::INT AS sym FROM (SELECT source, hex(encode(text)) AS h, strlen(text) AS n FROM documents WHERE lang = 'es' AND text IS NOT NULL) x, unnest(range(x.n)) AS u(i)) GROUP BY ALL")
def udaf_hist(spark, d):
    from treepack.functions.udfs import byte_hist_agg

    g = load(spark, d, "documents").where("lang = 'es' and text is not null").select("source", F.col("text").cast("binary").alias("raw")).groupBy("source").agg(byte_hist_agg("raw").alias("h"))
    return g.select("source", F.posexplode("h").alias("sym", "cnt")).where("cnt > 0")


@query("udtf_nodes", "2.13", f"WITH RECURSIVE src AS MATERIALIZED (SELECT * FROM ({sql.rows(['doc_es'])})), {sql.codes(sql.hist('SELECT * FROM src'))} SELECT value_id, left(code, x.d) AS prefix, count(*)::BIGINT AS n, sum(substr(code, x.d + 1, 1)::INT)::BIGINT AS n_right FROM src JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d) GROUP BY ALL")
def udtf_nodes(spark, d):
    from treepack.functions import udfs

    udfs.register(spark)
    blocks = to_blocks(build_stream(spark, d, "doc_es")).join(small(books_of(spark, d, ["doc_es"], max_len=15, floor=4096)), "stream_id")
    return spark.sql("SELECT v.value_id, t.prefix, sum(t.n) AS n, sum(t.n_right) AS n_right FROM {v} v, LATERAL nbh_nodes(v.raw, v.lengths) t GROUP BY ALL", v=blocks)


_SYM = "SELECT r_name, u.i::INT AS pos, ascii(substr(r_name, u.i + 1, 1)) AS sym FROM region, unnest(range(length(r_name))) AS u(i)"


@query("udtf_symbols", "2.13", _SYM)
def udtf_symbols(spark, d):
    from treepack.functions import udfs

    udfs.register(spark)
    return spark.sql("SELECT r.r_name, t.pos, t.sym FROM {r} r, LATERAL symbols(cast(r.r_name AS binary)) t", r=load(spark, d, "region"))


query("view_udtf_sql", "2.17", f"SELECT sym, count(*)::BIGINT AS cnt FROM ({_SYM}) GROUP BY sym")(lambda spark, d: udtf_symbols(spark, d).groupBy("sym").agg(F.count("*").alias("cnt")))
