"""Structured Streaming over a file source of events, run until all input is taken."""

from __future__ import annotations

from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.queries import sql
from treepack.registry import query
from treepack.sources.streams import build_stream
from treepack.sources.tables import load, scratch, staged
from treepack.streaming import ops


def source(spark, d, df=None, parts: int = 4):
    """A table as a stream of files, in the order of event time."""
    path = scratch(spark)
    df = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")) if df is None else df
    df.repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(path) if "ts" in df.columns else df.write.parquet(path)
    return spark.readStream.schema(df.schema).parquet(path)


def finish(stream, mode: str = "append", batch=None):
    """Runs a streaming query over all there is; its rows as a table."""
    spark, base = stream.sparkSession, scratch(stream.sparkSession)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        writer = writer.foreachBatch(batch) if batch else writer.format("parquet").option("path", f"{base}/out")
        writer.start().awaitTermination()
        return None if batch else spark.read.schema(stream.schema).parquet(f"{base}/out")
    writer.foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(f"{base}/last")).start().awaitTermination()  # complete mode: the last batch holds all
    return spark.read.schema(stream.schema).parquet(f"{base}/last")


@query("st_encode_roundtrip", "X1", sql.md5_of(["doc_es"]))
def st_encode_roundtrip(spark, d):
    from treepack.operators.blocks import decode_blocks
    from treepack.queries.common import digests

    values = build_stream(spark, d, "doc_es")
    books = staged(stats.codebooks(stats.byte_histogram(values)))
    return digests(decode_blocks(finish(ops.encode_stream(source(spark, d, values), books))))


_SYM = "SELECT ts, event_type, user_id, ascii(substr(props, u.i + 1, 1)) AS sym FROM (SELECT ts, event_type, user_id, props, strlen(props) AS n FROM events) e, unnest(range(n)) AS u(i)"


@query("st_tumbling_hist", "X2", f"SELECT epoch_us(date_trunc('day', ts)) AS start, event_type, sym, count(*) AS cnt FROM ({_SYM}) GROUP BY ALL")
def st_tumbling_hist(spark, d):
    h = ops.window_histogram(source(spark, d), "ts", "props", "1 day", by=("event_type",))
    return finish(h, "complete").select(F.unix_micros("start").alias("start"), "event_type", "sym", "cnt")


@query("st_sliding_entropy", "X2", f"WITH w AS (SELECT epoch_us(date_trunc('day', ts)) - k * 43200000000 AS s0, ts, sym FROM ({_SYM}), range(-1, 2) r(k)), h AS (SELECT s0 AS start, sym, count(*) AS c FROM w WHERE epoch_us(ts) >= s0 AND epoch_us(ts) < s0 + 86400000000 GROUP BY ALL), n AS (SELECT start, sum(c) AS n FROM h GROUP BY 1) SELECT start, round(sum(-c / n * log2(c / n)), 6) AS h FROM h JOIN n USING (start) GROUP BY start")
def st_sliding_entropy(spark, d):
    """Entropy of a day's bytes, a window every twelve hours."""
    h = finish(ops.window_histogram(source(spark, d), "ts", "props", "1 day", "12 hours"), "complete")
    n = h.groupBy("start").agg(F.sum("cnt").alias("n"))
    return h.join(n, "start").groupBy("start").agg(F.round(F.sum(-F.col("cnt") / F.col("n") * F.log2(F.col("cnt") / F.col("n"))), 6).alias("h")).select(F.unix_micros("start").alias("start"), "h")


@query("st_session_bytes", "X2", "WITH f AS (SELECT user_id, ts, props, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new_ FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new_) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM f) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n, sum(strlen(props))::BIGINT AS n_bytes FROM s GROUP BY user_id, k")
def st_session_bytes(spark, d):
    s = finish(ops.session_bytes(source(spark, d), "ts", "props", "30 minutes", "user_id"), "complete")
    return s.select("user_id", F.unix_micros("start").alias("start"), "n", "n_bytes")


@query("st_late_drop", "X3", "SELECT epoch_us(TIMESTAMP '2024-01-01 00:00:00') AS start, 3::BIGINT AS n UNION ALL SELECT epoch_us(TIMESTAMP '2024-01-01 05:00:00'), 2")
def st_late_drop(spark, d):
    """Three rows, then two five hours on, a batch each, so that the watermark has passed, then two late ones, then one that closes all windows: the late ones are left out."""
    path = scratch(spark)
    batches = [["00:01", "00:02", "00:59"], ["05:30"], ["05:31"], ["00:03", "00:30"], ["23:00"]]
    schema = "ts timestamp, x int"
    for k, times in enumerate(batches):
        spark.createDataFrame([(f"2024-01-01 {t}:00", k) for t in times], "t string, x int").select(F.to_timestamp("t").alias("ts"), "x").coalesce(1).write.mode("append").parquet(f"{path}/b={k}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/b=*")
    w = stream.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
    return finish(w).select(F.unix_micros("start").alias("start"), "n")


@query("st_block_builder", "X4", "SELECT event_type, (sum(strlen(props)) // 8192)::BIGINT AS full_blocks, true AS all_full FROM events GROUP BY event_type HAVING sum(strlen(props)) >= 8192")
def st_block_builder(spark, d):
    """Blocks that fill up while the stream runs; timers would send what is left."""
    b = finish(ops.block_builder(source(spark, d), "event_type", "props"))
    return b.groupBy("event_type").agg(F.count("*").alias("full_blocks"), F.min(F.col("n") == 8192).alias("all_full"))


@query("st_codebook_versions", "X5")
def st_codebook_versions(spark, d):
    return finish(ops.adaptive_codebook(source(spark, d), "event_type", "props")).select("event_type", "version", "n", F.round("drift", 6).alias("drift"))


@query("st_static_join", "X6", "SELECT event_id, n_name FROM events JOIN nation ON user_id % 25 = n_nationkey")
def st_static_join(spark, d):
    static = load(spark, d, "nation").select("n_nationkey", "n_name")
    return finish(source(spark, d).join(F.broadcast(static), F.expr("user_id % 25 = n_nationkey")).select("event_id", "n_name"))


@query("st_interval_join", "X6", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE WHERE a.event_type = 'error' AND b.event_type <> 'error'")
def st_interval_join(spark, d):
    e = source(spark, d)
    a = e.where("event_type = 'error'").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("first_id")).withWatermark("t1", "1 hour")
    b = source(spark, d).where("event_type <> 'error'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("second_id")).withWatermark("t2", "1 hour")
    return finish(a.join(b, F.expr("u1 = u2 and t2 >= t1 and t2 <= t1 + interval 5 minutes")).select("first_id", "second_id"))


@query("st_dedup", "X6", "SELECT event_id FROM events")
def st_dedup(spark, d):
    """Every event sent twice, kept once."""
    e = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return finish(source(spark, d, e.unionByName(e)).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("st_foreach_batch", "X7", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def st_foreach_batch(spark, d):
    path = scratch(spark)
    finish(source(spark, d).select("event_id", "event_type"), batch=ops.idempotent_writer(path))
    return spark.read.parquet(path).groupBy("event_type").agg(F.count("*").alias("n"))


