"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import functions as F

from treepack.queries import sql
from treepack.queries.both import TABLES
from treepack.queries.common import encoded
from treepack.registry import query
from treepack.sources.streams import build_stream, to_blocks
from treepack.sources.tables import load, scratch, write_blocks


@query("src_parquet", "2.17", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def src_parquet(spark, d):
    out = None
    for t in TABLES:
        one = load(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("src_json_csv_text", "2.17", " UNION ALL ".join(f"SELECT '{f}' AS format, n_nationkey, n_name, n_regionkey FROM nation" for f in ("json", "csv", "orc", "parquet", "text")))
def src_json_csv_text(spark, d):
    """nation written to and read from each file format, with the schema stated and (JSON) inferred."""
    t = load(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
    ddl, out = "n_nationkey int, n_name string, n_regionkey int", None
    for f in ("json", "csv", "orc", "parquet", "text"):
        path = scratch(spark)
        if f == "text":
            t.select(F.concat_ws("|", "n_nationkey", "n_name", "n_regionkey").alias("value")).write.text(path)
            p = F.split("value", r"\|")
            one = spark.read.text(path).select(p[0].cast("int").alias("n_nationkey"), p[1].alias("n_name"), p[2].cast("int").alias("n_regionkey"))
        else:
            t.write.format(f).save(path)
            reader = spark.read if f in ("json", "orc", "parquet") else spark.read.schema(ddl)
            one = reader.format(f).load(path).select(F.col("n_nationkey").cast("int").alias("n_nationkey"), "n_name", F.col("n_regionkey").cast("int").alias("n_regionkey"))
        one = one.select(F.lit(f).alias("format"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("src_binary_file", "2.17")
def src_binary_file(spark, d):
    return spark.read.format("binaryFile").load(f"{d}/region.parquet").select("length", F.octet_length("content").cast("long").alias("content_bytes"))


@query("src_range", "2.17", "SELECT least(5, floor(ln(1 - ((id * 2654435761) % 4294967296) / 4294967296.0::DOUBLE) / ln(0.2::DOUBLE)))::INT AS sym, count(*)::BIGINT AS cnt FROM range(1048576) r(id) GROUP BY 1")
def src_range(spark, d):
    u = F.expr("(id * 2654435761) % 4294967296") / 4294967296.0
    return spark.range(1 << 20).select(F.least(F.lit(5), F.floor(F.ln(1 - u) / F.ln(F.lit(0.2)))).cast("int").alias("sym")).groupBy("sym").agg(F.count("*").alias("cnt"))


@query("src_blocks", "2.17", "SELECT doc_id AS value_id, 0::BIGINT AS block_no, least(strlen(text), 8192)::INT AS n FROM documents WHERE lang = 'fr' AND text IS NOT NULL")
def src_blocks(spark, d):
    """The sink read with filters on stream and block number: a folder pruned, a filter pushed down."""
    path = scratch(spark)
    write_blocks(encoded(spark, d, ["doc_fr", "doc_es"]), path)
    return spark.read.parquet(path).where("stream_id = 'doc_fr' and block_no = 0").select("value_id", "block_no", "n")


@query("src_datasource_treepack", "2.17", sql.md5_of(["doc_es"]).replace("SELECT stream_id,", "SELECT stream_id,"))
def src_datasource_treepack(spark, d):
    from treepack.queries.common import digests
    from treepack.sources import datasource

    datasource.register(spark)
    path = scratch(spark)
    to_blocks(build_stream(spark, d, "doc_es")).select("stream_id", "value_id", "block_no", "raw").write.format("treepack").mode("append").save(path)
    return digests(spark.read.format("treepack").load(path))


@query("sink_partitioned", "2.17", "SELECT stream_id, count(*)::BIGINT AS blocks FROM (SELECT 'doc_' || lang AS stream_id, unnest(range(greatest(1, (strlen(text) + 8191) // 8192))) FROM documents WHERE lang IN ('fr', 'es') AND text IS NOT NULL) GROUP BY stream_id")
def sink_partitioned(spark, d):
    path = scratch(spark)
    write_blocks(encoded(spark, d, ["doc_fr", "doc_es"]), path)
    return spark.read.parquet(path).groupBy("stream_id").agg(F.count("*").alias("blocks"))


@query("sink_overwrite_append", "2.17", "SELECT r_regionkey, CASE WHEN r_regionkey = 1 THEN 1 ELSE 2 END::BIGINT AS copies FROM region")
def sink_overwrite_append(spark, d):
    """Twice appended, then one partition overwritten."""
    path, t = scratch(spark), load(spark, d, "region").select("r_regionkey", "r_name")
    for _ in range(2):
        t.write.mode("append").partitionBy("r_regionkey").parquet(path)
    t.where("r_regionkey = 1").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("r_regionkey").parquet(path)
    return spark.read.parquet(path).groupBy("r_regionkey").agg(F.count("*").alias("copies"))


@query("sink_json_report", "2.17", "SELECT lang, count(*)::BIGINT AS docs FROM documents GROUP BY lang")
def sink_json_report(spark, d):
    path = scratch(spark)
    load(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("docs")).write.json(path)
    return spark.read.schema("lang string, docs long").json(path)
