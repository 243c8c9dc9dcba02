"""Queries of sources, sinks and user-defined functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..operators import codec, inference as I, udfs
from ..registry import query, table
from ..session import shared_folder
from ..sources import renditions
from ..sources.rasters import text_blobs

MEAN = "SELECT doc_id AS raster_id, round(coalesce(list_avg([('0x' || v)::INTEGER for v in regexp_extract_all(hex(encode(coalesce(text, ''))), '..')]), 0), 6) AS score FROM documents"


def folder(spark) -> str:
    return shared_folder(spark, "renditions")


for impl in udfs.IMPLEMENTATIONS:
    query(f"b9_stack_{impl}", MEAN)(lambda spark, sf, impl=impl: udfs.stack(text_blobs(spark, sf), impl).withColumn("score", F.round("score", 6)))


@query("x5_table_function", "SELECT count(*) AS blocks FROM (SELECT unnest(range(ceil(octet_length(encode(coalesce(text, ''))) / 64)::BIGINT)) FROM documents)")
def x5(spark, sf):
    text_blobs(spark, sf).createOrReplaceTempView("rasterflow_blobs")
    spark.udtf.register("rasterflow_blocks", udfs.Blocks)
    return spark.sql("SELECT count(*) AS blocks FROM rasterflow_blobs, LATERAL rasterflow_blocks(payload)")


@query("x7_cogroup_renditions", "SELECT count(*) AS n FROM documents")
def x7(spark, sf):
    r = I.renditions(text_blobs(spark, sf), ("full", "half_png"))
    return udfs.compared(r.where("format_id = 'full'"), r.where("format_id = 'half_png'")).where("right_bytes > 0").agg(F.count("*").alias("n"))


@query("s4_rendition_store", "SELECT count(*) AS n, max(doc_id) AS last FROM documents")
def s4(spark, sf):
    """Written by format, one format read back: the others' bytes aren't read."""
    path = folder(spark)
    renditions.write(I.renditions(text_blobs(spark, sf)), path)
    return renditions.read(spark, path, "half_png", ["raster_id"]).agg(F.count("*").alias("n"), F.max("raster_id").alias("last"))


@query("s4_catalogue", "SELECT f AS format_id, count(*) AS n FROM documents CROSS JOIN (VALUES ('full'), ('half_png'), ('half_dct95'), ('half_dct75')) x(f) GROUP BY 1")
def catalogue(spark, sf):
    return renditions.catalogue(I.renditions(text_blobs(spark, sf))).select("format_id", "n")


@query("s5_data_source", "SELECT 200::BIGINT AS n, 199::BIGINT AS last, 256::BIGINT AS size")
def s5(spark, sf):
    spark.dataSource.register(renditions.GradientSource)
    d = spark.read.format("rasterblob").option("n", "200").option("parts", "5").load()
    return d.agg(F.count("*").alias("n"), F.max("raster_id").alias("last"), F.max(F.length("payload")).cast("long").alias("size"))


@query("s9_sql_functions", "SELECT * FROM (VALUES ('full', 527.0::DOUBLE), ('png161', 1995.0::DOUBLE)) x(format_id, est)")
def s9(spark, sf):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION est_pipelined(pre DOUBLE, ex DOUBLE) RETURNS DOUBLE RETURN least(pre, ex)")
    return spark.sql("SELECT format_id, est_pipelined(pre, 4513.0D) AS est FROM VALUES ('full', 527.0D), ('png161', 1995.0D) AS t(format_id, pre)")


@query("x4_grouped_estimator", "SELECT label, round(stddev_samp(v) / sqrt(count(*)), 6) AS error FROM (SELECT label, embedding[1]::DOUBLE AS v FROM embeddings) GROUP BY 1")
def x4(spark, sf):
    """The jackknife error of each label's mean, by a grouped aggregate function of our own."""
    d = table(spark, sf, "embeddings").select("label", F.col("embedding")[0].cast("double").alias("v"))
    return d.groupBy("label").agg(F.round(udfs.jackknife("v"), 6).alias("error"))


@query("s6_text_sources", "SELECT f AS format, count(*) AS n, round(sum(s_acctbal), 2) AS total FROM supplier CROSS JOIN (VALUES ('csv'), ('json'), ('orc')) x(f) GROUP BY 1")
def s6(spark, sf):
    """A calibration sheet through the other file formats, with a schema given."""
    d, out = table(spark, sf, "supplier").select("s_suppkey", "s_acctbal"), None
    for f in ("csv", "json", "orc"):
        path = folder(spark)
        d.write.format(f).save(path)
        one = spark.read.format(f).schema(d.schema).load(path).agg(F.count("*").alias("n"), F.round(F.sum("s_acctbal"), 2).alias("total")).select(F.lit(f).alias("format"), "n", "total")
        out = one if out is None else out.unionByName(one)
    return out


@query("s3_binary_files", "SELECT count(*) AS files, 'nation.parquet' AS name FROM (SELECT 1)")
def s3(spark, sf):
    """Opaque files: the path glob and the pruned content column leave only names and lengths to read."""
    d = spark.read.format("binaryFile").option("pathGlobFilter", "nation.parquet").load(sf).where("length > 0")
    return d.agg(F.count("*").alias("files"), F.max(F.element_at(F.split("path", "/"), -1)).alias("name"))


@query("m5_imported_weights", "SELECT vec_id, round(list_sum([embedding[i]::DOUBLE * cos(i::DOUBLE) for i in range(1, 65)]), 6) AS score FROM embeddings")
def m5(spark, sf):
    """A linear model that was saved elsewhere as JSON: read as a binary file, registered, and scored in the JVM."""
    path = folder(spark)
    made = I.Softmax(64, ["score"], np.cos(np.arange(1.0, 65.0))[:, None], np.zeros(1))
    spark.createDataFrame([(I.saved(made),)], "value string").coalesce(1).write.text(path)
    (model,) = I.imported(spark, path, "*.txt").values()
    w = F.array(*[F.lit(float(v[0])) for v in model.weights])
    s_ = F.aggregate(F.zip_with(F.col("embedding"), w, lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, v: s + v)
    return table(spark, sf, "embeddings").select("vec_id", F.round(s_, 6).alias("score"))


@query("q1_recursive_orders", "WITH RECURSIVE o(chain, k) AS (SELECT 'decode', 0 UNION ALL SELECT chain || '>' || n, k + 1 FROM o CROSS JOIN (VALUES ('resize'), ('crop'), ('cast'), ('normalise')) x(n) WHERE position(n IN chain) = 0 AND (n <> 'normalise' OR position('cast' IN chain) > 0)) SELECT chain FROM o WHERE k = 4")
def q1b(spark, sf):
    """Legal orders of a chain by a recursive query."""
    return spark.sql("WITH RECURSIVE o(chain, k) AS (SELECT 'decode', 0 UNION ALL SELECT concat(chain, '>', n), k + 1 FROM o CROSS JOIN (VALUES ('resize'), ('crop'), ('cast'), ('normalise')) x(n) WHERE NOT contains(chain, n) AND (n <> 'normalise' OR contains(chain, 'cast'))) SELECT chain FROM o WHERE k = 4")


@query("k7_decode_stages", "SELECT * FROM (VALUES (1, 'entropy', true), (2, 'inverse_transform', false), (3, 'deblock', false)) x(place, op, host_only)")
def k7(spark, sf):
    return spark.createDataFrame([(i + 1, op, host) for i, (op, host) in enumerate(codec.stages())], "place int, op string, host_only boolean")
