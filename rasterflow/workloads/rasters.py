"""Queries of raster operators in Catalyst expressions, over whole byte rasters of documents and blocks of embeddings."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Window as W, functions as F

from ..functions import rasters as R
from ..operators import codec
from ..operators.inference import augmented
from ..plans.engine import Engine
from ..registry import query, table
from ..sources.rasters import text_rasters, vector_rasters

BLOCK = "(SELECT vec_id AS raster_id, label, [greatest(0, least(255, floor((v::DOUBLE + 1) * 127.5)::INTEGER)) for v in embedding] AS p FROM embeddings)"
#: Whole texts as bytes in rows of 32, one row at least.
TEXT = """(SELECT doc_id AS raster_id, lang AS label, h, [('0x' || v)::INTEGER for v in regexp_extract_all(rpad(x, (h * 64)::INTEGER, '0'), '..')] AS p FROM
 (SELECT *, greatest(1, ceil(length(x) / 64))::BIGINT AS h FROM (SELECT doc_id, lang, hex(encode(coalesce(text, ''))) AS x FROM documents)))"""
#: One row for each pixel.
PIXELS = f"(SELECT raster_id, h, unnest(p) AS v, generate_subscripts(p, 1) - 1 AS i FROM {TEXT})"


def digest(c, places=6):
    """Sum and position-weighted sum of an array's values, so that a row of 64 compares exactly."""
    total = F.aggregate(c, F.lit(0.0), lambda s, v: s + v)
    weighted = F.aggregate(F.transform(c, lambda v, i: v * (i + 1)), F.lit(0.0), lambda s, v: s + v)
    return F.round(total, places).alias("total"), F.round(weighted, places).alias("weighted")


def digest_sql(expr: str, rel: str, places: int = 6) -> str:
    return f"SELECT raster_id, round(list_sum(q), {places}) AS total, round(list_sum([q[i] * i for i in range(1, len(q) + 1)]), {places}) AS weighted FROM (SELECT raster_id, [v::DOUBLE for v in {expr}] AS q FROM {rel})"


def of_blocks(name: str, expr: str, f, places: int = 4):
    query(name, digest_sql(expr, BLOCK, places))(lambda spark, sf: vector_rasters(spark, sf).select("raster_id", *digest(f(F.col("pixels")), places)))


of_blocks("o2_resize_nearest", "[p[floor((floor(i / 6) + 0.5) * 8 / 6)::INTEGER * 8 + floor((i % 6 + 0.5) * 8 / 6)::INTEGER + 1] for i in range(36)]", lambda p: R.resize_nearest(p, 8, 8, 6, 6))
of_blocks("o2_resize_box", "[floor((p[16 * (i // 4) + 2 * (i % 4) + 1] + p[16 * (i // 4) + 2 * (i % 4) + 2] + p[16 * (i // 4) + 2 * (i % 4) + 9] + p[16 * (i // 4) + 2 * (i % 4) + 10] + 2) / 4) for i in range(16)]", lambda p: R.box_half(p, 8, F.lit(8)))
BIL = """[(p[c[1] * 8 + c[3] + 1] * (1 - c[6]) + p[c[1] * 8 + c[4] + 1] * c[6]) * (1 - c[5]) + (p[c[2] * 8 + c[3] + 1] * (1 - c[6]) + p[c[2] * 8 + c[4] + 1] * c[6]) * c[5]
 for c in [[floor(y[1]), least(floor(y[1]) + 1, 7), floor(y[2]), least(floor(y[2]) + 1, 7), y[1] - floor(y[1]), y[2] - floor(y[2])] for y in [[greatest(0.0::DOUBLE, least(7.0::DOUBLE, (i // 6 + 0.5::DOUBLE) * 8 / 6 - 0.5)), greatest(0.0::DOUBLE, least(7.0::DOUBLE, (i % 6 + 0.5::DOUBLE) * 8 / 6 - 0.5))] for i in range(36)]]]"""
of_blocks("o2_resize_bilinear", BIL.replace("p[c[1] * 8 + c[3] + 1]", "p[(c[1] * 8 + c[3])::INTEGER + 1]").replace("p[c[1] * 8 + c[4] + 1]", "p[(c[1] * 8 + c[4])::INTEGER + 1]").replace("p[c[2] * 8 + c[3] + 1]", "p[(c[2] * 8 + c[3])::INTEGER + 1]").replace("p[c[2] * 8 + c[4] + 1]", "p[(c[2] * 8 + c[4])::INTEGER + 1]"), lambda p: R.resize_bilinear(p, 8, 8, 6, 6))
of_blocks("o3_center_crop", "[p[(i // 4 + 2) * 8 + i % 4 + 3] for i in range(16)]", lambda p: R.crop(p, 8, 2, 2, 6, 6))
of_blocks("o4_to_float", "[v / 255.0::DOUBLE for v in p]", lambda p: F.transform(p, lambda v: v / 255.0))
MEAN, STD = [0.485, 0.456, 0.406, 0.449], [0.229, 0.224, 0.225, 0.226]
NORM = "[(p[i + 1] / 255.0::DOUBLE - ([0.485, 0.456, 0.406, 0.449])[i % 4 + 1]) / ([0.229, 0.224, 0.225, 0.226])[i % 4 + 1]"
of_blocks("o5_normalise", NORM + " for i in range(64)]", lambda p: R.normalised(p, MEAN, STD, 4))
of_blocks("o6_channels_first", "[p[(i % 16) * 4 + i // 16 + 1] for i in range(64)]", lambda p: R.channels_first(p, 16, 4))
of_blocks("o7_fused", NORM.replace("i % 4", "j % 4").replace("p[i + 1]", "p[j + 1]") + " for j in [(i % 16) * 4 + i // 16 for i in range(64)]]", lambda p: R.fused(p, 16, MEAN, STD, 4))
BASIS = "(VALUES " + ", ".join(f"({i // 8}, {i % 8}, {v!r}::DOUBLE)" for i, v in enumerate(R.basis())) + ") AS {0}(k, x, v)"
DCT = f"""(SELECT raster_id, i, sum(bu.v * bv.v * (p[8 * bu.x + bv.x + 1] - 128)) AS c FROM {BLOCK} CROSS JOIN (SELECT unnest(range(64)) AS i)
 JOIN {BASIS.format('bu')} ON bu.k = i // 8 JOIN {BASIS.format('bv')} ON bv.k = i % 8 GROUP BY 1, 2)"""


@query("k9a_dct_forward", f"SELECT raster_id, round(sum(c), 3) AS total, round(sum(c * (i + 1)), 3) AS weighted FROM {DCT} GROUP BY 1")
def dct_forward(spark, sf):
    return vector_rasters(spark, sf).select("raster_id", *digest(R.dct(F.transform("pixels", lambda v: v - 128.0)), 3))


@query("k9a_dct_round_trip", "SELECT vec_id AS raster_id, 0.0::DOUBLE AS worst FROM embeddings")
def dct_round_trip(spark, sf):
    """Largest difference after the transform and its inverse."""
    d = vector_rasters(spark, sf).withColumn("back", R.dct(R.dct(F.transform("pixels", lambda v: v.cast("double"))), inverse=True))
    return d.select("raster_id", F.round(F.array_max(F.zip_with("pixels", "back", lambda a, b: F.abs(a - b))), 6).alias("worst"))


Q = [4, 12, 40]
@query("k9b_quantise_mse", f"SELECT raster_id, step::INTEGER AS step, round(sum((c - step * floor(c / step + 0.5)) ^ 2) / 64, 3) AS mse FROM {DCT} CROSS JOIN (SELECT unnest([4.0, 12.0, 40.0])::DOUBLE AS step) GROUP BY 1, 2")
def quantise(spark, sf):
    """Mean squared error of quantised coefficients (the transform is orthonormal, so also of pixels)."""
    c = vector_rasters(spark, sf).select("raster_id", R.dct(F.transform("pixels", lambda v: v - 128.0)).alias("c")).withColumn("step", F.explode(F.array(*map(F.lit, Q))))
    return c.select("raster_id", "step", F.round(R.mse(F.col("c"), F.transform("c", lambda v: F.col("step") * F.floor(v / F.col("step") + 0.5))), 3).alias("mse"))


@query("o5a_channel_stats", f"SELECT c, round(avg(v), 6) AS mean, round(stddev_pop(v), 6) AS std FROM (SELECT i % 4 AS c, p[i + 1] / 255.0::DOUBLE AS v FROM {BLOCK} CROSS JOIN (SELECT unnest(range(64)) AS i)) GROUP BY c")
def channel_stats(spark, sf):
    d = vector_rasters(spark, sf).select(F.posexplode("pixels").alias("i", "v")).select((F.col("i") % 4).cast("long").alias("c"), (F.col("v") / 255.0).alias("v"))
    return d.groupBy("c").agg(F.round(F.avg("v"), 6).alias("mean"), F.round(F.stddev_pop("v"), 6).alias("std"))


@query("d1_text_rasters", f"SELECT raster_id, h AS height, sum(v)::DOUBLE AS total, sum(v * (i + 1))::DOUBLE AS weighted FROM {PIXELS} GROUP BY 1, 2")
def text_digest(spark, sf):
    return text_rasters(spark, sf).select("raster_id", F.col("height").cast("long").alias("height"), *digest(F.col("pixels"), 0))


HIST = f"(SELECT raster_id, label, [len([1 for v in p if v // 16 = b]) for b in range(16)] AS q FROM {TEXT})"


@query("a7_pixel_histogram", f"SELECT label, b, sum(q[b + 1])::BIGINT AS n FROM {HIST} CROSS JOIN (SELECT unnest(range(16)) AS b) GROUP BY 1, 2")
def histogram(spark, sf):
    h = text_rasters(spark, sf).select("label", F.posexplode(R.histogram(F.col("pixels"), 16)).alias("b", "n"))
    return h.groupBy("label", F.col("b").cast("long").alias("b")).agg(F.sum("n").cast("long").alias("n"))


CELLS = f"(SELECT raster_id, i // 64 AS r, i % 32 // 2 AS c, count(*) AS n, (sum(v) * 4 // count(*) + 2) // 4 AS s FROM {PIXELS} GROUP BY 1, 2, 3)"


@query("m1_lowres_augment", f"SELECT raster_id, sum(s * n)::DOUBLE AS total FROM {CELLS} GROUP BY 1")
def lowres(spark, sf):
    """Down to half the resolution and up again, as training for small renditions does."""
    r = text_rasters(spark, sf).withColumn("small", R.box_half(F.col("pixels"), 32, F.col("height")))
    up = R.nearest_double(F.col("small"), 16, F.col("height"))
    return r.select("raster_id", F.round(F.aggregate(up, F.lit(0.0), lambda s, v: s + v), 0).alias("total"))


def histogram_model(spark, sf):
    """Nearest centroid of byte histograms (4 bins, as the tiny net): one pass for centroids, one to score."""
    bins = F.transform(R.histogram(F.col("pixels"), 4), lambda n: n / F.size("pixels"))
    h = text_rasters(spark, sf).select("raster_id", "label", (F.col("raster_id") % 5).alias("fold"), bins.alias("h"))
    means = h.where("fold <> 0").groupBy("label").agg(F.array(*[F.avg(F.element_at("h", k + 1)) for k in range(4)]).alias("m"))
    classes = means.agg(F.sort_array(F.collect_list(F.struct("label", "m"))).alias("classes"))  # one row of class means
    held = h.where("fold = 0").crossJoin(F.broadcast(classes))
    return held.select("raster_id", "label", Engine.nearest(F.col("h"), F.col("classes"), 4, places=12)[0]["label"].alias("guess"))


H4 = f"(SELECT raster_id, label, raster_id % 5 AS fold, [len([1 for v in p if v // 64 = b]) / len(p)::DOUBLE for b in range(4)] AS h FROM {TEXT})"
GUESS = f"""(SELECT raster_id, label, guess FROM (SELECT t.raster_id, t.label, m.label AS guess, row_number() OVER (PARTITION BY t.raster_id ORDER BY round((h[1] - m0) ^ 2 + (h[2] - m1) ^ 2 + (h[3] - m2) ^ 2 + (h[4] - m3) ^ 2, 12), m.label) AS n
 FROM {H4} t CROSS JOIN (SELECT label, avg(h[1]) AS m0, avg(h[2]) AS m1, avg(h[3]) AS m2, avg(h[4]) AS m3 FROM {H4} WHERE fold <> 0 GROUP BY label) m WHERE fold = 0) WHERE n = 1)"""


@query("m4_tiny_model", f"SELECT * FROM {GUESS}")
def tiny(spark, sf):
    return histogram_model(spark, sf)


@query("c9_holdout_accuracy", f"SELECT count(*) AS n, round(avg((label = guess)::INT), 6) AS acc, round(1.959964::DOUBLE * sqrt(avg((label = guess)::INT) * (1 - avg((label = guess)::INT)) / count(*)), 6) AS half_width FROM {GUESS}")
def holdout(spark, sf):
    hit = F.avg((F.col("label") == F.col("guess")).cast("int"))
    return histogram_model(spark, sf).agg(F.count("*").alias("n"), F.round(hit, 6).alias("acc"), F.round(F.lit(1.959964) * F.sqrt(hit * (1 - hit) / F.count("*")), 6).alias("half_width"))


@query("e3b_confusion", f"SELECT label, guess, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY label), 6) AS recall FROM {GUESS} GROUP BY 1, 2")
def confusion(spark, sf):
    d = histogram_model(spark, sf).groupBy("label", "guess").agg(F.count("*").alias("n"))
    return d.withColumn("recall", F.round(F.col("n") / F.sum("n").over(W.partitionBy("label")), 6))


@query("e3c_accuracy_cube", f"SELECT label, guess, count(*) AS n, grouping(label)::INT AS gl, grouping(guess)::INT AS gg FROM {GUESS} GROUP BY CUBE (label, guess)")
def cube(spark, sf):
    return histogram_model(spark, sf).cube("label", "guess").agg(F.count("*").alias("n"), F.grouping("label").cast("int").alias("gl"), F.grouping("guess").cast("int").alias("gg"))


@query("k11_raw_sizes", "SELECT source, sum(octet_length(encode(coalesce(text, ''))))::BIGINT AS bytes, sum(32 * greatest(1, ceil(octet_length(encode(coalesce(text, ''))) / 32)))::BIGINT AS raster_bytes FROM documents GROUP BY source")
def sizes(spark, sf):
    n = F.octet_length(F.coalesce("text", F.lit("")))
    return table(spark, sf, "documents").groupBy("source").agg(F.sum(n).cast("long").alias("bytes"), F.sum(32 * F.greatest(F.lit(1), F.ceil(n / 32))).cast("long").alias("raster_bytes"))


@query("z10_pixels_decoded", "SELECT count(*) AS rasters, sum(h * 32)::BIGINT AS pixels, sum(8 * ceil((h - h // 4 - h // 4) / 8) * 32)::BIGINT AS roi_pixels FROM (SELECT greatest(1, ceil(octet_length(encode(coalesce(text, ''))) / 32))::BIGINT AS h FROM documents)")
def decoded(spark, sf):
    """Pixels of whole rasters against those of the middle half, in blocks."""
    h = F.greatest(F.lit(1), F.ceil(F.octet_length(F.coalesce("text", F.lit(""))) / 32)).cast("long")
    d = table(spark, sf, "documents").select(h.alias("h"))
    middle = F.col("h") - F.floor(F.col("h") / 4) - F.floor(F.col("h") / 4)
    return d.agg(F.count("*").alias("rasters"), F.sum(F.col("h") * 32).cast("long").alias("pixels"), F.sum(8 * F.ceil(middle / 8) * 32).cast("long").alias("roi_pixels"))


@query("w24_article_roi", "SELECT page_id, (strpos(html, '<article') - 1)::BIGINT AS top, (strpos(html, '</article>') + 9)::BIGINT AS bottom, length(html)::BIGINT AS n FROM pages WHERE strpos(html, '<article') > 0")
def article(spark, sf):
    d = table(spark, sf, "pages").where(F.col("html").contains("<article"))
    return d.select("page_id", (F.locate("<article", "html") - 1).cast("long").alias("top"), (F.locate("</article>", "html") + 9).cast("long").alias("bottom"), F.length("html").cast("long").alias("n"))


@query("m6_linear_score", "SELECT vec_id, round(list_sum([embedding[i]::DOUBLE * cos(i::DOUBLE) for i in range(1, 65)]), 6) AS score FROM embeddings")
def linear(spark, sf):
    w = F.array(*[F.lit(math.cos(float(i))) for i in range(1, 65)])
    s = F.aggregate(F.zip_with(F.col("embedding"), w, lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, v: s + v)
    return table(spark, sf, "embeddings").select("vec_id", F.round(s, 6).alias("score"))


CENT = "(SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings CROSS JOIN (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2)"


@query("m6_nearest_centroid", f"SELECT vec_id, label, guess FROM (SELECT e.vec_id, e.label, c.label AS guess, row_number() OVER (PARTITION BY e.vec_id ORDER BY round(sum((e.embedding[c.i]::DOUBLE - c.m) ^ 2), 9), c.label) AS n FROM embeddings e CROSS JOIN {CENT} c GROUP BY 1, 2, 3) WHERE n = 1")
def centroid(spark, sf):
    """Ten centroids of 64 values are broadcast in one row; the nearest is found in the projection."""
    e = table(spark, sf, "embeddings").select("vec_id", "label", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    means = e.groupBy("label").agg(F.array(*[F.avg(F.element_at("x", i)) for i in range(1, 65)]).alias("m"))
    classes = means.agg(F.sort_array(F.collect_list(F.struct("label", "m"))).alias("classes"))
    return e.crossJoin(F.broadcast(classes)).select("vec_id", "label", Engine.nearest(F.col("x"), F.col("classes"), 64)[0]["label"].alias("guess"))


KNN = f"(SELECT label, list(m ORDER BY i) AS m FROM {CENT} GROUP BY 1)"
COS = "list_sum([embedding[i]::DOUBLE * m[i] for i in range(1, 65)]) / sqrt(list_sum([embedding[i]::DOUBLE * embedding[i]::DOUBLE for i in range(1, 65)])) / sqrt(list_sum([m[i] * m[i] for i in range(1, 65)]))"


@query("m6_cosine_knn", f"SELECT label, vec_id, n::INTEGER AS n FROM (SELECT c.label, e.vec_id, row_number() OVER (PARTITION BY c.label ORDER BY round({COS}, 9) DESC, e.vec_id) AS n FROM embeddings e CROSS JOIN {KNN} c) WHERE n <= 5")
def knn(spark, sf):
    """The five vectors nearest by angle to each class mean: the means travel in one row, and each task keeps five a class before anything is shuffled."""
    e = table(spark, sf, "embeddings").select("vec_id", "label", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    means = e.groupBy("label").agg(F.array(*[F.avg(F.element_at("x", i)) for i in range(1, 65)]).alias("m"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    d = e.drop("label").crossJoin(F.broadcast(means)).select("label", "vec_id", F.round(dot("x", "m") / F.sqrt(dot("x", "x")) / F.sqrt(dot("m", "m")), 9).alias("c"))
    return d.withColumn("n", F.row_number().over(W.partitionBy("label").orderBy(F.desc("c"), "vec_id"))).where("n <= 5").select("label", "vec_id", "n")


KEY = "('0x' || substr(md5(vec_id::VARCHAR), 1, 6))::INTEGER"


@query("m1a_standard_augment", f"SELECT raster_id, round(list_sum(q)::DOUBLE, 0) AS total, round(list_sum([q[i] * i for i in range(1, 65)])::DOUBLE, 0) AS weighted FROM (SELECT raster_id, [p[greatest(0, least(7, i // 8 + k // 2 % 3 - 1)) * 8 + CASE WHEN k % 2 = 1 THEN 7 - greatest(0, least(7, i % 8 + k // 6 % 3 - 1)) ELSE greatest(0, least(7, i % 8 + k // 6 % 3 - 1)) END + 1] for i in range(64)] AS q FROM (SELECT vec_id AS raster_id, {KEY} AS k, [greatest(0, least(255, floor((v::DOUBLE + 1) * 127.5)::INTEGER)) for v in embedding] AS p FROM embeddings))")
def augment(spark, sf):
    """Standard augmentation: a flip and a shift of each block, from a hash of its id."""

    def run(batches):
        for b in batches:
            out = [augmented(np.array(p, np.int64).reshape(8, 8), k).ravel() for p, k in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([float(q.sum()) for q in out]), pa.array([float((q * np.arange(1, 65)).sum()) for q in out])], ["raster_id", "total", "weighted"])

    key = F.conv(F.substring(F.md5(F.col("raster_id").cast("string")), 1, 6), 16, 10).cast("int")
    return vector_rasters(spark, sf).select("raster_id", "pixels", key.alias("key")).mapInArrow(run, "raster_id long, total double, weighted double")


SPAN = "(SELECT page_id, octet_length(encode(substr(html, 1, strpos(html, '<article') - 1))) AS a, octet_length(encode(substr(html, 1, strpos(html, '</article>') + 9))) AS b, [('0x' || v)::INTEGER for v in regexp_extract_all(hex(encode(html)), '..')] AS p FROM pages WHERE strpos(html, '<article') > 0 AND strpos(html, '</article>') > strpos(html, '<article'))"


@query("w24_article_decode", f"SELECT page_id, (ceil(b / 32) - a // 32)::BIGINT AS lines, list_sum(p[a // 32 * 32 + 1 : ceil(b / 32)::BIGINT * 32])::BIGINT AS total FROM {SPAN}")
def article_decode(spark, sf):
    """The region of interest of a page is decoded, and nothing after it: the article's lines of the page's raster, from its PNG."""

    def run(batches):
        for b in batches:
            ids, lines, totals = [], [], []
            for i, html in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), strict=True):
                start, end = html.find(b"<article"), html.find(b"</article>") + 10
                top, bottom = start // 32, -(-end // 32)
                rows = codec.png_decode(codec.png_encode(codec.text_raster(html)), bottom)[top:]
                ids.append(i), lines.append(bottom - top), totals.append(int(rows.sum()))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(lines, pa.int64()), pa.array(totals, pa.int64())], ["page_id", "lines", "total"])

    d = table(spark, sf, "pages").where(F.locate("</article>", "html") > F.locate("<article", "html")).where(F.locate("<article", "html") > 0)
    return d.select("page_id", "html").mapInArrow(run, "page_id long, lines long, total long")


POINTS = "(SELECT page_id, strpos(html, '<article') AS top, strpos(html, '</article>') AS bottom, unnest(range(1, len(string_split(html, '<p>')))) AS k, string_split(html, '<p>') AS s FROM pages)"


@query("j6_points_in_region", f"SELECT page_id, count(*) AS points, sum((pos BETWEEN top AND bottom)::INT)::BIGINT AS inside FROM (SELECT *, list_sum([length(s[i]) + 3 for i in range(1, k + 1)]) - 2 AS pos FROM {POINTS}) GROUP BY 1")
def points(spark, sf):
    """Paragraph starts joined with the article's region of their page: an equi-join by page, then the range."""
    pages = table(spark, sf, "pages")
    parts = pages.select("page_id", F.posexplode(F.split("html", "<p>")).alias("k", "s"))
    w = W.partitionBy("page_id").orderBy("k").rowsBetween(W.unboundedPreceding, W.currentRow)
    at = parts.withColumn("at", F.sum(F.length("s") + 3).over(w) - 2).withColumn("last", F.max("k").over(W.partitionBy("page_id"))).where("k < last")
    regions = pages.select("page_id", F.locate("<article", "html").alias("top"), F.locate("</article>", "html").alias("bottom"))
    return at.join(regions, "page_id").groupBy("page_id").agg(F.count("*").alias("points"), F.sum(F.col("at").between(F.col("top"), F.col("bottom")).cast("long")).alias("inside"))
