"""Queries that encode, decode and score renditions in the Arrow stage, over all documents or pages."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..operators import codec, inference as I, udfs
from ..plans import engine as E, profile
from ..registry import query
from ..sources.rasters import text_blobs
from . import studies
from .rasters import PIXELS


@query("w5_format_matrix", "SELECT f AS format_id, count(*) AS n FROM documents CROSS JOIN (VALUES ('full'), ('half_png'), ('half_dct95'), ('half_dct75')) x(f) GROUP BY 1")
def format_matrix(spark, sf):
    return I.renditions(text_blobs(spark, sf)).groupBy("format_id").agg(F.count("*").alias("n"))


@query("k11_compression")
def compression(spark, sf):
    r = I.renditions(text_blobs(spark, sf)).groupBy("format_id").agg(F.sum("n_bytes").alias("stored"), F.sum(F.col("height") * F.col("width")).alias("raw"))
    return r.withColumn("ratio", F.col("raw") / F.col("stored"))


def kernel(name, schema, f, source="documents", sql=None):
    """A query that applies f(raster) -> tuple to every raster of a table."""

    def run(spark, sf):
        kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string()}
        names = [c.split()[0] for c in schema.split(", ")]
        types = [kinds[c.split()[1]] for c in schema.split(", ")]

        def go(batches):
            for b in batches:
                rows = [f(codec.text_raster(p)) for p in b.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([r[k] for r in rows], t) for k, t in enumerate(types)]], ["raster_id", *names])

        return text_blobs(spark, sf, source).select("raster_id", "payload").mapInArrow(go, f"raster_id long, {schema}")

    return query(name, sql)(run)


def same(a, b) -> bool:
    return bool(np.array_equal(a, b))


def middle(r):
    h, w = r.shape
    return w // 4, h // 4, w - w // 4, h - h // 4


def early(r):
    """Sum of the first half of the rows, from a decoder that inflates no more."""
    blob, n = codec.png_encode(r), -(-len(r) // 2)
    return int(codec.png_decode(blob).sum()), int(codec.png_decode(blob, n).sum())


def roi(r):
    left, top, right, bottom = middle(r)
    p, i = codec.dct_encode(r, 75)
    return same(codec.dct_decode(p, i, (left, top, right, bottom)), codec.dct_decode(p, i)[top:bottom, left:right]), same(codec.dct_decode(p, i, (left, top, right, bottom), False), codec.dct_decode(p, i, deblock=False)[top:bottom, left:right])


def scanlines(r):
    """The middle by scanlines: whether it equals decode-and-crop, the block rows inflated, and those that the region touches."""
    left, top, right, bottom = middle(r)
    p, i = codec.dct_encode(r, 75)
    lines = codec.Scanlines(p, i, left, right)
    lines.skip(top)
    got = lines.read(bottom - top)
    return same(got, codec.dct_decode(p, i, deblock=False)[top:bottom, left:right]), lines.inflated


def pyramid(r):
    """Sums of each level, from the shortest prefix of the payload that holds it."""
    p, i = codec.pyramid_encode(r, 2)
    return tuple(int(codec.pyramid_decode(p[: i[3 - level]], i, level).sum()) for level in range(3))


TRUE = "SELECT doc_id AS raster_id, {} FROM documents"
HALVES = f"""px AS MATERIALIZED {PIXELS}, l1 AS (SELECT raster_id, r, c, (a + b + 2) // 4 AS s, (max(h) + 1) // 2 AS h FROM (SELECT raster_id, i // 64 AS r, i % 32 // 2 AS c, max(h) AS h, sum(CASE WHEN i // 32 % 2 = 0 THEN v ELSE 0 END) AS a, sum(CASE WHEN i // 32 = least(i // 64 * 2 + 1, h - 1) THEN v ELSE 0 END) AS b FROM px GROUP BY 1, 2, 3) GROUP BY 1, 2, 3, 4),
l2 AS (SELECT raster_id, (a + b + 2) // 4 AS s FROM (SELECT raster_id, r // 2 AS q, c // 2 AS c, sum(CASE WHEN r % 2 = 0 THEN s ELSE 0 END) AS a, sum(CASE WHEN r = least(r // 2 * 2 + 1, h - 1) THEN s ELSE 0 END) AS b FROM l1 GROUP BY 1, 2, 3))"""
kernel("k4_png_early_stop", "whole long, part long", early, sql=f"SELECT raster_id, sum(v)::BIGINT AS whole, sum(CASE WHEN i // 32 < (h + 1) // 2 THEN v ELSE 0 END)::BIGINT AS part FROM {PIXELS} GROUP BY 1")
kernel("k1_roi_decode", "filtered boolean, plain boolean", roi, sql=TRUE.format("true AS filtered, true AS plain"))
kernel("k3_scanline_decode", "equal boolean, inflated long", scanlines, sql=TRUE.format("true AS equal, CASE WHEN b > t THEN ceil(b / 8) - t // 8 ELSE 0 END::BIGINT AS inflated").replace("FROM documents", "FROM (SELECT doc_id, h // 4 AS t, h - h // 4 AS b FROM (SELECT doc_id, greatest(1, ceil(octet_length(encode(coalesce(text, ''))) / 32))::BIGINT AS h FROM documents))"))
kernel("k6_multi_resolution", "level0 long, level1 long, level2 long", pyramid, sql=f"WITH {HALVES} SELECT a.raster_id, level0, level1, level2 FROM (SELECT raster_id, sum(v)::BIGINT AS level0 FROM px GROUP BY 1) a JOIN (SELECT raster_id, sum(s)::BIGINT AS level1 FROM l1 GROUP BY 1) b USING (raster_id) JOIN (SELECT raster_id, sum(s)::BIGINT AS level2 FROM l2 GROUP BY 1) c USING (raster_id)")
kernel("k9_quality_ladder", "q20 double, q75 double, q95 double, ordered boolean", lambda r: (lambda e: (*e, e[0] >= e[1] >= e[2]))([float(((codec.dct_decode(*codec.dct_encode(r, q), deblock=False).astype(float) - r) ** 2).mean()) for q in (20, 75, 95)]))
kernel("k5_reduced_fidelity", "with_filter double, without double", lambda r: (lambda p, i: tuple(float(((codec.dct_decode(p, i, deblock=d).astype(float) - r) ** 2).mean()) for d in (True, False)))(*codec.dct_encode(r, 30)))
kernel("w3_large_rasters", "rows int, stored long", lambda r: (len(r), len(codec.png_encode(r))), source="pages")


def split(spark, sf):
    blobs = text_blobs(spark, sf)
    group = F.pmod(F.xxhash64(F.md5("payload")), F.lit(5)) == 0  # copies of a text stay on one side
    return blobs.where(~group), blobs.where(group)


def graded(spark, sf, names=("res18", "res34", "res50"), formats=codec.FORMATS):
    """Rows (model_id, training, format_id, n, acc): every model with both trainings on every format, in one pass over held-out renditions."""
    own, held = split(spark, sf)
    models = {f"{n}/{t}": m for (n, t), m in I.ladder(own, names).models.items()}
    got = I.infer_all(I.renditions(held, formats), models).groupBy("model", "format_id").agg(F.count("*").alias("n"), F.avg((F.col("label") == F.col("guess")).cast("double")).alias("acc"))
    part = F.split("model", "/")
    return got.select(part[0].alias("model_id"), part[1].alias("training"), "format_id", "n", "acc")


@query("w6_training_grid")
def training_grid(spark, sf):
    """Training by format by depth."""
    return graded(spark, sf, ("res34", "res50"))


@query("r4_runtime_lesions")
def lesions(spark, sf):
    """Seconds and results of the model stage with its parts switched off; the answers must agree."""
    own, held = split(spark, sf)
    m = I.train(own, I.BINS["res18"])
    r = I.renditions(held, ("half_png",))
    rows = []
    for name, runtime in (("all", I.Runtime()), ("no threads", I.Runtime(threads=0)), ("no reuse", I.Runtime(reuse=False)), ("batch 8", I.Runtime(batch=8))):
        began = time.perf_counter()
        got = I.infer(r, m, runtime).agg(F.count("*").alias("n"), F.sum((F.col("guess") == F.col("label")).cast("int")).alias("hits")).first()
        rows.append((name, got["n"], got["hits"], time.perf_counter() - began))
    return spark.createDataFrame(rows, "lesion string, n long, hits long, seconds double")


@query("e2m_stage_breakdown")
def breakdown(spark, sf):
    """Microseconds of each stage for an item: decoding and every operator of the declared and the optimised chain, and the deepest net; measured."""
    e, rows = studies.engine(spark, sf), []
    for f in e.formats:
        for name, chain in (("declared", E.CHAIN), ("optimised", e.chain(f))):
            rows += [(f, name, i, op, s * 1e6) for i, op, s in e.timed(f, chain)]
    x, m = np.ones((64, 16)), np.ones((4, 16))
    began = time.perf_counter()
    for _ in range(50):
        ((x[:, None, :] - m) ** 2).sum(2).argmin(1)
    rows.append(("all", "net", 0, E.NETS[-1].model_id, (time.perf_counter() - began) / 50 / 64 * 1e6))
    return spark.createDataFrame(rows, "format_id string, chain string, place int, op string, microseconds double")


@query("k5_choose_fidelity")
def choose_fidelity(spark, sf):
    """Proxy and target with and without the filter over block edges: accuracy and measured decoding of each, and the faster that loses at most a point."""
    own, held = split(spark, sf)
    rows, out = I.renditions(held, ("half_dct75",)).persist(), []
    for name in ("res18", "res50"):
        m = I.train(own, I.BINS[name])
        for deblock in (True, False):
            began = time.perf_counter()
            acc = I.infer(rows, m, deblock=deblock).agg(F.avg((F.col("guess") == F.col("label")).cast("double"))).first()[0]
            out.append((name, deblock, acc, time.perf_counter() - began))
    rows.unpersist()
    best = {n: max(a or 0.0 for k, _, a, _ in out if k == n) for n in ("res18", "res50")}
    chosen = {n: min((s, d) for k, d, a, s in out if k == n and (a or 0.0) >= best[n] - 0.01)[1] for n in ("res18", "res50")}
    return spark.createDataFrame([(*r, chosen[r[0]] == r[1]) for r in out], "model_id string, deblock boolean, acc double, seconds double, chosen boolean")


@query("z13_quality_sweep")
def quality_sweep(spark, sf):
    """Accuracy, size and decoding time of half-size block-DCT renditions over the quality, in one pass over held-out items."""
    own, held = split(spark, sf)
    m = spark.sparkContext.broadcast(I.train(own, I.BINS["res50"], "lowres"))

    def go(batches):
        for b in batches:
            for p, label in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                small, rows = codec.half(codec.text_raster(p)), []
                for q in (10, 30, 50, 75, 95):
                    payload, index = codec.dct_encode(small, q)
                    began = time.perf_counter()
                    r = codec.dct_decode(payload, index)
                    took = time.perf_counter() - began
                    guess = m.value.labels[int(m.value.scores(I.features(r, m.value.bins)[None, :])[0].argmax())]
                    rows.append((q, len(payload), took, guess == label))
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["quality", "n_bytes", "seconds", "hit"])

    s = held.where("label IS NOT NULL").select("payload", "label").mapInArrow(go, "quality long, n_bytes long, seconds double, hit boolean")
    return s.groupBy("quality").agg(F.count("*").alias("n"), F.avg("n_bytes").alias("n_bytes"), (F.avg("seconds") * 1e6).alias("microseconds"), F.avg(F.col("hit").cast("double")).alias("acc"))


@query("e16m_training_overhead")
def training_overhead(spark, sf):
    """Seconds of regular training and of the low-resolution rounds after it, and their ratio; measured."""
    own, _ = split(spark, sf)
    rows = []
    for name in ("res18", "res34", "res50"):
        began = time.perf_counter()
        m = I.train(own, I.BINS[name])
        middle_ = time.perf_counter()
        I.train(own, I.BINS[name], "lowres", start=m)
        rows.append((name, middle_ - began, time.perf_counter() - middle_))
    return spark.createDataFrame([(n, a, b, b / a) for n, a, b in rows], "model_id string, regular double, lowres double, overhead double")


@query("w7_own_stacks")
def own_stacks(spark, sf):
    """Items a second of the same score by each kind of user-defined function; measured."""
    rows, out = text_blobs(spark, sf).persist(), []
    n = rows.count()
    for impl in udfs.IMPLEMENTATIONS:
        out.append((impl, n / profile.seconds(udfs.stack(rows, impl), 2)))
    rows.unpersist()
    return spark.createDataFrame(out, "stack string, tput double")


@query("w17_own_cores")
def own_cores(spark, sf):
    """Items a second of the optimised and the declared chain on 1, 2 and 4 tasks at a time; measured."""
    own, held = split(spark, sf)
    m, out = I.train(own, I.BINS["res18"]), []
    for name, f in (("optimised", "half_png"), ("unoptimised", "full")):
        rows = I.renditions(held, (f,)).persist()
        n = rows.count()
        for cores in (1, 2, 4):
            out.append((name, cores, n / profile.seconds(I.infer(rows.coalesce(cores), m), 2)))
        rows.unpersist()
    return spark.createDataFrame(out, "chain string, cores int, tput double")


@query("w15_system_factors")
def system_factors(spark, sf):
    """Parts of the runtime added one by one, on full and small renditions: batches, buffer reuse, decoding threads, the optimised chain's rendition; measured, answers agree."""
    own, held = split(spark, sf)
    m, out = I.train(own, I.BINS["res50"]), []
    for f in ("full", "half_png"):
        rows = I.renditions(held, (f,)).persist()
        n = rows.count()
        for k, (name, r) in enumerate((("one by one", I.Runtime(threads=0, batch=1, reuse=False)), ("+ batches", I.Runtime(threads=0, reuse=False)), ("+ reuse", I.Runtime(threads=0)), ("+ threads", I.Runtime()), ("+ producers", I.Runtime(threads=None, consumers=2)))):
            got = I.infer(rows, m, r)
            hits = got.agg(F.sum((F.col("guess") == F.col("label")).cast("long"))).first()[0]
            out.append((f, k, name, n, hits, n / profile.seconds(got)))
        rows.unpersist()
    return spark.createDataFrame(out, "format_id string, step int, part string, n long, hits long, tput double")


@query("c6_profile")
def measured(spark, sf):
    """Stage rates measured here, in three regimes, with the three estimates and their errors."""
    own, held = split(spark, sf)
    m = I.train(own, I.BINS["res50"])
    rows = I.renditions(held, ("full",)).persist()
    out = []
    for name, work in (("pre_bound", 1), ("middle", 40), ("exec_bound", 400)):
        r = profile.measure(rows, m, I.Runtime(work=work))
        pre, ex, real = r["pre"], r["exec"], r["measured"]
        est = {"pipelined": min(pre, ex), "additive": 1 / (1 / pre + 1 / ex), "exec_only": ex}
        out += [(name, int(r["n"]), pre, ex, real, k, v, abs(v - real) / real) for k, v in est.items()]
    rows.unpersist()
    return spark.createDataFrame(out, "config string, n long, pre double, exec double, measured double, estimator string, est double, error double")
