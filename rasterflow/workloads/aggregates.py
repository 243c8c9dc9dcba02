"""Queries of aggregation under an error bound, over four streams of frames."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import aggregation as A
from ..registry import query
from ..sources.rasters import STREAM_SQL, STREAMS

R6 = lambda c: F.round(c, 6)


def union(parts):
    out = None
    for p in parts:
        out = p if out is None else out.unionByName(p)
    return out


def each(f):
    """f of every stream, with its name."""
    return lambda spark, sf: union(f(frames(spark, sf)).withColumn("stream", F.lit(name)) for name, frames in STREAMS.items())


def each_sql(body: str) -> str:
    return " UNION ALL ".join(f"SELECT '{name}' AS stream, * FROM ({body.replace('FRAMES', sql)})" for name, sql in STREAM_SQL.items())


query("w16_streams", each_sql("SELECT count(*) AS n, round(avg(y), 6) AS mean_y, round(var_samp(y), 6) AS var_y, round(corr(x, y), 6) AS rho, round(corr(weak, y), 6) AS rho_weak FROM FRAMES"))(
    each(lambda f: f.agg(F.count("*").alias("n"), R6(F.avg("y")).alias("mean_y"), R6(F.var_samp("y")).alias("var_y"), R6(F.corr("x", "y")).alias("rho"), R6(F.corr("weak", "y")).alias("rho_weak")))
)
query("b6_exact_mean", each_sql("SELECT round(avg(y), 6) AS estimate, count(y) AS target_calls FROM FRAMES"))(each(lambda f: A.exact(f).withColumn("estimate", R6("estimate"))))

SAMPLED = "(SELECT * FROM FRAMES ORDER BY md5('0-' || frame_id), frame_id LIMIT 100)"
query("b5_plain_sampling", each_sql(f"SELECT round(avg(y), 6) AS estimate, round(1.959964::DOUBLE * sqrt(var_samp(y) / count(*) * (1 - count(*) / (SELECT count(*) FROM FRAMES)::DOUBLE)), 6) AS half_width FROM {SAMPLED}"))(
    each(lambda f: A.control_variate(f, 100).select(R6("plain").alias("estimate"), R6("plain_half_width").alias("half_width")))
)
CV = f"""SELECT round(my - c * (mx - mu), 5) AS estimate, round(1.959964::DOUBLE * sqrt(greatest(0, vy - 2 * c * cov + c * c * vx) / n * (1 - n / total::DOUBLE)), 5) AS half_width, n AS target_calls
 FROM (SELECT *, CASE WHEN vx > 0 THEN {{C}} ELSE 0.0 END AS c FROM (SELECT count(*) AS n, avg(y) AS my, avg(x) AS mx, var_samp(y) AS vy, var_samp(x) AS vx, covar_samp(y, x) AS cov FROM {SAMPLED}) CROSS JOIN (SELECT avg(x) AS mu, count(*) AS total FROM FRAMES))"""
R5 = lambda c: F.round(c, 5)
query("b4_control_variate", each_sql(CV.replace("{C}", "cov / vx")))(each(lambda f: A.control_variate(f, 100).select(R5("estimate").alias("estimate"), R5("half_width").alias("half_width"), "target_calls")))
query("b4a_fixed_coefficient", each_sql(CV.replace("CASE WHEN vx > 0 THEN {C} ELSE 0.0 END", "0.05::DOUBLE")))(each(lambda f: A.control_variate(f, 100, coef=0.05).select(R5("estimate").alias("estimate"), R5("half_width").alias("half_width"), "target_calls")))
query("b4b_residual_variance", each_sql("SELECT round(var_samp(y) * (1 - corr(x, y) ^ 2), 6) AS residual, round(var_samp(y) * (1 - corr(weak, y) ^ 2), 6) AS residual_weak FROM FRAMES"))(
    each(lambda f: f.agg(R6(F.var_samp("y") * (1 - F.pow(F.corr("x", "y"), 2))).alias("residual"), R6(F.var_samp("y") * (1 - F.pow(F.corr("weak", "y"), 2))).alias("residual_weak")))
)

NEED = "ceil(q / (1 + q / total))::BIGINT"
SWEEP = f"""SELECT eps, n_plain, n_cv, n_weak, round(n_plain / 4.0::DOUBLE, 4) AS plain_s, round(total / 1995.0::DOUBLE + n_cv / 4.0::DOUBLE, 4) AS cv_s, round(total / 527.0::DOUBLE + n_cv / 4.0::DOUBLE, 4) AS cv_full_s, total / 1995.0::DOUBLE < (n_plain - n_cv) / 4.0::DOUBLE AS pays FROM
 (SELECT eps, total, {NEED.replace('q', '(1.959964::DOUBLE * 1.959964::DOUBLE * v / (eps * m * eps * m))')} AS n_plain, {NEED.replace('q', '(1.959964::DOUBLE * 1.959964::DOUBLE * v * (1 - r * r) / (eps * m * eps * m))')} AS n_cv, {NEED.replace('q', '(1.959964::DOUBLE * 1.959964::DOUBLE * v * (1 - rw * rw) / (eps * m * eps * m))')} AS n_weak
 FROM (SELECT count(*)::DOUBLE AS total, avg(y) AS m, var_samp(y) AS v, round(corr(x, y), 9) AS r, round(corr(weak, y), 9) AS rw FROM FRAMES) CROSS JOIN (SELECT unnest([0.01, 0.02, 0.03, 0.04, 0.05])::DOUBLE AS eps))"""


def sweep(f):
    """Target calls and modelled seconds over requested errors, relative to the mean; low-resolution and full decoding."""
    s = f.agg(F.count("*").cast("double").alias("total"), F.avg("y").alias("m"), F.var_samp("y").alias("v"), F.round(F.corr("x", "y"), 9).alias("r"), F.round(F.corr("weak", "y"), 9).alias("rw"))
    s = s.withColumn("eps", F.explode(F.array(*[F.lit(e) for e in (0.01, 0.02, 0.03, 0.04, 0.05)])))
    need = lambda v: A.required_n(v, F.col("eps") * F.col("m"), population=F.col("total"))
    s = s.withColumn("n_plain", need(F.col("v"))).withColumn("n_cv", need(F.col("v") * (1 - F.col("r") * F.col("r")))).withColumn("n_weak", need(F.col("v") * (1 - F.col("rw") * F.col("rw"))))
    time = lambda pre: F.round(A.total_time(F.col("total"), F.lit(pre), F.lit(250000.0), F.col("n_cv"), F.lit(4.0)), 4)
    return s.select("eps", "n_plain", "n_cv", "n_weak", F.round(F.col("n_plain") / 4.0, 4).alias("plain_s"), time(1995.0).alias("cv_s"), time(527.0).alias("cv_full_s"), (F.col("total") / 1995.0 < (F.col("n_plain") - F.col("n_cv")) / 4.0).alias("pays"))


query("b7_required_samples", each_sql(SWEEP))(each(sweep))

COVER = """SELECT round(avg((abs(est - truth) <= 1.959964::DOUBLE * sqrt(var))::INT), 6) AS coverage, round(var_samp(est) / nullif(var_samp(my), 0), 4) AS variance_ratio FROM
 (SELECT my, truth, my - c * (mx - mu) AS est, greatest(0, vy - c * cov) / n * (1 - n / total::DOUBLE) AS var FROM (SELECT *, CASE WHEN vx > 0 THEN cov / vx ELSE 0 END AS c FROM
 (SELECT seed, count(*) AS n, avg(y) AS my, avg(x) AS mx, var_samp(y) AS vy, var_samp(x) AS vx, covar_samp(y, x) AS cov FROM
 (SELECT *, row_number() OVER (PARTITION BY seed ORDER BY md5(seed::VARCHAR || '-' || frame_id), frame_id) AS r FROM FRAMES CROSS JOIN (SELECT unnest(range(40)) AS seed)) WHERE r <= 100 GROUP BY seed)
 CROSS JOIN (SELECT avg(x) AS mu, avg(y) AS truth, count(*) AS total FROM FRAMES)))"""
query("e6m_coverage", each_sql(COVER))(each(lambda f: A.coverage(f, 100, range(40)).select(R6("coverage").alias("coverage"), F.round(F.try_divide("cv_variance", "plain_variance"), 4).alias("variance_ratio"))))


@query("e7m_negative_control", f"SELECT round(corr(none, y), 6) AS rho, round(1 - corr(none, y) ^ 2, 6) AS variance_factor FROM {STREAM_SQL['v2_orders']}")
def negative(spark, sf):
    """A proxy without a connection to the count gains nothing."""
    return STREAMS["v2_orders"](spark, sf).agg(R6(F.corr("none", "y")).alias("rho"), R6(1 - F.pow(F.corr("none", "y"), 2)).alias("variance_factor"))


ADAPT = """SELECT arg_max(estimate, k) AS estimate, arg_max(half, k) AS half_width, arg_max(n, k)::BIGINT AS target_calls, max(k)::INTEGER AS rounds, arg_max(abs(estimate - m) / m, k) AS error FROM (
WITH RECURSIVE f AS (SELECT y, x, row_number() OVER (ORDER BY md5('0-' || frame_id), frame_id) AS r FROM FRAMES),
o AS (SELECT count(*) AS total, avg(y) AS m, avg(x) AS mu, 0.03::DOUBLE * avg(y) AS eps FROM f),
t AS (SELECT n, my - c * (mx - mu) AS estimate, 1.959964::DOUBLE * sqrt(greatest(0.0::DOUBLE, vy - 2 * c * cov + c * c * vx) / n * (1 - n / total::DOUBLE)) AS half FROM (SELECT *, CASE WHEN vx > 0 THEN cov / vx ELSE 0.0 END AS c FROM
 (SELECT r AS n, avg(y) OVER w AS my, avg(x) OVER w AS mx, var_samp(y) OVER w AS vy, var_samp(x) OVER w AS vx, covar_samp(y, x) OVER w AS cov FROM f WINDOW w AS (ORDER BY r)) CROSS JOIN o)),
s(k, n, half) AS (SELECT 1, least(50, total), half FROM o JOIN t ON t.n = least(50, total)
 UNION ALL SELECT k + 1, t.n, t.half FROM s CROSS JOIN o JOIN t ON t.n = least(total, greatest(s.n + 1, ceil(1.1::DOUBLE * (s.n * (s.half / eps) ^ 2))::BIGINT)) WHERE s.half > eps AND s.n < total AND k <= 8)
SELECT s.k, s.n, s.half, t.estimate, m FROM s JOIN t ON t.n = s.n CROSS JOIN o)"""


@query("b7a_adaptive", each_sql(ADAPT).replace("estimate, half_width", "estimate, half_width"))
def adaptive(spark, sf):
    """Rounds of a growing sample until the error is within 3 % of the mean."""
    rows = []
    for name, f in STREAMS.items():
        frames = f(spark, sf)
        mean = frames.agg(F.avg("y")).first()[0]
        out, tried = A.adaptive(frames, 0.03 * mean)
        r = out.first()
        rows.append((name, r["estimate"], r["half_width"], r["target_calls"], len(tried), abs(r["estimate"] - mean) / mean))
    return spark.createDataFrame(rows, "stream string, estimate double, half_width double, target_calls long, rounds int, error double")


@query("z14_video_attribution", each_sql("SELECT round(ln((1 - corr(weak, y) ^ 2) / (1 - corr(x, y) ^ 2)), 6) AS better_proxy, round(ln(1995.0::DOUBLE / 527.0::DOUBLE), 6) AS cheaper_rendition FROM FRAMES"))
def attribution(spark, sf):
    """Log gains: in target calls from the better proxy, in proxy rate from the cheaper rendition."""
    one = lambda f: f.agg(R6(F.log((1 - F.pow(F.corr("weak", "y"), 2)) / (1 - F.pow(F.corr("x", "y"), 2)))).alias("better_proxy"), R6(F.log(F.lit(1995.0) / F.lit(527.0))).alias("cheaper_rendition"))
    return each(one)(spark, sf)


@query("w22_count_per_video", f"SELECT substr(frame_id, 1, 10) AS video, round(avg(y), 6) AS per_frame, sum(y) AS total FROM {STREAM_SQL['v1_events']} GROUP BY 1")
def w22(spark, sf):
    return STREAMS["v1_events"](spark, sf).groupBy(F.substring("frame_id", 1, 10).alias("video")).agg(R6(F.avg("y")).alias("per_frame"), F.sum("y").alias("total"))
