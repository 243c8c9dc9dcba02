"""Mixing sources to target weights with a time-varying curriculum, in DataFrame functions only.

Each source has a weight schedule, piecewise linear over training progress 0..1.  Its integral is the source's weight
in the mix; targets share the token budget by weight, and stop at `cap` times the source's size (the excess is shared
again by weight: one level, found from sorted ratios).  A document's words stand at offsets along its source's demand,
in the order of md5(doc_id); inverting the schedule's integral at an offset gives the progress at which it is trained
on.  Prefix sums are taken in two steps (hash buckets of a source, then documents of a bucket), so that a source with
most of the rows is spread over all buckets.

Null source: a source of its own, last.  Null or empty text: size 0, never taken.  Null doc_id: ordered first in its
bucket.  Repeated rows are taken one by one.  An empty table gives no rows.  Other columns pass through in the struct
`row`, whatever their names.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .common import WORD, written

#: Weight over progress: knots (progress, weight).  The integrals are 3, 1 and 2.
SCHEDULES = (((0.0, 4.0), (1.0, 2.0)), ((0.0, 0.5), (1.0, 1.5)), ((0.0, 2.0), (0.5, 2.0), (1.0, 2.0)))

Schedule = Sequence[tuple[float, float]]


def integral(knots: Schedule) -> list[float]:
    """The integral from 0 to each knot."""
    out = [0.0]
    for (t0, w0), (t1, w1) in zip(knots, knots[1:], strict=False):
        out.append(out[-1] + (t1 - t0) * (w0 + w1) / 2)
    return out


def progress_at(share: Column, knots: Schedule) -> Column:
    """Progress at which `share` of the schedule's integral is reached."""
    done = integral(knots)
    area = share * F.lit(done[-1])
    out = F.lit(float(knots[-1][0]))
    for (t0, w0), (t1, w1), a0, a1 in reversed(list(zip(knots, knots[1:], done, done[1:], strict=False))):
        slope, rest = (w1 - w0) / (t1 - t0), area - F.lit(a0)
        root = F.lit(w0) + F.sqrt(F.greatest(F.lit(0.0), F.lit(w0 * w0) + F.lit(2 * slope) * rest))
        x = F.when(root > 0, 2 * rest / root).otherwise(0.0)
        out = F.when(area < a1, F.lit(t0) + F.greatest(F.lit(0.0), F.least(F.lit(t1 - t0), x))).otherwise(out)
    return out


def size_of(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def targets(totals: DataFrame, schedules: Sequence[Schedule], budget: float, cap: float) -> DataFrame:
    """Rows (skey, source, source_size, class, target) from rows (skey, source, source_size), one a source."""
    weights = F.array(*[F.lit(integral(s)[-1]) for s in schedules])
    order = W.orderBy(F.col("source").asc_nulls_last())
    ranked = totals.withColumn("class", ((F.row_number().over(order) - 1) % len(schedules)).cast("int"))
    ranked = ranked.withColumn("weight", F.element_at(weights, F.col("class") + 1)).withColumn("most", F.lit(cap) * F.col("source_size"))
    by_ratio = W.orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last())
    before, rest, whole = by_ratio.rowsBetween(W.unboundedPreceding, -1), by_ratio.rowsBetween(0, W.unboundedFollowing), by_ratio.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    level = (F.lit(budget) * F.sum("source_size").over(whole) - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / F.sum("weight").over(rest)
    ranked = ranked.withColumn("level_here", level)
    ranked = ranked.withColumn("level", F.max(F.when(F.col("level_here") <= F.col("most") / F.col("weight"), F.col("level_here"))).over(whole))
    return ranked.select("skey", "source_size", "class", F.coalesce(F.least(F.col("most"), F.col("level") * F.col("weight")), F.col("most")).alias("target"))


#: Documents that a bucket of a source should hold; buckets are the first 3 to 5 hex digits of md5(id).
BUCKET = 4096


def placed(docs: DataFrame, schedules: Sequence[Schedule], budget: float, cap: float, id_col: str, text_col: str, source_col: str, keep: Sequence[str] | None) -> DataFrame:
    """Rows (row, id, size, source_size, target, taken, first_position, positions), in no order.

    A row's columns travel in the struct `row`, so none can clash with ours.  The buckets only divide the work: their
    number follows that of the documents, and no result depends on it.
    """
    digits, n = 3, docs.count()
    while digits < 5 and n > BUCKET * 16**digits:
        digits += 1
    key = F.coalesce(F.concat(F.lit("s"), F.col(source_col).cast("string")), F.lit("n"))
    turn = F.coalesce(F.md5(F.col(id_col).cast("string")), F.lit(""))
    rows = docs.select(F.struct(*(docs.columns if keep is None else keep)).alias("row"), F.col(id_col).alias("id"), F.col(source_col).alias("source"), key.alias("skey"), turn.alias("turn_key"), size_of(text_col).alias("size"))
    rows = rows.withColumn("bucket", F.substring("turn_key", 1, digits))
    sums = written(rows.groupBy("skey", "source", "bucket").agg(F.sum("size").alias("words")))
    totals = sums.groupBy("skey", "source").agg(F.sum("words").alias("source_size"))
    shares = targets(totals, schedules, budget, cap)
    starts = sums.select("skey", "bucket", F.coalesce(F.sum("words").over(W.partitionBy("skey").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    per_bucket = starts.join(shares, "skey")
    in_bucket = W.partitionBy("skey", "bucket").orderBy("turn_key", "id", "size").rowsBetween(W.unboundedPreceding, -1)
    out = rows.drop("source").join(per_bucket, ["skey", "bucket"]).withColumn("before", F.col("start") + F.coalesce(F.sum("size").over(in_bucket), F.lit(0)))
    # the source's demand is a line of `target` words; a document's words lie on it at `before`, and again each source_size later
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    out = out.withColumn("copies", whole).withColumn("rest", F.floor("target") - F.col("copies") * F.col("source_size"))
    part = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), F.col("rest") - F.col("before")))
    out = out.withColumn("taken", F.col("copies") * F.col("size") + part)
    n = F.when(F.col("size") > 0, F.ceil(F.col("taken") / F.col("size"))).otherwise(0).cast("int")
    share = lambda i: (i * F.col("source_size") + F.col("before")) / F.col("target")
    progress = lambda i: F.coalesce(*[F.when(F.col("class") == c, progress_at(share(i), s)) for c, s in enumerate(schedules)])
    out = out.withColumn("first_position", F.when(F.col("taken") > 0, progress(F.lit(0))))
    out = out.withColumn("positions", F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), progress)).otherwise(F.array().cast("array<double>")))
    return out.select("row", "id", "size", "source_size", "target", "taken", "first_position", "positions")


def mix(docs: DataFrame, schedules: Sequence[Schedule] = SCHEDULES, budget: float = 1.5, cap: float = 2.0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", keep: Sequence[str] | None = None) -> DataFrame:
    """Rows (row, id, size, source_size, target, taken, first_position, positions), in order of training.

    `row` holds the input's columns, or those in `keep`.  `taken` counts whole copies and a part of one; a source's sum
    is its target rounded down.  `positions` has the progress 0..1 at which each copy begins.  The rows are
    range-partitioned and sorted by the first position (never taken: last).
    """
    out = placed(docs, schedules, budget, cap, id_col, text_col, source_col, keep)
    return out.repartitionByRange(F.col("first_position").asc_nulls_last(), "id").sortWithinPartitions(F.col("first_position").asc_nulls_last(), "id")


def copies(docs: DataFrame, schedules: Sequence[Schedule] = SCHEDULES, budget: float = 1.5, cap: float = 2.0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """Rows (row, position, copy), one for each copy that the mix takes, in order of training; a part of a copy is a whole row.

    Whole texts cross two shuffles: to the bucket that places them, and to their range of positions.
    """
    out = placed(docs, schedules, budget, cap, id_col, text_col, source_col, None)
    out = out.select("row", "id", F.posexplode("positions").alias("copy", "position"))
    return out.repartitionByRange("position", "id", "copy").sortWithinPartitions("position", "id", "copy").select("row", "position", "copy")


#: The op8 contract in SQL.
ORACLE = r"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size, coalesce(md5(doc_id::VARCHAR), '') AS h FROM documents),
t AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
r AS (SELECT *, ((row_number() OVER (ORDER BY source ASC NULLS LAST)) - 1) % 3 AS k FROM t),
w AS (SELECT *, CASE k WHEN 0 THEN 3.0::DOUBLE WHEN 1 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS weight, 2.0::DOUBLE * source_size AS most FROM r),
l AS (SELECT *, (1.5::DOUBLE * (sum(source_size) OVER ())::DOUBLE - coalesce(sum(most) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE)) / sum(weight) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS here FROM w),
g AS (SELECT *, max(CASE WHEN here <= most / weight THEN here END) OVER () AS level FROM l),
s AS (SELECT source, source_size, k, coalesce(least(most, level * weight), most) AS target FROM g),
c AS (SELECT d.doc_id, d.size, s.source_size, s.k, s.target, coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.h, d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before,
  CASE WHEN s.source_size > 0 THEN floor(s.target / s.source_size) ELSE 0 END::BIGINT AS copies FROM d JOIN s ON d.source IS NOT DISTINCT FROM s.source),
p AS (SELECT *, (copies * size + greatest(0, least(size, floor(target)::BIGINT - copies * source_size - before)))::BIGINT AS taken FROM c),
q AS (SELECT *, CASE WHEN size > 0 THEN ceil(taken / size) ELSE 0 END::BIGINT AS n_copies FROM p),
a AS (SELECT *, CASE WHEN taken > 0 THEN before / target END AS first_share, CASE WHEN taken > 0 THEN ((n_copies - 1) * source_size + before) / target END AS last_share FROM q)
SELECT doc_id, size, source_size, target, taken, n_copies, PLACE(first_share) AS first_position, PLACE(last_share) AS last_position FROM a
"""
# progress at a share of the three schedules' integrals, by the quadratic formula
_place = "CASE k WHEN 0 THEN CASE WHEN {x} * 3.0::DOUBLE < 3.0::DOUBLE THEN 2 * ({x} * 3.0::DOUBLE) / (4.0::DOUBLE + sqrt(greatest(0.0::DOUBLE, 16.0::DOUBLE - 4.0::DOUBLE * ({x} * 3.0::DOUBLE)))) ELSE 1.0::DOUBLE END WHEN 1 THEN CASE WHEN {x} < 1.0::DOUBLE THEN CASE WHEN {x} = 0 THEN 0.0::DOUBLE ELSE 2 * {x} / (0.5::DOUBLE + sqrt(greatest(0.0::DOUBLE, 0.25::DOUBLE + 2.0::DOUBLE * {x}))) END ELSE 1.0::DOUBLE END ELSE CASE WHEN {x} * 2.0::DOUBLE < 1.0::DOUBLE THEN 2 * ({x} * 2.0::DOUBLE) / 4.0::DOUBLE WHEN {x} * 2.0::DOUBLE < 2.0::DOUBLE THEN 0.5::DOUBLE + 2 * ({x} * 2.0::DOUBLE - 1.0::DOUBLE) / 4.0::DOUBLE ELSE 1.0::DOUBLE END END"
for _x in ("first_share", "last_share"):
    ORACLE = ORACLE.replace(f"PLACE({_x})", f"CASE WHEN {_x} IS NOT NULL THEN {_place.format(x=_x)} END")
