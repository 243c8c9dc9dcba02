"""Further queries: baselines, image workloads, functions, sessions and ingestion."""

from __future__ import annotations

from pyspark.sql import Window as W, functions as F

from ..functions import cost
from ..operators import inference as I
from ..plans import select
from ..registry import query, table as t
from ..session import shared_folder
from ..sources import lines, literals as L
from ..sources.rasters import text_blobs
from ..streaming import frames as S
from .surround import folder

R6 = lambda c: F.round(c, 6)


@query("b1_naive_plans", f"SELECT model_id, format_id, least(pre, exec) AS est_tput FROM {lines.CANDIDATES} WHERE format_id = 'full' AND model_id <> 'net1'")
def b1(spark, sf):
    """The residual ladder on full renditions only."""
    return select.estimate(lines.candidates(spark, sf).where("format_id = 'full' AND model_id <> 'net1'")).select("model_id", "format_id", "est_tput")


@query("b8_control_variate_configuration", f"SELECT model_id, format_id, exec AS exec_only, least(pre, exec) AS pipelined FROM {lines.CANDIDATES} WHERE model_id = 'net1' AND format_id = 'full'")
def b8(spark, sf):
    """One model, one format, and the estimate that leaves out preparation, beside the one that doesn't."""
    d = lines.candidates(spark, sf).where("model_id = 'net1' AND format_id = 'full'")
    return d.select("model_id", "format_id", cost.est_exec_only(F.col("pre"), F.col("exec")).alias("exec_only"), cost.est_pipelined(F.col("pre"), F.col("exec")).alias("pipelined"))


@query("b3_filter_toxic", "SELECT count(*) AS n, sum(hit::INT)::BIGINT AS passed, sum((hit AND toxic = 1)::INT)::BIGINT AS found, sum((toxic = 1)::INT)::BIGINT AS truth FROM (SELECT toxic, regexp_matches(text, '(idiot|moron|worthless|clown)') AS hit FROM documents JOIN labels USING (doc_id))")
def b3(spark, sf):
    """A cheap word filter before the costly check."""
    j = t(spark, sf, "documents").select("doc_id", F.col("text").rlike("(idiot|moron|worthless|clown)").alias("hit")).join(t(spark, sf, "labels"), "doc_id")
    return j.agg(F.count("*").alias("n"), F.count_if("hit").alias("passed"), F.count_if(F.col("hit") & (F.col("toxic") == 1)).alias("found"), F.count_if(F.col("toxic") == 1).alias("truth"))


@query("w1_two_classes")
def w1(spark, sf):
    """English or not, and good or bad: held-out accuracy and balanced accuracy of the ladder's middle net."""
    blobs, out = text_blobs(spark, sf), None
    quality = t(spark, sf, "labels").select(F.col("doc_id").alias("raster_id"), F.col("quality").cast("string").alias("q"))
    tasks = {"english": blobs.withColumn("label", (F.col("label") == "en").cast("string")), "quality": blobs.join(quality, "raster_id").select("raster_id", "payload", F.col("q").alias("label"))}
    for name, rows in tasks.items():
        own, held = rows.where("raster_id % 5 <> 0"), rows.where("raster_id % 5 = 0")
        g = I.infer(I.renditions(held, ("full",)), I.train(own, I.BINS["res34"]))
        per = g.groupBy("label").agg(F.count("*").alias("n"), F.avg((F.col("label") == F.col("guess")).cast("double")).alias("recall"))
        one = per.agg(F.lit(name).alias("task"), F.sum("n").alias("n"), (F.sum(F.col("n") * F.col("recall")) / F.sum("n")).alias("acc"), F.avg("recall").alias("balanced"))
        out = one if out is None else out.unionByName(one)
    return out


@query("w11_full_load", "SELECT config, round(abs(pipelined - measured) / measured, 6) AS pipelined, round(abs(additive - measured) / measured, 6) AS additive FROM (SELECT config, measured, least(pre, exec) AS pipelined, 1 / (1 / pre + 1 / exec) AS additive FROM " + L.REGIMES.sql() + ") WHERE config = 'full_load'")
def w11(spark, sf):
    d = L.REGIMES.df(spark).where("config = 'full_load'")
    err = lambda e: R6(cost.rel_error(e(F.col("pre"), F.col("exec")), F.col("measured")))
    return d.select("config", err(cost.est_pipelined).alias("pipelined"), err(cost.est_additive).alias("additive"))


@query("a2_object_aggregates", "SELECT user_id, max_by(event_id, (ts, event_id)) AS last, min_by(event_type, (ts, event_id)) AS first_type, len(list(event_id)) AS n FROM events GROUP BY 1")
def a2(spark, sf):
    k = F.struct("ts", "event_id")
    return t(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_id", k).alias("last"), F.min_by("event_type", k).alias("first_type"), F.count("event_id").alias("n"))


@query("f2_dates", "SELECT year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::INT AS d FROM orders GROUP BY 1, 2")
def f2(spark, sf):
    d = F.col("o_orderdate")
    return t(spark, sf, "orders").groupBy(F.year(d).alias("y"), F.quarter(d).alias("q")).agg(F.count("*").alias("n"), F.max(F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date"))).alias("d"))


@query("f3_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, greatest(p_size, 10)::INT AS g, (p_partkey % 7)::BIGINT AS m FROM part")
def f3(spark, sf):
    return t(spark, sf, "part").select("p_partkey", R6(F.log("p_retailprice")).alias("l"), R6(F.sqrt("p_size")).alias("s"), F.greatest("p_size", F.lit(10)).cast("int").alias("g"), F.pmod("p_partkey", F.lit(7)).cast("long").alias("m"))


@query("f5_maps", "SELECT e AS event_type, n FROM (SELECT event_type AS e, count(*) AS n FROM events GROUP BY 1)")
def f5(spark, sf):
    """Counts as one map and back."""
    c = t(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    m = c.agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select(F.explode("m").alias("event_type", "n"))


@query("f7_nulls", "SELECT doc_id, coalesce(toxic, -1)::INT AS toxic, nullif(quality, 0)::INT AS good FROM documents LEFT JOIN labels USING (doc_id)")
def f7(spark, sf):
    j = t(spark, sf, "documents").select("doc_id").join(t(spark, sf, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"), F.nullif("quality", F.lit(0)).alias("good"))


@query("j11_lateral", "SELECT c.c_custkey, o.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) o")
def j11(spark, sf):
    """Each customer's largest order: one aggregation instead of a correlated join."""
    o = t(spark, sf, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.max_by("o_orderkey", F.struct("o_totalprice", (-F.col("o_orderkey")).alias("k"))).alias("o_orderkey"))
    return o.join(t(spark, sf, "customer").select("c_custkey"), "c_custkey", "left_semi")


@query("t2_distributed_sort", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey)::BIGINT AS place FROM orders")
def t2(spark, sf):
    """All orders by price, with their places: range-partitioned and sorted, then counts of the parts before are added; no task sees all rows."""
    path = shared_folder(spark, "sorted")
    o = t(spark, sf, "orders").select("o_orderkey", "o_totalprice").repartitionByRange("o_totalprice", "o_orderkey").sortWithinPartitions("o_totalprice", "o_orderkey")
    o.withColumn("part", F.spark_partition_id()).write.parquet(path)
    o = spark.read.parquet(path)
    parts = o.groupBy("part").agg(F.count("*").alias("n"))  # a row for each partition
    before = parts.select("part", F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    own = F.row_number().over(W.partitionBy("part").orderBy("o_totalprice", "o_orderkey"))
    return o.join(F.broadcast(before), "part").select("o_orderkey", (F.col("before") + own).cast("long").alias("place"))


SESSIONS = """SELECT user_id, count(*) AS sessions, max(n)::BIGINT AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
 (SELECT *, coalesce((ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE)::INT, 0) AS new FROM events)) GROUP BY 1, 2) GROUP BY 1"""


@query("st4_sessions", SESSIONS)
def st4(spark, sf):
    """Sessions of users as a stream, in complete mode: those that are still open at the end too."""
    d = S.finished(S.sessions(S.source(spark, f"{sf}/events.parquet")), "complete", shared_folder(spark, "stream"))
    return d.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


@query("st4_sessions_batch", SESSIONS)
def st4b(spark, sf):
    return S.sessions(S.batch(spark, f"{sf}/events.parquet")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


@query("w25_nightly_ingestion", "SELECT count(*) AS n, sum(value > 50)::BIGINT AS large FROM events")
def w25(spark, sf):
    """Micro-batches into numbered folders, each replaced if it is run again."""
    path = folder(spark)
    S.into(S.source(spark, f"{sf}/events.parquet"), f"{path}/out", f"{path}/state", lambda d: d.select("event_id", "value"))
    return spark.read.parquet(f"{path}/out").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("large"))
