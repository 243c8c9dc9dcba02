"""Queries of the operators around the methods: joins, aggregates, windows, sets, functions, over the given tables."""

from __future__ import annotations

from pyspark.sql import Window as W, functions as F

from ..operators import joins
from ..plans.engine import Engine
from ..registry import query, table as t

R6 = lambda c: F.round(c, 6)

@query("j3_broadcast_join", "SELECT r_name, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def j3(spark, sf):
    """Nation and region are 25 and 5 rows by definition."""
    o = t(spark, sf, "orders").join(t(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    o = o.join(F.broadcast(t(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return o.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("j4_merge_join", "SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_quantity > 10 GROUP BY 1")
def j4(spark, sf):
    l = t(spark, sf, "lineitem").where("l_quantity > 10")
    j = l.join(t(spark, sf, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("j6_band_join", "SELECT e.event_id, count(*) AS near FROM events e JOIN events x ON x.event_type = 'error' AND x.ts BETWEEN e.ts - INTERVAL 5 MINUTE AND e.ts + INTERVAL 5 MINUTE WHERE e.event_type = 'purchase' GROUP BY 1")
def j6(spark, sf):
    e = t(spark, sf, "events")
    left = e.where("event_type = 'purchase'").select("event_id", "ts")
    right = e.where("event_type = 'error'").select(F.col("ts").alias("other"))
    return joins.band(left, right, "ts", "other", 300).groupBy("event_id").agg(F.count("*").alias("near"))


@query("j7_asof_join", "SELECT e.event_id, x.event_id AS last_signup FROM (SELECT * FROM events WHERE event_type = 'click') e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'signup' GROUP BY 1, 2) x ON x.user_id = e.user_id AND e.ts >= x.ts")
def j7(spark, sf):
    e = t(spark, sf, "events")
    right = e.where("event_type = 'signup'").select("user_id", "ts", F.col("event_id").alias("last_signup"))
    return joins.asof(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), right, "user_id", "ts", "last_signup").select("event_id", "last_signup")


@query("j9_semi_anti", "SELECT (SELECT count(*) FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)) AS labelled, (SELECT count(*) FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)) AS unlabelled")
def j9(spark, sf):
    d, l = t(spark, sf, "documents").select("doc_id"), t(spark, sf, "labels").select("doc_id")
    return d.join(l, "doc_id", "left_semi").agg(F.count("*").alias("labelled")).crossJoin(d.join(l, "doc_id", "left_anti").agg(F.count("*").alias("unlabelled")))


@query("j9_calibration_exclusion", "SELECT count(*) AS n FROM documents d WHERE doc_id % 5 = 0 AND NOT EXISTS (SELECT 1 FROM benchmark b WHERE md5(b.text) = md5(d.text))")
def j9b(spark, sf):
    b = t(spark, sf, "benchmark").select(F.md5("text").alias("k"))
    return t(spark, sf, "documents").where("doc_id % 5 = 0").select(F.md5("text").alias("k")).join(b, "k", "left_anti").agg(F.count("*").alias("n"))


@query("j10_outer_empty_frames", "SELECT count(*) AS empty_orders FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey WHERE l_orderkey IS NULL")
def j10(spark, sf):
    j = t(spark, sf, "orders").join(t(spark, sf, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left")
    return j.where("l_orderkey IS NULL").agg(F.count("*").alias("empty_orders"))


@query("a3_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) FILTER (WHERE value > 50) AS large FROM events GROUP BY 1 HAVING count(*) > 1")
def a3(spark, sf):
    return t(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count_if(F.col("value") > 50).alias("large"), F.count("*").alias("n")).where("n > 1").drop("n")


@query("a3_hll_sketch")
def a3b(spark, sf):
    """Distinct users of days from mergeable sketches, rolled up to the month."""
    days = t(spark, sf, "events").groupBy(F.to_date("ts").alias("day")).agg(F.hll_sketch_agg("user_id").alias("s"))
    return days.groupBy(F.trunc("day", "month").alias("month")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users"))


@query("a4_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(avg(l_discount), 4) AS d, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def a4(spark, sf):
    return t(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.avg("l_discount"), 4).alias("d"), F.grouping_id().alias("g"))


@query("a4_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def a4b(spark, sf):
    d = t(spark, sf, "documents")
    return d.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"))


@query("a5_statistics", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev_samp(l_quantity), 6) AS s, round(regr_slope(l_extendedprice, l_quantity), 4) AS b FROM lineitem GROUP BY 1")
def a5(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(R6(F.corr("l_quantity", "l_extendedprice")).alias("r"), R6(F.stddev_samp("l_quantity")).alias("s"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("b"))


@query("a6_pivot", "SELECT lang, count(*) FILTER (WHERE quality = 0) AS bad, count(*) FILTER (WHERE quality = 1) AS good FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def a6(spark, sf):
    j = t(spark, sf, "documents").select("doc_id", "lang").join(t(spark, sf, "labels"), "doc_id")
    p = j.groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1)))
    return p.select("lang", F.coalesce("0", F.lit(0)).alias("bad"), F.coalesce("1", F.lit(0)).alias("good"))


@query("n1_ranking", "SELECT p_brand, p_partkey, r, d FROM (SELECT p_brand, p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS n FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice DESC)) WHERE n <= 3")
def n1(spark, sf):
    w = W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"))
    p = t(spark, sf, "part").select("p_brand", "p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.row_number().over(W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")).alias("n"))
    return p.where("n <= 3").drop("n")


@query("n2_frame_delta", "SELECT user_id, event_id, round(value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), 6) AS delta FROM events")
def n2(spark, sf):
    return t(spark, sf, "events").select("user_id", "event_id", R6(F.col("value") - F.lag("value").over(W.partitionBy("user_id").orderBy("ts", "event_id"))).alias("delta"))


@query("n3_running_mean", "SELECT event_id, round(avg(value) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS m FROM events")
def n3(spark, sf):
    return t(spark, sf, "events").select("event_id", R6(F.avg("value").over(W.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(-4, 0))).alias("m"))


@query("n4_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch(ts) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def n4(spark, sf):
    """Events of a type in the hour before each: a window by type and stretch of time, so that a type's events are spread."""
    e = t(spark, sf, "events").select("event_id", "event_type", (F.unix_micros(F.to_timestamp("ts")) / 1e6).alias("s"))
    return joins.back_range(e, "event_type", "s", 3600).select("event_id", "n")


@query("t1_top_k", "SELECT page_id, length(html)::BIGINT AS n FROM pages ORDER BY length(html) DESC, page_id LIMIT 10")
def t1(spark, sf):
    return t(spark, sf, "pages").select("page_id", F.length("html").cast("long").alias("n")).orderBy(F.desc("n"), "page_id").limit(10)


@query("t3_stratified_sample", "SELECT source, count(*) AS n FROM (SELECT source, row_number() OVER (PARTITION BY source ORDER BY md5('0-' || doc_id)) AS r FROM documents) WHERE r <= 5 GROUP BY 1")
def t3(spark, sf):
    d = t(spark, sf, "documents").select("source", F.row_number().over(W.partitionBy("source").orderBy(F.md5(F.concat(F.lit("0-"), F.col("doc_id").cast("string"))))).alias("r"))
    return d.where("r <= 5").groupBy("source").agg(F.count("*").alias("n"))


@query("u1_set_operations", "SELECT 'both' AS k, count(*) AS n FROM (SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels) UNION ALL SELECT 'rest', count(*) FROM (SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels)")
def u1(spark, sf):
    d, l = t(spark, sf, "documents").select("doc_id"), t(spark, sf, "labels").select("doc_id")
    return d.intersect(l).agg(F.count("*").alias("n")).select(F.lit("both").alias("k"), "n").unionByName(d.exceptAll(l.distinct()).distinct().agg(F.count("*").alias("n")).select(F.lit("rest").alias("k"), "n"))


@query("f1_strings", "SELECT p_partkey, upper(p_name) AS u, md5(p_name) AS h, length(replace(p_type, ' ', ''))::INT AS n, levenshtein(p_name, p_type)::INT AS lev FROM part")
def f1(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("u"), F.md5("p_name").alias("h"), F.length(F.replace("p_type", F.lit(" "))).alias("n"), F.levenshtein("p_name", "p_type").alias("lev"))


@query("f6_json", "SELECT event_type, sum((props::JSON ->> '$.k')::BIGINT)::BIGINT AS k FROM events GROUP BY 1")
def f6(spark, sf):
    return t(spark, sf, "events").groupBy("event_type").agg(F.sum(F.from_json("props", "k long")["k"]).alias("k"))


@query("q1_correlated_subquery", "SELECT p_partkey FROM part p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part x WHERE x.p_brand = p.p_brand)")
def q1(spark, sf):
    p = t(spark, sf, "part")
    return spark.sql("SELECT p_partkey FROM {part} p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM {part} x WHERE x.p_brand = p.p_brand)", part=p)


@query("w21_presence_cascade", "SELECT count(*) AS frames, sum((n > 3)::INT)::BIGINT AS reach, sum((n > 3 AND err > 0)::INT)::BIGINT AS found, sum((err > 0)::INT)::BIGINT AS truth FROM (SELECT date_trunc('hour', ts), count(*) AS n, sum((event_type = 'error')::INT) AS err FROM events GROUP BY 1)")
def w21(spark, sf):
    """Binary presence: a cheap count filters frames, the costly check sees only those that pass."""
    f = t(spark, sf, "events").groupBy(F.date_trunc("hour", "ts").alias("f")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("err"))
    return f.agg(F.count("*").alias("frames"), F.count_if(F.col("n") > 3).alias("reach"), F.count_if((F.col("n") > 3) & (F.col("err") > 0)).alias("found"), F.count_if(F.col("err") > 0).alias("truth"))


THR = "(SELECT n AS th, sum(pos) OVER (ORDER BY n DESC) / sum(pos) OVER ()::DOUBLE AS recall, sum(tot) OVER (ORDER BY n DESC)::BIGINT AS passed FROM (SELECT n, sum((err > 0)::INT) AS pos, count(*) AS tot FROM (SELECT date_trunc('hour', ts), count(*) AS n, sum((event_type = 'error')::INT) AS err FROM events GROUP BY 1) GROUP BY n))"


@query("b3a_filter_threshold", f"SELECT th, round(recall, 6) AS recall, passed FROM {THR} WHERE recall >= 0.95 ORDER BY th DESC LIMIT 1")
def b3a(spark, sf):
    """The largest threshold of a cheap score that keeps 95 % of the frames with the object."""
    f = t(spark, sf, "events").groupBy(F.date_trunc("hour", "ts").alias("f")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("err"))
    g = f.groupBy(F.col("n").alias("th")).agg(F.count_if(F.col("err") > 0).alias("pos"), F.count("*").alias("tot"))
    down = W.orderBy(F.desc("th"))
    g = g.select("th", (F.sum("pos").over(down) / F.sum("pos").over(W.partitionBy())).alias("recall"), F.sum("tot").over(down).alias("passed"))
    return g.where("recall >= 0.95").orderBy(F.desc("th")).limit(1).select("th", R6("recall").alias("recall"), "passed")


@query("c2b_pass_rates", "SELECT source, round(avg((n_chars BETWEEN 500 AND 2000)::INT), 6) AS pass_rate FROM documents GROUP BY 1")
def c2b(spark, sf):
    return t(spark, sf, "documents").groupBy("source").agg(R6(F.avg(F.col("n_chars").between(500, 2000).cast("int"))).alias("pass_rate"))


KINDS = {"vowels": "[aeiou]", "capitals": "[A-Z]", "wide": "[^\\x00-\\x7F]", "accents": "[àâçéèêëîôûäöüßñáíóú]"}
PREFIX = "(SELECT doc_id, lang, doc_id % 5 = 0 AS held, z.k AS n_prefix, CASE WHEN z.k = 0 THEN coalesce(text, '') ELSE substr(coalesce(text, ''), 1, z.k) END AS x FROM documents CROSS JOIN (VALUES (0), (32), (128), (512)) z(k) WHERE lang IS NOT NULL)"
SHARES = "(SELECT doc_id, lang, held, n_prefix, " + ", ".join(f"len(regexp_extract_all(x, '{p}')) / greatest(length(x), 1)::DOUBLE AS {k}" for k, p in KINDS.items()) + f" FROM {PREFIX})"


@query(
    "w26_prefix_decoding",
    f"""WITH h AS MATERIALIZED {SHARES}, m AS (SELECT n_prefix, lang AS guess, {', '.join(f'avg({k}) AS {k}' for k in KINDS)} FROM h WHERE NOT held GROUP BY 1, 2),
g AS (SELECT h.n_prefix, h.lang, arg_min(m.guess, (round({' + '.join(f'(h.{k} - m.{k}) ^ 2' for k in KINDS)}, 12), m.guess)) AS guess FROM h JOIN m ON m.n_prefix = h.n_prefix WHERE held GROUP BY h.n_prefix, h.lang, h.doc_id)
SELECT n_prefix, count(*) AS n, round(avg((lang = guess)::INT), 6) AS acc FROM g GROUP BY 1""",
)
def w26(spark, sf):
    """Text as the medium: the language of a document from a decoded prefix of it (0: the whole), by nearest class means."""
    d = t(spark, sf, "documents").where("lang IS NOT NULL").select("doc_id", "lang", (F.col("doc_id") % 5 == 0).alias("held"), F.coalesce("text", F.lit("")).alias("text"))
    d = d.withColumn("n_prefix", F.explode(F.array(*map(F.lit, (0, 32, 128, 512))))).withColumn("part", F.when(F.col("n_prefix") == 0, F.col("text")).otherwise(F.expr("left(text, n_prefix)")))
    x = F.array(*[F.regexp_count("part", F.lit(p)) / F.greatest(F.length("part"), F.lit(1)) for p in KINDS.values()])
    h = d.select("lang", "held", "n_prefix", x.alias("x"))
    means = h.where("NOT held").groupBy("n_prefix", F.col("lang").alias("label")).agg(F.array(*[F.avg(F.element_at("x", k + 1)) for k in range(len(KINDS))]).alias("m"))
    classes = means.groupBy("n_prefix").agg(F.sort_array(F.collect_list(F.struct("label", "m"))).alias("classes"))
    guess = Engine.nearest(F.col("x"), F.col("classes"), len(KINDS), places=12)[0]["label"]
    return h.where("held").join(F.broadcast(classes), "n_prefix").groupBy("n_prefix").agg(F.count("*").alias("n"), R6(F.avg((guess == F.col("lang")).cast("int"))).alias("acc"))


@query("w26_turns_by_role", "SELECT role, count(*) AS n, sum(length(text))::BIGINT AS chars, sum(length(text) - length(replace(text, ' ', '')) + 1)::BIGINT AS words FROM conversations GROUP BY 1")
def w26b(spark, sf):
    """Characters and words of turns by role."""
    return t(spark, sf, "conversations").groupBy("role").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"), F.sum(F.length("text") - F.length(F.replace("text", F.lit(" "))) + 1).cast("long").alias("words"))


@query("j10_full_outer", "SELECT a IS NOT NULL AS in_first, b IS NOT NULL AS in_second, count(*) AS n, sum((x = y)::INT)::BIGINT AS agree FROM (SELECT user_id AS a, count(*) AS x FROM events WHERE event_type = 'error' GROUP BY 1) p FULL JOIN (SELECT user_id AS b, count(*) AS y FROM events WHERE event_type = 'purchase' GROUP BY 1) q ON p.a = q.b GROUP BY 1, 2")
def j10b(spark, sf):
    """Results of two plans side by side, whichever has an item."""
    e = t(spark, sf, "events")
    p = e.where("event_type = 'error'").groupBy(F.col("user_id").alias("a")).agg(F.count("*").alias("x"))
    q = e.where("event_type = 'purchase'").groupBy(F.col("user_id").alias("b")).agg(F.count("*").alias("y"))
    j = p.join(q, F.col("a") == F.col("b"), "full")
    return j.groupBy(F.col("a").isNotNull().alias("in_first"), F.col("b").isNotNull().alias("in_second")).agg(F.count("*").alias("n"), F.sum((F.col("x") == F.col("y")).cast("long")).alias("agree"))
