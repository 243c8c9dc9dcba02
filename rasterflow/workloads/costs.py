"""Queries of cost modelling, plan selection, placement, geometry and price."""

from __future__ import annotations

from pyspark.sql import Window as W, functions as F

from ..functions import cost, geometry
from ..plans import dag, placement, select
from ..registry import query
from ..sources import lines, literals as L
from .studies import FLAGGED, flagged

R6 = lambda c: F.round(c, 6)
EXAMPLE, REGIMES = L.EXAMPLE.sql(), L.REGIMES.sql()
PLANS = f"(SELECT model_id || '/' || format_id AS plan_id, *, least(pre, exec) AS est_tput FROM {EXAMPLE})"


def example(spark):
    return select.estimate(L.EXAMPLE.df(spark).select(F.concat_ws("/", "model_id", "format_id").alias("plan_id"), "*"))


def line_plans(spark, sf):
    return select.estimate(lines.plans(spark, sf))


def _cols(df):
    return df.select("plan_id", "acc", R6("est_tput").alias("est_tput"))


@query("c1a_throughput_floor", f"SELECT plan_id, acc, round(est_tput, 6) AS est_tput FROM {lines.PLANS} WHERE est_tput >= 1000 ORDER BY acc DESC, plan_id LIMIT 1")
def c1a(spark, sf):
    return _cols(select.choose(line_plans(spark, sf), "acc", "est_tput", 1000.0))


@query("c1b_accuracy_floor", f"SELECT plan_id, acc, round(est_tput, 6) AS est_tput FROM {lines.PLANS} WHERE acc >= 50 ORDER BY est_tput DESC, plan_id LIMIT 1")
def c1b(spark, sf):
    return _cols(select.choose(line_plans(spark, sf), "est_tput", "acc", 50.0))


@query("c1c_infeasible_closest", f"SELECT plan_id, acc, round(est_tput, 6) AS est_tput FROM {lines.PLANS} ORDER BY abs(est_tput - 9000), plan_id LIMIT 1")
def c1c(spark, sf):
    return _cols(select.choose(line_plans(spark, sf), "acc", "est_tput", 9000.0, on_infeasible="closest"))


@query("c1d_unconstrained", f"SELECT plan_id, acc, round(est_tput, 6) AS est_tput FROM {lines.PLANS} ORDER BY est_tput DESC, plan_id LIMIT 1")
def c1d(spark, sf):
    return _cols(select.choose(line_plans(spark, sf), "est_tput"))


@query("c1e_effective_floor", f"SELECT model_id, format_id, least(1000.0::DOUBLE, pre) AS bound FROM {lines.CANDIDATES}")
def c1e(spark, sf):
    return lines.candidates(spark, sf).select("model_id", "format_id", cost.effective_floor(F.lit(1000.0), F.col("pre")).alias("bound"))


STAGES = f"(SELECT *, coalesce(exp(sum(ln(CASE WHEN pass_rate > 0 THEN pass_rate ELSE 1 END)) OVER (PARTITION BY plan_id ORDER BY stage ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)), 1.0) AS reach FROM {lines.CASCADES})"



@query("c2_cascade_arriving", f"SELECT plan_id, round(1 / sum(reach / rate), 4) AS exec FROM {STAGES} GROUP BY plan_id")
def c2(spark, sf):
    reach = F.coalesce(F.exp(F.sum(F.log(F.when(F.col("pass_rate") > 0, F.col("pass_rate")).otherwise(1.0))).over(W.partitionBy("plan_id").orderBy("stage").rowsBetween(W.unboundedPreceding, -1))), F.lit(1.0))
    stages = lines.cascades(spark, sf).withColumn("share", reach)
    plans = stages.groupBy("plan_id").agg(F.sort_array(F.collect_list(F.struct("stage", "rate", "share"))).alias("s"))
    return plans.select("plan_id", F.round(cost.cascade_exec(F.col("s")), 4).alias("exec"))


@query("c2a_cascade_literal", f"SELECT plan_id, round(1 / sum(reach / rate), 4) AS exec FROM {STAGES} GROUP BY plan_id")
def c2a(spark, sf):
    plans = lines.cascades(spark, sf).groupBy("plan_id").agg(F.sort_array(F.collect_list(F.struct("stage", "rate", F.col("pass_rate").alias("share")))).alias("s"))
    return plans.select("plan_id", F.round(cost.cascade_exec(F.col("s"), "literal"), 4).alias("exec"))


EST = f"SELECT config, pre, exec, measured, exec AS exec_only, 1 / (1 / pre + 1 / exec) AS additive, least(pre, exec) AS pipelined FROM {REGIMES}"


def estimators(spark):
    pre, ex = F.col("pre"), F.col("exec")
    return L.REGIMES.df(spark).select("config", "pre", "exec", "measured", cost.est_exec_only(pre, ex).alias("exec_only"), cost.est_additive(pre, ex).alias("additive"), cost.est_pipelined(pre, ex).alias("pipelined"))


@query("c3_est_exec_only", f"SELECT plan_id AS config, exec AS exec_only FROM {lines.PLANS}")
def c3(spark, sf):
    return lines.plans(spark, sf).select(F.col("plan_id").alias("config"), cost.est_exec_only(F.col("pre"), F.col("exec")).alias("exec_only"))


@query("c4_est_additive", f"SELECT config, round(additive, 6) AS additive FROM ({EST})")
def c4(spark, sf):
    return estimators(spark).select("config", R6("additive").alias("additive"))


@query("c5_est_pipelined", f"SELECT config, pipelined FROM ({EST})")
def c5(spark, sf):
    return estimators(spark).select("config", "pipelined")


@query("c5a_est_overhead", f"SELECT config, round(least(pre, exec) * (1 - 0.14::DOUBLE), 6) AS est FROM {REGIMES}")
def c5a(spark, sf):
    return L.REGIMES.df(spark).select("config", R6(cost.est_pipelined(F.col("pre"), F.col("exec"), 0.14)).alias("est"))


LONG = f"(SELECT config, e.name, abs(e.est - measured) / measured AS err FROM ({EST}) CROSS JOIN LATERAL (VALUES ('pipelined', pipelined), ('additive', additive), ('exec_only', exec_only)) AS e(name, est) WHERE measured IS NOT NULL)"


def errors(spark):
    long = estimators(spark).unpivot(["config", "measured"], ["pipelined", "additive", "exec_only"], "name", "est").where("measured IS NOT NULL")
    return long.select("config", "name", cost.rel_error(F.col("est"), F.col("measured")).alias("err"))


@query("c7_rel_error", f"SELECT config, name, round(err, 6) AS err FROM {LONG}")
def c7(spark, sf):
    return errors(spark).select("config", "name", R6("err").alias("err"))


@query("c7a_mean_error", f"SELECT name, round(avg(err), 6) AS mean_err FROM {LONG} GROUP BY name")
def c7a(spark, sf):
    return errors(spark).groupBy("name").agg(R6(F.avg("err")).alias("mean_err"))


@query("c7b_best_estimator", f"SELECT config, name FROM (SELECT config, name, rank() OVER (PARTITION BY config ORDER BY round(err, 9)) AS r FROM {LONG}) WHERE r = 1")
def c7b(spark, sf):
    return errors(spark).withColumn("r", F.rank().over(W.partitionBy("config").orderBy(F.round("err", 9)))).where("r = 1").select("config", "name")


@query("c8_regime", f"SELECT config, CASE WHEN abs(pre - exec) / greatest(pre, exec) <= 0.25 THEN 'balanced' WHEN pre < exec THEN 'pre_bound' ELSE 'exec_bound' END AS regime FROM {REGIMES}")
def c8(spark, sf):
    return L.REGIMES.df(spark).select("config", cost.regime(F.col("pre"), F.col("exec")).alias("regime"))


SLOW = f"(SELECT * FROM {lines.PLANS} WHERE model_id >= 'net5')"


@query("c10a_no_model_is_fast_enough", f"SELECT format_id, model_id, exec < pre AS exec_bound FROM (SELECT *, row_number() OVER (PARTITION BY format_id ORDER BY exec >= pre DESC, CASE WHEN exec >= pre THEN -acc ELSE -exec END, model_id) AS n FROM {SLOW}) WHERE n = 1")
def c10a(spark, sf):
    """The deep nets are slower than the preparation of small renditions: the fastest is kept and flagged."""
    return select.matched_model(lines.plans(spark, sf).where("model_id >= 'net5'")).select("format_id", "model_id", "exec_bound")


@query("c10_matched_model", f"SELECT format_id, model_id, exec_bound FROM (SELECT *, exec < pre AS exec_bound, row_number() OVER (PARTITION BY format_id ORDER BY exec < pre, CASE WHEN exec >= pre THEN -acc ELSE -exec END, model_id) AS n FROM {lines.PLANS}) WHERE n = 1")
def c10(spark, sf):
    return select.matched_model(lines.plans(spark, sf)).select("format_id", "model_id", "exec_bound")


MODELS, FORMATS = L.MODELS.sql(), L.FORMATS.sql()
CAND = f"(SELECT m.model_id, m.depth, m.exec, f.format_id, f.short_side, f.lossless, f.pre FROM {MODELS.replace('AS lit', 'AS m')} CROSS JOIN {FORMATS.replace('AS lit', 'AS f')})"


def cand(spark):
    return select.candidates(L.MODELS.df(spark), L.FORMATS.df(spark))


@query("p1_candidates", f"SELECT model_id, format_id, pre, exec FROM {CAND}")
def p1(spark, sf):
    return cand(spark).select("model_id", "format_id", "pre", "exec")


TRAIN = L.TRAINING.sql()
JOINED = f"(SELECT c.*, t.training, t.acc, least(c.pre, c.exec) AS est_tput FROM {CAND} c JOIN {TRAIN.replace('AS lit', 'AS t')} ON t.model_id = c.model_id AND t.format_id = c.format_id)"


def trained(spark):
    return select.estimate(cand(spark).join(F.broadcast(L.TRAINING.df(spark)), ["model_id", "format_id"]))


@query("p1a_compatible", f"SELECT model_id, format_id, training FROM {JOINED} WHERE (training = 'lowres') = (short_side < 256)")
def p1a(spark, sf):
    sided = L.MODELS.df(spark).crossJoin(spark.createDataFrame([("regular", 256), ("lowres", 161)], "training string, train_side int"))
    plans = select.candidates(sided, L.FORMATS.df(spark), compat="resolution")
    return plans.join(L.TRAINING.df(spark), ["model_id", "format_id", "training"], "left_semi").select("model_id", "format_id", "training")


OPS = ["decode", "resize", "crop", "normalise"]


@query("p2_expand_splits", f"SELECT model_id, format_id, s AS split, array_to_string((['decode', 'resize', 'crop', 'normalise'])[1:s], '>') AS host_ops FROM {CAND} CROSS JOIN (SELECT unnest([1, 2, 3, 4])::INTEGER AS s)")
def p2(spark, sf):
    return select.expand(cand(spark), OPS).select("model_id", "format_id", "split", F.array_join("host_ops", ">").alias("host_ops"))


@query("p3_estimate", f"SELECT model_id, format_id, training, acc, est_tput FROM {JOINED}")
def p3(spark, sf):
    return trained(spark).select("model_id", "format_id", "training", "acc", "est_tput")


def undominated(rel: str, acc: str = "acc", by: str = "") -> str:
    same = f" AND a.{by} = b.{by}" if by else ""
    return f"SELECT a.* FROM {rel} a WHERE NOT EXISTS (SELECT 1 FROM {rel} b WHERE round(b.{acc}, 6) >= round(a.{acc}, 6) AND round(b.est_tput, 6) >= round(a.est_tput, 6) AND (round(b.{acc}, 6) > round(a.{acc}, 6) OR round(b.est_tput, 6) > round(a.est_tput, 6)){same})"


FRONT = undominated(JOINED)


@query("p4_frontier", f"SELECT model_id, format_id, training, acc, est_tput FROM ({FRONT})")
def p4(spark, sf):
    return select.frontier(trained(spark)).select("model_id", "format_id", "training", "acc", "est_tput")


@query("p4a_frontier_bruteforce", f"SELECT model_id, format_id, training, acc, est_tput FROM ({FRONT})")
def p4a(spark, sf):
    return select.frontier_bruteforce(trained(spark)).select("model_id", "format_id", "training", "acc", "est_tput")


LES = f"(SELECT *, tput AS est_tput FROM {FLAGGED})"


@query("p4b_frontier_by_dataset", f"SELECT dataset, lowres, dag, acc, est_tput FROM ({undominated(LES, by='dataset')})")
def p4b(spark, sf):
    return select.frontier(flagged(spark, sf).withColumn("est_tput", F.col("tput")), by=["dataset"]).select("dataset", "lowres", "dag", "acc", "est_tput")


@query("p6_model_space", f"SELECT model_id, depth, exec, round(exec / min(exec) OVER (), 6) AS over_deepest FROM {MODELS}")
def p6(spark, sf):
    return L.MODELS.df(spark).select("model_id", "depth", "exec", R6(F.col("exec") / F.min("exec").over(W.partitionBy())).alias("over_deepest"))


@query("p7_formats", f"SELECT format_id, lossless, round(pre / max(CASE WHEN format_id = 'full' THEN pre END) OVER (), 6) AS speedup FROM {FORMATS}")
def p7(spark, sf):
    full = F.max(F.when(F.col("format_id") == "full", F.col("pre"))).over(W.partitionBy())
    return L.FORMATS.df(spark).select("format_id", "lossless", R6(F.col("pre") / full).alias("speedup"))


@query("p7a_worked_example", f"SELECT plan_id, acc, est_tput FROM ({undominated(PLANS)})")
def p7a(spark, sf):
    return select.frontier(example(spark)).select("plan_id", "acc", "est_tput")


@query("p9_downsample_after_decode", f"SELECT model_id, format_id, CASE WHEN derived THEN 527.0::DOUBLE ELSE pre END AS pre, derived FROM {CAND} CROSS JOIN (SELECT unnest([true, false]) AS derived) WHERE NOT derived OR short_side < 256")
def p9(spark, sf):
    """Small inputs that are made after a full decode prepare at the full format's rate."""
    both = cand(spark).crossJoin(spark.createDataFrame([(True,), (False,)], "derived boolean")).where("NOT derived OR short_side < 256")
    return both.select("model_id", "format_id", F.when(F.col("derived"), 527.0).otherwise(F.col("pre")).alias("pre"), "derived")


@query("z11_export_plans", f"SELECT model_id, format_id, training, acc, est_tput FROM ({FRONT})")
def z11(spark, sf):
    """The frontier as JSON and back."""
    kind = "model_id string, format_id string, training string, acc double, est_tput double"
    lines = p4(spark, sf).select(F.to_json(F.struct("*")).alias("j"))
    return lines.select(F.inline(F.array(F.from_json("j", kind))))


@query("z12_guard", f"SELECT model_id, format_id, training, (training = 'regular') = (short_side = 256) AS trained_for FROM {JOINED}")
def z12(spark, sf):
    return trained(spark).select("model_id", "format_id", "training", ((F.col("training") == "regular") == (F.col("short_side") == 256)).alias("trained_for"))


@query("m7_weights_per_format", f"SELECT format_id, model_id, training FROM (SELECT *, row_number() OVER (PARTITION BY format_id, model_id ORDER BY acc DESC, training) AS n FROM {TRAIN}) WHERE n = 1")
def m7(spark, sf):
    return select.choose(L.TRAINING.df(spark), "acc", tie=("training",), by=("format_id", "model_id")).select("format_id", "model_id", "training")


CHAIN = L.Relation("plan_id string, exec double, place int, op string, seconds double, host_only boolean", tuple((p, e, i + 1, o, s, i == 0) for p, e in (("res18", 12592.0), ("res50", 4513.0), ("rcnn", 4.0)) for i, (o, s) in enumerate((("decode", 5.0e-3), ("resize", 1.2e-3), ("crop", 1.0e-5), ("normalise", 8.0e-4), ("reorder", 3.0e-4)))))
SPLITS = f"""(SELECT plan_id, place AS split, 4.0::DOUBLE / sum(seconds) OVER w AS host_rate,
 1 / (1 / exec + coalesce(sum(seconds) OVER (PARTITION BY plan_id ORDER BY place ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0.0) / 20.0::DOUBLE) AS accel_rate
 FROM {CHAIN.sql()} WINDOW w AS (PARTITION BY plan_id ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW))"""


@query("l1_splits", f"SELECT plan_id, split, round(host_rate, 4) AS host_rate, round(accel_rate, 4) AS accel_rate FROM {SPLITS}")
def l1(spark, sf):
    return placement.splits(CHAIN.df(spark), cores=4.0, speedup=20.0).select("plan_id", "split", F.round("host_rate", 4).alias("host_rate"), F.round("accel_rate", 4).alias("accel_rate"))


@query("l2_placement_rule", f"SELECT config, CASE WHEN exec < pre THEN 'host' ELSE 'accel' END AS place FROM {REGIMES}")
def l2(spark, sf):
    return L.REGIMES.df(spark).select("config", placement.rule(F.col("pre"), F.col("exec")).alias("place"))


@query("l3_best_split", f"SELECT plan_id, split FROM (SELECT *, row_number() OVER (PARTITION BY plan_id ORDER BY round(least(host_rate, accel_rate), 9) DESC, split DESC) AS n FROM {SPLITS}) WHERE n = 1")
def l3(spark, sf):
    return placement.best_split(CHAIN.df(spark), cores=4.0, speedup=20.0).select("plan_id", "split")


@query("l4_hardware_aware", f"SELECT plan_id, cores, split FROM (SELECT s.plan_id, k.cores::INTEGER AS cores, split, row_number() OVER (PARTITION BY plan_id, k.cores ORDER BY round(least(host_rate / 4 * k.cores, accel_rate), 9) DESC, split DESC) AS n FROM {SPLITS} s CROSS JOIN (SELECT unnest([4, 16, 64]) AS cores) k) WHERE n = 1")
def l4(spark, sf):
    out = None
    for cores in (4, 16, 64):
        one = placement.best_split(CHAIN.df(spark), cores=float(cores), speedup=20.0).select("plan_id", F.lit(cores).alias("cores"), "split")
        out = one if out is None else out.unionByName(one)
    return out


SHAPES = L.Relation("h int, w int", ((512, 512), (375, 500), (500, 375), (256, 256), (1080, 1920), (300, 301), (224, 640)))
CROP = f"""(SELECT *, greatest(0, floor(floor((rw - 224) / 2) * sc)) AS l, greatest(0, floor(floor((rh - 224) / 2) * sc)) AS t, least(w, ceil((floor((rw - 224) / 2) + 224) * sc)) AS r, least(h, ceil((floor((rh - 224) / 2) + 224) * sc)) AS b
 FROM (SELECT h, w, floor(h * 256 / least(h, w)::DOUBLE + 0.5) AS rh, floor(w * 256 / least(h, w)::DOUBLE + 0.5) AS rw, least(h, w) / 256::DOUBLE AS sc FROM {SHAPES.sql()}))"""


def shapes(spark):
    d = SHAPES.df(spark)
    return d, geometry.center_crop_source(F.col("h"), F.col("w"), F.lit(256.0), F.lit(224))


@query("k2_center_crop_source", f"SELECT h, w, l::BIGINT AS l, t::BIGINT AS t, r::BIGINT AS r, b::BIGINT AS b FROM {CROP}")
def k2(spark, sf):
    d, roi = shapes(spark)
    return d.select("h", "w", *[roi[k].alias(k[0]) for k in ("left", "top", "right", "bottom")])


ALIGN = f"(SELECT h, w, (8 * floor(l / 8))::BIGINT AS l, (8 * floor(t / 8))::BIGINT AS t, least(8 * ceil(w / 8), 8 * ceil(r / 8))::BIGINT AS r, least(8 * ceil(h / 8), 8 * ceil(b / 8))::BIGINT AS b FROM {CROP})"


@query("k1_align_blocks", f"SELECT * FROM {ALIGN}")
def k1(spark, sf):
    d, roi = shapes(spark)
    region = geometry.aligned(roi, F.col("h"), F.col("w"))
    return d.select("h", "w", *[region[k].cast("long").alias(k[0]) for k in ("left", "top", "right", "bottom")])


@query("k1a_block_share", f"SELECT h, w, round((r - l) / 8 * ((b - t) / 8) / (ceil(w / 8) * ceil(h / 8)), 6) AS share FROM {ALIGN}")
def k1a(spark, sf):
    d, roi = shapes(spark)
    return d.select("h", "w", R6(geometry.block_share(geometry.aligned(roi, F.col("h"), F.col("w")), F.col("h"), F.col("w"))).alias("share"))


@query("k4_early_stop_rows", f"SELECT h, w, round(b / h, 6) AS rows_share FROM {CROP}")
def k4(spark, sf):
    d, roi = shapes(spark)
    return d.select("h", "w", R6(roi["bottom"] / F.col("h")).alias("rows_share"))


@query("k8_codec_features", f"SELECT codec, feature FROM {L.CODECS.sql()} CROSS JOIN LATERAL (VALUES ('partial_decode', partial_decode), ('early_stop', early_stop), ('reduced_fidelity', reduced_fidelity), ('multi_resolution', multi_resolution)) AS f(feature, there) WHERE there")
def k8(spark, sf):
    names = ["partial_decode", "early_stop", "reduced_fidelity", "multi_resolution"]
    return L.CODECS.df(spark).unpivot(["codec"], names, "feature", "there").where("there").select("codec", "feature")


def orders_of(spark, h, w):
    rows = [(h, w, d.names(), str([o.size for o in d.ops if o.size]), dag.count(d, h, w), d in dag.prune(dag.orders(dag.Dag.standard(), h, w), h, w)) for d in dag.orders(dag.Dag.standard(), h, w)]
    return spark.createDataFrame(rows, "h int, w int, chain string, sizes string, ops long, kept boolean")


def order_sql() -> str:
    """All legal chains from positions: a recursive walk that appends any op that may come next."""
    return """WITH RECURSIVE sizes AS (SELECT * FROM (VALUES (480, 640), (512, 512)) s(h, w)),
v AS (SELECT h, w, first, fuse, CASE WHEN first = 'crop' THEN floor(224 * least(h, w) / 256.0 + 0.5)::INTEGER ELSE 224 END AS c, CASE WHEN first = 'crop' THEN 224 ELSE 256 END AS s FROM sizes CROSS JOIN (VALUES ('resize'), ('crop')) a(first) CROSS JOIN (VALUES (true), (false)) b(fuse)),
o AS (SELECT h AS h0, w AS w0, h, w, first, fuse, c, s, 'decode' AS chain, 1 AS omega, 0::BIGINT AS ops, false AS fp FROM v
 UNION ALL SELECT h0, w0,
  CASE n WHEN 'resize' THEN floor(h * s / least(h, w)::DOUBLE + 0.5)::INTEGER WHEN 'crop' THEN least(h, c) ELSE h END,
  CASE n WHEN 'resize' THEN floor(w * s / least(h, w)::DOUBLE + 0.5)::INTEGER WHEN 'crop' THEN least(w, c) ELSE w END, first, fuse, c, s, chain || '>' || n,
  CASE WHEN n IN ('cast', 'fused') THEN 4 ELSE omega END,
  ops + CASE n WHEN 'resize' THEN 7 * floor(h * s / least(h, w)::DOUBLE + 0.5)::BIGINT * floor(w * s / least(h, w)::DOUBLE + 0.5)::BIGINT * 3 * omega WHEN 'crop' THEN 0 WHEN 'cast' THEN h * w * 3 * 4 WHEN 'normalise' THEN 3 * h * w * 3 * omega WHEN 'fused' THEN 2 * h * w * 3 * 4 ELSE h * w * 3 * omega END, false
 FROM o CROSS JOIN (VALUES ('resize'), ('crop'), ('cast'), ('normalise'), ('reorder'), ('fused')) x(n)
 WHERE position(n IN chain) = 0 AND (n = 'fused') <= fuse AND (NOT fuse OR n IN ('resize', 'crop', 'fused')) AND (n <> 'normalise' OR position('cast' IN chain) > 0)
  AND (n <> 'resize' OR first = 'resize' OR position('crop' IN chain) > 0) AND (n <> 'crop' OR first = 'crop' OR position('resize' IN chain) > 0))
SELECT h0 AS h, w0 AS w, chain, ops FROM o WHERE length(chain) - length(replace(chain, '>', '')) = CASE WHEN fuse THEN 3 ELSE 5 END"""


@query("g2_dag_orders", order_sql())
def g2(spark, sf):
    return orders_of(spark, 480, 640).unionByName(orders_of(spark, 512, 512)).select("h", "w", "chain", "ops")


@query("g3_prune_rules", f"SELECT h, w, chain, ops FROM ({order_sql()}) q WHERE chain = 'decode>crop>resize>fused'")
def g3(spark, sf):
    return orders_of(spark, 480, 640).unionByName(orders_of(spark, 512, 512)).where("kept").select("h", "w", "chain", "ops")


@query("g5_best_order", f"SELECT h, w, arg_min(chain, ops) AS chain, min(ops) AS ops FROM ({order_sql()}) q GROUP BY h, w")
def g5(spark, sf):
    rows = [(h, w, b.names(), dag.count(b, h, w)) for h, w in ((480, 640), (512, 512)) for b in [dag.best(dag.Dag.standard(), h, w)]]
    return spark.createDataFrame(rows, "h int, w int, chain string, ops long")


INST, PRICE = L.INSTANCES.sql(), L.PRICES.sql()


@query("e8m_cents_per_million", f"SELECT i.vcpus, i.optimised, round(p.price_hour * 1e8 / (3600 * i.tput), 2) AS cents FROM {INST.replace('AS lit', 'AS i')} JOIN {PRICE.replace('AS lit', 'AS p')} ON p.vcpus = i.vcpus")
def e8m(spark, sf):
    return L.INSTANCES.df(spark).join(F.broadcast(L.PRICES.df(spark)), "vcpus").select("vcpus", "optimised", F.round(cost.cents_per_million(F.col("price_hour"), F.col("tput")), 2).alias("cents"))


@query("e9m_core_price_fit", f"SELECT round(regr_intercept(price_hour, vcpus), 6) AS a, round(regr_slope(price_hour, vcpus), 6) AS b, round(regr_r2(price_hour, vcpus), 6) AS r2 FROM {PRICE}")
def e9m(spark, sf):
    x, y = F.col("vcpus"), F.col("price_hour")
    return L.PRICES.df(spark).agg(R6(F.regr_intercept(y, x)).alias("a"), R6(F.regr_slope(y, x)).alias("b"), R6(F.regr_r2(y, x)).alias("r2"))


@query("e10m_match_cost", f"SELECT m.model_id, round(m.tput / (527.0::DOUBLE / 4) * 0.0639::DOUBLE, 6) AS pre_hour, 0.218::DOUBLE AS accel_hour FROM {L.DEPTHS.sql().replace('AS lit', 'AS m')}")
def e10m(spark, sf):
    return L.DEPTHS.df(spark).select("model_id", R6(cost.match_cores(F.col("tput"), F.lit(527.0)) * L.VCPU_HOUR).alias("pre_hour"), F.lit(L.ACCELERATOR_HOUR).alias("accel_hour"))


@query("e11m_match_watts", f"SELECT model_id, round(tput / (527.0::DOUBLE / 4) * 4.375::DOUBLE, 6) AS pre_watts, 70.0::DOUBLE AS accel_watts FROM {L.DEPTHS.sql()}")
def e11m(spark, sf):
    return L.DEPTHS.df(spark).select("model_id", R6(cost.match_cores(F.col("tput"), F.lit(527.0)) * L.VCPU_WATTS).alias("pre_watts"), F.lit(L.ACCELERATOR_WATTS).alias("accel_watts"))


@query("e12m_core_scaling", f"SELECT a.vcpus, a.optimised, round(a.tput / (a.vcpus / 4.0::DOUBLE * b.tput), 6) AS efficiency FROM {INST.replace('AS lit', 'AS a')} JOIN {INST.replace('AS lit', 'AS b')} ON a.optimised = b.optimised AND b.vcpus = 4")
def e12m(spark, sf):
    i = L.INSTANCES.df(spark)
    base = i.where("vcpus = 4").select("optimised", F.col("tput").alias("base"))
    return i.join(base, "optimised").select("vcpus", "optimised", R6(F.col("tput") / (F.col("vcpus") / 4.0 * F.col("base"))).alias("efficiency"))


@query("e13m_lesion_deltas", f"SELECT a.dataset, a.name, round(f.tput / a.tput, 6) AS loss FROM (SELECT dataset, CASE WHEN lowres THEN 'without dag' ELSE 'without lowres' END AS name, tput FROM {FLAGGED} WHERE lowres <> dag) a JOIN {FLAGGED[:-3]}f ON f.dataset = a.dataset AND f.lowres AND f.dag")
def e13m(spark, sf):
    d = flagged(spark, sf)
    whole = d.where("lowres AND dag").select("dataset", F.col("tput").alias("whole"))
    return d.where("lowres <> dag").join(whole, "dataset").select("dataset", F.when(F.col("lowres"), "without dag").otherwise("without lowres").alias("name"), R6(F.col("whole") / F.col("tput")).alias("loss"))


@query("e13n_factor_increments", f"SELECT dataset, k::INTEGER AS step, round(tput / lag(tput) OVER (PARTITION BY dataset ORDER BY k), 6) AS gain FROM (SELECT dataset, tput, CASE WHEN lowres THEN 2 WHEN dag THEN 1 ELSE 0 END AS k FROM {FLAGGED} WHERE dag OR NOT lowres)")
def e13n(spark, sf):
    d = flagged(spark, sf).where("dag OR NOT lowres").withColumn("step", F.when(F.col("lowres"), 2).when(F.col("dag"), 1).otherwise(0))
    return d.select("dataset", "step", R6(F.col("tput") / F.lag("tput").over(W.partitionBy("dataset").orderBy("step"))).alias("gain"))


HV = f"(SELECT dataset, acc, est_tput FROM ({undominated(LES, by='dataset')}))"


@query("e14m_hypervolume", f"SELECT dataset, round(sum(greatest(0, est_tput - below) * acc), 4) AS hypervolume FROM (SELECT *, coalesce(max(est_tput) OVER (PARTITION BY dataset ORDER BY acc DESC, est_tput DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM {HV}) GROUP BY dataset")
def e14m(spark, sf):
    return select.hypervolume(p4b(spark, sf), by=["dataset"]).select("dataset", F.round("hypervolume", 4).alias("hypervolume"))


@query("e15m_generations", f"SELECT device, round(tput / first_value(tput) OVER (ORDER BY released, tput), 6) AS ratio FROM {L.GENERATIONS.sql()}")
def e15m(spark, sf):
    return L.GENERATIONS.df(spark).select("device", R6(F.col("tput") / F.first("tput").over(W.orderBy("released", "tput"))).alias("ratio"))


@query("e4m_speedup_at_accuracy", f"SELECT dataset, round(max(CASE WHEN lowres AND dag THEN tput END) / max(CASE WHEN NOT lowres AND NOT dag THEN tput END), 6) AS speedup FROM {FLAGGED} GROUP BY dataset")
def e4m(spark, sf):
    d = flagged(spark, sf).groupBy("dataset")
    return d.agg(R6(F.max(F.when(F.col("lowres") & F.col("dag"), F.col("tput"))) / F.max(F.when(~F.col("lowres") & ~F.col("dag"), F.col("tput")))).alias("speedup"))


@query("z1_latency_limit", f"SELECT model_id, format_id, round(64 / pre + 64 / exec, 6) AS latency FROM {EXAMPLE} WHERE 64 / pre + 64 / exec <= 0.05 ORDER BY least(pre, exec) DESC, model_id || '/' || format_id LIMIT 1")
def z1(spark, sf):
    d = example(spark).withColumn("latency", cost.latency(F.lit(64), F.col("pre"), F.col("exec")))
    return select.choose(d, "est_tput", "latency", 0.05, "le").select("model_id", "format_id", R6("latency").alias("latency"))


@query("z2_cents_limit", f"SELECT vcpus, optimised, tput FROM {INST} WHERE cents <= 8 ORDER BY tput DESC, vcpus LIMIT 1")
def z2(spark, sf):
    return select.choose(L.INSTANCES.df(spark), "tput", "cents", 8.0, "le", tie=("vcpus",)).select("vcpus", "optimised", "tput")


@query("z3_cores_saved", f"SELECT a.vcpus, round(a.vcpus - a.vcpus * b.tput / a.tput, 6) AS saved FROM {INST.replace('AS lit', 'AS a')} JOIN {INST.replace('AS lit', 'AS b')} ON a.vcpus = b.vcpus AND a.optimised AND NOT b.optimised")
def z3(spark, sf):
    i = L.INSTANCES.df(spark)
    slow = i.where("NOT optimised").select("vcpus", F.col("tput").alias("before"))
    return i.where("optimised").join(slow, "vcpus").select("vcpus", R6(cost.cores_saved(F.col("before"), F.col("tput"), F.col("vcpus"))).alias("saved"))


@query("z4_cost_balance", f"SELECT vcpus, round(0.218::DOUBLE / 0.0639::DOUBLE, 6) AS accel_in_vcpus, round(vcpus * 0.0639::DOUBLE / 0.218::DOUBLE, 6) AS host_over_accel FROM {PRICE}")
def z4(spark, sf):
    return L.PRICES.df(spark).select("vcpus", F.lit(round(L.ACCELERATOR_HOUR / L.VCPU_HOUR, 6)).alias("accel_in_vcpus"), R6(F.col("vcpus") * L.VCPU_HOUR / L.ACCELERATOR_HOUR).alias("host_over_accel"))


@query("z5_pipeline_overhead", f"SELECT config, round(least(pre, exec) / measured - 1, 6) AS overhead FROM {REGIMES} WHERE measured IS NOT NULL")
def z5(spark, sf):
    return estimators(spark).where("measured IS NOT NULL").select("config", R6(F.col("pipelined") / F.col("measured") - 1).alias("overhead"))


@query("z6_gap", f"SELECT model_id, format_id, round(exec / pre, 6) AS gap FROM {CAND}")
def z6(spark, sf):
    return cand(spark).select("model_id", "format_id", R6(F.col("exec") / F.col("pre")).alias("gap"))


@query("z7_sensitivity", f"SELECT config, dx::DOUBLE AS d_exec, dp::DOUBLE AS d_pre, round(least(pre * dp, exec * dx) / least(pre, exec), 6) AS gain FROM {REGIMES} CROSS JOIN (VALUES (1.0, 2.0), (2.0, 1.0), (2.0, 2.0)) AS f(dx, dp)")
def z7(spark, sf):
    f = spark.createDataFrame([(1.0, 2.0), (2.0, 1.0), (2.0, 2.0)], "d_exec double, d_pre double")
    return L.REGIMES.df(spark).crossJoin(F.broadcast(f)).select("config", "d_exec", "d_pre", R6(cost.sensitivity(F.col("pre"), F.col("exec"), F.col("d_exec"), F.col("d_pre"))).alias("gain"))


SHAP = f"(SELECT dataset, max(CASE WHEN NOT lowres AND NOT dag THEN ln(tput) END) AS n, max(CASE WHEN lowres AND NOT dag THEN ln(tput) END) AS l, max(CASE WHEN dag AND NOT lowres THEN ln(tput) END) AS g, max(CASE WHEN dag AND lowres THEN ln(tput) END) AS b FROM {FLAGGED} GROUP BY dataset)"


@query("z8_attribution", f"SELECT dataset, round(((l - n) + (b - g)) / 2, 6) AS lowres_log_gain, round(((g - n) + (b - l)) / 2, 6) AS dag_log_gain FROM {SHAP}")
def z8(spark, sf):
    """Each flag's mean log gain over both orders of adding them."""
    at = lambda lo, g: F.max(F.when((F.col("lowres") == lo) & (F.col("dag") == g), F.log("tput")))
    d = flagged(spark, sf).groupBy("dataset").agg(at(False, False).alias("n"), at(True, False).alias("l"), at(False, True).alias("g"), at(True, True).alias("b"))
    return d.select("dataset", R6(F.expr("((l - n) + (b - g)) / 2")).alias("lowres_log_gain"), R6(F.expr("((g - n) + (b - l)) / 2")).alias("dag_log_gain"))


@query("z9_cascade_true_pre", f"SELECT a::DOUBLE AS share, round(1 / (1 / 527.0::DOUBLE + a / 1995.0::DOUBLE), 6) AS pre FROM (SELECT unnest([0.0, 0.1, 0.3, 1.0])::DOUBLE AS a)")
def z9(spark, sf):
    d = spark.createDataFrame([(0.0,), (0.1,), (0.3,), (1.0,)], "share double")
    return d.select("share", R6(cost.true_pre(F.lit(527.0), F.lit(1995.0), F.col("share"))).alias("pre"))


@query("z15_hardware_decoder", f"SELECT format_id, decoder, least(CASE WHEN decoder = 'device' THEN 9000.0::DOUBLE ELSE pre END, 4513.0) AS est FROM {FORMATS} CROSS JOIN (VALUES ('host'), ('device')) AS d(decoder) WHERE decoder = 'host' OR codec = 'jpeg'")
def z15(spark, sf):
    d = L.FORMATS.df(spark).crossJoin(spark.createDataFrame([("host",), ("device",)], "decoder string")).where("decoder = 'host' OR codec = 'jpeg'")
    return d.select("format_id", "decoder", cost.est_pipelined(F.when(F.col("decoder") == "device", 9000.0).otherwise(F.col("pre")), F.lit(4513.0)).alias("est"))


@query("w7_software_stacks", f"SELECT stack, round(tput / min(tput) OVER (), 6) AS speedup FROM {L.STACKS.sql()}")
def w7(spark, sf):
    return L.STACKS.df(spark).select("stack", R6(F.col("tput") / F.min("tput").over(W.partitionBy())).alias("speedup"))


@query("w9_depth_ladder", f"SELECT model_id, round(acc - lag(acc) OVER (ORDER BY depth), 6) AS acc_gain, round(tput / lag(tput) OVER (ORDER BY depth), 6) AS tput_ratio FROM {L.DEPTHS.sql()}")
def w9(spark, sf):
    w = W.orderBy("depth")
    return L.DEPTHS.df(spark).select("model_id", R6(F.col("acc") - F.lag("acc").over(w)).alias("acc_gain"), R6(F.col("tput") / F.lag("tput").over(w)).alias("tput_ratio"))


@query("w6_training_grid_published", f"SELECT format_id, model_id, round(max(CASE WHEN training = 'lowres' THEN acc END) - max(CASE WHEN training = 'regular' THEN acc END), 6) AS lowres_gain FROM {TRAIN} GROUP BY 1, 2")
def w6(spark, sf):
    p = L.TRAINING.df(spark).groupBy("format_id", "model_id").pivot("training", ["lowres", "regular"]).agg(F.max("acc"))
    return p.select("format_id", "model_id", R6(F.col("lowres") - F.col("regular")).alias("lowres_gain"))


@query("w12_datasets", f"SELECT dataset, classes, round(train_n / classes::DOUBLE, 6) AS per_class FROM {L.DATASETS.sql()}")
def w12(spark, sf):
    return L.DATASETS.df(spark).select("dataset", "classes", R6(F.col("train_n") / F.col("classes")).alias("per_class"))
