"""Studies on the engine's own plans: four image sets, Pareto sets against both baselines, lesions, factors, cascades, runs of a plan.

Accuracies are measured on held-out rows; rates are the engine's nominal ones, so every figure has an SQL twin.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from ..operators import cascade
from ..plans import dag, engine as E, lower, placement, select
from ..registry import query, table
from ..session import shared_folder
from ..sources import renditions
from ..sources.rasters import text_images

R6 = lambda c: F.round(c, 6)
DATASETS = ("quality", "lang", "lang_quality", "source")  # 2, 4, 8 and 20 classes
_stores: dict[tuple[str, str], str] = {}


def store(spark: SparkSession, sf: str) -> str:
    """The renditions of a folder's documents, encoded once in an application."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _stores:
        path = shared_folder(spark, "images")
        renditions.write(text_images(table(spark, sf, "documents")), path)
        _stores[key] = path
    return _stores[key]


def truth(spark: SparkSession, sf: str) -> DataFrame:
    """Rows (dataset, raster_id, label) of the four tasks."""
    docs = table(spark, sf, "documents").select(F.col("doc_id").alias("raster_id"), "lang", "source")
    graded = table(spark, sf, "labels").select(F.col("doc_id").alias("raster_id"), F.col("quality").cast("string").alias("quality"))
    both = docs.join(graded, "raster_id").withColumn("lang_quality", F.concat("lang", "quality"))
    named = lambda d, c: d.select(F.lit(c).alias("dataset"), "raster_id", F.col(c).alias("label")).where("label IS NOT NULL")
    return named(docs, "lang").unionByName(named(docs, "source")).unionByName(named(graded, "quality")).unionByName(named(both, "lang_quality"))


def engine(spark: SparkSession, sf: str, **switches) -> E.Engine:
    return E.Engine(spark, store(spark, sf), truth(spark, sf), **switches)


# SQL ---------------------------------------------------------------------------


def picked() -> str:
    """(format_id, j, i): the source pixel of each of the chain's values."""
    h, w = lower.shape(E.CHAIN.ops, 8, 8)
    rows = []
    for f, side in E.SIDES.items():
        place = lower.to_kernel([o for o in E.CHAIN.ops if o.name in ("resize", "crop")], side, side, 0, 1)
        rows += [f"('{f}', {j}, {i})" for j, i in enumerate(place(np.arange(side * side).reshape(side, side)).ravel().tolist())]
    assert len(rows) == len(E.SIDES) * h * w
    return f"(VALUES {', '.join(rows)}) AS pick(format_id, j, i)"


def operators(dag_opt: bool = True, every: bool = False) -> str:
    """(format_id, chain, place, seconds) of chains."""
    rows = []
    for f, side in E.SIDES.items():
        for d in dag.orders(E.CHAIN, side, side, exact=True) if every else [dag.best(E.CHAIN, side, side, 1, optimise=dag_opt, exact=True)]:
            rows += [f"('{f}', '{d.names()}', {i}, {s!r}::DOUBLE)" for i, _, s in E.seconds_of(d, f)]
    return f"(VALUES {', '.join(rows)}) AS ops(format_id, chain, place, seconds)"


NETS = "(VALUES " + ", ".join(f"('{n.model_id}', {n.values}, {n.rate!r}::DOUBLE)" for n in E.NETS) + ") AS nets(model_id, n_values, rate)"


def splits(ops: str) -> str:
    return f"""(SELECT model_id, format_id, chain, place AS split, 1 / sum(seconds) OVER (PARTITION BY model_id, format_id, chain ORDER BY place) AS host_rate,
 1 / (1 / rate + coalesce(sum(seconds) OVER (PARTITION BY model_id, format_id, chain ORDER BY place ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) / {E.ADVANTAGE!r}::DOUBLE) AS accel_rate FROM {ops} CROSS JOIN {NETS})"""


def placed(dag_opt: bool = True) -> str:
    order = "round(least(host_rate, accel_rate), 9) DESC, split DESC" if dag_opt else "split DESC"
    return f"(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY model_id, format_id, chain ORDER BY {order}) AS n FROM {splits(operators(dag_opt))}) WHERE n = 1)"


IMAGES = f"""img AS MATERIALIZED (SELECT d.doc_id AS raster_id, b.i, least(255, coalesce(c.n, 0) * 1020 // greatest(1, octet_length(encode(coalesce(text, ''))))) AS v FROM documents d CROSS JOIN (SELECT unnest(range(64)) AS i) b
 LEFT JOIN (SELECT doc_id, ('0x' || x)::INT // 4 AS i, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(hex(encode(coalesce(text, ''))), '..')) AS x FROM documents) GROUP BY 1, 2) c ON c.doc_id = d.doc_id AND c.i = b.i),
hlf AS (SELECT raster_id, (i // 16) * 4 + i % 8 // 2 AS i, (sum(v) + 2) // 4 AS v FROM img GROUP BY 1, 2),
qrt AS (SELECT raster_id, (i // 8) * 2 + i % 4 // 2 AS i, (sum(v) + 2) // 4 AS v FROM hlf GROUP BY 1, 2),
raw AS (SELECT 'full' AS format_id, * FROM img UNION ALL SELECT 'half_png', * FROM hlf UNION ALL SELECT 'quarter_png', * FROM qrt),
x AS MATERIALIZED (SELECT raster_id, raw.format_id, j, (v / 255.0::DOUBLE - {E.MEAN!r}::DOUBLE) / {E.STD!r}::DOUBLE AS v FROM raw JOIN {picked()} ON pick.format_id = raw.format_id AND pick.i = raw.i),
truth AS (SELECT 'lang' AS dataset, doc_id AS raster_id, lang AS label FROM documents WHERE lang IS NOT NULL UNION ALL SELECT 'source', doc_id, source FROM documents WHERE source IS NOT NULL
 UNION ALL SELECT 'quality', doc_id, quality::VARCHAR FROM labels WHERE quality IS NOT NULL UNION ALL SELECT 'lang_quality', doc_id, lang || quality::VARCHAR FROM documents JOIN labels USING (doc_id) WHERE lang IS NOT NULL AND quality IS NOT NULL),
cen AS MATERIALIZED (SELECT format_id, dataset, label, j, avg(v) AS m FROM x JOIN truth USING (raster_id) WHERE raster_id % 5 <> 0 GROUP BY 1, 2, 3, 4)"""
GUESSES = f"""dist AS (SELECT x.raster_id, x.format_id, t.dataset, t.label, training, model_id, c.label AS guess, round(sum((x.v - c.m) ^ 2), 9) AS d FROM x JOIN truth t USING (raster_id) CROSS JOIN (VALUES ('regular'), ('lowres')) AS tr(training) CROSS JOIN {NETS}
 JOIN cen c ON c.dataset = t.dataset AND c.j = x.j AND c.format_id = CASE training WHEN 'regular' THEN 'full' ELSE x.format_id END WHERE x.raster_id % 5 = 0 AND x.j < n_values GROUP BY ALL),
best AS (SELECT dataset, model_id, training, format_id, raster_id, label, arg_min(guess, (d, guess)) AS guess FROM dist GROUP BY 1, 2, 3, 4, 5, 6),
acc AS MATERIALIZED (SELECT dataset, model_id, training, format_id, count(*) AS n, avg((label = guess)::INT) AS acc FROM best GROUP BY 1, 2, 3, 4)"""
GRADED = f"WITH {IMAGES}, {GUESSES}"


def plan_rows(dag_opt: bool = True, lowres: bool = True) -> str:
    return f"(SELECT dataset, a.model_id, training, a.format_id, chain, split, host_rate AS pre, accel_rate AS exec, least(host_rate, accel_rate) AS est_tput, acc FROM acc a JOIN {placed(dag_opt)} p ON p.model_id = a.model_id AND p.format_id = a.format_id{'' if lowres else chr(32) + 'WHERE a.format_id = ' + chr(39) + 'full' + chr(39)})"


def undominated(rel: str, by: str) -> str:
    same = " AND ".join(f"a.{k} = b.{k}" for k in by.split())
    return f"(SELECT a.* FROM {rel} a WHERE NOT EXISTS (SELECT 1 FROM {rel} b WHERE round(b.acc, 6) >= round(a.acc, 6) AND round(b.est_tput, 6) >= round(a.est_tput, 6) AND (round(b.acc, 6) > round(a.acc, 6) OR round(b.est_tput, 6) > round(a.est_tput, 6)) AND {same}))"


# engine --------------------------------------------------------------------------


@query("engine_accuracy", f"{GRADED} SELECT dataset, model_id, training, format_id, n, round(acc, 6) AS acc FROM acc")
def accuracy(spark, sf):
    """Nets by trainings by renditions on the four image sets."""
    return engine(spark, sf).accuracy().withColumn("acc", R6("acc"))


@query("p2_expand_orders_and_splits", f"SELECT model_id, format_id, chain, split::INTEGER AS split, round(host_rate, 6) AS host_rate, round(accel_rate, 6) AS accel_rate FROM {splits(operators(every=True))}")
def expanded(spark, sf):
    """Every net and rendition with every order of the chain that keeps results and every cut of it."""
    return engine(spark, sf).cuts(every_order=True).select("model_id", "format_id", "chain", "split", R6("host_rate").alias("host_rate"), R6("accel_rate").alias("accel_rate"))


FRONTIER = undominated(plan_rows(), "dataset")


@query("engine_frontier", f"{GRADED} SELECT dataset, model_id, training, format_id, chain, split::INTEGER AS split, round(acc, 6) AS acc, round(est_tput, 6) AS est_tput FROM {FRONTIER}")
def frontier(spark, sf):
    """The flagship: nets x renditions x trainings with optimised chains and placed operators, calibrated on held-out rows; the Pareto set of each image set."""
    return engine(spark, sf).frontier().select("dataset", "model_id", "training", "format_id", "chain", "split", R6("acc").alias("acc"), R6("est_tput").alias("est_tput"))


CHOSEN = f"(SELECT * FROM {plan_rows()} WHERE dataset = 'lang' AND est_tput >= 1500 ORDER BY acc DESC, est_tput, dataset || '/' || model_id || '/' || training || '/' || format_id LIMIT 1)"


@query(
    "engine_run",
    f"""{GRADED}, chosen AS MATERIALIZED (SELECT c.*, n_values FROM {CHOSEN} c JOIN {NETS} USING (model_id)),
far AS (SELECT x.raster_id, c.label AS guess, round(sum((x.v - c.m) ^ 2), 9) AS d FROM x JOIN chosen p ON p.format_id = x.format_id JOIN cen c ON c.dataset = 'lang' AND c.j = x.j AND c.format_id = CASE training WHEN 'regular' THEN 'full' ELSE p.format_id END WHERE x.j < n_values GROUP BY 1, 2)
SELECT raster_id, arg_min(guess, (d, guess)) AS guess, round(min(d), 6) AS d FROM far GROUP BY 1""",
)
def run(spark, sf):
    """The most accurate plan of the language set that is estimated at 1500 items a second, run over every item."""
    e = engine(spark, sf)
    plan = e.choose("lang", throughput=1500.0).first()
    return e.run(plan["plan_id"]).select("raster_id", "guess", R6("d").alias("d"))


@query("engine_run_without_dag", f"{GRADED} SELECT format_id, n, hits, hits AS declared_hits FROM (SELECT format_id, count(*) AS n, sum((label = guess)::INT)::BIGINT AS hits FROM best WHERE dataset = 'lang' AND model_id = 'res50' AND training = 'lowres' GROUP BY 1)")
def without_dag(spark, sf):
    """The deepest net on every rendition, with the optimiser and without: the answers are the same."""
    out = None
    for f in E.SIDES:
        one = None
        for name, e in (("hits", engine(spark, sf)), ("declared_hits", engine(spark, sf, dag_opt=False))):
            own = e.truth.where("dataset = 'lang' AND raster_id % 5 = 0")
            got = e.run(f"lang/res50/lowres/{f}").join(own, "raster_id").agg(F.count("*").alias("n"), F.sum((F.col("guess") == F.col("label")).cast("long")).alias(name))
            one = got if one is None else one.join(got, "n")
        one = one.select(F.lit(f).alias("format_id"), "n", "hits", "declared_hits")
        out = one if out is None else out.unionByName(one)
    return out


SAMPLE_CUTS = (1, 2, 4)


@query("g6_lowerings", f"WITH {IMAGES} SELECT format_id, round(sum(v), 4) AS total, round(sum(v * (j + 1)), 4) AS weighted, k::INTEGER AS cut, o::INTEGER AS place FROM x CROSS JOIN (VALUES {', '.join(f'({k})' for k in SAMPLE_CUTS)}) AS cuts(k) CROSS JOIN (VALUES (0), (1)) AS orders(o) WHERE format_id = 'half_png' GROUP BY format_id, k, o")
def lowerings(spark, sf):
    """Sums over the chain's values for the first and last order, cut in three places: every lowering agrees with the chain in SQL."""
    e, out = engine(spark, sf), None
    all_ = sorted(dag.orders(E.CHAIN, 4, 4, exact=True), key=dag.Dag.names)
    for o, d in enumerate((all_[0], all_[-1])):
        for k in SAMPLE_CUTS:
            x = e.prepared("half_png", d, min(k, len(d.ops))).select(F.posexplode("x").alias("j", "v"))
            one = x.agg(F.round(F.sum("v"), 4).alias("total"), F.round(F.sum(F.col("v") * (F.col("j") + 1)), 4).alias("weighted")).select(F.lit("half_png").alias("format_id"), "total", "weighted", F.lit(k).alias("cut"), F.lit(o).alias("place"))
            out = one if out is None else out.unionByName(one)
    return out


@query("l5_measured_rates")
def measured(spark, sf):
    """Measured seconds of each operator and the cut that they ask for; figures differ from run to run."""
    e = engine(spark, sf, measured=True)
    return placement.best_split(e.rates([(f, e.chain(f)) for f in e.formats]), ("model_id", "format_id", "chain"), 1.0, E.ADVANTAGE).select("model_id", "format_id", "chain", "split", "host_rate", "accel_rate", "tput")


# cascades --------------------------------------------------------------------------

SMALL = "(VALUES " + ", ".join(f"('{cascade.name(v, f)}', {v}, {f}, {cascade.SMALL_RATE / v!r}::DOUBLE)" for v, f in cascade.SMALL) + ") AS small(net, n_values, first_value, rate)"
STAGED = f"""sd AS (SELECT x.raster_id, t.dataset, t.label, net, c.label AS guess, round(sum((x.v - c.m) ^ 2), 9) AS d FROM x JOIN truth t USING (raster_id) JOIN cen c ON c.dataset = t.dataset AND c.j = x.j AND c.format_id = 'full' CROSS JOIN {SMALL}
 WHERE x.format_id = 'full' AND x.j >= first_value AND x.j < first_value + n_values GROUP BY ALL),
sr AS (SELECT *, row_number() OVER w AS r, lead(d) OVER w AS second FROM sd WINDOW w AS (PARTITION BY dataset, net, raster_id ORDER BY d, guess)),
st AS MATERIALIZED (SELECT dataset, net, raster_id, label, guess, CASE WHEN second IS NULL THEN 1.0::DOUBLE ELSE round((second - d) / greatest(second, 1e-9), 9) END AS margin FROM sr WHERE r = 1),
used AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY dataset ORDER BY round(acc, 9) DESC, rate DESC, net) <= {cascade.USED} AS used FROM (SELECT dataset, net, rate, avg((label = guess)::INT) AS acc FROM st JOIN {SMALL} USING (net) WHERE raster_id % 5 <> 0 GROUP BY 1, 2, 3))"""
FULL_PRE = f"(SELECT max(host_rate) FROM {placed()} WHERE format_id = 'full')"
DEEP = max(E.NETS, key=lambda n: n.values)
CASCADES = f"""cs AS (SELECT s.dataset, s.net, threshold, avg((margin < threshold)::INT) AS share, avg((CASE WHEN margin < threshold THEN b.guess ELSE s.guess END = s.label)::INT) AS acc FROM st s
 JOIN best b ON b.dataset = s.dataset AND b.raster_id = s.raster_id AND b.model_id = '{DEEP.model_id}' AND b.training = 'regular' AND b.format_id = 'full' CROSS JOIN (VALUES {', '.join(f'({t!r}::DOUBLE)' for t in cascade.THRESHOLDS)}) AS th(threshold) GROUP BY 1, 2, 3),
cp AS (SELECT cs.*, pre, 1 / (1 / rate + share / {DEEP.rate!r}::DOUBLE) AS exec FROM cs JOIN used USING (dataset, net) CROSS JOIN (SELECT {FULL_PRE} AS pre) WHERE used),
cascades AS MATERIALIZED (SELECT *, 1 / (1 / pre + 1 / exec) AS est_tput, least(1 / (1 / pre + share / pre), exec) AS true_tput FROM cp)"""
WITH_CASCADES = f"WITH {IMAGES}, {GUESSES}, {STAGED}, {CASCADES}"


@query("b2b_cascade_space", f"WITH {IMAGES}, {STAGED} SELECT dataset, net, rate, round(acc, 6) AS acc, used FROM used")
def small_nets(spark, sf):
    """24 small nets, trained and graded on the training fold, and the 8 that are chained."""
    return cascade.small_nets(engine(spark, sf)).withColumn("acc", R6("acc"))


@query("b2_cascade", f"{WITH_CASCADES} SELECT dataset, net, threshold, round(share, 6) AS share, round(acc, 6) AS acc, round(est_tput, 4) AS est_tput, round(true_tput, 4) AS true_tput FROM cascades")
def cascades(spark, sf):
    """Every used net chained to the deepest at three thresholds: pass rates and accuracy from held-out margins, the additive estimate, and the true rate."""
    return cascade.plans(engine(spark, sf)).select("dataset", "net", "threshold", R6("share").alias("share"), R6("acc").alias("acc"), F.round("est_tput", 4).alias("est_tput"), F.round("true_tput", 4).alias("true_tput"))


@query("b2a_cascade_run", f"WITH {IMAGES}, {GUESSES}, {STAGED} SELECT count(*) AS n, sum((margin < 0.5)::INT)::BIGINT AS deep_calls, sum((margin < 0.5)::INT * 64)::BIGINT AS pixels_again, sum((CASE WHEN margin < 0.5 THEN b.guess ELSE s.guess END = s.label)::INT)::BIGINT AS hits FROM st s JOIN best b ON b.dataset = s.dataset AND b.raster_id = s.raster_id AND b.model_id = '{DEEP.model_id}' AND b.training = 'regular' AND b.format_id = 'full' WHERE s.dataset = 'lang' AND net = 'tiny4at2'")
def cascade_run(spark, sf):
    """A cascade over the items: survivors alone reach the deepest net, and their pixels are prepared again; counted on the held-out fold."""
    e = engine(spark, sf)
    got = cascade.run(e, "lang", 4, 2, 0.5).join(e.truth.where("dataset = 'lang' AND raster_id % 5 = 0"), "raster_id")
    deep = (F.col("stage") == 2).cast("long")
    return got.agg(F.count("*").alias("n"), F.sum(deep).alias("deep_calls"), F.sum(deep * 64).alias("pixels_again"), F.sum((F.col("guess") == F.col("label")).cast("long")).alias("hits"))


@query("c2b_held_out_pass_rates", f"WITH {IMAGES}, {STAGED} SELECT dataset, net, threshold, round(avg((margin < threshold)::INT), 6) AS pass_rate FROM st CROSS JOIN (VALUES (0.2::DOUBLE), (0.5::DOUBLE), (0.8::DOUBLE)) AS th(threshold) JOIN used USING (dataset, net) WHERE raster_id % 5 = 0 AND used GROUP BY 1, 2, 3")
def pass_rates(spark, sf):
    """Share of held-out items that each first stage forwards."""
    return cascade.plans(engine(spark, sf)).select("dataset", "net", "threshold", R6("share").alias("pass_rate"))


# four image sets: Pareto sets, lesions, factors -------------------------------------

METHODS = f"""m AS MATERIALIZED (SELECT dataset, 'engine' AS method, model_id || '/' || training || '/' || format_id AS plan, acc, est_tput FROM {plan_rows()}
 UNION ALL SELECT dataset, 'naive', model_id || '/' || training || '/' || format_id, acc, est_tput FROM {plan_rows(False, False)} WHERE training = 'regular'
 UNION ALL SELECT dataset, 'cascade', net || '@' || threshold, acc, est_tput FROM cascades)"""


def methods(spark, sf) -> DataFrame:
    """Rows (dataset, method, plan, acc, est_tput) of the engine, the naive ladder on full renditions and the cascades."""
    e = engine(spark, sf)
    graded = e.accuracy().cache()
    plan = F.concat_ws("/", "model_id", "training", "format_id").alias("plan")
    own = e.plans(graded).select("dataset", F.lit("engine").alias("method"), plan, "acc", "est_tput")
    plain = e.without(dag_opt=False, lowres=False)
    naive = plain.plans(graded.where("format_id = 'full'")).where("training = 'regular'").select("dataset", F.lit("naive").alias("method"), plan, "acc", "est_tput")
    chained = cascade.plans(e).select("dataset", F.lit("cascade").alias("method"), F.concat_ws("@", "net", F.col("threshold").cast("string")).alias("plan"), "acc", "est_tput")
    return own.unionByName(naive).unionByName(chained)


@query("w12_pareto", f"{WITH_CASCADES}, {METHODS} SELECT dataset, method, plan, round(acc, 6) AS acc, round(est_tput, 4) AS est_tput FROM {undominated('m', 'dataset method')}")
def pareto(spark, sf):
    """Pareto sets of the engine, the naive ladder and the cascades on four image sets."""
    return select.frontier(methods(spark, sf), by=["dataset", "method"]).select("dataset", "method", "plan", R6("acc").alias("acc"), F.round("est_tput", 4).alias("est_tput"))


@query("w12_speedup", f"{WITH_CASCADES}, {METHODS} SELECT n.dataset, round(max(n.est_tput) FILTER (m.method = 'engine') / max(n.est_tput) FILTER (m.method = 'naive'), 6) AS over_naive, round(max(n.est_tput) FILTER (m.method = 'engine') / max(n.est_tput) FILTER (m.method = 'cascade'), 6) AS over_cascade FROM m n JOIN m ON m.dataset = n.dataset AND m.method = n.method AND m.plan = n.plan JOIN (SELECT dataset, max(acc) AS best FROM m WHERE method = 'naive' GROUP BY 1) b ON b.dataset = n.dataset WHERE n.acc >= 0.95 * b.best GROUP BY 1")
def speedup(spark, sf):
    """The engine's best rate over the baselines' among plans that keep 95 % of the naive ladder's best accuracy."""
    m = methods(spark, sf)
    best = m.where("method = 'naive'").groupBy("dataset").agg(F.max("acc").alias("best"))
    top = lambda k: F.max(F.when(F.col("method") == k, F.col("est_tput")))
    return m.join(best, "dataset").where("acc >= 0.95 * best").groupBy("dataset").agg(R6(top("engine") / top("naive")).alias("over_naive"), R6(top("engine") / top("cascade")).alias("over_cascade"))


def flagged(spark, sf) -> DataFrame:
    """Rows (dataset, lowres, dag, tput, acc): with each switch on or off, the fastest plan that keeps 95 % of the naive ladder's best accuracy."""
    whole = engine(spark, sf)
    graded = whole.accuracy().cache()
    floor = graded.where("format_id = 'full' AND training = 'regular'").groupBy("dataset").agg((0.95 * F.max("acc")).alias("floor"))
    out = None
    for lowres in (False, True):
        for dag_opt in (False, True):
            e = whole.without(dag_opt=dag_opt, lowres=lowres)
            p = e.plans(graded if lowres else graded.where("format_id = 'full'")).join(F.broadcast(floor), "dataset").where("acc >= floor")
            one = p.groupBy("dataset").agg(F.max("est_tput").alias("tput"), F.max_by("acc", F.struct(F.round("est_tput", 6), "acc")).alias("acc")).select("dataset", F.lit(lowres).alias("lowres"), F.lit(dag_opt).alias("dag"), "tput", "acc")
            out = one if out is None else out.unionByName(one)
    return out


def flagged_sql() -> str:
    """The same as a FROM item."""
    parts = [f"SELECT p.dataset, {str(lo).lower()} AS lowres, {str(g).lower()} AS dag, max(est_tput) AS tput, arg_max(acc, (round(est_tput, 6), acc)) AS acc FROM {plan_rows(g, lo)} p JOIN floors USING (dataset) WHERE acc >= floor GROUP BY 1" for lo in (False, True) for g in (False, True)]
    return f"({GRADED}, floors AS (SELECT dataset, 0.95 * max(acc) AS floor FROM acc WHERE format_id = 'full' AND training = 'regular' GROUP BY 1) {' UNION ALL '.join(parts)}) AS lit"


FLAGGED = flagged_sql()


@query("w13_lesion", f"SELECT dataset, lowres, dag, round(tput, 4) AS tput, round(acc, 6) AS acc FROM {FLAGGED} WHERE lowres OR dag")
def lesion(spark, sf):
    """The engine with the chain optimiser or low-resolution renditions taken away."""
    return flagged(spark, sf).where("lowres OR dag").select("dataset", "lowres", "dag", F.round("tput", 4).alias("tput"), R6("acc").alias("acc"))


@query("w14_factor", f"SELECT dataset, step::INTEGER AS step, round(tput, 4) AS tput, round(tput / lag(tput) OVER (PARTITION BY dataset ORDER BY step), 6) AS gain FROM (SELECT *, CASE WHEN lowres THEN 2 WHEN dag THEN 1 ELSE 0 END AS step FROM {FLAGGED} WHERE dag OR NOT lowres)")
def factor(spark, sf):
    """Nothing, then the chain optimiser, then low-resolution renditions."""
    d = flagged(spark, sf).where("dag OR NOT lowres").withColumn("step", F.when(F.col("lowres"), 2).when(F.col("dag"), 1).otherwise(0))
    return d.select("dataset", "step", F.round("tput", 4).alias("tput"), R6(F.col("tput") / F.lag("tput").over(W.partitionBy("dataset").orderBy("step"))).alias("gain"))
