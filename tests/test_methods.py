"""Methods of the reference: worked examples, invariants, and agreement of every form of an operator."""

import numpy as np
import pytest

from rasterflow import workloads
from rasterflow.operators import aggregation, codec, inference
from rasterflow.plans import dag, placement, select
from rasterflow.sources import literals as L

SF = "/root/testdata/sf0.001"


def rasters(n=20, seed=0):
    rng = np.random.default_rng(seed)
    for _ in range(n):
        h, w = rng.integers(1, 70, 2)
        y, x = np.mgrid[:h, :w]
        yield ((y * 3 + x * 2) % 256 + rng.integers(0, 20, (h, w))).clip(0, 255).astype(np.uint8)


def test_codecs_and_partial_decoding():
    for r in rasters():
        h, w = r.shape
        blob = codec.png_encode(r)
        assert np.array_equal(codec.png_decode(blob), r) and np.array_equal(codec.png_decode(blob, h // 2), r[: h // 2])
        p, i = codec.dct_encode(r, 75)
        box = (w // 4, h // 4, max(w // 4 + 1, 3 * w // 4), max(h // 4 + 1, 3 * h // 4))
        for deblock in (True, False):
            assert np.array_equal(codec.dct_decode(p, i, box, deblock), codec.dct_decode(p, i, deblock=deblock)[box[1] : box[3], box[0] : box[2]])
        assert codec.dct_decode(p, i, (5, 5, 5, 9)).size == 0
        q, j = codec.pyramid_encode(r, 2)
        assert np.array_equal(codec.pyramid_decode(q, j), r) and np.array_equal(codec.pyramid_decode(q, j, 1), codec.half(r))
        errors = [((codec.dct_decode(*codec.dct_encode(r, k), deblock=False).astype(float) - r) ** 2).mean() for k in (10, 50, 100)]
        assert errors[0] >= errors[1] >= errors[2]
    with pytest.raises(ValueError):
        codec.png_decode(b"nothing")


def test_spark_reads_our_png(spark, tmp_path):
    r = next(rasters())
    (tmp_path / "a.png").write_bytes(codec.png_encode(r))
    row = spark.read.format("image").load(str(tmp_path)).select("image.height", "image.width", "image.data").first()
    assert (row[0], row[1]) == r.shape and bytes(row[2]) == r.tobytes()


def test_worked_example(spark):
    plans = select.estimate(L.EXAMPLE.df(spark)).select("model_id", "format_id", "acc", "est_tput", "pre", "exec")
    rows = {(r["model_id"], r["format_id"]): r["est_tput"] for r in plans.collect()}
    assert rows["res34", "full"] == 527 and rows["res50", "png161"] == 1995
    front = {(r["model_id"], r["format_id"]) for r in select.frontier(plans).collect()}
    assert ("res34", "full") not in front and ("res50", "png161") in front
    matched = {r["format_id"]: r["model_id"] for r in select.matched_model(L.EXAMPLE.df(spark)).collect()}
    assert matched == {"full": "res50", "png161": "res50"}


def test_frontier_equals_brute_force(spark):
    rng = np.random.default_rng(1)
    rows = [(f"p{i}", float(rng.integers(0, 12)), float(rng.integers(0, 12)), f"g{i % 3}") for i in range(120)]
    d = spark.createDataFrame(rows, "plan_id string, acc double, est_tput double, g string")
    for by in ((), ("g",)):
        a, b = ({r["plan_id"] for r in f(d, by=by).collect()} for f in (select.frontier, select.frontier_bruteforce))
        assert a == b and a
    assert select.choose(d, "acc", "est_tput", 99.0).count() == 0
    with pytest.raises(ValueError):
        select.choose(d, "acc", "est_tput", 99.0, on_infeasible="raise")


def test_chain_optimiser():
    standard = dag.Dag.standard()
    for h, w in ((480, 640), (512, 512), (375, 500)):
        best = dag.best(standard, h, w)
        assert best.names() == "decode>crop>resize>fused"
        assert dag.count(best, h, w) <= min(dag.count(d, h, w) for d in dag.orders(standard, h, w))
        assert dag.best(standard, h, w, optimise=False) is standard
    assert all(dag.legal(d.ops) for d in dag.orders(standard, 480, 640))


def test_placement_agrees_with_the_rule(spark):
    ops = [("pre_bound", 1e6, i + 1, s, i == 0) for i, s in enumerate((1e-3, 1e-3, 1e-3))] + [("exec_bound", 1.0, i + 1, s, i == 0) for i, s in enumerate((1e-3, 1e-3, 1e-3))]
    d = spark.createDataFrame(ops, "plan_id string, exec double, place int, seconds double, host_only boolean")
    got = {r["plan_id"]: r["split"] for r in placement.best_split(d, speedup=1000.0).collect()}
    assert got == {"pre_bound": 1, "exec_bound": 3}


def test_estimators_order(spark):
    from rasterflow.workloads.costs import c7a

    e = {r["name"]: r["mean_err"] for r in c7a(spark, SF).collect()}
    assert e["pipelined"] < e["additive"] < e["exec_only"]


def test_control_variate(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(10, 2, 500)
    rows = [(str(i), float(2 * v + rng.normal(0, 1)), float(v), 1.0) for i, v in enumerate(x)]
    d = spark.createDataFrame(rows, "frame_id string, y double, x double, flat double")
    truth = float(np.mean([r[1] for r in rows]))
    cv = aggregation.control_variate(d, 60).first()
    assert cv["half_width"] < cv["plain_half_width"] and abs(cv["estimate"] - truth) <= 3 * cv["half_width"]
    assert abs(aggregation.control_variate(d, 500).first()["estimate"] - truth) < 1e-9
    flat = aggregation.control_variate(d, 60, x="flat").first()
    assert flat["estimate"] == flat["plain"]
    out, tried = aggregation.adaptive(d, 0.15)
    assert out.first()["half_width"] <= 0.15 and tried == sorted(tried)
    assert aggregation.coverage(d, 80, range(40)).first()["coverage"] >= 0.85


def test_model_stage(spark):
    from rasterflow.sources.rasters import text_blobs

    blobs = text_blobs(spark, SF)
    m = inference.train(blobs, inference.BINS["res34"])
    r = inference.renditions(blobs, ("full", "half_dct75"))
    bad = r.limit(1).selectExpr("raster_id", "label", "'full' AS format_id", "height", "width", "n_bytes", "index", "X'00' AS payload")
    rows = r.unionByName(bad)
    plain = lambda d: sorted(map(str, ((*r[:3], r[3] and round(r[3], 9), r[4]) for r in d.collect())))  # noqa: E731  batches of other sizes add up in another order
    got = [plain(inference.infer(rows, m, k)) for k in (inference.Runtime(), inference.Runtime(threads=0), inference.Runtime(threads=3, batch=7, depth=2, reuse=False))]
    assert got[0] == got[1] == got[2]
    assert inference.infer(bad, m).first()["error"]
    full = inference.infer(r.where("format_id = 'full'"), m).selectExpr("avg(int(guess = label))").first()[0]
    assert full > 0.9


def test_low_resolution_training_helps(spark):
    from rasterflow.sources.rasters import text_blobs

    blobs = text_blobs(spark, "/root/testdata/sf0.01")
    models = inference.ladder(blobs, ("res50",)).models
    half = inference.renditions(blobs, ("half_png",))
    acc = {t: inference.infer(half, m).selectExpr("avg(int(guess = label))").first()[0] for (_, t), m in models.items()}
    assert acc["lowres"] > acc["regular"] + 0.05


def test_scanlines_skip_and_stop():
    for r in rasters():
        h, w = r.shape
        p, i = codec.dct_encode(r, 75)
        whole = codec.dct_decode(p, i, deblock=False)
        for top, bottom, left, right in ((0, h, 0, w), (h // 3, h - h // 4, w // 5, w), (h - 1, h + 9, 0, 1), (2, 2, 0, w)):
            assert np.array_equal(codec.decode_rows(p, i, top, bottom, left, right), whole[top:bottom, left:right])
        lines = codec.Scanlines(p, i)
        assert np.array_equal(np.concatenate([lines.read(3) for _ in range(-(-h // 3))]), whole)
        assert codec.Scanlines(p, i[: 1 + -(-min(8, h) // 8)]).read(min(8, h)).shape == (min(8, h), w)  # later block rows aren't touched


def test_lowerings_agree(spark):
    """Every order that keeps results, cut anywhere, in the JVM and in NumPy."""
    from pyspark.sql import functions as F

    from rasterflow.plans import engine as E, lower

    rng = np.random.default_rng(0)
    for side in (8, 4, 2):
        x = rng.integers(0, 256, (5, side, side))
        want = lower.to_kernel(E.CHAIN.ops[1:], side, side, E.MEAN, E.STD)(x).reshape(5, -1)
        d = spark.createDataFrame([(i, [float(v) for v in r.ravel()]) for i, r in enumerate(x)], "i int, p array<double>")
        for chain in sorted(dag.orders(E.CHAIN, side, side, exact=True), key=dag.Dag.names)[::5]:
            ops = chain.ops[1:]
            assert np.allclose(lower.to_kernel(ops, side, side, E.MEAN, E.STD)(x).reshape(5, -1), want)
            got = d.select("i", lower.to_column(ops, F.col("p"), side, side, E.MEAN, E.STD).alias("v")).orderBy("i").collect()
            assert np.allclose([r["v"] for r in got], want)


def test_engine_switches_and_pruning(spark):
    from rasterflow.workloads import studies

    e = studies.engine(spark, SF)
    assert {f for f, _ in e.chains()} == {"full", "half_png", "quarter_png"}
    plain = e.without(dag_opt=False, lowres=False)
    assert plain.formats == ("full",) and plain.chain("full") is studies.E.CHAIN
    fast, slow = ({(r["model_id"], r["format_id"]): min(r["pre"], r["exec"]) for r in x.placed().collect()} for x in (e, e.without(dag_opt=False)))
    assert all(fast[k] >= slow[k] for k in slow) and any(fast[k] > slow[k] for k in slow)
    plan = e.run("lang/res50/regular/half_png")._jdf.queryExecution().toString()
    assert "format_id = half_png" in plan.replace("format_id#", "format_id = ").replace("isnotnull", "") or "PartitionFilters" in plan


def test_cascade_sends_survivors_only(spark):
    from rasterflow.operators import cascade
    from rasterflow.workloads import studies

    e = studies.engine(spark, SF)
    none, all_ = (cascade.run(e, "lang", 4, 2, t) for t in (0.0, 1.1))
    assert none.where("stage = 2").count() == 0 and all_.where("stage = 1").count() == 0
    deep = {r["raster_id"]: r["guess"] for r in e.run("lang/res50/regular/full").collect()}
    assert {r["raster_id"]: r["guess"] for r in all_.collect()} == deep


def test_runtime_threads_end(spark):
    import threading

    from rasterflow.sources.rasters import text_blobs

    blobs = text_blobs(spark, SF)
    r = inference.renditions(blobs, ("half_png",))
    m = inference.train(blobs, inference.BINS["res18"])
    plain = lambda d: sorted(map(str, ((*r[:3], round(r[3], 9), r[4]) for r in d.collect())))
    want = plain(inference.infer(r, m, inference.Runtime(threads=0)))
    for k in (inference.Runtime(threads=None), inference.Runtime(threads=2, consumers=3, depth=3, batch=16)):
        assert plain(inference.infer(r, m, k)) == want
    assert inference.infer(r, m, inference.Runtime(threads=2)).limit(1).count() == 1  # stopped early
    assert inference.default_producers(spark) >= 1 and threading.active_count() < 200


def test_models_are_trained_on_demand_and_imported(spark, tmp_path):
    from rasterflow.sources.rasters import text_blobs

    blobs = text_blobs(spark, SF)
    lazy = inference.ladder(blobs, ("res18",), lazy=True)
    assert not lazy.models
    m = lazy["res18", "lowres"]
    assert set(lazy.models) == {("res18", "regular"), ("res18", "lowres")}
    with pytest.raises(KeyError):
        lazy["res50", "regular"]
    (tmp_path / "mine.json").write_text(inference.saved(m))
    back = inference.imported(spark, str(tmp_path))["mine"]
    assert np.array_equal(back.weights, m.weights) and back.labels == m.labels


def test_seeds_draw_the_same_samples(spark):
    import hashlib

    rows = [(f"f{i}", float(i), float(i % 7)) for i in range(3000)]
    d = spark.createDataFrame(rows, "frame_id string, y double, x double")
    got = {}
    for r in aggregation.drawn(d, 25, range(6)).collect():
        got.setdefault(r["seed"], set()).add(r["frame_id"])
    for s in range(6):
        assert got[s] == set(sorted((f for f, _, _ in rows), key=lambda f: (hashlib.md5(f"{s}-{f}".encode()).hexdigest(), f))[:25])
    few = aggregation.drawn(d.limit(10), 25, range(3))
    assert few.count() == 30


def test_late_rows_are_dropped(spark, tmp_path):
    from rasterflow.streaming import frames as S

    def events(i, *at):
        spark.createDataFrame([(i * 10 + k, f"2024-01-01 {x}", 1, "click", 1.0, None) for k, x in enumerate(at)], "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", __import__("pyspark.sql.functions", fromlist=["F"]).col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(str(tmp_path / "e" / f"p{i}"))

    for i, at in enumerate((("10:00:00", "12:00:00"), ("12:30:00",), ("10:01:00", "12:31:00"))):
        events(i, *at)
    import shutil

    (tmp_path / "in").mkdir()
    for i in range(3):
        part = next((tmp_path / "e" / f"p{i}").glob("*.parquet"))
        shutil.copy(part, tmp_path / "in" / f"{i}.parquet")
        __import__("os").utime(tmp_path / "in" / f"{i}.parquet", (1000 + i, 1000 + i))
    stream = S.counts(S.source(spark, str(tmp_path / "in" / "*.parquet")))
    q = stream.writeStream.format("memory").queryName("late").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    assert S.late_rows(q) >= 1
    chooser = S.PlanChooser([("good", 0.9, 100.0), ("fast", 0.8, 1000.0)])
    for rate, plan in ((50.0, "good"), (500.0, "fast"), (5000.0, "fast"), (0.0, "good")):
        chooser.arrived(rate)
        assert chooser.plan == plan


@pytest.mark.parametrize("name", ["b1_naive_plans", "b8_control_variate_configuration", "c10_matched_model", "c10a_no_model_is_fast_enough", "c1a_throughput_floor", "c1b_accuracy_floor", "c1c_infeasible_closest", "c1d_unconstrained", "c1e_effective_floor", "c2_cascade_arriving", "c2a_cascade_literal", "c3_est_exec_only"])
def test_plans_come_from_a_given_table(name, spark):
    """Spark's tasks read the lines of orders."""
    assert any("lineitem.parquet" in f for f in workloads.QUERIES[name](spark, SF).inputFiles())
