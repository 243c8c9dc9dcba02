"""The engine: from nets, renditions and a calibration fold to plans, and the run of one.

A plan is a net, a rendition, a training, an order of the preparation chain and a cut in it.  `plans` makes them all
on small tables: chain orders from plans.dag (or the declared chain), cuts from plans.placement, estimates from rates,
accuracies from held-out rows of the calibration labels.  `choose` picks one under a constraint, and `run` lowers it to
one scan of one rendition: partitions of other renditions aren't read, operators before the cut run in the Arrow stage
beside decoding, those after it and the net in the JVM.

Items are the 8 x 8 byte-class rasters of whole texts (sources.rasters.text_images); a net is the nearest class mean
over so many of the values that the chain gives, with a nominal accelerator rate.  Rates of preparation are counted
operations times nominal costs, equal on every machine, or measured (`measured=True`).
"""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..operators import codec
from ..sources import renditions
from . import dag, lower, placement, select


@dataclass(frozen=True)
class Net:
    model_id: str
    values: int
    rate: float  # items a second on the accelerator (nominal: the published rates of the residual ladder)


NETS = (Net("res18", 4, 12592.0), Net("res34", 8, 6860.0), Net("res50", 16, 4513.0))
#: Side of each rendition.  All are lossless.
SIDES = {"full": 8, "half_png": 4, "quarter_png": 2}
TRAININGS = ("regular", "lowres")
#: The declared chain: every rendition is brought to 6 x 6 by nearest pixels, the middle 4 x 4 is cut out and normalised.
CHAIN = dag.Dag.standard(6, 4, "nearest")
MEAN, STD = 0.4, 0.2
#: Nominal costs in seconds on one core: of an item, of a decoded pixel, of an operation; the accelerator's advantage in operations.
ITEM, PIXEL, OPERATION, ADVANTAGE = 1e-4, 2.5e-5, 5e-7, 10.0


def seconds_of(chain: dag.Dag, format_id: str) -> list[tuple[int, str, float]]:
    """Nominal host seconds of each operator of a chain on a rendition: rows (place, op, seconds)."""
    side = SIDES[format_id]
    return [(i + 1, name, ITEM + PIXEL * side * side if name == "decode" else OPERATION * n) for i, (name, n) in enumerate(dag.steps(chain, side, side, 1))]


class Engine:
    """truth: rows (dataset, raster_id, label), the labels of every task; rows of `store` are renditions of raster_ids.

    dag_opt, lowres: switches for studies.  Labels are few, so class means travel as one row for each dataset.
    """

    def __init__(self, spark: SparkSession, store: str, truth: DataFrame, nets: Sequence[Net] = NETS, formats: Sequence[str] = tuple(SIDES), trainings: Sequence[str] = TRAININGS, dag_opt: bool = True, lowres: bool = True, cores: float = 1.0, estimator: str = "pipelined", measured: bool = False):
        self.spark, self.store, self.truth, self.nets = spark, store, truth, nets
        self.formats = tuple(formats) if lowres else tuple(f for f in formats if f == "full")
        self.trainings, self.dag_opt, self.cores, self.estimator, self.measured = tuple(trainings), dag_opt, cores, estimator, measured

    # preparation and nets ---------------------------------------------------

    def chain(self, format_id: str) -> dag.Dag:
        side = SIDES[format_id]
        return dag.best(CHAIN, side, side, 1, optimise=self.dag_opt, exact=True)

    def prepared(self, format_id: str, chain: dag.Dag | None = None, split: int | None = None) -> DataFrame:
        """Rows (raster_id, x): operators up to `split` (decoding is 1) in the Arrow stage, the others in the JVM."""
        chain = chain or self.chain(format_id)
        split = len(chain.ops) if split is None else split
        side = SIDES[format_id]
        rows = renditions.read(self.spark, self.store, format_id, ["raster_id", "payload"])
        before, after = chain.ops[1:split], chain.ops[split:]
        h, w = lower.shape(before, side, side)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            kernel = lower.to_kernel(before, side, side, MEAN, STD)
            for b in batches:
                for i in range(0, b.num_rows, 1024):
                    part = b.slice(i, 1024)
                    stack = np.stack([codec.png_decode(p) for p in part.column(1).to_pylist()])
                    x = kernel(stack).astype(np.float64).reshape(part.num_rows, -1)
                    offsets = np.arange(part.num_rows + 1, dtype=np.int32) * x.shape[1]
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(offsets, x.ravel())], ["raster_id", "x"])

        rows = rows.mapInArrow(run, "raster_id long, x array<double>")
        return rows.select("raster_id", lower.to_column(after, F.col("x"), h, w, MEAN, STD).alias("x")) if after else rows

    def labelled(self, formats: Sequence[str]) -> DataFrame:
        """Rows (format_id, raster_id, x, dataset, label, held): one for each label of an item; every fifth item is held out."""
        out = None
        for f in formats:
            one = self.prepared(f).select(F.lit(f).alias("format_id"), "raster_id", "x")
            out = one if out is None else out.unionByName(one)
        return out.join(self.truth, "raster_id").withColumn("held", F.pmod("raster_id", F.lit(5)) == 0)

    def means(self, formats: Sequence[str]) -> DataFrame:
        """Rows (format_id, dataset, classes array<struct<label, m>>): class means of the training fold, one row for each rendition and dataset."""
        h, w = lower.shape(CHAIN.ops, 8, 8)
        parts = [F.avg(F.element_at("x", i + 1)) for i in range(h * w)]
        by = self.labelled(formats).where("NOT held").groupBy("format_id", "dataset", "label").agg(F.array(*parts).alias("m"))
        return by.groupBy("format_id", "dataset").agg(F.sort_array(F.collect_list(F.struct("label", "m"))).alias("classes"))

    @staticmethod
    def nearest(x: Column, classes: Column, values: int, first: int = 0, places: int = 9) -> Column:
        """Structs (d, label) of all classes by rising distance over `values` values from `first`; ties by label."""
        square = lambda a, b: (a - b) * (a - b)
        part = F.slice(x, first + 1, values)
        far = lambda c: F.round(F.aggregate(F.zip_with(part, F.slice(c["m"], first + 1, values), square), F.lit(0.0), lambda s, v: s + v), places)
        return F.array_sort(F.transform(classes, lambda c: F.struct(far(c).alias("d"), c["label"].alias("label"))))

    def scored(self) -> DataFrame:
        """Held-out rows of `labelled` with classes (their rendition's means) and regular (those of full renditions)."""
        means = self.means(tuple({*self.formats, "full"}))
        full = means.where("format_id = 'full'").select("dataset", F.col("classes").alias("regular"))
        return self.labelled(self.formats).where("held").join(F.broadcast(means.join(full, "dataset")), ["format_id", "dataset"])

    def accuracy(self) -> DataFrame:
        """Rows (dataset, model_id, training, format_id, n, acc): every net, training and rendition on the held-out fold.

        One pass scores all of them; nothing is shuffled but labels and sums.
        """
        hits, pairs = [], []
        for t in self.trainings:
            for n in self.nets:
                guess = self.nearest(F.col("x"), F.col("regular" if t == "regular" else "classes"), n.values)[0]["label"]
                name = f"{n.model_id}_{t}"
                hits.append(F.avg((guess == F.col("label")).cast("double")).alias(name))
                pairs.append(F.struct(F.lit(n.model_id).alias("model_id"), F.lit(t).alias("training"), F.col(name).alias("acc")))
        wide = self.scored().groupBy("dataset", "format_id").agg(F.count("*").alias("n"), *hits)
        return wide.select("dataset", "format_id", "n", F.explode(F.array(*pairs)).alias("p")).select("dataset", "p.model_id", "p.training", "format_id", "n", "p.acc")

    # plans --------------------------------------------------------------------

    def chains(self) -> list[tuple[str, dag.Dag]]:
        """(format, order) for every order that keeps results; with dag_opt off, the declared one."""
        return [(f, d) for f in self.formats for d in (sorted(dag.orders(CHAIN, SIDES[f], SIDES[f], exact=True), key=dag.Dag.names) if self.dag_opt else [CHAIN])]

    def rates(self, chains: Sequence[tuple[str, dag.Dag]]) -> DataFrame:
        """Rows (model_id, format_id, chain, exec, place, op, seconds, host_only): nominal or measured seconds of each operator."""
        rows = []
        for f, d in chains:
            took = self.timed(f, d) if self.measured else seconds_of(d, f)
            rows += [(n.model_id, f, d.names(), n.rate, i, o, s, i == 1) for n in self.nets for i, o, s in took]
        return self.spark.createDataFrame(rows, "model_id string, format_id string, chain string, exec double, place int, op string, seconds double, host_only boolean")

    def timed(self, format_id: str, chain: dag.Dag, rows: int = 512) -> list[tuple[int, str, float]]:
        """Host seconds of each operator for an item, timed in one task over `rows` stored items."""
        side = SIDES[format_id]
        few = renditions.read(self.spark, self.store, format_id, ["payload"]).limit(rows)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                payloads = b.column(0).to_pylist()
                began = time.perf_counter()
                x = np.stack([codec.png_decode(p) for p in payloads])
                took, h, w = [(time.perf_counter() - began) / len(payloads)], side, side
                for o in chain.ops[1:]:
                    kernel = lower.to_kernel([o], h, w, MEAN, STD)
                    began = time.perf_counter()
                    x = kernel(x)
                    took.append(max(1e-9, (time.perf_counter() - began) / len(payloads)))
                    h, w = dag.shape_after(o, h, w)
                yield pa.RecordBatch.from_arrays([pa.array(range(1, len(took) + 1), pa.int32()), pa.array(took)], ["place", "seconds"])

        seen = few.coalesce(1).mapInArrow(run, "place int, seconds double").groupBy("place").agg(F.min("seconds").alias("s")).collect()
        by = {r["place"]: r["s"] for r in seen}
        return [(i + 1, o.name, by[i + 1]) for i, o in enumerate(chain.ops)]

    def cuts(self, every_order: bool = False) -> DataFrame:
        """Rows (model_id, format_id, chain, split, host_rate, accel_rate, tput): each cut of the chosen chains, or of all orders."""
        chains = self.chains() if every_order else [(f, self.chain(f)) for f in self.formats]
        return placement.splits(self.rates(chains), ("model_id", "format_id", "chain"), self.cores, ADVANTAGE)

    def placed(self) -> DataFrame:
        """Rows (model_id, format_id, chain, split, pre, exec): the best cut of each pair's chain (with dag_opt off, everything on the host)."""
        by = ("model_id", "format_id", "chain")
        chains = [(f, self.chain(f)) for f in self.formats]
        rates = self.rates(chains)
        best = placement.best_split(rates, by, self.cores, ADVANTAGE) if self.dag_opt else placement.splits(rates, by, self.cores, ADVANTAGE).where(F.col("split") == len(CHAIN.ops))
        return best.select(*by, "split", F.col("host_rate").alias("pre"), F.col("accel_rate").alias("exec"))

    def plans(self, accuracy: DataFrame | None = None) -> DataFrame:
        """Rows (plan_id, dataset, model_id, training, format_id, chain, split, pre, exec, est_tput, acc), one for each candidate."""
        rows = (self.accuracy() if accuracy is None else accuracy).join(F.broadcast(self.placed()), ["model_id", "format_id"])
        rows = select.estimate(rows, self.estimator)
        return rows.select(F.concat_ws("/", "dataset", "model_id", "training", "format_id").alias("plan_id"), "dataset", "model_id", "training", "format_id", "chain", "split", "pre", "exec", "est_tput", "acc")

    def frontier(self, plans: DataFrame | None = None) -> DataFrame:
        return select.frontier(self.plans() if plans is None else plans, by=["dataset"])

    def choose(self, dataset: str, throughput: float | None = None, accuracy: float | None = None, plans: DataFrame | None = None) -> DataFrame:
        """One row: the most accurate plan at least as fast as asked, or the fastest at least as accurate, or the fastest."""
        rows = (self.plans() if plans is None else plans).where(F.col("dataset") == dataset)
        if throughput is not None:
            return select.choose(rows, "acc", "est_tput", throughput, tie=("est_tput", "plan_id"))
        if accuracy is not None:
            return select.choose(rows, "est_tput", "acc", accuracy)
        return select.choose(rows, "est_tput")

    # execution ------------------------------------------------------------------

    def run(self, plan_id: str, chain: dag.Dag | None = None, split: int | None = None) -> DataFrame:
        """Rows (raster_id, guess, d) of all stored items, by the plan of that id.

        One scan of the plan's rendition, with the chain and cut that the plan table gives unless others are named.
        """
        dataset, model_id, training, format_id = plan_id.split("/")
        net = next(n for n in self.nets if n.model_id == model_id)
        chain = chain or self.chain(format_id)
        if split is None:
            split = self.placed().where((F.col("model_id") == model_id) & (F.col("format_id") == format_id)).first()["split"]
        classes = self.means(("full" if training == "regular" else format_id,)).where(F.col("dataset") == dataset).select("classes")
        rows = self.prepared(format_id, chain, split).crossJoin(F.broadcast(classes))  # one row of class means
        best = self.nearest(F.col("x"), F.col("classes"), net.values)[0]
        return rows.select("raster_id", best["label"].alias("guess"), best["d"].alias("d"))

    def without(self, **switches: bool) -> Engine:
        """The same engine with switches (dag_opt, lowres) set."""
        lowres = switches.get("lowres", True)
        return Engine(self.spark, self.store, self.truth, self.nets, self.formats if lowres else ("full",), self.trainings, switches.get("dag_opt", self.dag_opt), lowres, self.cores, self.estimator, self.measured)

