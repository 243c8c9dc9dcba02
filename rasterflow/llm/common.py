"""Helpers shared by the operators: bounded Arrow slices and lineage cuts."""

from __future__ import annotations

import contextlib
import ctypes
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

#: Bytes of text that one slice of a batch may hold (a longer text is a slice of its own).
SLICE_BYTES = 4 << 20

#: A word as the contracts define it: bytes between ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that `column` has about `limit` bytes in each piece."""
    for batch in batches:
        size, first, total = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist(), 0, 0
        for i, n in enumerate(size):
            if total and total + n > limit:
                yield batch.slice(first, i - first)
                first, total = i, 0
            total += n
        if first < batch.num_rows:
            yield batch.slice(first)


def texts(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    """The texts of a slice; null reads as empty."""
    return [x or "" for x in batch.column(column).to_pylist()]


def raw_texts(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """The same in UTF-8."""
    return [x or b"" for x in batch.column(column).cast(pa.binary()).to_pylist()]


def settled(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """`run` as a task's body that gives memory back when its partition ends: the worker lives on beside those of other stages."""

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(AttributeError, OSError):  # only where the C library has it
                ctypes.CDLL(None).malloc_trim(0)

    return body


def shared_folder(spark: SparkSession) -> str:
    """A new path in the folder that driver and executors share, the session's spark.checkpoint.dir.

    Where that is unset, a local session gets a folder of its own (tests); any other is refused, as executors couldn't
    read a folder of the driver's machine.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or getattr(shared_folder, "own", None)
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = shared_folder.own = tempfile.mkdtemp(prefix="shared-")
    return f"{base.rstrip('/')}/table-{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it again: it is computed once and survives lost executors."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def crc_of_id(column: str = "doc_id"):
    """crc32 of an id written as text."""
    return F.crc32(F.encode(F.col(column).cast("string"), "UTF-8"))


#: Rows of a written table that ask together for a key's value.
CHUNK_BITS = 12


def chunked(rows: DataFrame) -> DataFrame:
    """The rows, written, with a column chunk: runs of at most 2 ** CHUNK_BITS rows that lie together."""
    return written(rows.withColumn("chunk", F.shiftright(F.monotonically_increasing_id(), CHUNK_BITS)))


def looked_up(rows: DataFrame, key: str, table: DataFrame) -> DataFrame:
    """Rows of a `chunked` table with what `table` (unique by key) has of their key, else null.

    Each chunk asks once for each of its keys, and the answers are joined by chunk and key: a key that a third of all
    rows share costs one row a chunk and doesn't meet in one task.
    """
    asked = rows.where(F.col(key).isNotNull()).select("chunk", key).distinct()
    return rows.join(asked.join(table, key), ["chunk", key], "left")


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of a graph on numbers that aren't the smallest of their component, and the smallest."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, root = at[: len(a)], at[len(a) :], np.arange(len(ids))
    while True:
        low = np.minimum(root[x], root[y])
        new = root.copy()
        np.minimum.at(new, root[x], low)
        np.minimum.at(new, root[y], low)
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            break
        root = new
    far = np.flatnonzero(root != np.arange(len(ids)))
    return ids[far], ids[root[far]]


#: Edges that a task joins up at once.
FOREST = 1 << 20


def connected(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Components of a graph on longs: rows (node, root), root the smallest id reachable, for each node with a link.

    Tasks first join up the edges that they hold.  Then rounds alternate: the larger end of every edge moves to the
    least neighbour of the smaller end, and every smaller neighbour of a node to the node's least.  Each round is
    written, so lineage stays short and lost executors cost one round; rounds grow with the logarithm of the graph's
    diameter.  The first step asks by chunk (`looked_up`), so a hub's edges are never in one task; in the second a node
    has at most one edge for each task of the step before.  Nothing is collected but one count a round.
    """

    def forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def out() -> pa.RecordBatch:
            t = pa.Table.from_batches(held)
            return pa.RecordBatch.from_arrays([pa.array(x) for x in roots(t["u"].to_numpy(), t["v"].to_numpy())], ["u", "v"])

        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= FOREST:
                yield out()
                held, n = [], 0
        if n:
            yield out()

    ends = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v")
    e = chunked(ends.mapInArrow(settled(forest), "u long, v long").distinct())
    before = None
    while True:
        least = e.groupBy("u").agg(F.min("v").alias("m"))
        larger = looked_up(e, "v", least.withColumnRenamed("u", "v")).select("u", F.coalesce("m", "v").alias("v"))
        smaller = larger.withColumn("m", F.min("v").over(W.partitionBy("u")))
        ends = F.when(F.col("v") == F.col("m"), F.array("u")).otherwise(F.array("u", "v"))
        e = chunked(smaller.select(F.explode(ends).alias("u"), F.col("m").alias("v")).distinct())
        state = e.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0)).alias("s")).first()
        if state == before:
            break
        before = state
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


#: Words of 64 bits in an id filter: 2 MB, whatever the number of ids.
FILTER_WORDS = 1 << 18


def id_filter(ids: DataFrame, column: str, words: int = FILTER_WORDS) -> DataFrame:
    """One row (bits array<long>) to broadcast: a bit is set for each id's hash.

    Of bounded size: with many more ids than bits it lets everything pass, and only the join after it decides.
    """
    spark, place = ids.sparkSession, F.pmod(F.xxhash64(F.col(column).cast("long")), F.lit(64 * words))
    set_bits = ids.select(place.alias("p")).groupBy(F.floor(F.col("p") / 64).cast("int").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(p % 64 AS INT))")).alias("b")).toArrow()
    bits = np.zeros(words, np.int64)
    bits[set_bits["w"].to_numpy()] = set_bits["b"].to_numpy()
    offsets = pa.array([0, words], pa.int32())
    return spark.createDataFrame(pa.table({"bits": pa.ListArray.from_arrays(offsets, pa.array(bits))}))


def passing(rows: DataFrame, column: str, bits: DataFrame, words: int = FILTER_WORDS, passes: bool = True) -> DataFrame:
    """Rows whose id may be among those of the filter (or, with passes=False, those whose id surely isn't, and null ids)."""
    place = F.pmod(F.xxhash64(F.col(column).cast("long")), F.lit(64 * words))
    word = F.element_at("bits", (F.floor(place / 64) + 1).cast("int"))
    bit = F.when(F.col(column).isNull(), 0).otherwise(F.call_function("getbit", word, (place % 64).cast("int")))
    return rows.join(F.broadcast(bits), bit == int(passes), "left_semi")


def without(rows: DataFrame, column: str, ids: DataFrame) -> DataFrame:
    """Rows whose id isn't in `ids`; only those that the filter can't tell apart are shuffled for the join."""
    bits = id_filter(ids, column)
    return passing(rows, column, bits, passes=False).unionByName(passing(rows, column, bits).join(ids.select(column).distinct(), column, "left_anti").select(*rows.columns))

