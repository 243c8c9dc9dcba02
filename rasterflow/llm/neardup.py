"""Near-duplicates by an LSH forest.

Documents are sets of distinct word shingles.  Those with equal sets collapse to one representative first.  Each tree
of the forest is a sequence of minhashes, and all representatives are range-sorted by it; neighbours whose longest
common prefix reaches the depth of their region are candidates.  The depth is DEPTH where few share a prefix; where
more than CROWD do, the region's members are sorted again by DEEP longer orders of depth DEEPER, each of minhashes of
its own, so that text that many documents share doesn't tie them together and no pair gets a worse chance.  The sort
splits regions over tasks: those that touch the edge of a task are counted by key over all tasks before they are taken
for a crowd, and the pieces of one that isn't are joined up, as they are at the last depth.

Candidates are kept as connected groups, not as pairs, and links are confirmed on full sets of whole texts.  A group
is dealt over blocks by size of set and hash.  First each block meets by itself and with the group's first; then only
sets that are still apart from the first's component meet the other blocks of sizes that a link allows.  No candidate
is dropped.  Within a task, inverted lists give the intersections of a set with all others at once, and sets already
connected aren't compared again.

Null or empty text: no shingles, linked with nothing, kept.  Fewer words than a shingle takes: the whole sequence is
one shingle.  Null id: its own component (null), kept, linked with nothing.  Rows that repeat an id are compared like
others and share its component.  An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from .common import chunked, connected, id_filter, looked_up, passing, raw_texts, settled, slices, written

#: Trees of the forest and their depth; orders and depth where a region is crowded, and from what size.
#: No two orders share a minhash: at 0.8, (1 - 0.8^3)^20 = 5.9e-7 is missed by the trees and (1 - 0.8^5)^35 = 9.3e-7 in crowds.
TREES, DEPTH = 20, 3
DEEP, DEEPER = 35, 5
CROWD = 64
#: Sets and shingles that a block should hold; a larger group meets block by block.
BLOCK_SETS, BLOCK_SHINGLES = 1024, 1 << 20

_rng = np.random.default_rng(20240607)
MULTIPLY = _rng.integers(0, 1 << 63, TREES * DEPTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
ADD = _rng.integers(0, 1 << 63, TREES * DEPTH, dtype=np.uint64)
DEEP_MULTIPLY = _rng.integers(0, 1 << 63, DEEP * DEEPER, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
DEEP_ADD = _rng.integers(0, 1 << 63, DEEP * DEEPER, dtype=np.uint64)


def shingles(text: bytes, words: int) -> np.ndarray:
    """The distinct shingles of a text as 64-bit hashes, ascending."""
    w = text.lower().split()
    if not w:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, w), np.uint64, len(w))
    k = min(words, len(w))
    out = np.full(len(w) - k + 1, np.uint64(k if len(w) < words else 0))
    for i in range(k):
        out = (out ^ h[i : len(w) - k + 1 + i]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(32)
    out.sort()
    return out[np.concatenate(([True], out[1:] != out[:-1]))]


def minhashes(s: np.ndarray, multiply: np.ndarray = MULTIPLY, add: np.ndarray = ADD) -> np.ndarray:
    low, step = np.full(len(multiply), np.uint64(2**64 - 1)), (1 << 18) // len(multiply)
    for i in range(0, len(s), step):
        low = np.minimum(low, (s[i : i + step, None] * multiply + add).min(0))
    return (low >> np.uint64(32)).astype(np.uint32)


def sort_keys(signatures: np.ndarray, depth: int, salt: int) -> list[bytes]:
    """The keys of each signature in every order: the number of the order, then its minhashes, all big-endian."""
    orders = signatures.reshape(len(signatures), -1, depth)
    number = np.broadcast_to(np.arange(orders.shape[1], dtype=np.uint32)[None, :, None] + np.uint32(salt), (*orders.shape[:2], 1))
    flat = np.concatenate([number, orders], 2).astype(">u4").tobytes()
    width = 4 * (1 + depth)
    return [flat[i : i + width] for i in range(0, len(flat), width)]


def described(docs: DataFrame, words: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (id, n_shingles, class, signature): class is a digest of the set, null without shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, text_col):
            n, own, sig = [], [], []
            for x in raw_texts(b, text_col):
                s = shingles(x, words)
                n.append(len(s))
                own.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                sig.append(minhashes(s).tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(own, pa.binary()), pa.array(sig, pa.binary())], ["id", "n_shingles", "class", "signature"])

    return docs.select(F.col(id_col).cast("long").alias("id"), text_col).mapInArrow(run, "id long, n_shingles long, class binary, signature binary")


def ordered(representatives: DataFrame) -> DataFrame:
    """Rows (key, rep): the key of each representative in each of the TREES orders."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 2000):
                b = whole.slice(i, 2000)
                keys = sort_keys(np.array([np.frombuffer(x, np.uint32) for x in b.column(1).to_pylist()]), DEPTH, 0)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), b.column(0).take(pa.array(np.repeat(np.arange(b.num_rows), TREES)))], ["key", "rep"])

    return representatives.select("rep", "signature").mapInArrow(settled(run), "key binary, rep long")


def ordered_deeply(crowded: DataFrame, docs: DataFrame, words: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (key, rep): the key of the representatives in `crowded` in each of the DEEP orders, from their texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = [shingles(x, words) for x in raw_texts(b)]
            own = [i for i, s in enumerate(sets) if len(s)]
            if own:
                keys = sort_keys(np.array([minhashes(sets[i], DEEP_MULTIPLY, DEEP_ADD) for i in own]), DEEPER, TREES)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), b.column(0).take(pa.array(np.repeat(own, DEEP)))], ["key", "rep"])

    texts = docs.select(F.col(id_col).cast("long").alias("rep"), F.col(text_col).alias("text"))
    rows = passing(texts, "rep", id_filter(crowded, "rep")).join(crowded, "rep", "left_semi")
    return rows.select("rep", "text").mapInArrow(settled(run), "key binary, rep long")


def regions(rows: DataFrame, depth: int, crowd: int | None) -> DataFrame:
    """Rows (a, b, key) from rows (key, rep), sorted in ranges: a and b are neighbours in a region.

    With `crowd`, b is null for members of regions of more members, and for those of regions that touch the edge of a
    task, whose `key` is given.  Without, all neighbours are there, and `key` is given, with b null, once for each piece
    of such a region.
    """
    width, crowd_ = 1 + depth, crowd or 1 << 62

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, reps = np.empty((0, width), ">u4"), np.empty(0, np.int64)
        first_region = True  # whether no earlier region began in this task

        def out(start: np.ndarray, size: np.ndarray, edge: np.ndarray) -> pa.RecordBatch:
            """The regions given; edge: those that may go on in another task."""
            at = np.repeat(start, size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            if crowd:
                deep = np.repeat((size > crowd) | edge, size)
                a, b = reps[at[deep]], np.empty(0, np.int64)
                near = at[~deep]
                near = near[~np.isin(near, start)]
                marks: list[bytes | None] = [keys[i].tobytes() if e else None for i, e in zip(at[deep].tolist(), np.repeat(edge, size)[deep].tolist(), strict=True)]
            else:
                a = reps[start[edge]]
                near = at[~np.isin(at, start)]
                marks = [keys[i].tobytes() for i in start[edge].tolist()]
            a_ = pa.array(np.concatenate([reps[near], a]), pa.int64())
            b_ = pa.array(np.concatenate([reps[near - 1], np.zeros(len(a), np.int64)]), pa.int64(), mask=np.concatenate([np.zeros(len(near), bool), np.ones(len(a), bool)]))
            return pa.RecordBatch.from_arrays([a_, b_, pa.array([None] * len(near) + marks, pa.binary())], ["a", "b", "key"])

        def bounds() -> tuple[np.ndarray, np.ndarray]:
            start = np.flatnonzero(np.concatenate([[True], (keys[1:] != keys[:-1]).any(1)]))
            return start, np.diff(np.append(start, len(keys)))

        for batch in batches:
            if not batch.num_rows:
                continue
            new = np.frombuffer(b"".join(batch.column(0).to_pylist()), ">u4").reshape(-1, width)
            keys, reps = np.concatenate([keys, new]), np.concatenate([reps, batch.column(1).to_numpy()])
            start, size = bounds()
            last = start[-1]
            if len(start) > 1:
                edge = np.zeros(len(start) - 1, bool)
                edge[0] = first_region
                first_region = False
                yield out(start[:-1], size[:-1], edge)
            keys, reps = keys[last:], reps[last:]
            if len(keys) > 1 << 16:  # a huge region: what is done of it goes out, and its last member stays for the next link
                n = np.array([len(keys)])
                yield out(np.array([0]), n, np.array([bool(crowd) or first_region]))
                stay = 1 if crowd is None else min(len(keys), crowd_ + 1)
                keys, reps = keys[-stay:], reps[-stay:]
        if len(keys):
            yield out(*bounds(), np.array([True]))

    return rows.repartitionByRange("key", "rep").sortWithinPartitions("key", "rep").mapInArrow(settled(run), "a long, b long, key binary")


def candidate_links(representatives: DataFrame, docs: DataFrame, words: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (a, b): neighbours in the sorted orders, enough to connect every region at its depth."""
    found = written(regions(ordered(representatives), DEPTH, CROWD).distinct())
    edge = found.where(F.col("key").isNotNull()).select("a", "key")
    whole = edge.groupBy("key").agg(F.count("*").alias("n"), F.min("a").alias("b"))  # two keys a task at most
    edge = written(edge.join(F.broadcast(whole), "key").select("a", "b", "n"))
    near = found.where(F.col("b").isNotNull()).select("a", "b").unionByName(edge.where((F.col("n") <= CROWD) & (F.col("a") != F.col("b"))).select("a", "b"))
    crowded = written(found.where(F.col("b").isNull() & F.col("key").isNull()).select("a").unionByName(edge.where(F.col("n") > CROWD).select("a")).distinct().withColumnRenamed("a", "rep"))
    if crowded.isEmpty():
        return near
    deep = written(regions(written(ordered_deeply(crowded, docs, words, id_col, text_col)), DEEPER, None).distinct())
    pieces = deep.where(F.col("b").isNull()).select("a", "key")
    whole = pieces.groupBy("key").agg(F.min("a").alias("b"))
    across = pieces.join(whole, "key").where("a <> b").select("a", "b")  # two rows a task at most
    return near.unionByName(deep.where(F.col("b").isNotNull()).select("a", "b")).unionByName(across).distinct()


def links_between(sets: list[np.ndarray], percent: int, root: np.ndarray | None = None, asks: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that join up sets (numbers of two), enough to connect all that are linked.

    root: what is connected already (the least number of each).  asks: only pairs with one of these count.
    """
    n = len(sets)
    size = np.array([len(s) for s in sets])
    flat = np.concatenate([*sets, np.empty(0, np.uint64)])
    _, code = np.unique(flat, return_inverse=True)
    owner = np.repeat(np.arange(n), size)
    order = np.argsort(code, kind="stable")
    by_code, first = owner[order], np.concatenate([[0], np.cumsum(np.bincount(code))])
    at = np.concatenate([[0], np.cumsum(size)])
    root = np.arange(n) if root is None else root.copy()
    out = []
    for i in range(n) if asks is None else np.flatnonzero(asks):
        if (root == root[i]).all():
            continue
        c = code[at[i] : at[i + 1]]
        a, length = first[c], first[c + 1] - first[c]
        alone = length == 1
        a, length = a[~alone], length[~alone]
        if not len(a):
            continue
        places = np.repeat(a - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(length.sum())
        common = np.bincount(by_code[places], minlength=n)
        linked = 100 * common >= percent * (size[i] + size - common)
        for j in np.flatnonzero(linked & (root != root[i])).tolist():
            if root[j] != root[i]:
                out.append((i, j))
                root[root == root[j]] = root[i]
    return out


def dealt_groups(groups: DataFrame, percent: int) -> DataFrame:
    """Rows (node, root, band, part, parts, single): the block of each node.

    Links keep sizes within a factor of 100 / percent, so a band (a step of the size's logarithm) meets itself and the
    next ones only; a band of a group has enough parts for blocks of BLOCK_SETS sets and BLOCK_SHINGLES shingles.
    """
    step = float(np.log(100 / percent) * 1.001) if percent < 100 else 1.0
    sets = chunked(groups.withColumn("band", F.floor(F.log("n_shingles") / step).cast("int")))
    enough = lambda sets, all_: F.greatest(F.ceil(sets / BLOCK_SETS), F.ceil(all_ / BLOCK_SHINGLES), F.lit(1)).cast("int")
    of_band = sets.groupBy("root", "band").agg(F.count("*").alias("sets"), F.sum("n_shingles").alias("all"))
    of_group = of_band.groupBy("root").agg(F.sum("sets").alias("sets"), F.sum("all").alias("all"))
    of_band = of_band.select("root", "band", F.least(enough(F.col("sets"), F.col("all")), F.col("sets").cast("int")).alias("parts"))
    of_band = of_band.join(of_group.select("root", (enough(F.col("sets"), F.col("all")) == 1).alias("single")), "root")
    named = F.struct("root", "band")
    sets = looked_up(sets.withColumn("cell", named), "cell", of_band.select(named.alias("cell"), "parts", "single"))
    return sets.select("node", "root", F.when(F.col("single"), 0).otherwise(F.col("band")).alias("band"), F.when(F.col("single"), 0).otherwise(F.pmod(F.xxhash64("node"), F.col("parts"))).cast("int").alias("part"), F.when(F.col("single"), 1).otherwise(F.col("parts")).alias("parts"), "single")


def confirmed_links(groups: DataFrame, docs: DataFrame, words: int, percent: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (a, b): links that hold on full sets, enough to connect each component.  groups: rows (node, root, n_shingles)."""
    dealt = written(dealt_groups(groups, percent))
    texts = docs.select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("text"))
    rows = passing(texts, "node", id_filter(groups, "node")).join(dealt, "node")

    def sets_of(t: pa.Table) -> tuple[pa.Table, list[np.ndarray]]:
        """Rows by node and their sets; rows that repeat an id are there once for each text."""
        t = t.sort_by([("node", "ascending")])
        seen = {}
        for i, x in enumerate(zip(t["node"].to_pylist(), t["text"].cast(pa.binary()).to_pylist(), strict=True)):
            seen.setdefault(x, i)
        return t.take(list(seen.values())), [shingles(x or b"", words) for _, x in seen]

    def pairs(node: np.ndarray, found: list[tuple[int, int]], apart: np.ndarray) -> pa.Table:
        """Links, and with b null the nodes that are apart."""
        a = np.concatenate([node[[p[0] for p in found]], node[apart]]) if len(node) else node
        b = np.concatenate([node[[p[1] for p in found]], np.zeros(len(apart), np.int64)]) if len(node) else node
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64(), mask=np.arange(len(b)) >= len(found))], names=["a", "b"])

    def meet(t: pa.Table) -> pa.Table:
        """A block by itself, with the group's first."""
        t, sets = sets_of(t)
        node, root, single = t["node"].to_numpy(), t["root"][0].as_py(), t["single"][0].as_py()
        found = links_between(sets, percent)
        if single:
            return pairs(node, found, np.empty(0, np.int64))
        below = np.arange(len(node))
        for i, j in found:
            below[below == below[j]] = below[i]
        first = np.flatnonzero(node == root)
        return pairs(node, found, np.flatnonzero(below != below[first[0]]) if len(first) else np.arange(len(node)))

    firsts = rows.where("node = root").select("node", "text", "root", "single")
    blocks = dealt.where("NOT single").select("root", "band", "part").distinct()
    with_first = rows.select("node", "text", "root", "band", "part", "single").unionByName(firsts.where("NOT single").join(blocks, "root").select("node", "text", "root", "band", "part", "single"))
    met = written(with_first.groupBy("root", "band", "part").applyInArrow(meet, "a long, b long"))
    links = met.where(F.col("b").isNotNull())
    apart = dealt.join(met.where(F.col("b").isNull()).select(F.col("a").alias("node")).distinct(), "node", "left_semi")
    apart = written(apart.where("NOT single"))
    if apart.isEmpty():
        return links

    # blocks of those that are apart, and each block that they meet
    parts = apart.groupBy("root", "band").agg(F.count("*").alias("n"))
    parts = parts.select("root", F.col("band").alias("asks_band"), F.ceil(F.col("n") / BLOCK_SETS).cast("int").alias("asks_parts"))
    bands = dealt.where("NOT single").select("root", "band", "parts").distinct()
    meetings = written(parts.join(bands, "root").where(F.abs(F.col("band") - F.col("asks_band")) <= 1))
    asks = apart.select("node", "root", F.col("band").alias("asks_band")).join(meetings, ["root", "asks_band"])
    asks = asks.select("node", "root", "asks_band", F.pmod(F.xxhash64(F.lit(7), "node"), F.col("asks_parts")).cast("int").alias("asks_part"), "band", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(True).alias("asks"))
    rest = dealt.where("NOT single").join(meetings.drop("parts"), ["root", "band"])
    rest = rest.select("node", "root", "asks_band", F.explode(F.sequence(F.lit(0), F.col("asks_parts") - 1)).alias("asks_part"), "band", "part", F.lit(False).alias("asks"))
    cells = asks.unionByName(rest)

    def meet_apart(t: pa.Table) -> pa.Table:
        asked = set(t.filter(t["asks"])["node"].to_pylist())
        if not asked:
            return pairs(np.empty(0, np.int64), [], np.empty(0, np.int64))
        t, sets = sets_of(t)
        node = t["node"].to_numpy()
        return pairs(node, links_between(sets, percent, asks=np.array([x in asked for x in node.tolist()])), np.empty(0, np.int64))

    rows = passing(texts, "node", id_filter(cells, "node")).join(cells, "node")
    more = rows.groupBy("root", "asks_band", "asks_part", "band", "part").applyInArrow(meet_apart, "a long, b long")
    return links.unionByName(more)


def components(docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, n_shingles, component_id, kept) of every document; links have 100 * intersection >= percent * union."""
    base = chunked(described(docs, words, id_col, text_col))
    classes = written(base.where(F.col("class").isNotNull() & F.col("id").isNotNull()).groupBy("class").agg(F.min("id").alias("rep")))
    chosen = base.join(classes.select(F.col("class"), F.col("rep").alias("id")), ["class", "id"], "left_semi")
    representatives = written(chosen.dropDuplicates(["id", "class"]).select(F.col("id").alias("rep"), "n_shingles", "signature"))
    groups = connected(candidate_links(representatives, docs, words, id_col, text_col))
    sized = groups.join(representatives.groupBy("rep").agg(F.max("n_shingles").alias("n_shingles")).withColumnRenamed("rep", "node"), "node")
    links = confirmed_links(written(sized), docs, words, percent, id_col, text_col)
    roots = connected(links)
    of_class = classes.join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").select("class", F.coalesce("root", "rep").alias("component_id"))
    out = looked_up(base.drop("signature"), "class", of_class)  # a class may hold a third of all rows
    component = F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id"))
    return out.select(F.col("id").alias(id_col), "n_shingles", component.alias("component_id"), (component.isNull() | (component == F.col("id"))).alias("kept"))


#: Brute force in SQL: all pairs that share a shingle, and components by the smallest id reachable.
ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]] ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT p.a, p.b FROM p JOIN n x ON x.doc_id = p.a JOIN n y ON y.doc_id = p.b WHERE 100 * p.c >= 80 * (x.n + y.n - p.c)),
r(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
m AS (SELECT a, min(b) AS m FROM r GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.m AS component_id, d.doc_id = m.m AS kept FROM documents d JOIN m ON m.a = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""
