"""A hidden Markov language model.

Baum-Welch: in every round each partition runs scaled forward and backward recursions over its whole training texts
and sums expected counts, partial sums are added up in a tree, and the driver gets one small matrix.  Emissions are
mixed with the unigram shares (by the state's distinct words, at least SHARE), so a word that a state never showed isn't
ruled out there.  Rounds over all
training texts go on until the gain of log likelihood a token falls below GAIN, ROUNDS at most.  They start from a
mixture of unigrams, a state for each class of texts, fitted by MIXTURES rounds over all training texts as well (a
mixture's round is an HMM's whose states never change, and is much cheaper).  Nothing is learnt from a sample.

A text's likelihood is the exact scaled forward recursion over all its tokens.  Texts go in lockstep, in groups whose
grid (rows times the longest) is bounded; longer ones go by blocks, whose transfer matrices are multiplied in order,
and which then run in lockstep between the states at their ends.

The emission alphabet is the WORDS most frequent training words, the end token and one class for all other words; a
word of that class has its smoothed share of the class.  So the model's arrays are bounded while counts cover every
word: those of other words are joined by word, not broadcast.  Words of more than LONGEST bytes are never broadcast.

Null text: empty, just the end token.  Null id: its text is training text and gets a row.  Repeated rows are counted
and scored one by one.  Without training rows the counts are 0 and the model is uniform.  An empty table gives no
rows; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import crc_of_id, raw_texts, settled, slices, written

STATES = 6
#: Words with a symbol of their own; the most frequent ones.
WORDS = 32768
#: Bytes of the longest word that is broadcast.
LONGEST = 64
#: Words whose counts are broadcast (a bound too); the counts of others are joined.
KNOWN = 1 << 18
ROUNDS = 2
#: Gain of log likelihood a token (natural) below which training ends.
GAIN = 0.01
#: Least share of the unigram in each state's emissions.
SHARE = 0.1
#: Rounds of the mixture of unigrams that training starts from.
MIXTURES = 3
#: Distinct words that a task holds before it sends their counts on.
HELD = 200_000
#: Partial sums of expected counts meet in so many tasks before the driver adds them.
FAN = 16


@dataclass
class Alphabet:
    """Words whose counts are broadcast, by falling count; the first `letters` of them are symbols of their own."""

    ids: dict[bytes, int]
    counts: np.ndarray
    letters: int
    ends: int  # count of the end token
    total: int
    distinct: int

    @property
    def end(self) -> int:
        return self.letters

    @property
    def other(self) -> int:
        return self.letters + 1

    @property
    def symbol_counts(self) -> np.ndarray:
        first = self.counts[: self.letters]
        return np.array([*first, self.ends, self.total - self.ends - first.sum()], np.float64)

    @property
    def other_mass(self) -> float:
        """Smoothed count of all words without a symbol, and of one unseen."""
        return float(self.symbol_counts[-1]) + 0.5 * (max(0, self.distinct - (self.ends > 0) - self.letters) + 1)


@dataclass
class Model:
    start: np.ndarray
    move: np.ndarray  # states x states
    emit: np.ndarray  # symbols x states


def counted(docs: DataFrame, text_col: str) -> DataFrame:
    """Rows (word binary, n) of the whole texts' words; word null: the ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter[bytes] = Counter()
        rows = 0
        out = lambda words, n: pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(n, pa.int64())], ["word", "n"])
        for b in slices(batches, text_col):
            for x in raw_texts(b, text_col):
                held.update(x.lower().split())
            rows += b.num_rows
            if len(held) > HELD:
                yield out(list(held), list(held.values()))
                held.clear()
        yield out([*held, None], [*held.values(), rows])

    return docs.select(text_col).mapInArrow(settled(run), "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).where("n > 0")


def alphabet(counts: DataFrame, words: int, known: int = KNOWN) -> Alphabet:
    """From rows (word, n); the driver gets `known` rows at most, a histogram of counts and three sums.

    The words are those whose count reaches a level that no more than `known` words reach.  The level comes from a
    histogram over 64 steps a doubling, so no task sorts or gathers the words (a top-k would send `known` rows from
    every partition to one task).
    """
    sums = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*"), F.coalesce(F.sum(F.when(F.col("word").isNull(), F.col("n"))), F.lit(0))).first()
    step = F.floor(F.log2(F.col("n")) * 64).cast("int")
    real = counts.where(F.octet_length("word") <= LONGEST)
    level, found = None, 0
    for r in sorted(real.groupBy(step.alias("step")).count().collect(), key=lambda r: -r["step"]):
        found += r["count"]
        if found > known:
            break
        level = r["step"]
    top = real.where(step >= level if level is not None else F.lit(False)).toArrow()
    top = top.sort_by([("n", "descending"), ("word", "ascending")])
    ids = {w: i for i, w in enumerate(top["word"].to_pylist())}
    return Alphabet(ids, top["n"].to_numpy().astype(np.int64), min(words, len(ids)), int(sums[2]), int(sums[0]), int(sums[1]))


def shares(a: Alphabet) -> np.ndarray:
    """Smoothed unigram shares of the symbols."""
    base = a.symbol_counts + 0.5
    return base / base.sum()


def initial(a: Alphabet, states: int, seed: int = 0) -> Model:
    """Sticky states, whose emissions stray from the unigram."""
    rng = np.random.default_rng(seed)
    emit = shares(a)[:, None] * np.exp(rng.standard_normal((a.letters + 2, states)))
    move = 0.02 / states + 0.98 * np.eye(states)
    return Model(np.full(states, 1 / states), move / move.sum(1, keepdims=True), emit / emit.sum(0))


def fitted(start: np.ndarray, move: np.ndarray, emit: np.ndarray, base: np.ndarray, share: float) -> Model:
    """The model of expected counts.

    A state emits the unigram with a weight of its distinct words over its tokens and them, at least `share`.
    """
    e = emit + base[:, None]  # a state without tokens emits the unigram
    types = (emit > 0.5).sum(0)
    unigram = np.maximum(share, types / (emit.sum(0) + types + 1))
    return Model((start + 1) / (start + 1).sum(), (move + 1) / (move + 1).sum(1, keepdims=True), (1 - unigram) * e / e.sum(0) + unigram * base[:, None])


def encoded(texts: list[bytes], a: Alphabet) -> tuple[list[np.ndarray], list[list[bytes]]]:
    """Places of each text's words in the alphabet (len(ids): not there), and its words."""
    get, none = a.ids.get, repeat(len(a.ids))
    words = [x.lower().split() for x in texts]
    return [np.fromiter(map(get, w, none), np.int32, len(w)) for w in words], words


def symbols_of(places: np.ndarray, a: Alphabet) -> np.ndarray:
    return np.append(np.where(places < a.letters, places, a.other), a.end).astype(np.int32)


#: Tokens of a block of a long text; texts of more than LONG tokens go by blocks.
BLOCK = 256
LONG = 4096
#: Places of a grid: rows times the longest of them.
GRID = 200_000


def lockstep(rows: list[np.ndarray], pad: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols as (positions, rows), rows by falling length, with the order and how many rows are live at each position."""
    size = np.array([len(r) for r in rows])
    order = np.argsort(-size, kind="stable")
    grid = np.full((int(size.max()), len(rows)), pad, np.int32)
    for j, i in enumerate(order):
        grid[: size[i], j] = rows[i]
    live = np.searchsorted(-size[order], -np.arange(grid.shape[0]), "left")
    return grid, order, live


def forward_log(rows: list[np.ndarray], m: Model) -> np.ndarray:
    """Natural log of each row's likelihood."""
    out, one = np.zeros(len(rows)), np.ones(len(m.start))  # a product with ones adds up short rows much faster than sum(1)
    for own, part in grouped(rows):
        if len(part[0]) > LONG:
            out[own[0]] = sum(logs for _, _, logs in ends_of_blocks(part[0], m))
            continue
        grid, order, live = lockstep(part, 0)
        alpha, logs = np.tile(m.start, (len(part), 1)) * m.emit[grid[0]], np.zeros(len(part))
        for t in range(grid.shape[0]):
            n = live[t]
            if t:
                alpha[:n] = (alpha[:n] @ m.move) * m.emit[grid[t, :n]]
            s = alpha[:n] @ one
            alpha[:n] /= s[:, None]
            logs[:n] += np.log(s)
        out[np.array(own)[order]] = logs
    return out


def transfers(blocks: np.ndarray, tail: int, m: Model) -> tuple[np.ndarray, np.ndarray]:
    """Scaled transfer matrices of blocks of symbols (the last has `tail` of them), and the logs of their scales."""
    n, k = len(blocks), len(m.start)
    transfer, logs = np.tile(np.eye(k), (n, 1, 1)), np.zeros(n)
    for t in range(blocks.shape[1]):
        live = n if t < tail else n - 1
        if not live:
            break
        transfer[:live] = (transfer[:live] @ m.move) * m.emit[blocks[:live, t]][:, None, :]
        s = transfer[:live].sum((1, 2))
        transfer[:live] /= s[:, None, None]
        logs[:live] += np.log(s)
    return transfer, logs


def ends_of_blocks(row: np.ndarray, m: Model) -> Iterator[tuple[np.ndarray, np.ndarray, float]]:
    """For each block of a row: its transfer matrix, the filtered state at its end, and its log likelihood given what came before.

    The first token is a block of its own, so that every other is entered by a move.
    """
    now = m.start * m.emit[row[0]]
    s = now.sum()
    now /= s
    yield np.eye(len(now)), now, float(np.log(s))
    for i in range(1, len(row), BLOCK * 512):
        part = row[i : i + BLOCK * 512]
        n = -(-len(part) // BLOCK)
        blocks = np.zeros((n, BLOCK), np.int32)
        blocks.ravel()[: len(part)] = part
        for matrix, log in zip(*transfers(blocks, len(part) - (n - 1) * BLOCK, m), strict=True):
            now = now @ matrix
            s = now.sum()
            now = now / s
            yield matrix, now, float(np.log(s) + log)


Counts = tuple[np.ndarray, np.ndarray, np.ndarray, float]


def expected(rows: list[np.ndarray], m: Model) -> Counts:
    """Expected starts, moves and emissions of whole rows, and their log likelihood."""
    k = len(m.start)
    total: list = [np.zeros(k), np.zeros((k, k)), np.zeros_like(m.emit), 0.0]
    for _, part in grouped(rows):
        found = expected_long(part[0], m) if len(part[0]) > LONG else expected_between(part, np.tile(m.start, (len(part), 1)), np.ones((len(part), k)), m)[:4]
        total = [x + y for x, y in zip(total, found, strict=True)]
    return tuple(total)


def expected_long(row: np.ndarray, m: Model) -> Counts:
    """The same for one long row: the states at the ends of its blocks first, then 512 blocks at a time between them."""
    parts = list(ends_of_blocks(row, m))  # one matrix for each BLOCK tokens
    n, k = len(parts) - 1, len(m.start)
    tails = np.ones((n + 1, k))
    for i in range(n, 0, -1):  # what follows block i - 1, scaled so that it weighs 1 with the filtered state there
        ahead = parts[i][0] @ tails[i]
        tails[i - 1] = ahead / (parts[i - 1][1] @ ahead)
    first = parts[0][1] * tails[0]
    total: list = [first, np.zeros((k, k)), np.zeros_like(m.emit), float(np.log((m.start * m.emit[row[0]]).sum()))]
    total[2][row[0]] += first
    for i in range(0, n, 512):
        own = range(i, min(n, i + 512))
        blocks = [row[1 + b * BLOCK : 1 + (b + 1) * BLOCK] for b in own]
        before = np.array([parts[b][1] for b in own])
        _, move, emit, log, entered = expected_between(blocks, before @ m.move, tails[i + 1 : i + 1 + len(blocks)], m)
        move += before.T @ entered * m.move
        total = [total[0], total[1] + move, total[2] + emit, total[3] + log]
    return tuple(total)


def expected_between(rows: list[np.ndarray], first: np.ndarray, tail: np.ndarray, m: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray, float, np.ndarray]:
    """Expected starts, moves within rows and emissions of rows that begin with the weights `first` and are followed by `tail`.

    Also the log likelihood, and for each row what each state weighs when it is entered (the moves into the row, but
    for the state before and the move's weight).
    """
    k = len(m.start)
    grid, order, live = lockstep(rows, 0)
    steps = grid.shape[0]
    offset = np.concatenate([[0], np.cumsum(live)])
    alpha, scale = np.empty((offset[-1], k)), np.empty(offset[-1])
    symbol = np.concatenate([grid[t, : live[t]] for t in range(steps)])
    like = m.emit[symbol]
    at = lambda t: slice(offset[t], offset[t + 1])
    now, last, one = first[order] * like[at(0)], tail[order], np.ones(k)
    for t in range(steps):
        if t:
            now = (now[: live[t]] @ m.move) * like[at(t)]
        s = now @ one
        now = now / s[:, None]
        alpha[at(t)], scale[at(t)] = now, s
    move, emit = np.zeros((k, k)), np.zeros_like(m.emit)
    after = lambda t, n, beta: np.concatenate([beta, last[n : live[t]] / ((alpha[at(t)][n:] * last[n : live[t]]) @ one)[:, None]]) if n < live[t] else beta
    beta = after(steps - 1, 0, np.empty((0, k)))
    gamma = np.empty_like(alpha)
    gamma[at(steps - 1)] = alpha[at(steps - 1)] * beta
    for t in range(steps - 2, -1, -1):
        n = live[t + 1]
        ahead = like[at(t + 1)] * beta / scale[at(t + 1)][:, None]
        move += alpha[at(t)][:n].T @ ahead
        beta = after(t, n, ahead @ m.move.T)
        gamma[at(t)] = alpha[at(t)] * beta
    entered = np.empty((len(rows), k))
    entered[order] = like[at(0)] * beta / scale[at(0)][:, None]
    for j in range(k):
        emit[:, j] += np.bincount(symbol, gamma[:, j], minlength=len(emit))
    return gamma[at(0)].sum(0), move * m.move, emit, float(np.log(scale).sum()), entered


def mixed(rows: list[np.ndarray], m: Model) -> Counts:
    """The same if the state of a row's start holds to its end: expected rows and emissions of each state."""
    size, log_emit = np.array([len(r) for r in rows]), np.log(m.emit.T)
    flat, first = np.concatenate(rows).astype(np.intp), np.cumsum(size) - size
    logs = np.stack([np.add.reduceat(x[flat], first) for x in log_emit], 1) + np.log(m.start)  # by state: a long text takes little memory
    most = logs.max(1, keepdims=True)
    weight = np.exp(logs - most)
    total = weight.sum(1, keepdims=True)
    weight /= total
    emit = np.stack([np.bincount(flat, np.repeat(w, size), minlength=len(m.emit)) for w in weight.T], 1)
    return weight.sum(0), np.zeros_like(m.move), emit, float((np.log(total) + most).sum())


def grouped(rows: list[np.ndarray]) -> Iterator[tuple[list[int], list[np.ndarray]]]:
    """Numbers and rows of groups of similar lengths, whose grid has at most GRID places; a row of more than LONG tokens alone."""
    part: list[int] = []
    for i in sorted(range(len(rows)), key=lambda i: len(rows[i])):
        if part and (len(rows[i]) > LONG or (len(part) + 1) * len(rows[i]) > GRID):
            yield part, [rows[k] for k in part]
            part = []
        part.append(i)
    if part:
        yield part, [rows[k] for k in part]


def train(docs: DataFrame, a: Alphabet, states: int = STATES, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text", seed: int = 0, gain: float = GAIN, share: float = SHARE) -> tuple[Model, list[float]]:
    """Baum-Welch over whole training texts; also the log likelihood before each round."""
    spark = docs.sparkSession
    letters = spark.sparkContext.broadcast(a)
    symbols = a.letters + 2
    if symbols > 1 << 16:
        raise ValueError("the alphabet has more than 65534 words")
    base = shares(a)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = letters.value
        for b in slices(batches, text_col):
            places, _ = encoded(raw_texts(b, text_col), a)
            yield pa.RecordBatch.from_arrays([pa.array([symbols_of(x, a).astype("<u2").tobytes() for x in places], pa.binary())], ["symbols"])

    def rows_of(b: pa.RecordBatch) -> list[np.ndarray]:
        return [np.frombuffer(x, "<u2").astype(np.int32) for x in b.column("symbols").to_pylist()]

    rows = written(docs.select(text_col).mapInArrow(settled(encode), "symbols binary"))

    def summed(m: Model, counts: Callable[[list[np.ndarray], Model], Counts]) -> Counts:
        """What `counts` gives of all training texts."""
        held = spark.sparkContext.broadcast(m)

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m = held.value
            total = np.zeros(1 + states + states * states + symbols * states)
            for b in slices(batches, "symbols", 1 << 20):
                s, v, e, log = counts(rows_of(b), m)
                total += np.concatenate([[log], s, v.ravel(), e.ravel()])
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = None
            for b in batches:
                for x in b.column(0).to_pylist():
                    total = np.frombuffer(x).copy() if total is None else total + np.frombuffer(x)
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

        part = rows.mapInArrow(settled(count), "sums binary").repartition(FAN).mapInArrow(settled(add), "sums binary").collect()
        total = sum((np.frombuffer(r["sums"]) for r in part), np.zeros(1 + states + states * states + symbols * states))
        held.destroy()
        return total[1 : 1 + states], total[1 + states : 1 + states + states**2].reshape(states, states), total[1 + states + states**2 :].reshape(symbols, states), float(total[0])

    m, history = initial(a, states, seed), []
    for _ in range(MIXTURES):
        s, _, e, _ = summed(m, mixed)
        m = Model((s + 1) / (s + 1).sum(), m.move, fitted(s, m.move, e, base, share).emit)
    m = Model(np.full(states, 1 / states), m.move, m.emit)
    for _ in range(rounds):
        s, v, e, log = summed(m, expected)
        history.append(log)
        m = fitted(s, v, e, base, share)
        if len(history) > 1 and history[-1] - history[-2] < gain * max(1, a.total):
            break
    letters.destroy()
    return m, history


def score(docs: DataFrame, training: DataFrame, words: int = WORDS, states: int = STATES, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, held_out, n_tokens, n_known, train_tokens, base_score, score) of docs, which have a column held_out."""
    counts = written(counted(training, text_col))
    a = alphabet(counts, words)
    m, _ = train(training, a, states, rounds, id_col, text_col)
    held = docs.sparkSession.sparkContext.broadcast((a, m))
    below = a.total + 0.5 * (a.distinct + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, m = held.value
        base = np.append(np.log10((a.counts + 0.5) / below), 0.0)
        base_end = float(np.log10((a.ends + 0.5) / below))
        within = np.append(np.log10((a.counts + 0.5) / a.other_mass), 0.0)  # of a word's share of the class
        within[: a.letters] = 0.0
        none = len(a.ids)
        for b in slices(batches, text_col):
            places, words = encoded(raw_texts(b, text_col), a)
            rare = [Counter([w[i] for i in np.flatnonzero(x == none).tolist()]) for x, w in zip(places, words, strict=True)]
            n_tokens = [len(x) + 1 for x in places]
            n_known = [int((x < none).sum()) + (a.ends > 0) for x in places]
            bases = [float(base[x].sum()) + base_end for x in places]
            logs = np.array([float(within[x].sum()) for x in places])
            logs += forward_log([symbols_of(x, a) for x in places], m) / np.log(10)
            offsets = np.concatenate([[0], np.cumsum([len(r) for r in rare])]).astype(np.int32)
            found = pa.StructArray.from_arrays([pa.array([w for r in rare for w in r], pa.binary()), pa.array([n for r in rare for n in r.values()], pa.int64())], names=["word", "n"])
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(n_tokens, pa.int64()), pa.array(n_known, pa.int64()), pa.array(bases, pa.float64()), pa.array(logs, pa.float64()), pa.ListArray.from_arrays(offsets, found)],
                [id_col, "held_out", "n_tokens", "n_known", "base_score", "score", "rare"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(id_col, "held_out", text_col).mapInArrow(settled(run), f"{id_col} {kind}, held_out boolean, n_tokens long, n_known long, base_score double, score double, rare array<struct<word:binary,n:long>>")
    rows = written(rows).withColumn("row", F.monotonically_increasing_id())  # of a written table: the same at each reading
    words_ = rows.select("row", F.inline("rare")).join(counts.where(F.col("word").isNotNull()).select("word", F.col("n").alias("c")), "word", "left")
    c = F.coalesce(F.col("c"), F.lit(0))
    of_rare = words_.groupBy("row").agg(F.sum(F.when(c > 0, F.col("n")).otherwise(0)).alias("k"), F.sum(F.col("n") * F.log10((c + 0.5) / F.lit(float(below)))).alias("b"), F.sum(F.col("n") * F.log10((c + 0.5) / F.lit(float(a.other_mass)))).alias("s"))
    both = rows.drop("rare").join(of_rare, "row", "left")
    zero = lambda x: F.coalesce(F.col(x), F.lit(0))
    return both.select(id_col, "held_out", "n_tokens", (F.col("n_known") + zero("k")).alias("n_known"), F.lit(a.total).cast("long").alias("train_tokens"), (F.col("base_score") + zero("b")).alias("base_score"), (F.col("score") + zero("s")).alias("score"))


def split(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """docs with held_out: the remainder of crc32(id) by 5 is 1 (a null id is training text)."""
    return docs.withColumn("held_out", F.coalesce(crc_of_id(id_col) % 5 == 1, F.lit(False)))
