"""Quality classifier: random-indexing word vectors, pooled per document, and a two-layer network.

Every word gives two tokens: its lower-cased form and its shape (runs of upper case, lower case,
digits, and each other byte). Tokens fall into a fixed number of buckets by hash. A bucket has a
sparse random index vector; its context vector is the integer sum of the index vectors found beside
it. A document is the weighted mean of the vectors of its tokens, with its length, the means'
lengths and the share of words repeated at once. A network with one hidden layer scores it. Limited-memory
BFGS fits it to all training rows: each evaluation of loss and gradient is one pass over the stored
inputs. A temperature fitted on rows kept back from the network calibrates the probability.

Nothing comes from a sample: word vectors and rarity are counted over all texts that are not held
out, and every labelled row that is not held out is learnt from. No held-out text or label is read in
training, and never lang, source or doc_id enters a score.

Edge cases: null and empty texts have the zero vector and a score like any other text; without
labels of both classes every score is the labels' smoothed rate; rows with a null id are scored and
are not held out; repeated rows each get their own result row; an empty table gives an empty
result; extra columns are ignored. Every label of a doc_id counts for every document that has it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, DoubleType, StructField, StructType

from .scratch import bound_arrow, counted, discard, release, table
from .textscan import SPACED, find_words, hash_words, small_batches, text_bytes

BUCKETS, WIDTH, WINDOW = 1 << 14, 48, 2
#: Buckets of one row of sums; neighbours counted at once.
_BLOCK, _PAIRS = 512, 1 << 22
#: Inputs of a document: two means and their lengths, two shares of repeats, its length.
INPUTS = 2 * (WIDTH + 1) + 3
#: Training rows whose inputs the driver holds and passes over itself; more stay with the workers.
LOCAL_ROWS = 10_000

_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[65:91] = 65
_SHAPE[97:123] = 97
_SHAPE[48:58] = 48
_SHAPE[128:] = 97


@dataclass(frozen=True)
class QualityConfig:
    """accept: least score that predicts 1; hidden, rounds (of BFGS), decay, seed: of the network."""

    accept: float = 0.3
    hidden: int = 24
    rounds: int = 60
    decay: float = 1e-4
    seed: int = 7


def _index_places() -> tuple[np.ndarray, np.ndarray]:
    """Per bucket six places and their signs; equal in every process."""
    rng = np.random.Generator(np.random.PCG64(20260202))
    return rng.integers(0, WIDTH, (2 * BUCKETS, 6)), rng.integers(0, 2, (2 * BUCKETS, 6)) * 2 - 1


def _index_vectors() -> np.ndarray:
    """Ternary: the sum of a bucket's places of +1 or -1."""
    out = np.zeros((2 * BUCKETS, WIDTH), np.int32)
    places, signs = _index_places()
    np.add.at(out, (np.arange(2 * BUCKETS)[:, None], places), signs)
    return out


def _tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word buckets, shape buckets (offset by BUCKETS) and the texts' bounds."""
    data, offsets = text_bytes(column)
    starts, ends, bounds = find_words(data, offsets, SPACED)
    words = (hash_words(data, starts, ends) % np.uint64(BUCKETS)).astype(np.int64)
    kind = _SHAPE[data]
    keep = np.ones(len(data), bool)
    keep[1:] = kind[1:] != kind[:-1]
    keep[starts] = True
    before = np.concatenate([[0], np.cumsum(keep)])
    shapes = hash_words(kind[keep], before[starts], before[ends], fold=False) % np.uint64(BUCKETS)
    return words, shapes.astype(np.int64) + BUCKETS, bounds


def _add_pairs(total: np.ndarray, places: np.ndarray, signs: np.ndarray, keys: list[np.ndarray]) -> None:
    """Adds to each token's row the index vectors of its neighbours; keys: first * BUCKETS + second, uint32."""
    pairs, n = np.unique(np.concatenate(keys), return_counts=True)
    first, second = (pairs // BUCKETS).astype(np.int64), (pairs % BUCKETS).astype(np.int64)
    for own, other in ((first, second), (second, first)):
        for k in range(places.shape[1]):
            # sums of whole numbers below 2^53: exact
            told = np.bincount(own * WIDTH + places[other, k], n * signs[other, k], total.size)
            total += told.astype(np.int64).reshape(total.shape)


def _contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of neighbours' index vectors and token counts of the partition, a row per block of buckets."""
    places, signs = _index_places()
    total, seen = np.zeros((2 * BUCKETS, WIDTH), np.int64), np.zeros(2 * BUCKETS, np.int64)
    halves = [slice(0, BUCKETS), slice(BUCKETS, 2 * BUCKETS)]
    keys: list[list[np.ndarray]] = [[], []]
    for batch in small_batches(batches, "text", 1 << 20):
        words, shapes, bounds = _tokens(batch.column(0))
        owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
        for half, tokens, held in zip(halves, (words, shapes - BUCKETS), keys, strict=True):
            seen[half] += np.bincount(tokens, minlength=BUCKETS)
            tokens = tokens.astype(np.uint32)
            for step in range(1, WINDOW + 1):
                same = owner[step:] == owner[:-step]
                held.append(tokens[:-step][same] * np.uint32(BUCKETS) + tokens[step:][same])
            if sum(map(len, held)) >= _PAIRS:
                _add_pairs(total[half], places[half], signs[half], held)
                held.clear()
    for half, held in zip(halves, keys, strict=True):
        if held:
            _add_pairs(total[half], places[half], signs[half], held)
    yield from _blocks({b: np.column_stack([seen[b : b + _BLOCK], total[b : b + _BLOCK]]) for b in range(0, 2 * BUCKETS, _BLOCK) if seen[b : b + _BLOCK].any()})


def _blocks(sums: dict[int, np.ndarray]) -> Iterator[pa.RecordBatch]:
    for b, v in sums.items():
        yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([v.tobytes()], pa.binary())], ["block", "sums"])


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    out: dict[int, np.ndarray] = {}
    for batch in batches:
        for b, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            v = np.frombuffer(v, np.int64).reshape(_BLOCK, 1 + WIDTH)
            out[b] = out[b] + v if b in out else v
    yield from _blocks(out)


def word_vectors(texts: DataFrame) -> np.ndarray:
    """float32 vectors of all buckets, weighted by rarity, from a whole table of texts. As many tasks as
    cores count them; sums by block of buckets meet in a shuffle, and one row a block on the driver."""
    cores = texts.sparkSession.sparkContext.defaultParallelism
    parts = texts.select("text").coalesce(cores).mapInArrow(_contexts, "block int, sums binary")
    sums = np.zeros((2 * BUCKETS, 1 + WIDTH), np.int64)
    for r in parts.repartition(min(cores, 2 * BUCKETS // _BLOCK), "block").mapInArrow(_summed, "block int, sums binary").collect():  # 64 rows at most
        sums[r["block"] : r["block"] + _BLOCK] += np.frombuffer(r["sums"], np.int64).reshape(_BLOCK, 1 + WIDTH)
    seen, total = sums[:, 0], sums[:, 1:]
    own = _index_vectors() / np.sqrt(6.0)
    context = total / np.maximum(np.linalg.norm(total, axis=1, keepdims=True), 1.0)
    vectors = np.concatenate([own[:, : WIDTH // 2], context[:, WIDTH // 2 :]], axis=1)
    for half in (slice(0, BUCKETS), slice(BUCKETS, 2 * BUCKETS)):
        p = seen[half] / max(1, seen[half].sum())
        vectors[half] *= (1e-2 / (1e-2 + p))[:, None]
    return vectors.astype(np.float32)


def _pooled(column: pa.Array, vectors: np.ndarray) -> np.ndarray:
    words, shapes, bounds = _tokens(column)
    counts = np.diff(bounds)
    some = counts > 0
    parts = []
    for tokens in (words, shapes):
        out = np.zeros((len(counts), WIDTH), np.float32)
        if some.any():
            out[some] = np.add.reduceat(vectors[tokens], bounds[:-1][some], axis=0) / counts[some][:, None]
        parts += [out, np.linalg.norm(out, axis=1, keepdims=True)]
    owner = np.repeat(np.arange(len(counts)), counts)
    for step in (1, 2):  # coherence of neighbours: the share of words that stand again one or two places on
        again = np.flatnonzero((words[step:] == words[:-step]) & (owner[step:] == owner[:-step]))
        parts.append((np.bincount(owner[again], minlength=len(counts)) / np.maximum(counts, 1))[:, None])
    return np.concatenate([*parts, np.log1p(counts)[:, None]], axis=1).astype(np.float64)


def _minimise(evaluate: Callable[[np.ndarray], tuple[float, np.ndarray]], w: np.ndarray, rounds: int, memory: int = 12) -> np.ndarray:
    """Limited-memory BFGS with a backtracking search; evaluate gives loss and gradient."""
    loss, grad = evaluate(w)
    moves: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(rounds):
        if np.abs(grad).max() < 1e-5:
            break
        down, parts = -grad, []
        for s, y in reversed(moves):
            parts.append(s @ down / (s @ y))
            down = down - parts[-1] * y
        down = down * (moves[-1][0] @ moves[-1][1] / (moves[-1][1] @ moves[-1][1]) if moves else 1 / np.linalg.norm(grad))
        for (s, y), part in zip(moves, reversed(parts), strict=True):
            down = down + (part - y @ down / (s @ y)) * s
        step, slope = 1.0, grad @ down
        for _ in range(12):
            there = evaluate(w + step * down)
            if there[0] <= loss + 1e-4 * step * slope:
                break
            step /= 2
        else:
            break
        move = step * down, there[1] - grad
        if move[0] @ move[1] > 1e-12:
            moves = [*moves[1 - memory :], move]
        gain, w, (loss, grad) = loss - there[0], w + move[0], there
        if gain < 1e-6 * abs(loss):
            break
    return w


def _shaped(w: np.ndarray, hidden: int) -> list[np.ndarray]:
    a, b = INPUTS * hidden, (INPUTS + 1) * hidden
    return [w[:a].reshape(INPUTS, hidden), w[a:b], w[b : b + hidden], w[b + hidden :]]


#: Rows of inputs: x (float64), n0 and n1 (labels of each class), kept (from the network, for the temperature).
Rows = tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]


def _moments(rows: Rows) -> np.ndarray:
    x, n0, n1, kept = rows
    n = n0 + n1
    return np.concatenate([[n0.sum(), n1.sum(), n0[~kept].sum(), n1[~kept].sum()], n @ x, n @ (x * x)])


def _logits(x: np.ndarray, layers: list[np.ndarray]) -> np.ndarray:
    return np.tanh(x @ layers[0] + layers[1]) @ layers[2] + layers[3]


def _gradient(rows: Rows, mean: np.ndarray, scale: np.ndarray, w: np.ndarray, hidden: int) -> np.ndarray:
    """Summed loss and gradient of the rows that are not kept back."""
    x, n0, n1, kept = rows
    x, n0, n1 = (x[~kept] - mean) / scale, n0[~kept], n1[~kept]
    layers = _shaped(w, hidden)
    h = np.tanh(x @ layers[0] + layers[1])
    logits = h @ layers[2] + layers[3]
    error = (n0 + n1) / (1 + np.exp(-np.clip(logits, -30, 30))) - n1
    back = error[:, None] * layers[2] * (1 - h * h)
    loss = n0 @ np.logaddexp(0, logits) + n1 @ np.logaddexp(0, -logits)
    return np.concatenate([[loss], (x.T @ back).ravel(), back.sum(axis=0), h.T @ error, [error.sum()]])


_TEMPERATURES = np.geomspace(0.5, 8, 60)


def _tempered(rows: Rows, mean: np.ndarray, scale: np.ndarray, w: np.ndarray, hidden: int) -> np.ndarray:
    """Loss of the rows kept back at each temperature."""
    x, n0, n1, kept = rows
    logits = _logits((x[kept] - mean) / scale, _shaped(w, hidden))
    return np.array([n0[kept] @ np.logaddexp(0, logits / t) + n1[kept] @ np.logaddexp(0, -logits / t) for t in _TEMPERATURES])


class TrainingRows:
    """A table (x, n0, n1, kept) over which sums are taken: where it lies, or for few rows on the driver."""

    def __init__(self, table: DataFrame, n: int):
        self.table, self.n, self.local = table, n, None
        if n <= LOCAL_ROWS:
            found = table.toArrow().combine_chunks()  # LOCAL_ROWS at most
            x, *rest = _rows_of(found)
            order = np.lexsort((rest[1], rest[0], *x.T))
            self.local = x[order], *(v[order] for v in rest)

    def sum(self, measure: Callable[..., np.ndarray], *args) -> np.ndarray:
        if self.local is not None:
            return measure(self.local, *args)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = None
            for batch in batches:
                if batch.num_rows:
                    part = measure(_rows_of(batch), *args)
                    total = part if total is None else total + part
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

        parts = [np.frombuffer(r["sums"]) for r in self.table.mapInArrow(run, "sums binary").collect()]  # one a task
        return np.sum(sorted(parts, key=bytes), axis=0)


def _rows_of(batch: pa.RecordBatch | pa.Table) -> Rows:
    data = batch.column(0)
    raw, _ = text_bytes(data)
    n0, n1, kept = (batch.column(c).to_numpy(zero_copy_only=False) if isinstance(batch, pa.RecordBatch) else batch.column(c).to_numpy() for c in (1, 2, 3))
    return raw.view(np.float32).reshape(-1, INPUTS).astype(np.float64), n0.astype(np.float64), n1.astype(np.float64), kept.astype(bool)


class QualityModel:
    """Standardised inputs, one hidden tanh layer, a logit and its temperature."""

    def __init__(self, vectors: np.ndarray, rows: TrainingRows, config: QualityConfig):
        self.vectors, self.layers, self.rate = vectors, None, 0.5
        if rows.n:
            told = rows.sum(_moments)
            n0, n1, used0, used1 = told[:4]
            self.rate = float((n1 + 1) / (n0 + n1 + 2))
            if n0 and n1 and used0 + used1:
                self.mean = told[4 : 4 + INPUTS] / (n0 + n1)
                self.scale = np.sqrt(np.maximum(told[4 + INPUTS :] / (n0 + n1) - self.mean**2, 0)) + 1e-6
                self._fit(rows, used0 + used1, n0 + n1 > used0 + used1, config)

    def _fit(self, rows: TrainingRows, used: float, kept: bool, c: QualityConfig) -> None:
        rng = np.random.Generator(np.random.PCG64(c.seed))
        w = [rng.normal(0, 1 / np.sqrt(INPUTS), INPUTS * c.hidden), np.zeros(c.hidden), rng.normal(0, 1 / np.sqrt(c.hidden), c.hidden), np.zeros(1)]
        decay = np.concatenate([np.full(len(v), c.decay * (n in (0, 2))) for n, v in enumerate(w)])

        def evaluate(at: np.ndarray) -> tuple[float, np.ndarray]:
            told = rows.sum(_gradient, self.mean, self.scale, at, c.hidden) / used
            return float(told[0] + decay @ (at * at) / 2), told[1:] + decay * at

        w = _minimise(evaluate, np.concatenate(w), c.rounds)
        self.temperature = float(_TEMPERATURES[int(np.argmin(rows.sum(_tempered, self.mean, self.scale, w, c.hidden)))]) if kept else 1.0
        self.layers = _shaped(w, c.hidden)

    def score(self, column: pa.Array) -> np.ndarray:
        if self.layers is None:
            return np.full(len(column), self.rate)
        logits = _logits((_pooled(column, self.vectors) - self.mean) / self.scale, self.layers)
        return 1 / (1 + np.exp(-np.clip(logits / self.temperature, -500, 500)))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 5 == 0, F.lit(False))


def _features(vectors: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 1 << 20):
            x = _pooled(batch.column(1), vectors).astype(np.float32)
            ends = pa.py_buffer(np.arange(len(x) + 1, dtype=np.int32) * (4 * INPUTS))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.Array.from_buffers(pa.binary(), len(x), [None, ends, pa.py_buffer(x)])], ["doc_id", "x"])

    return run


def train(docs: DataFrame, labels: DataFrame, config: QualityConfig = QualityConfig()) -> QualityModel:
    """docs: doc_id, text; labels: doc_id, quality. Held-out rows are never read."""
    bound_arrow(docs.sparkSession)
    seen = docs.select("doc_id", "text").where(~held_out(F.col("doc_id")))
    vectors = word_vectors(seen)
    labels = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    one = F.col("quality").cast("int") == 1
    # counts of labels and not the labels are joined: no more rows than documents
    labels = labels.groupBy("doc_id").agg(F.count_if(~one).alias("n0"), F.count_if(one).alias("n1"))
    # narrow inputs are shuffled, not texts
    inputs = seen.where(F.col("doc_id").isNotNull()).mapInArrow(_features(vectors), StructType([seen.schema["doc_id"], StructField("x", BinaryType())]))
    rows = inputs.join(labels, "doc_id").select("x", "n0", "n1", (F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 0).alias("kept"))
    rows, n = counted(rows, "quality-rows")
    model = QualityModel(vectors, TrainingRows(rows, n), config)
    discard(rows)
    release(docs.sparkSession)
    return model


def with_score(docs: DataFrame, model: QualityModel, name: str = "score") -> DataFrame:
    """docs, which has a column text, with the score as one more column."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 1 << 20):
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(model.score(batch.column(at)), pa.float64())], [*batch.schema.names, name])

    return docs.mapInArrow(run, StructType([*docs.schema.fields, StructField(name, DoubleType())]))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    config = QualityConfig()
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = with_score(docs, train(docs, table(spark, sf_dir, "labels"), config))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= config.accept).cast("int").alias("predicted"))
