"""Quality classifier: a byte-level convolutional network in numpy.

Each byte has a learned vector; learned filters of ``WIDTH`` bytes slide over the whole text in steps of ``STEP``; their
rectified answers are max-pooled in overlapping chunks that cover the text; the largest and the mean of the chunk
maxima are combined into one probability. Only the bytes of the text go in.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import lean, small_batches
from ldpspark.llm.textkernel import runs, texts_of

WIDTH, STEP, DIM, FILTERS = 8, 4, 8, 32
#: Positions in half a chunk: a chunk is 1,024 bytes and starts every 512.
HALF = 128
#: Bytes of texts that are worked at once.
RUN = 1 << 18
#: Bound of the training sample, in rows of each label, whatever the size of the corpus.
PER_LABEL = 2000
EPOCHS, BATCH, RATE = 6, 32, 0.01
#: Weight of label 1 in training: losing a good text counts more than keeping a bad one.
CLEAN_WEIGHT = 0.85


@dataclass
class Network:
    """Weights; ``constant`` replaces the network where the labels do not allow training."""

    vectors: np.ndarray
    filters: np.ndarray
    offsets: np.ndarray
    mix: np.ndarray
    bias: float
    constant: float | None = None

    @staticmethod
    def fresh(seed: int = 11) -> Network:
        rng = np.random.default_rng(seed)
        return Network(
            rng.normal(0, 0.5, (256, DIM)).astype(np.float32),
            rng.normal(0, (2 / (WIDTH * DIM)) ** 0.5, (WIDTH * DIM, FILTERS)).astype(np.float32),
            np.zeros(FILTERS, np.float32),
            rng.normal(0, 0.1, 2 * FILTERS).astype(np.float32),
            0.0,
        )


def _padded(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Texts laid out at multiples of STEP with WIDTH zero bytes at least behind each; their first positions."""
    lengths = np.diff(offsets)
    room = -(-(lengths + WIDTH) // STEP) * STEP
    at = np.concatenate(([0], np.cumsum(room)))
    out = np.zeros(at[-1], np.uint8)
    to = np.repeat(at[:-1] - offsets[:-1], lengths) + np.arange(len(raw))
    out[to] = raw
    return out, at // STEP


def _forward(net: Network, raw: np.ndarray, offsets: np.ndarray) -> tuple:
    laid, first = _padded(raw, offsets)
    rows = net.vectors[laid].reshape(-1, STEP * DIM)
    half = STEP * DIM
    answer = rows @ net.filters[:half]
    answer[:-1] += rows[1:] @ net.filters[half:]
    answer += net.offsets
    # windows of one text: from its first position to the last that starts in it (one for an empty text)
    count = np.maximum(1, -(-np.diff(offsets) // STEP))
    pieces = -(-count // HALF)
    of = np.repeat(np.arange(len(count)), pieces)
    nth = np.arange(len(of)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    a = first[of] + nth * HALF
    b = np.minimum(a + HALF, first[of] + count[of])
    bounds = np.stack([a, b], 1).ravel()
    bounds[-1] = min(bounds[-1], len(answer) - 1)
    top = np.maximum.reduceat(answer, bounds, axis=0)[::2]
    top = np.maximum(top, 0)
    # a chunk is a piece and the next one of the same text; the last piece of a longer text has no chunk of its own
    joined = top.copy()
    more = np.flatnonzero(of[:-1] == of[1:])
    joined[more] = np.maximum(top[more], top[more + 1])
    keep = np.ones(len(of), bool)
    keep[1:] = ~((of[1:] == of[:-1]) & np.concatenate((of[1:-1] != of[2:], [True])))
    chunk_of = of[keep]
    joined = joined[keep]
    edges = np.searchsorted(chunk_of, np.arange(len(count)))
    largest = np.maximum.reduceat(joined, edges, axis=0)
    chunks = np.diff(np.concatenate((edges, [len(joined)])))
    mean = np.add.reduceat(joined, edges, axis=0) / chunks[:, None]
    feature = np.concatenate((largest, mean), axis=1)
    logit = feature @ net.mix + net.bias
    return logit, feature, largest, joined, chunk_of, chunks, np.flatnonzero(keep), a, b, answer, laid


def _probability(logit: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(logit, -30, 30)))


def _gradients(net: Network, raw: np.ndarray, offsets: np.ndarray, label: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
    logit, feature, largest, joined, chunk_of, chunks, kept, a, b, answer, laid = _forward(net, raw, offsets)
    delta = ((_probability(logit) - label) * weight / weight.sum()).astype(np.float32)
    d_mix = delta @ feature
    up = joined > 0
    share = delta[:, None] * net.mix[FILTERS:] / chunks[:, None]
    is_top = (joined == largest[chunk_of]) & up
    # overlapping chunks hold the same maximum: it counts once
    tops = np.maximum(1, np.add.reduceat(is_top.astype(np.float32), np.cumsum(chunks) - chunks, axis=0))
    d_joined = share[chunk_of] * up + (delta[:, None] * net.mix[:FILTERS] / tops)[chunk_of] * is_top
    c, f = np.nonzero(d_joined)
    value = d_joined[c, f]
    # the window behind each maximum
    spot = np.empty(len(c), np.int64)
    for k in np.unique(c):
        own = np.flatnonzero(c == k)
        p = kept[k]
        stop = b[p + 1] if p + 1 < len(a) and k < len(chunk_of) and b[p] - a[p] == HALF and a[p + 1] == b[p] else b[p]
        spot[own] = a[p] + answer[a[p] : stop][:, f[own]].argmax(axis=0)
    window = laid[(spot * STEP)[:, None] + np.arange(WIDTH)]
    x = net.vectors[window].reshape(len(spot), WIDTH * DIM)
    d_filters = np.zeros_like(net.filters)
    for k in range(FILTERS):
        own = f == k
        d_filters[:, k] = value[own] @ x[own]
    d_offsets = np.bincount(f, value, FILTERS).astype(np.float32)
    d_x = (value[:, None] * net.filters[:, f].T).reshape(-1, DIM)
    d_vectors = np.stack([np.bincount(window.ravel(), d_x[:, k], 256) for k in range(DIM)], 1).astype(np.float32)
    return [d_vectors, d_filters, d_offsets, d_mix, np.array([delta.sum()], np.float32)]


def fit(texts: list[str], labels: list[int], seed: int = 11) -> Network:
    """Trains on a list of texts by Adam; label 1 weighs ``CLEAN_WEIGHT`` of all. Without both labels the network is a constant."""
    y = np.array(labels, np.float32)
    net = Network.fresh(seed)
    if not len(y) or y.min() == y.max():
        net.constant = float(y.mean()) if len(y) else 1.0
        return net
    weight = np.where(y == 1, CLEAN_WEIGHT / y.sum(), (1 - CLEAN_WEIGHT) / (1 - y).sum()).astype(np.float32) * len(y)
    rng = np.random.default_rng(seed)
    state = [[0.0, 0.0] for _ in range(5)]
    step = 0
    for epoch in range(EPOCHS):
        order = rng.permutation(len(texts))
        for i in range(0, len(order), BATCH):
            own = order[i : i + BATCH]
            raw, offsets = texts_of(pa.array([texts[k] for k in own], pa.string()))
            g = _gradients(net, raw, offsets, y[own], weight[own])
            step += 1
            rate = RATE * (0.6 ** (epoch // 2))
            for k, d in enumerate(g):
                state[k][0] = 0.9 * state[k][0] + 0.1 * d
                state[k][1] = 0.99 * state[k][1] + 0.01 * d * d
                move = rate * (state[k][0] / (1 - 0.9**step)) / (np.sqrt(state[k][1] / (1 - 0.99**step)) + 1e-8)
                if k == 4:
                    net.bias -= float(move[0])
                else:
                    target = (net.vectors, net.filters, net.offsets, net.mix)[k]
                    target -= move.astype(np.float32)
    return net


def predict(net: Network, column: pa.Array) -> np.ndarray:
    """Probability of label 1 for each text of a column; every byte of every text is read."""
    raw, offsets = texts_of(column)
    if net.constant is not None:
        return np.full(len(offsets) - 1, net.constant)
    out = [np.zeros(0)]
    for a, b in runs(offsets, RUN):
        out.append(_probability(_forward(net, raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])[0].astype(np.float64)))
    return np.concatenate(out)


def held_out(doc_id: str = "doc_id"):
    """Rows never trained on: crc32 of the id as text is 1 modulo 3. A null id has no labels and is not held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 3 == 1, F.lit(False))


def trained(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL, seed: int = 11) -> Network:
    """Fits the network on at most ``per_label`` rows of each label that are not held out, chosen by a hash of the id.

    The sample is the one thing that comes to the driver. Rows without a label, with a null text, or whose id repeats with
    different labels (the larger counts) need no care.
    """
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality")).where(~held_out())
    chosen = None
    for label in (0, 1):
        part = known.where(F.col("quality") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_label)
        chosen = part if chosen is None else chosen.unionByName(part)
    ids = [(r["doc_id"], r["quality"]) for r in chosen.collect()]
    spark = docs.sparkSession
    small = spark.createDataFrame(ids or [(None, None)], "doc_id long, quality int")
    # at most 2 * per_label rows by construction
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(small), "doc_id")
    found = sorted({(r["doc_id"], r["text"], r["quality"]) for r in rows.collect()})[: 2 * per_label]
    return fit([x[1] for x in found], [x[2] for x in found], seed)


def scored(docs: DataFrame, net: Network, column: str = "score") -> DataFrame:
    """``docs`` with the probability that a text is of label 1, to six decimals. Null text is scored as the empty text."""
    from pyspark.sql import types as T

    small_batches(docs.sparkSession)
    model = docs.sparkSession.sparkContext.broadcast(net)
    at = docs.columns.index("text")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = np.round(predict(model.value, batch.column(at)), 6)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p, pa.float64())], names=[*batch.schema.names, column])

    return docs.mapInArrow(lean(work), T.StructType([*docs.schema.fields, T.StructField(column, T.DoubleType())]))


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id``, ``held_out``, ``score``, ``predicted`` for every row of ``docs``; rows that repeat are scored each; further columns are ignored."""
    net = trained(docs, labels)
    rows = scored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), net)
    return rows.select("doc_id", held_out().alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).cast("int").alias("predicted"))


def good_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without the rows that the classifier rejects; columns unchanged."""
    net = trained(docs, labels)
    slot = next(f"_score{i}" for i in range(len(docs.columns) + 1) if f"_score{i}" not in docs.columns)
    return scored(docs, net, slot).where(F.col(slot) >= 0.5).drop(slot)
