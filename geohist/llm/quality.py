"""Document quality by a byte-level convolutional network written in NumPy."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geohist.llm.common import as_strings, byte_view, steps

#: Shape of the network: bytes of a chunk and from one chunk to the next, bytes and step of a filter.
CHUNK, HOP, WIDTH, STRIDE, DEPTH, FILTERS = 512, 448, 6, 2, 8, 24
#: Bounds of the training sample: labelled documents, and chunks of each, spread over the whole text.
SAMPLE_ROWS, SAMPLE_CHUNKS = 4000, 8
#: Training: batches at least, passes at most, and the share of documents seen as one short crop, so that short texts score as long ones do.
LEAST_BATCHES, MOST_EPOCHS, CROPS = 500, 16, 0.3


@dataclass
class Network:
    """Embedding of bytes, filters and their bias, weights of pooled responses and their bias."""

    embed: np.ndarray
    filters: np.ndarray
    bias: np.ndarray
    weights: np.ndarray
    shift: float

    def windows(self, chunks: np.ndarray) -> np.ndarray:
        """Embedded bytes under the filters: (chunks, positions, WIDTH * DEPTH)."""
        e = self.embed[chunks].reshape(len(chunks), -1)
        view = np.lib.stride_tricks.sliding_window_view(e, WIDTH * DEPTH, axis=1)
        return view[:, :: STRIDE * DEPTH]

    def pooled(self, chunks: np.ndarray) -> np.ndarray:
        """Largest response of each filter over each chunk."""
        out = np.empty((len(chunks), FILTERS), np.float32)
        for lo in range(0, len(chunks), 64):
            x = np.ascontiguousarray(self.windows(chunks[lo : lo + 64]))
            out[lo : lo + 64] = (x.reshape(-1, WIDTH * DEPTH) @ self.filters).reshape(*x.shape[:2], FILTERS).max(axis=1)
        return np.maximum(out + self.bias, 0)

    def logits(self, pooled: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Of documents whose chunks start at rows `first`: mean and maximum over chunks, combined."""
        count = np.diff(np.append(first, len(pooled)))[:, None]
        both = np.concatenate([np.add.reduceat(pooled, first, axis=0) / count, np.maximum.reduceat(pooled, first, axis=0)], axis=1)
        return both @ self.weights + self.shift


def chunk_starts(off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin of each of the overlapping chunks that cover every text whole, the end of its text, and each text's first chunk."""
    count = np.maximum(1, -(-(np.diff(off) - CHUNK + HOP) // HOP))
    first = np.cumsum(count) - count
    return np.repeat(off[:-1], count) + (np.arange(count.sum()) - np.repeat(first, count)) * HOP, np.repeat(off[1:], count), first


def chunks_at(raw: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """The chunks of these begins; the last of a text is filled with zero bytes."""
    at = begin[:, None] + np.arange(CHUNK)
    inside = at < end[:, None]
    return np.where(inside, raw[np.minimum(at, len(raw) - 1)], np.uint8(0)) if len(raw) else np.zeros(at.shape, np.uint8)


def cut_chunks(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All chunks of the texts, and each text's first chunk."""
    begin, end, first = chunk_starts(off)
    return chunks_at(raw, begin, end), first


def fit(samples: list[tuple[np.ndarray, int]], epochs: int | None = None, batch: int = 32, rate: float = 0.01, seed: int = 7) -> Network:
    """Train on (chunks, label) samples by Adam on the log loss; the same samples and seed give the same network."""
    rng = np.random.default_rng(seed)
    epochs = epochs or min(MOST_EPOCHS, max(4, -(-LEAST_BATCHES * batch // max(1, len(samples)))))

    def seen(chunks: np.ndarray) -> np.ndarray:
        if rng.random() >= CROPS:
            return chunks
        crop = chunks[rng.integers(len(chunks))][None].copy()
        length = int(np.exp(rng.uniform(np.log(12), np.log(CHUNK))))
        begin = rng.integers(0, max(1, np.count_nonzero(crop) - length + 1))
        crop = np.roll(crop, -begin, axis=1)
        crop[:, length:] = 0
        return crop

    net = Network(
        rng.normal(0, 0.5, (256, DEPTH)).astype(np.float32),
        rng.normal(0, (WIDTH * DEPTH) ** -0.5, (WIDTH * DEPTH, FILTERS)).astype(np.float32),
        np.zeros(FILTERS, np.float32),
        rng.normal(0, 0.1, 2 * FILTERS).astype(np.float32),
        0.0,
    )
    net.embed[0] = 0
    shift = np.zeros(1, np.float32)
    params = [net.embed, net.filters, net.bias, net.weights, shift]
    moment, square, t = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
    for epoch in range(epochs):
        order = rng.permutation(len(samples))
        for lo in range(0, len(order), batch):
            picked = [(seen(samples[i][0]), samples[i][1]) for i in order[lo : lo + batch]]
            chunks = np.concatenate([c for c, _ in picked])
            count = np.array([len(c) for c, _ in picked])
            first, doc, y = np.cumsum(count) - count, np.repeat(np.arange(len(picked)), count), np.array([y for _, y in picked], np.float32)
            x = np.ascontiguousarray(net.windows(chunks))
            response = (x.reshape(-1, WIDTH * DEPTH) @ net.filters).reshape(*x.shape[:2], FILTERS)
            where = response.argmax(axis=1)
            top = np.take_along_axis(response, where[:, None], axis=1)[:, 0] + net.bias
            h = np.maximum(top, 0)
            mean, most = np.add.reduceat(h, first, axis=0) / count[:, None], np.maximum.reduceat(h, first, axis=0)
            both = np.concatenate([mean, most], axis=1)
            p = 1 / (1 + np.exp(-(both @ net.weights + shift[0])))
            d = (p - y) / len(picked)
            g_both = d[:, None] * net.weights
            g_h = g_both[doc, :FILTERS] / count[doc][:, None] + g_both[doc, FILTERS:] * (h == most[doc])
            g_top = g_h * (top > 0)
            hit = x[np.arange(len(chunks))[:, None], where]  # (chunks, filters, WIDTH * DEPTH)
            g_filters = np.einsum("cfk,cf->kf", hit, g_top, optimize=True)
            g_hit = (g_top[:, :, None] * net.filters.T[None]).reshape(-1, WIDTH, DEPTH)
            bytes_hit = chunks[np.arange(len(chunks))[:, None, None], where[:, :, None] * STRIDE + np.arange(WIDTH)].reshape(-1, WIDTH)
            g_embed = np.zeros_like(net.embed)
            np.add.at(g_embed, bytes_hit, g_hit)
            g_embed[0] = 0
            t += 1
            step = rate * (1 - epoch / epochs) + 0.05 * rate
            for q, g, m, v in zip(params, (g_embed, g_filters, g_top.sum(axis=0), both.T @ d + 1e-4 * net.weights, np.array([d.sum()], np.float32)), moment, square):
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                q -= (step * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
    net.shift = float(shift[0])
    return net


def held_out(doc_id: Column) -> Column:
    """Rows whose labels are never learned: crc32 of the id as text leaves 2 when divided by 4."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def training_sample(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, chunks: int = SAMPLE_CHUNKS, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> list[tuple[np.ndarray, int]]:
    """At most `rows` labelled documents outside the held-out part, those of smallest id hash, with at most `chunks` chunks each.

    The bound holds at every size of input: rows * chunks * CHUNK bytes reach the driver.
    """
    chosen = (
        labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label"))
        .where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1) & ~held_out(F.col("doc_id")))
        .groupBy("doc_id")
        .agg(F.min("label").alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(rows)
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, out = as_strings(b.column(1)), []
            for i in range(len(texts)):
                raw, off = byte_view(texts.slice(i, 1))
                begin, end, _ = chunk_starts(off)
                if len(begin) > chunks:
                    begin = begin[np.linspace(0, len(begin) - 1, chunks).astype(int)]
                out.append(chunks_at(raw, begin, end[: len(begin)]).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary()), b.column(2)], ["doc_id", "chunks", "label"])

    rows_ = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "doc_id")  # at most `rows` small rows
    got = rows_.select("doc_id", "text", "label").mapInArrow(run, "doc_id long, chunks binary, label int").collect()
    got.sort(key=lambda r: (r["doc_id"], bytes(r["chunks"])))
    return [(np.frombuffer(bytes(r["chunks"]), np.uint8).reshape(-1, CHUNK), r["label"]) for r in got[:rows]]


def train(docs: DataFrame, labels: DataFrame, **options) -> Network | None:
    """The fitted network; None if the sample lacks one of the two labels (all documents then score 1)."""
    sample = training_sample(docs, labels, **options)
    return fit(sample) if len({y for _, y in sample}) == 2 else None


def with_score(docs: DataFrame, net: Network | None, score_col: str = "score", text_col: str = "text") -> DataFrame:
    """docs and a score from 0 to 1, of the whole text only; null counts as empty, and empty texts get a score too.

    Repeated rows get the same score each; an empty table stays empty. A score column that docs has already is refused
    (`common.free_name` gives one that it has not).
    """
    if score_col in docs.columns:
        raise ValueError(f"column {score_col} exists")
    if net is None:
        return docs.withColumn(score_col, F.lit(1.0))
    schema = T.StructType([*docs.schema.fields, T.StructField(score_col, T.DoubleType())])
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, scores = as_strings(b.column(at)), []
            for lo, hi in steps(texts, 500_000):
                raw, off = byte_view(texts.slice(lo, hi - lo))
                begin, end, first = chunk_starts(off)
                pooled = np.concatenate([net.pooled(chunks_at(raw, begin[i : i + 1024], end[i : i + 1024])) for i in range(0, len(begin), 1024)])  # a very long text in parts
                scores.append(1 / (1 + np.exp(-np.clip(net.logits(pooled, first).astype(np.float64), -60, 60))))
            score = pa.array(np.concatenate(scores) if scores else np.zeros(0))
            yield pa.RecordBatch.from_arrays([*b.columns, score], names=[*b.schema.names, score_col])

    return docs.mapInArrow(run, schema)


def op6_quality(spark, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    scored = with_score(docs.select("doc_id", "text"), train(docs, labels))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
