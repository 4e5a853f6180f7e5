"""Quality: a byte-level convolutional network in numpy.

A text is cut into overlapping chunks that cover all its bytes; the last is padded. Bytes are
embedded, learned filters slide over each chunk, each filter's largest response in a chunk is
kept, and the mean and the maximum over the chunks are combined into one probability. Training is
back-propagation with Adam, on chunks of at most `sample` labelled rows and `per_doc` chunks each;
scoring reads every chunk.

Defined results: a null or empty text is one chunk of padding; without both labels in the
training rows every score is their share of 1 (0.5 with no rows).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import fold, free_of, table
from .toxicity import training_rows


@dataclass(frozen=True)
class CnnConfig:
    """chunk, overlap: bytes; dim: of a byte's embedding; width, stride, filters: of the
    convolution; sample, per_doc: training rows and chunks of each; steps, batch, rate, decay: of
    the optimiser."""

    chunk: int = 256
    overlap: int = 32
    dim: int = 5
    width: int = 6
    stride: int = 2
    filters: int = 16
    sample: int = 4000
    per_doc: int = 16
    steps: int = 500
    batch: int = 64
    rate: float = 0.01
    decay: float = 1e-4
    seed: int = 7


def chunk_counts(sizes: np.ndarray, cfg: CnnConfig) -> np.ndarray:
    return 1 + np.maximum(0, -(-(sizes - cfg.chunk) // (cfg.chunk - cfg.overlap)))


def chunks(data: np.ndarray, begins: np.ndarray, ends: np.ndarray, cfg: CnnConfig) -> np.ndarray:
    """(n, chunk) bytes from each begin, 0 after each end."""
    at = begins[:, None] + np.arange(cfg.chunk)
    inside = at < ends[:, None]
    out = np.zeros(at.shape, dtype=np.uint8)
    out[inside] = data[at[inside]]
    return out


class Cnn:
    def __init__(self, cfg: CnnConfig, prior: float = 0.5) -> None:
        rng = np.random.default_rng(cfg.seed)
        f = np.float32
        self.cfg = cfg
        self.emb = rng.normal(0, 0.5, (256, cfg.dim)).astype(f)
        self.w = rng.normal(0, 1 / np.sqrt(cfg.dim * cfg.width), (cfg.dim * cfg.width, cfg.filters)).astype(f)
        self.b = np.zeros(cfg.filters, dtype=f)
        self.out = np.zeros(2 * cfg.filters, dtype=f)
        p = min(max(prior, 1e-6), 1 - 1e-6)
        self.bias = np.array([np.log(p / (1 - p))], dtype=f)

    def windows(self, x: np.ndarray) -> np.ndarray:
        """(n, positions, width * dim), overlapping in memory."""
        c = self.cfg
        e = self.emb[x]
        n, size, d = e.shape
        item = e.itemsize
        return np.lib.stride_tricks.as_strided(e, (n, (size - c.width) // c.stride + 1, c.width * d), (size * d * item, c.stride * d * item, item), writeable=False)

    def pooled(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Largest response of each filter in each chunk, before the rectifier, and where."""
        win = self.windows(x)
        n, p, k = win.shape
        pre = (self.w.T @ np.ascontiguousarray(win).reshape(n * p, k).T).reshape(-1, n, p)
        return pre.max(axis=2).T + self.b, pre

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        c = self.cfg
        n = chunk_counts(np.diff(offsets), c)
        doc = np.repeat(np.arange(len(n)), n)
        first = np.cumsum(n) - n
        begins = offsets[doc] + (np.arange(len(doc)) - first[doc]) * (c.chunk - c.overlap)
        got = np.empty((len(doc), c.filters), dtype=np.float32)
        for i in range(0, len(doc), 256):
            s = slice(i, i + 256)
            got[s] = self.pooled(chunks(data, begins[s], offsets[doc[s] + 1], c))[0]
        np.maximum(got, 0, out=got)
        mean = np.add.reduceat(got, first, axis=0, dtype=np.float64) / n[:, None]
        most = np.maximum.reduceat(got, first, axis=0)
        z = mean @ self.out[: c.filters] + most @ self.out[c.filters :] + float(self.bias[0])
        return 1 / (1 + np.exp(-np.clip(z, -500, 500)))

    def train(self, docs: list[np.ndarray], y: np.ndarray) -> None:
        """docs: (chunks, bytes) of each training row."""
        c = self.cfg
        rng = np.random.default_rng(c.seed)
        params = [self.emb, self.w, self.b, self.out, self.bias]
        m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        by = [np.flatnonzero(y == k) for k in (0, 1)]
        weight = len(y) / (2 * np.array([max(1, len(x)) for x in by]))
        for t in range(1, c.steps + 1):
            # Half of a batch of each label; the loss weighs them back to their shares.
            pick = np.concatenate([rng.choice(x, c.batch // 2) for x in by])
            part = [docs[k] if len(docs[k]) <= 6 else docs[k][rng.choice(len(docs[k]), 6, replace=False)] for k in pick]
            n = np.array([len(p) for p in part])
            x, doc, first = np.concatenate(part), np.repeat(np.arange(len(n)), n), np.cumsum(n) - n
            top, pre = self.pooled(x)
            at = pre.argmax(axis=2).T
            act = np.maximum(top, 0)
            mean, most = np.add.reduceat(act, first, axis=0) / n[:, None], np.maximum.reduceat(act, first, axis=0)
            z = mean @ self.out[: c.filters] + most @ self.out[c.filters :] + self.bias[0]
            gz = (1 / (1 + np.exp(-z)) - y[pick]) / weight[y[pick].astype(int)] / len(pick)
            gz = gz.astype(np.float32)
            g_out = np.concatenate([mean.T @ gz, most.T @ gz]) + c.decay * self.out
            g_act = (gz / n)[doc][:, None] * self.out[: c.filters] + (act == most[doc]) * gz[doc][:, None] * self.out[c.filters :]
            g_top = g_act * (top > 0)
            win = self.windows(x)
            g_w, g_emb = np.zeros_like(self.w), np.zeros_like(self.emb)
            rows = np.arange(len(x))
            for k in range(c.filters):
                g = g_top[:, k]
                g_w[:, k] = g @ win[rows, at[:, k]]
                for j in range(c.width):
                    byte = x[rows, at[:, k] * c.stride + j]
                    part_w = self.w[j * c.dim : (j + 1) * c.dim, k]
                    g_emb += np.bincount(byte, weights=g, minlength=256)[:, None].astype(np.float32) * part_w
            grads = [g_emb, g_w + c.decay * self.w, g_top.sum(axis=0), g_out, np.array([gz.sum()], dtype=np.float32)]
            rate = c.rate * (1 if t < 0.6 * c.steps else 0.3)
            for p, g, a, b in zip(params, grads, m, v, strict=True):
                a += 0.1 * (g - a)
                b += 0.001 * (g * g - b)
                p -= rate * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.999**t)) + 1e-8)


def fit(rows: DataFrame, cfg: CnnConfig = CnnConfig()) -> Cnn:
    """Learns from a bounded frame of (text, y)."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for i, j, data, off in K.slices(b.column(0)):
                n = chunk_counts(np.diff(off), cfg)
                for k in range(j - i):
                    pick = np.arange(n[k]) if n[k] <= cfg.per_doc else np.linspace(0, n[k] - 1, cfg.per_doc).astype(int)
                    at = off[k] + pick * (cfg.chunk - cfg.overlap)
                    out.append(chunks(data, at, np.full(len(at), off[k + 1]), cfg).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(1).cast(pa.int32()), pa.array(out, pa.binary())], ["y", "x"])

    got = rows.mapInArrow(cut, "y int, x binary").toPandas()
    got = got.sort_values(["y", "x"], kind="stable")  # the order of arrival differs from run to run
    y = got["y"].to_numpy(dtype=np.float32)
    net = Cnn(cfg, float(y.mean()) if len(y) else 0.5)
    if len(y) and 0 < y.sum() < len(y):
        net.train([np.frombuffer(x, dtype=np.uint8).reshape(-1, cfg.chunk) for x in got["x"]], y)
    return net


def score(docs: DataFrame, net: Cnn, text: str = "text") -> DataFrame:
    """All columns of docs, with quality (0 to 1), which takes the place of a column of that name."""
    shared = docs.sparkSession.sparkContext.broadcast(net)
    docs = free_of(docs, ["quality"])
    fields = docs.schema.fieldNames()
    where = fields.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = np.zeros(b.num_rows)
            for i, j, data, off in K.slices(b.column(where)):
                out[i:j] = shared.value.score(data, off)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out)], [*fields, "quality"])

    return docs.mapInArrow(run, docs.select("*", F.lit(0.0).alias("quality")).schema)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    cfg = CnnConfig()
    net = fit(training_rows(docs, table(spark, sf_dir, "labels"), "quality", fold("doc_id", 4) != 2, cfg.sample), cfg)
    out = score(docs, net)
    return out.select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), F.col("quality").alias("score"), (F.col("quality") >= 0.7).cast("int").alias("predicted"))
