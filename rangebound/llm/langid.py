"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts are aggregated in Spark, from a sample of at most `per_lang` documents a
language; the log-probability matrix (buckets x languages, 256 KB for each language that occurs) is broadcast, and a
batch of documents is scored as a sparse matrix whose non-zeros are the n-gram occurrences, a block of languages
after the other.

Defined results: a text that is null, empty or has no letter is `und` with score 0. With no
training row at all every text is `und`. Ties go to the language that sorts first. Repeated rows
are scored alike. Extra columns stay; those named lang_pred or lang_score give way to the results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import free_of, fold, table

UNDETERMINED = "und"
_LUTS: dict[str, np.ndarray] = {}


@dataclass(frozen=True)
class LangConfig:
    """orders: n-gram lengths; buckets: hash buckets (a power of two); alpha: additive smoothing;
    per_lang: most training documents of a language; block_langs: languages that are counted or scored at once."""

    orders: tuple[int, ...] = (1, 2, 3)
    buckets: int = 1 << 15
    alpha: float = 0.1
    per_lang: int = 5000
    block_langs: int = 64


def _luts() -> tuple[np.ndarray, np.ndarray]:
    """Lower-case code point (0x20 for what is no letter), and whether it is a letter, for the first plane."""
    if not _LUTS:
        low, alpha = np.full(65536, 0x20, dtype=np.uint32), np.zeros(65536, dtype=bool)
        for c in range(65536):
            s = chr(c)
            if s.isalpha():
                alpha[c] = True
                low[c] = ord(x) if len(x := s.lower()) == 1 else c
        _LUTS["low"], _LUTS["alpha"] = low, alpha
    return _LUTS["low"], _LUTS["alpha"]


def _letters(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Normalised code points (runs of non-letters are one space, each document starts with one),
    document offsets among them, and the number of letters of each document."""
    low, alpha = _luts()
    try:
        cps = np.frombuffer(data.tobytes().decode("utf-8").encode("utf-32-le"), dtype=np.uint32)
        at = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])[offsets]
    except UnicodeDecodeError:
        parts = [np.frombuffer(data[a:b].tobytes().decode("utf-8", "replace").encode("utf-32-le"), dtype=np.uint32) for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
        cps, at = np.concatenate(parts), np.cumsum([0, *map(len, parts)])
    n_docs = len(offsets) - 1
    cps = np.insert(cps, at[:-1], 0x20)
    at = at + np.arange(n_docs + 1)
    bmp = np.minimum(cps, 0xFFFF)
    norm, is_letter = low[bmp], alpha[bmp]
    if (far := cps > 0xFFFF).any():
        for c in np.unique(cps[far]).tolist():
            if chr(c).isalpha():
                norm[cps == c], is_letter[cps == c] = c, True
    letters = np.concatenate([[0], np.cumsum(is_letter)])
    space = ~is_letter
    keep = np.ones(len(cps), dtype=bool)
    keep[1:] = ~(space[1:] & space[:-1])
    keep[at[:-1]] = True
    kept = np.concatenate([[0], np.cumsum(keep)])
    return norm[keep], kept[at], letters[at[1:]] - letters[at[:-1]]


def ngram_buckets(data: np.ndarray, offsets: np.ndarray, cfg: LangConfig) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each order: bucket of the n-gram that starts at each position (the last bucket + 1
    where the document ends before it does), with document offsets."""
    cps, at, _ = _letters(data, offsets)
    yield from _ngrams(cps, at, cfg)


def _ngrams(cps: np.ndarray, at: np.ndarray, cfg: LangConfig) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    h = np.zeros(len(cps), dtype=np.uint32)
    shift = np.uint32(32 - cfg.buckets.bit_length() + 1)
    for n in range(1, max(cfg.orders) + 1):
        tail = cps[n - 1 :]
        h = h[: len(tail)] * np.uint32(0x01000193) + tail + np.uint32(1)
        if n in cfg.orders:
            idx = np.full(len(cps), cfg.buckets, dtype=np.int32)
            idx[: len(h)] = ((h ^ (h >> np.uint32(15))) * np.uint32(0x9E3779B1)) >> shift
            for k in range(1, n):  # the last n-1 positions of a document
                p = at[1:] - k
                idx[p[p >= at[:-1]]] = cfg.buckets
            yield idx, at


@dataclass
class LangModel:
    langs: list[str]
    weights: np.ndarray  # (languages, buckets + 1); the last column is 0
    prior: np.ndarray
    cfg: LangConfig

    def score(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the best language (-1: none) and its posterior."""
        cps, at, letters = _letters(data, offsets)
        n_docs = len(offsets) - 1
        best, prob = np.full(n_docs, -1), np.zeros(n_docs)
        if not self.langs:
            return best, prob
        grams = [idx for idx, _ in _ngrams(cps, at, self.cfg)]
        top, most, mass = np.zeros(n_docs, dtype=int), np.full(n_docs, -np.inf), np.zeros(n_docs)
        for first in range(0, len(self.langs), self.cfg.block_langs):
            part = slice(first, first + self.cfg.block_langs)
            total = np.tile(self.prior[part, None], (1, n_docs))
            for idx in grams:
                for i, row in enumerate(self.weights[part]):
                    total[i] += np.add.reduceat(row[idx], at[:-1])
            here = total.max(axis=0)
            top = np.where(here > most, first + total.argmax(axis=0), top)
            now = np.maximum(most, here)
            mass = mass * np.exp(most - now) + np.exp(total - now).sum(axis=0)  # relative to the best so far
            most = now
        known = letters > 0
        best[known], prob[known] = top[known], 1 / mass[known]
        return best, prob


def fit(train: DataFrame, cfg: LangConfig = LangConfig(), text: str = "text", lang: str = "lang", key: str = "doc_id") -> LangModel:
    """Learns from rows with a text and a language; at most about cfg.per_lang of each language."""
    rows = train.select(F.col(key).alias("k"), F.col(text).alias("text"), F.col(lang).alias("lang")).where("lang is not null and text is not null")
    sizes = rows.groupBy("lang").agg(F.count(F.lit(1)).alias("size"))
    u = F.pmod(F.xxhash64("k"), F.lit(1_000_000)) / 1_000_000
    # One row a language.
    picked = rows.join(F.broadcast(sizes), "lang").where(u < F.lit(float(cfg.per_lang)) / F.col("size")).select("lang", "text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        acc: dict[str, np.ndarray] = {}
        docs: dict[str, int] = {}

        def flush() -> Iterator[pa.RecordBatch]:
            for name, got in acc.items():
                got[-1] = docs[name]
                nz = np.flatnonzero(got)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(nz), pa.string()), pa.array(nz.astype(np.int32)), pa.array(got[nz])], ["lang", "bucket", "n"])
            acc.clear()
            docs.clear()

        for b in batches:
            names = b.column(0).to_pylist()
            for i, j, data, off in K.slices(b.column(1)):
                of = np.array(names[i:j], dtype=object)
                grams = list(ngram_buckets(data, off, cfg))
                for name in set(names[i:j]):
                    if name not in acc and len(acc) >= cfg.block_langs:
                        yield from flush()
                    pick = of == name
                    docs[name] = docs.get(name, 0) + int(pick.sum())
                    got = acc.setdefault(name, np.zeros(cfg.buckets + 1, dtype=np.int64))
                    for idx, at in grams:
                        got += np.bincount(idx[np.repeat(pick, np.diff(at))], minlength=cfg.buckets + 1)
        yield from flush()

    counts = picked.mapInArrow(count, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(counts["lang"].unique())
    dense = np.zeros((len(langs), cfg.buckets + 1))
    dense[counts["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy(dtype=int), counts["bucket"].to_numpy()] = counts["n"].to_numpy()
    weights = dense.copy()
    weights[:, :-1] = np.log((dense[:, :-1] + cfg.alpha) / (dense[:, :-1].sum(axis=1, keepdims=True) + cfg.alpha * cfg.buckets)) if langs else 0
    weights[:, -1] = 0
    # Priors are shares of all training rows, not of the sample.
    known = {r["lang"]: r["size"] for r in sizes.collect()} if langs else {}
    share = np.array([float(known[x]) for x in langs])
    return LangModel(langs, weights, np.log(share / share.sum()) if langs else np.zeros(0), cfg)


def predict(docs: DataFrame, model: LangModel, text: str = "text") -> DataFrame:
    """All columns of docs, with lang_pred and lang_score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = free_of(docs, ["lang_pred", "lang_score"])
    fields = docs.schema.fieldNames()
    where = fields.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            best, prob = np.full(b.num_rows, -1), np.zeros(b.num_rows)
            for i, j, data, off in K.slices(b.column(where)):
                best[i:j], prob[i:j] = m.score(data, off)
            names = pa.array([*m.langs, UNDETERMINED]).take(pa.array(np.where(best < 0, len(m.langs), best)))
            yield pa.RecordBatch.from_arrays([*b.columns, names, pa.array(prob)], [*fields, "lang_pred", "lang_score"])

    schema = docs.select("*", F.lit("").alias("lang_pred"), F.lit(0.0).alias("lang_score")).schema
    return docs.mapInArrow(run, schema)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = fit(docs.where(fold("doc_id", 5) != 0))
    out = predict(docs.select("doc_id", "text"), model)
    return out.select("doc_id", F.coalesce(fold("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))
