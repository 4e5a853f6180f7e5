"""Benchmark decontamination by greedy string tiling.

Documents and benchmark items are compared on lower-case words without punctuation. A seed is a
run of `least` words; documents that share a seed with an item are joined to it, and the two are
tiled: the longest common unmarked runs of words are marked, again and again, down to `least`
words, found by a running Karp-Rabin hash. The share of an item's words under tiles is its
coverage; tiles may lie in any order, so a passage with its sentences reordered is still covered.

The benchmark is searched in blocks of at most `block_words` words, so what is broadcast is of
bounded size; each block is one pass over all documents. Whole documents are searched.

Defined results: null and empty texts match nothing; an item of fewer than `least` words is
sought as one whole seed; repeated rows are reported each; an item whose id is null is sought like any other and
reported with a null item_id; an empty table gives no rows.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import table


@dataclass(frozen=True)
class TileConfig:
    """least: shortest tile in words; coverage: least share of an item's words under tiles to be
    a leak; block_words: words of the benchmark searched in one pass."""

    least: int = 5
    coverage: float = 0.5
    block_words: int = 4_000_000


_MASK = (1 << 61) - 1
_BASE = 1_000_003


def _runs(words: list[int], free: list[bool], size: int) -> Iterator[tuple[int, int]]:
    """(start, running hash) of each stretch of `size` unmarked words."""
    lead = pow(_BASE, size - 1, _MASK)
    h = have = 0
    for i, w in enumerate(words):
        if not free[i]:
            h = have = 0
            continue
        if have == size:
            h = (h - words[i - size] * lead) % _MASK
            have -= 1
        h = (h * _BASE + w) % _MASK
        have += 1
        if have == size:
            yield i - size + 1, h


def tile(a: list[int], b: list[int], least: int) -> list[tuple[int, int, int]]:
    """Non-overlapping common stretches (start in a, start in b, length), longest first; ties go
    to the first in a, then in b."""
    fa, fb = [True] * len(a), [True] * len(b)
    out: list[tuple[int, int, int]] = []
    size = min(len(a), len(b))
    # The longest match bounds where the search starts: double until none is found.
    probe = least
    while probe < size:
        seen = {h for _, h in _runs(a, fa, probe)}
        if not any(h in seen for _, h in _runs(b, fb, probe)):
            size = probe
            break
        probe *= 2
    while size >= least:
        at: dict[int, list[int]] = defaultdict(list)
        for i, h in _runs(a, fa, size):
            at[h].append(i)
        hits = [(i, j) for j, h in _runs(b, fb, size) for i in at.get(h, ())] if at else []
        for i, j in sorted(hits):
            if a[i : i + size] == b[j : j + size] and all(fa[i : i + size]) and all(fb[j : j + size]):
                fa[i : i + size] = [False] * size
                fb[j : j + size] = [False] * size
                out.append((i, j, size))
        size -= 1
    return out


def _word_ids(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    s, e, c = K.words(data, offsets, K.ALNUM_WORDS)
    return K.hash_words(data, s, e), c


class Index:
    """A block of the benchmark: seeds and words of its items."""

    def __init__(self, ids: list[int], texts: list[str], cfg: TileConfig) -> None:
        self.ids, self.items, self.cfg = ids, [], cfg
        seeds: dict[int, set[int]] = defaultdict(set)
        for t in texts:
            data = np.frombuffer((t or "").lower().encode(), dtype=np.uint8)
            h, c = _word_ids(data, np.array([0, len(data)]))
            self.items.append((h >> np.uint64(4)).astype(np.int64).tolist())
            size = min(cfg.least, len(h))
            if size:
                for x in K.shingles(h, c, cfg.least)[0].tolist() if size == cfg.least else K.shingles(h, c, size)[0].tolist():
                    seeds[x].add(len(self.items) - 1)
        self.short = sorted({len(x) for x in self.items if 0 < len(x) < cfg.least})
        self.seeds = dict(seeds)
        self.maybe = np.zeros(1 << 20, dtype=bool)
        for x in seeds:
            self.maybe[x >> 44] = True

    def search(self, data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int, int, int, int]]:
        """(document, item, words under tiles, tiles, words of the item) for coverage above 0."""
        h, counts = _word_ids(data, offsets)
        first = np.cumsum(counts) - counts
        doc_of = np.repeat(np.arange(len(counts)), counts)
        found: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
        for size in [self.cfg.least, *self.short]:
            if len(h) < size:
                continue
            sh, n = K.shingles(h, np.where(counts >= size, counts, 0), size) if (counts >= size).all() else self._long(h, counts, size)
            if not len(sh):
                continue
            begin = np.concatenate([first[d] + np.arange(k) for d, k in enumerate(n.tolist()) if k])
            for p in np.flatnonzero(self.maybe[(sh >> np.uint64(44)).astype(np.int64)]).tolist():
                for item in self.seeds.get(int(sh[p]), ()):
                    w = int(begin[p])
                    found[int(doc_of[w]), item].append((w, w + size))
        ids = (h >> np.uint64(4)).astype(np.int64)
        for (doc, item), spans in sorted(found.items()):
            # Outside stretches of seeds no tile can lie; what lies between counts as one break.
            words: list[int] = []
            end = -1
            for lo, hi in sorted(spans):
                if lo > end >= 0:
                    words.append(-1)
                words.extend(ids[max(lo, end) : hi].tolist())
                end = max(end, hi)
            own = self.items[item]
            tiles = tile(own, words, min(self.cfg.least, len(own)))
            if tiles:
                yield doc, item, sum(t[2] for t in tiles), len(tiles), len(own)

    @staticmethod
    def _long(h: np.ndarray, counts: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Shingles of exactly `size` words; shorter documents have none."""
        keep = np.repeat(counts >= size, counts)
        sh, n = K.shingles(h[keep], np.where(counts >= size, counts, 0), size)
        return sh, n


def blocks(benchmark: DataFrame, cfg: TileConfig, key: str, text: str) -> Iterator[Index]:
    """The benchmark in blocks of bounded size; items are dealt by a hash of id and text, so those without an id or with the same one are spread too."""
    slim = benchmark.select(F.col(key).cast("long").alias("k"), F.col(text).alias("t")).where("t is not null")
    total = slim.agg(F.sum(F.length("t"))).first()[0] or 0
    n = 1 + total // (4 * cfg.block_words)
    for i in range(n):
        rows = slim.where(F.pmod(F.xxhash64("k", "t"), F.lit(n)) == i).orderBy("k", "t").collect()
        if rows:
            yield Index([r["k"] for r in rows], [r["t"] for r in rows], cfg)


def leaks(docs: DataFrame, benchmark: DataFrame, cfg: TileConfig = TileConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, item_id, n_words, tiled_words, n_tiles, coverage) of each document and item whose
    coverage is at least cfg.coverage."""
    spark = docs.sparkSession
    slim = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    schema = "doc_id long, item_id long, n_words int, tiled_words int, n_tiles int, coverage double"
    out = spark.createDataFrame([], schema)
    for index in blocks(benchmark, cfg, "item_id", "text"):
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ix = shared.value
            for b in batches:
                ids = b.column(0).to_pylist()
                rows = []
                for i, _, data, off in K.slices(K.lowered(b.column(1))):
                    for doc, item, under, n, size in ix.search(data, off):
                        if under >= cfg.coverage * size:
                            rows.append((ids[i + doc], ix.ids[item], size, under, n, under / size))
                if rows:
                    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "item_id", "n_words", "tiled_words", "n_tiles", "coverage"])

        out = out.union(slim.mapInArrow(run, schema))
    return out


def clean(docs: DataFrame, benchmark: DataFrame, cfg: TileConfig = TileConfig(), text: str = "text") -> DataFrame:
    """docs without the documents that leak an item: filtered where they are read, a block of the
    benchmark after the other; nothing is joined or moved."""
    spark = docs.sparkSession
    where = docs.schema.fieldNames().index(text)
    for index in blocks(benchmark, cfg, "item_id", "text"):
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for b in batches:
                keep = np.ones(b.num_rows, dtype=bool)
                for i, _, data, off in K.slices(K.lowered(b.column(where))):
                    for doc, _, under, _, size in shared.value.search(data, off):
                        if under >= cfg.coverage * size:
                            keep[i + doc] = False
                yield b.filter(pa.array(keep))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
