"""Similarity join of documents on word shingles, exact, with adaptive multi-match prefixes.

All documents order their shingles alike: by how often the corpus has them (a counting sketch over all
texts, so rare ones come first), then by hash. Two sets with at least `percent` Jaccard similarity
share at least l shingles within the first n - ceil(percent n) + l of each, for any l. Each
document picks its own l: a longer prefix costs more postings, but asks for more shared ones before
anything is verified; a pair uses the smaller l of the two.

From postings to links without listing the pairs of a group:
- equal shingle sets are one class, known by a 128-bit signature; a task posts each of its classes once;
- postings are dealt by token and read in order, so that no long list is held: a short list gives its pairs; pairs with
  l shared postings are candidates; a long list gives edges from its members to the first of like length, but only
  from those that are in so many long lists that these alone may make l;
- a counted pair is an edge only if bitmaps of both sets leave room for a link: what one's bitmap has and the other's has
  not is surely not shared, so this drops pairs that cannot link, and no other;
- candidate edges give clusters, and a cluster is dealt in blocks of bounded size, with a few leaders in each.
  There an inverted index finds all partners of one document at a time, and documents of the largest
  component found so far need not be asked: their partners outside it ask for them;
- what is left outside the largest component of a cluster of several blocks is compared with all blocks.
Sketch and hashes decide order and grouping alone; a link is an exact comparison of sets of 64-bit hashes.

Defined results, row by row: null, empty and blank texts have no shingles and are linked with nothing; fewer
words than a shingle are one shingle; repeated rows are one class; rows that share an id but not
a text are documents of their own; rows without an id are alone. Other columns aren't read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import aside, discard, materialise, table
from .components import components


@dataclass(frozen=True)
class JoinConfig:
    """words: of a shingle; percent: least Jaccard similarity; deepest: largest l; verify: cost of
    verifying a candidate, in postings; short: longest posting list whose pairs are counted one by one;
    block: documents of a block, weight: its shingles; leaders: documents put into each block of a cluster;
    cells: least of the sketch (a power of two), load: shingles a cell at most, while there are no more than `most_cells`;
    bits: of the bitmap of ids."""

    words: int = 5
    percent: int = 80
    deepest: int = 8
    verify: float = 16.0
    short: int = 64
    block: int = 512
    weight: int = 1 << 20
    leaders: int = 16
    cells: int = 1 << 20
    load: int = 32
    most_cells: int = 1 << 26
    bits: int = 1 << 23


SKETCH_PARTS = 64
#: Places in the order that a posting tells apart.
PLACES = 4095


def sets(column: pa.Array, words: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, sorted distinct shingle hashes of these rows, how many each has)."""
    for i, j, data, off in K.slices(column):
        s, e, c = K.words(data, off, K.SPACE_WORDS)
        v, n = K.distinct(*K.shingles(K.hash_words(data, s, e), c, words))
        yield i, j, v, n


def signatures(v: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Two 64-bit sums over each document's shingles, a row for each document."""
    end = np.cumsum(n)
    out = np.zeros((len(n), 2), dtype=np.uint64)
    for k, salt in enumerate((0, 0xA5A5A5A55A5A5A5A)):
        run = np.concatenate([np.zeros(1, np.uint64), np.cumsum(K.mix(v ^ np.uint64(salt)), dtype=np.uint64)])
        out[:, k] = run[end] - run[end - n]
    return out


def _binary(sig: np.ndarray) -> pa.Array:
    return pa.array([x.tobytes() for x in np.ascontiguousarray(sig)], pa.binary())


def bitmaps(v: np.ndarray, n: np.ndarray) -> list[bytes]:
    """For each document a bitmap of its shingles' low bits: the least power of two that has two bits for each, 64 at least."""
    size = np.array([max(64, 1 << int(2 * x - 1).bit_length()) if x else 64 for x in n.tolist()], dtype=np.int64)
    end = np.cumsum(size)
    at = np.repeat(end - size, n) + (v & np.repeat(size - 1, n).astype(np.uint64)).astype(np.int64)
    flags = np.zeros(int(size.sum()), dtype=bool)
    flags[at] = True
    packed = np.packbits(flags, bitorder="little").tobytes()
    return [packed[(e - s) // 8 : e // 8] for e, s in zip(end.tolist(), size.tolist(), strict=True)]


def may_link(n: int, bits: bytes, m: int, other: bytes, percent: int) -> bool:
    """False only for sets (of n and m shingles, with these bitmaps) that surely don't link. The finer bitmap is folded."""
    x, y = int.from_bytes(bits, "little"), int.from_bytes(other, "little")
    a, b = 8 * len(bits), 8 * len(other)
    while a > b:
        a //= 2
        x = (x >> a) | (x & ((1 << a) - 1))
    while b > a:
        b //= 2
        y = (y >> b) | (y & ((1 << b) - 1))
    both = (x & y).bit_count()
    most = min(n - x.bit_count() + both, m - y.bit_count() + both)
    return 100 * most >= percent * (n + m - most)


PROFILE = "id long, n long, sig binary, cid long, bits binary, part int, cells binary"


def _added(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """(cells in order, counts) of all parts together."""
    cells, counts = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(cells, kind="stable")
    cells, counts = cells[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], cells[1:] != cells[:-1]])) if len(cells) else np.zeros(0, np.int64)
    return cells[first], np.add.reduceat(counts, first) if len(first) else counts


def _planes(x: np.ndarray) -> bytes:
    """Whole numbers byte by byte, low bytes first: high ones are mostly zero."""
    return np.ascontiguousarray(x.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()


def _from_planes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(4, -1).T).view("<u4").ravel().astype(np.int64)


def profile(docs: DataFrame, cfg: JoinConfig) -> DataFrame:
    """docs: (id, text). A row for each document: id, n, the signature of its set, the first half of that
    as a number (cid) and its bitmap; and rows with the parts of each task's sketch (part, cells): the cells that it has met, of the
    finest sketch there may be, as steps and counts."""
    shift = np.uint64(64 - cfg.most_cells.bit_length() + 1)
    names = ["id", "n", "sig", "cid", "bits", "part", "cells"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: list[tuple[np.ndarray, np.ndarray]] = []
        wait: list[np.ndarray] = []
        held = 0

        def fold() -> None:
            cells, counts = np.unique(np.concatenate(wait), return_counts=True)
            met.append((cells, counts.astype(np.uint32)))
            while len(met) > 1 and len(met[-1][0]) * 2 > len(met[-2][0]):
                met[-2:] = [_added(met[-2:])]

        for b in batches:
            n_all = np.zeros(b.num_rows, dtype=np.int64)
            sig = np.zeros((b.num_rows, 2), dtype=np.uint64)
            bits: list[bytes] = []
            for i, j, v, n in sets(b.column(1), cfg.words):
                n_all[i:j] = n
                sig[i:j] = signatures(v, n)
                bits += bitmaps(v, n)
                wait.append((v >> shift).astype(np.uint32))
                held += len(v)
                if held > 1 << 21:
                    fold()
                    wait, held = [], 0
            cid = np.ascontiguousarray(sig[:, 0]).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n_all), _binary(sig), pa.array(cid), pa.array(bits, pa.binary()), pa.nulls(b.num_rows, pa.int32()), pa.nulls(b.num_rows, pa.binary())], names)
        if held:
            fold()
        if met:
            cells, counts = _added(met)
            pack = zstandard.ZstdCompressor(level=1)
            size = cfg.most_cells // SKETCH_PARTS
            ends = np.searchsorted(cells, np.arange(SKETCH_PARTS + 1) * size)
            rows = [pack.compress(_planes(np.diff(cells[i:j], prepend=np.uint32(0))) + _planes(counts[i:j])) for i, j in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            null = pa.nulls(SKETCH_PARTS, pa.int64())
            yield pa.RecordBatch.from_arrays([null, null, pa.nulls(SKETCH_PARTS, pa.binary()), null, pa.nulls(SKETCH_PARTS, pa.binary()), pa.array(range(SKETCH_PARTS), pa.int32()), pa.array(rows, pa.binary())], names)

    return docs.mapInArrow(run, PROFILE)


def sketch(profiled: DataFrame, cfg: JoinConfig) -> tuple[np.ndarray, float]:
    """(frequency class of each cell, mean count of a cell): the tasks' sketches, streamed by part. The more shingles
    there are, the more cells, or all would look alike frequent; a cell takes a byte on the driver."""
    total = profiled.agg(F.sum("n")).first()[0] or 0
    cells = cfg.cells
    while cells < cfg.most_cells and cells * cfg.load < total:
        cells *= 2
    shift, size = (cfg.most_cells // cells).bit_length() - 1, cells // SKETCH_PARTS

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        acc: dict[int, np.ndarray] = {}
        unpack = zstandard.ZstdDecompressor()
        for b in batches:
            for part, packed in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                raw = unpack.decompress(packed)
                at = (np.cumsum(_from_planes(raw[: len(raw) // 2])) >> shift) - part * size
                np.add.at(acc.setdefault(part, np.zeros(size, dtype=np.int64)), at, _from_planes(raw[len(raw) // 2 :]))
        for part, x in acc.items():
            kind = np.floor(2 * np.log2(np.maximum(x, 1))).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([kind.tobytes()], pa.binary())], ["part", "cells"])

    rows = profiled.where("part is not null").select("part", "cells").repartition(SKETCH_PARTS, "part").mapInArrow(add, "part int, cells binary").toLocalIterator()
    out = np.zeros(cells, dtype=np.uint8)
    for r in rows:
        out[r["part"] * size : (r["part"] + 1) * size] = np.frombuffer(r["cells"], dtype=np.uint8)
    return out, total / cells


def _depth(own: np.ndarray, cost: np.ndarray, cfg: JoinConfig) -> tuple[int, int]:
    """(l, length of the prefix for l = 1) of a document with these ordered tokens: the l at which what the prefix's
    postings cost, and the verifications that so many shared ones let through, is least."""
    least = -(-cfg.percent * len(own) // 100)
    first = len(own) - least + 1
    top = min(cfg.deepest, max(1, least))
    spend = np.cumsum(cost[(own[: first + top - 1] >> np.uint64(57)).astype(np.int64)])
    return 1 + int(np.argmin([spend[first + k - 1] * (1 + cfg.verify / (k + 1)) for k in range(top)])), first


def postings(docs: DataFrame, counts: tuple[np.ndarray, float], cfg: JoinConfig) -> DataFrame:
    """docs: (id, text). (token, cid, n) for each token of each class's prefix in the common order. A token is a shingle's
    frequency class and hash, in 48 bits (that two share one costs a comparison, no more), then l in 4 and its place in the
    order, or PLACES if it is later, in 12. A task posts a class once, however many of its rows are copies."""
    classes, load = counts[0], max(1.0, counts[1])
    costs = 1 + np.maximum(0.0, 2.0 ** (np.arange(128) / 2) - 2 * load)
    shared = docs.sparkSession.sparkContext.broadcast((classes, costs))
    shift = np.uint64(64 - len(classes).bit_length() + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cls, cost = shared.value
        done: set[int] = set()
        for b in batches:
            for _, _, v, n in sets(b.column(0), cfg.words):
                cid = np.ascontiguousarray(signatures(v, n)[:, 0]).view(np.int64).tolist()
                key = (cls[(v >> shift).astype(np.int64)].astype(np.uint64) << np.uint64(57)) | (v >> np.uint64(7))
                tokens, who, sizes = [], [], []
                at = 0
                for size, c in zip(n.tolist(), cid, strict=True):
                    own = key[at : at + size]
                    at += size
                    if not size or c in done:
                        continue
                    done.add(c)
                    own.sort()
                    deep, first = _depth(own, cost, cfg)
                    own = own[: first + deep - 1]
                    rest = np.minimum(np.arange(len(own)), PLACES).astype(np.uint64) | np.uint64(deep << 12)
                    tokens.append(((own & np.uint64(0xFFFFFFFFFFFF0000)) | rest).view(np.int64))
                    who.append(np.full(len(own), c, dtype=np.int64))
                    sizes.append(np.full(len(own), size, dtype=np.int32))
                if tokens:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (tokens, who, sizes)], ["token", "cid", "n"])

    return docs.select("text").mapInArrow(run, "token long, cid long, n int")


def _lists(token: np.ndarray, cid: np.ndarray, low: np.ndarray, n: np.ndarray, cfg: JoinConfig, going: bool) -> np.ndarray:
    """Rows (kind, a, b, c) of whole posting lists in order of token and cid, low having l and the place; going: the first is
    known to be long. For short lists their pairs that may link, as (0, u, v, l that the pair needs); for long ones their
    members (1, cid, token, 16 n + l).

    Two sets that link share `least` tokens, by their sizes; so they share l of the first n - least + l of each, which is
    often less than what they have posted, and with a shared token at places i and j no more than what precedes the
    nearer and follows the farther."""
    keep = np.ones(len(token), dtype=bool)
    keep[1:] = (token[1:] != token[:-1]) | (cid[1:] != cid[:-1]) | (low[1:] != low[:-1]) | (n[1:] != n[:-1])
    token, cid, low, n = token[keep], cid[keep], low[keep], n[keep]
    deep, place = low >> 12, low & PLACES
    new = np.ones(len(token), dtype=bool)
    new[1:] = token[1:] != token[:-1]
    start = np.flatnonzero(new)
    own = np.diff(np.append(start, len(token)))
    size, first = np.repeat(own, own), np.repeat(start, own)
    long = size > cfg.short
    if going and len(start):
        long[: own[0]] = True
    out = [np.stack([np.ones(int(long.sum()), np.int64), cid[long], token[long], n[long] << 4 | deep[long]])]
    end = first + size
    a = np.flatnonzero(~long)
    for d in range(1, cfg.short):
        a = a[a + d < end[a]]
        if not len(a):
            break
        z = a + d
        need = np.minimum(deep[a], deep[z])
        least = -(-cfg.percent * (n[a] + n[z]) // (100 + cfg.percent))
        ok = (100 * np.minimum(n[a], n[z]) >= cfg.percent * np.maximum(n[a], n[z])) & (cid[a] != cid[z])
        ok &= (place[a] < n[a] - least + need) & (place[z] < n[z] - least + need)
        late = np.maximum(place[a], place[z]) == PLACES
        ok &= late | (np.minimum(place[a], place[z]) + np.minimum(n[a] - place[a], n[z] - place[z]) >= least)
        u, v = cid[a[ok]], cid[z[ok]]
        out.append(np.stack([np.zeros(len(u), np.int64), np.minimum(u, v), np.maximum(u, v), need[ok]]))
    return np.concatenate(out, axis=1)


def scan_lists(post: DataFrame, cfg: JoinConfig) -> DataFrame:
    """(kind, a, b, c), see _lists; postings are dealt by token and read in order, a buffer at a time."""
    n_parts = int(post.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    token = F.shiftrightunsigned("token", 16)
    ordered = post.repartition(n_parts, token).sortWithinPartitions(token, "cid", "token", "n")
    most = 1 << 17

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((4, 0), dtype=np.int64)
        going = False  # the first token held belongs to a list whose beginning has been given out

        def give(part: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x) for x in _lists(*part, cfg, going)], ["kind", "a", "b", "c"])

        for b in batches:
            token, cid, n = (c.to_numpy() for c in b.columns)
            held = np.concatenate([held, np.stack([(token.view(np.uint64) >> np.uint64(16)).view(np.int64), cid, token & 0xFFFF, n])], axis=1)
            if held.shape[1] < most:
                continue
            cut = int(np.searchsorted(held[0], held[0, -1]))  # the last list may go on
            if cut:
                yield give(held[:, :cut])
                held, going = held[:, cut:], False
            if held.shape[1] > most // 2:
                # One list fills the buffer; it is long, unless its rows repeat.
                held = held[:, np.concatenate([[True], (held[:, 1:] != held[:, :-1]).any(axis=0)])]
                if held.shape[1] > cfg.short:
                    going = True
                    yield give(held[:, :-1])
                    held = held[:, -1:]
        if held.shape[1]:
            yield give(held)

    return ordered.mapInArrow(run, "kind long, a long, b long, c long")


def _stars(members: DataFrame, percent: int) -> DataFrame:
    """Edges (u, v) from each member of a token's list to the first of those whose lengths may go with its own: in order
    of length, a gap that no link crosses starts anew. members: (token, n, cid)."""
    n_parts = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[int, int, int] | None = None  # token, n, first cid of the run
        for b in batches:
            token, n, cid = (c.to_numpy() for c in b.columns)
            if not len(token):
                continue
            before = np.concatenate([[last[0] if last else 0], token[:-1]]), np.concatenate([[last[1] if last else 0], n[:-1]])
            new = (token != before[0]) | (100 * before[1] < percent * n)
            new[0] |= last is None
            at = np.maximum.accumulate(np.where(new, np.arange(len(token)), -1))
            head = np.where(at >= 0, cid[at], last[2] if last else 0)
            last = int(token[-1]), int(n[-1]), int(head[-1])
            other = cid != head
            yield pa.RecordBatch.from_arrays([pa.array(cid[other]), pa.array(head[other])], ["u", "v"])

    return members.select("token", "n", "cid").repartition(n_parts, "token").sortWithinPartitions("token", "n", "cid").mapInArrow(run, "u long, v long").distinct()


def likely(pairs: DataFrame, rows: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) of cids whose bitmaps leave room for a link. rows: (n, sig, cid, bits), repeated or not; should
    two sets share a cid, a pair of either stays."""
    ids = pairs.select(F.col("u").alias("cid")).union(pairs.select(F.col("v").alias("cid"))).distinct()
    own = materialise(rows.join(ids, "cid", "left_semi").groupBy("cid", "sig", "n").agg(F.first("bits").alias("bits")).drop("sig"))
    side = lambda c: own.select(F.col("cid").alias(c), F.col("n").alias(f"n_{c}"), F.col("bits").alias(f"bits_{c}"))

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = [may_link(*x, percent) for x in zip(*(b.column(i).to_pylist() for i in range(2, 6)), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(i).filter(pa.array(ok, pa.bool_())) for i in range(2)], ["u", "v"])

    both = pairs.join(side("u"), "u").join(side("v"), "v").select("u", "v", "n_u", "bits_u", "n_v", "bits_v")
    return both.mapInArrow(test, "u long, v long")


def candidates(post: DataFrame, cfg: JoinConfig, rows: DataFrame | None = None) -> DataFrame:
    """Edges (u, v) between classes that have to meet, over cid: all pairs that share enough of their prefixes and, given
    rows (see likely), whose bitmaps allow it, and more.

    Pairs that share a short list are counted, with the long lists that both are in. A pair that shares long lists
    alone shares `deepest` of them, or one has a smaller l: so each class brings its first long lists but deepest - 1,
    and all to a list with a class of smaller l; such lists stay linear in their members."""
    seen = materialise(scan_lists(post, cfg))
    pairs = seen.where("kind = 0").groupBy(F.col("a").alias("u"), F.col("b").alias("v")).agg(F.count(F.lit(1)).alias("k"), F.min("c").alias("l"))
    long = seen.where("kind = 1").groupBy(F.col("a").alias("cid")).agg(F.sort_array(F.collect_set("b")).alias("lists"), F.max(F.shiftright("c", 4)).alias("n"), F.max(F.col("c") % 16).alias("l"))
    side = lambda c: long.select(F.col("cid").alias(c), F.col("lists").alias(f"_{c}"))
    few = pairs.where("k < l").join(side("u"), "u").join(side("v"), "v").where(F.col("k") + F.size(F.array_intersect("_u", "_v")) >= F.col("l"))
    posted = long.select("cid", "n", (F.col("l") < cfg.deepest).alias("odd"), F.size("lists").alias("m"), F.posexplode("lists").alias("pos", "token"))
    odd = posted.where("odd").select("token").distinct()
    first = posted.where(~F.col("odd") & (F.col("pos") <= F.col("m") - cfg.deepest))
    members = first.select("token", "n", "cid").union(posted.join(odd, "token", "left_semi").select("token", "n", "cid"))
    counted = pairs.where("k >= l").select("u", "v").union(few.select("u", "v"))
    if rows is not None:
        counted = likely(materialise(counted), rows, cfg.percent)
    return counted.union(_stars(members, cfg.percent))


class Tile:
    """The distinct documents of a tile, and an inverted index of the shingles that two of them share."""

    def __init__(self, column: pa.Array, given: list[bytes], cfg: JoinConfig) -> None:
        parts = list(sets(column, cfg.words))
        n = np.concatenate([p[3] for p in parts])
        v = np.concatenate([p[2] for p in parts])
        sig = [x.tobytes() for x in np.concatenate([signatures(p[2], p[3]) for p in parts])]
        #: Rows of the distinct documents; rows whose text isn't that of their class don't count.
        first = {x: i for i, x in reversed(list(enumerate(sig))) if x == given[i]}
        self.rows = sorted(first.values())
        self.ids = [sig[i] for i in self.rows]
        place = np.full(len(n), -1)
        place[self.rows] = np.arange(len(self.rows))
        doc = np.repeat(place, n)
        v, doc = v[doc >= 0], doc[doc >= 0]
        self.n, self.percent = n[self.rows], cfg.percent
        order = np.argsort(v, kind="stable")
        v, doc = v[order], doc[order]
        new = np.ones(len(v), dtype=bool)
        new[1:] = v[1:] != v[:-1]
        col = np.cumsum(new) - 1
        size = np.bincount(col) if len(col) else np.zeros(0, np.int64)
        shared = size[col] > 1
        self.doc = doc[shared]
        size = size[size > 1]
        self.first, self.size = np.cumsum(size) - size, size
        col = np.repeat(np.arange(len(size)), size)
        back = np.argsort(self.doc, kind="stable")
        self.cols = col[back]
        self.cut = np.searchsorted(self.doc[back], np.arange(len(self.rows) + 1))

    def partners(self, d: int) -> np.ndarray:
        """Places of the documents that link with document d."""
        cols = self.cols[self.cut[d] : self.cut[d + 1]]
        size = self.size[cols]
        at = np.repeat(self.first[cols] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        both = np.bincount(self.doc[at], minlength=len(self.rows))
        ok = (100 * both >= self.percent * (self.n + self.n[d] - both)) & (both > 0)
        ok[d] = False
        return np.flatnonzero(ok)


def explore(tile: Tile, label: np.ndarray, asks: np.ndarray, core: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links (places) that join what the label hasn't joined. Documents outside the component of the core ask for
    their partners, one by one, until none that may ask is left; the core is a set of one label, or the largest
    component of the moment. So all pairs with a document outside it are compared, and those within it are joined."""
    out = []
    open_ = asks.copy()
    fixed = None if core is None else int(np.argmax(core)) if core.any() else -1
    while len(label):
        inner = int(np.argmax(np.bincount(label))) if fixed is None else int(label[fixed]) if fixed >= 0 else -1
        wait = np.flatnonzero(open_ & (label != inner))
        if not len(wait):
            break
        d = int(wait[0])
        open_[d] = False
        met = tile.partners(d)
        for x in np.unique(label[met]).tolist():
            if x != label[d]:
                out.append((d, int(met[label[met] == x][0])))
        label[np.isin(label, label[met])] = label[d]
    return out


def id_filter(spark: SparkSession, ids: DataFrame, bits: int = 1 << 23) -> tuple[DataFrame, Callable[[str], Column]]:
    """A bitmap of hashed ids, of fixed size, as a frame of one row, and the test of an id column against it.
    What it rejects isn't among the ids; the more ids, the more others it lets through."""
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(bits))
    got = ids.select(place(F.col("id")).alias("h")).groupBy(F.shiftright("h", 6).cast("int").alias("word")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("h") % 64).cast("int"))).alias("mask")).toArrow()
    words = np.zeros(bits // 64, dtype=np.int64)
    words[got.column("word").to_numpy()] = got.column("mask").to_numpy()
    bitmap = spark.createDataFrame(pa.table({"_bitmap": pa.array([words], pa.list_(pa.int64()))}))

    def hit(c: str) -> Column:
        h = place(F.col(c).cast("long"))
        return F.coalesce(F.call_function("getbit", F.get("_bitmap", F.shiftright(h, 6).cast("int")), (h % 64).cast("int")) == 1, F.lit(False))

    return bitmap, hit


def without(docs: DataFrame, ids: DataFrame, key: str = "doc_id", bits: int = 1 << 23) -> DataFrame:
    """docs whose key isn't among ids.id. Only rows that the bitmap doesn't clear are joined; the
    others aren't moved."""
    bitmap, hit = id_filter(docs.sparkSession, ids, bits)
    docs, back = aside(docs, ["_bitmap", "_hit", "_id"])
    marked = docs.crossJoin(F.broadcast(bitmap)).withColumn("_hit", hit(key)).drop("_bitmap")  # one row
    clear = marked.where(~F.col("_hit")).drop("_hit")
    asked = marked.where("_hit").drop("_hit")
    return back(clear.unionByName(asked.join(ids.select(F.col("id").alias("_id")), F.col(key) == F.col("_id"), "left_anti")))


def placed(heads: DataFrame, clusters: DataFrame, cfg: JoinConfig) -> DataFrame:
    """heads: (sig, cid, head, n); clusters: (id, component) over cid. Members (sig, head, component, blocks, block)."""
    members = heads.join(clusters, F.col("cid") == F.col("id")).select("sig", "head", "n", "component")
    sizes = members.groupBy("component").agg(F.ceil(F.greatest(F.count(F.lit(1)) / cfg.block, F.sum("n") / cfg.weight)).cast("int").alias("blocks"))
    return members.join(sizes, "component").select("sig", "head", "component", "blocks", F.pmod(F.xxhash64("sig"), F.col("blocks")).cast("int").alias("block"))


def _with_texts(docs: DataFrame, dealt: DataFrame, bitmap: DataFrame, hit: Callable[[str], Column]) -> DataFrame:
    """dealt, with the text of each head. The dealt side is the hashed one at every size: it has no texts."""
    asked = docs.crossJoin(F.broadcast(bitmap)).where(hit("id")).drop("_bitmap")  # one row; spares the join other texts
    return asked.join(dealt.hint("shuffle_hash"), F.col("id") == F.col("head")).drop("id", "head")


LINK = "u binary, v binary"


def _links(t: pa.Table, found: list[tuple[bytes, bytes]]) -> pa.Table:
    return pa.table({"u": pa.array([x[0] for x in found], pa.binary()), "v": pa.array([x[1] for x in found], pa.binary())})


def block_links(docs: DataFrame, places: DataFrame, cfg: JoinConfig, bitmap: DataFrame, hit: Callable[[str], Column]) -> DataFrame:
    """Links (u, v) of signatures that span the similar documents of each block."""
    own = places.select("component", "block", "sig", "head")
    least = places.where("blocks > 1").groupBy("component", "blocks", F.pmod(F.xxhash64("sig", F.lit(1)), F.lit(cfg.leaders))).agg(F.min(F.struct("sig", "head")).alias("x"))
    lead = least.select("component", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "x.sig", "x.head")

    def compare(t: pa.Table) -> pa.Table:
        found: list[tuple[bytes, bytes]] = []
        if t.num_rows > 1:
            tile = Tile(t.column("text").combine_chunks(), t.column("sig").to_pylist(), cfg)
            m = len(tile.ids)
            found = [(tile.ids[a], tile.ids[b]) for a, b in explore(tile, np.arange(m), np.ones(m, dtype=bool))]
        return _links(t, found)

    return _with_texts(docs, own.unionByName(lead), bitmap, hit).groupBy("component", "block").applyInArrow(compare, LINK)


def rest_links(docs: DataFrame, places: DataFrame, known: DataFrame, cfg: JoinConfig) -> DataFrame | None:
    """known: (id, component), the components that blocks have found. Links between them, over their names; None if
    every cluster of several blocks is one component. Documents outside the largest component of their cluster meet
    all its blocks."""
    large = places.where("blocks > 1").join(known.select(F.col("id").alias("sig"), F.col("component").alias("c")), "sig", "left").withColumn("own", F.coalesce("c", "sig")).drop("c")
    sizes = large.groupBy("component", "own").agg(F.count(F.lit(1)).alias("size")).groupBy("component").agg(F.max_by("own", F.struct("size", "own")).alias("giant"), F.sum("size").alias("all"), F.max("size").alias("most"))
    left = materialise(sizes.where("all > most").select("component", "giant", F.ceil((F.col("all") - F.col("most")) / cfg.block).cast("int").alias("parts")))
    if left.isEmpty():
        discard(left)
        return None
    # Only the texts of these clusters are dealt again.
    bitmap, hit = id_filter(docs.sparkSession, large.join(left, "component", "left_semi").select(F.col("head").alias("id")), cfg.bits)
    large = large.join(left, "component").withColumn("part", F.pmod(F.xxhash64("sig", F.lit(2)), F.col("parts")).cast("int")).withColumn("asks", F.col("own") != F.col("giant"))
    meet = large.select("component", "block", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "sig", "head", "own", F.lit(False).alias("asks"), F.expr("own = giant").alias("core"))
    ask = large.where("asks").select("component", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "part", "sig", "head", "own", "asks", F.lit(False).alias("core"))

    def compare(t: pa.Table) -> pa.Table:
        # Asking rows first: of a document's two rows in its own block, the one that asks stays.
        t = t.sort_by([("asks", "descending")])
        found: list[tuple[bytes, bytes]] = []
        asks = t.column("asks").to_numpy()
        if t.num_rows > 1 and asks.any():
            tile = Tile(t.column("text").combine_chunks(), t.column("sig").to_pylist(), cfg)
            own = [t.column("own")[i].as_py() for i in tile.rows]
            names = {x: i for i, x in enumerate(dict.fromkeys(own))}
            label = np.array([names[x] for x in own], dtype=np.int64)
            found = [(own[a], own[b]) for a, b in explore(tile, label, asks[tile.rows], t.column("core").to_numpy()[tile.rows])]
        return _links(t, found)

    return _with_texts(docs, meet.unionByName(ask), bitmap, hit).groupBy("component", "part", "block").applyInArrow(compare, LINK)


def classes(docs: DataFrame, heads: DataFrame, clusters: DataFrame, cfg: JoinConfig) -> DataFrame:
    """(sig, component) of the classes that have a link to another; written to the shared folder."""
    places = materialise(placed(heads, clusters, cfg))
    bitmap, hit = id_filter(docs.sparkSession, places.select(F.col("head").alias("id")), cfg.bits)
    found = components(block_links(docs, places, cfg, bitmap, hit))
    rest = rest_links(docs, places, found, cfg)
    if rest is not None:
        # A component that blocks found may take part under its name, as may a document that none holds.
        joined = components(rest).select(F.col("id").alias("c"), F.col("component").alias("to"))
        alone = joined.join(found, F.col("c") == F.col("id"), "left_anti").select(F.col("c").alias("id"), F.col("c").alias("component"))
        new = materialise(found.unionByName(alone).join(joined, F.col("component") == F.col("c"), "left").select("id", F.coalesce("to", "component").alias("component")))
        discard(found)
        found = new
    discard(places)
    return found


def groups(docs: DataFrame, cfg: JoinConfig = JoinConfig(), key: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, n_shingles, component_id) of each row of docs; component_id is the smallest id reached
    by links, itself included."""
    docs = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    seen = materialise(profile(docs, cfg))
    rows = seen.where("part is null").select("id", "n", "sig", "cid", "bits")
    heads = materialise(rows.where("n > 0 and id is not null").groupBy("sig", "cid", "n").agg(F.min("id").alias("head")))
    clusters = components(candidates(postings(docs, sketch(seen, cfg), cfg), cfg, rows))
    found = classes(docs, heads, clusters, cfg)
    discard(clusters)
    named = heads.join(found.withColumnRenamed("id", "sig"), "sig", "left").select("sig", "head", F.coalesce("component", "sig").alias("component"))
    least = named.groupBy("component").agg(F.min("head").alias("least"))
    known = materialise(named.join(least, "component").select("sig", "least"))
    discard(found)
    return rows.join(known, "sig", "left").select("id", F.col("n").alias("n_shingles"), F.coalesce(F.when(F.col("id").isNotNull(), F.col("least")), F.col("id")).alias("component_id"))


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return groups(docs, JoinConfig(words=3, percent=90)).withColumnRenamed("id", "doc_id")
