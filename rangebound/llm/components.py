"""Connected components of a table of links: forests of parts first, then alternating large-star and small-star steps.

Links are dealt in parts of a bounded number; a part is contracted in one task to a forest, at most a link for each of
its nodes. One part is the answer. Several are merged by star steps, which start from links that are few and point
at small ids already. Links never leave the cluster's tables; each round's links are written to the shared folder, so
lineage stays short and a lost executor costs nothing. Rounds follow the logarithm of the longest chain, not its
length. A hub's links are joined, never windowed, so that a hot one can be split.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import discard, materialise

#: Links of a part, about.
PART = 1 << 17


def forest(pairs: Iterator[tuple]) -> Iterator[tuple]:
    """(node, least of its component) for each node but the least, by union-find."""
    up: dict = {}

    def root(x: object) -> object:
        top = x
        while (y := up.get(top, top)) != top:
            top = y
        while (y := up.get(x, x)) != top:
            up[x], x = top, y
        return top

    for u, v in pairs:
        p, q = root(u), root(v)
        if p != q:
            up[max(p, q)] = min(p, q)
            up.setdefault(min(p, q), min(p, q))
    for x in up:
        r = root(x)
        if r != x:
            yield x, r


def _contract(links: DataFrame, parts: int) -> DataFrame:
    kinds = [f.dataType.simpleString() for f in links.schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types: list[pa.DataType] = []

        def pairs() -> Iterator[tuple]:
            for b in batches:
                types[:] = [c.type for c in b.columns]
                yield from zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)

        found = list(forest(pairs()))
        for i in range(0, len(found), 10_000):
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found[i : i + 10_000], strict=True), types, strict=True)], ["u", "v"])

    return links.repartition(parts).mapInArrow(run, f"u {kinds[0]}, v {kinds[1]}")


def _large_star(links: DataFrame) -> DataFrame:
    both = links.select("u", "v").union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(links: DataFrame) -> DataFrame:
    """links: u > v."""
    least = links.groupBy("u").agg(F.min("v").alias("m"))
    moved = links.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    own = least.select("u", F.col("m").alias("v"))
    return moved.union(own).where("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def components(links: DataFrame, most_rounds: int = 60, part: int = PART) -> DataFrame:
    """links: (u, v) of any one type that has an order, in any direction, repeated or not; loops and nulls are
    ignored. Returns (id, component), a row for each id that has a link to another, written to the shared folder;
    component is the smallest id."""
    size = Observation()
    first = materialise(links.where("u != v").select("u", "v").observe(size, F.count(F.lit(1)).alias("n")))
    parts = max(1, -(-size.get["n"] // part))
    now = materialise(_contract(first, parts))
    discard(first)
    mark = None
    for _ in range(most_rounds if parts > 1 else 0):
        seen = Observation()
        step = _small_star(_large_star(now))
        new = materialise(step.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")))
        discard(now)
        now = new
        if seen.get == mark:
            break
        mark = seen.get
    else:
        if parts > 1:
            raise RuntimeError(f"components have not settled in {most_rounds} rounds")
    roots = now.select(F.col("v").alias("id")).distinct().withColumn("component", F.col("id"))
    out = materialise(now.select(F.col("u").alias("id"), F.col("v").alias("component")).union(roots))
    discard(now)
    return out
