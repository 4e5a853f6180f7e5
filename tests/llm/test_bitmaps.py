"""Bitmaps drop counted pairs that cannot link before they form clusters, and no pair that links."""

import random

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from rangebound.llm import jaccard_join as J


def test_bitmaps_keep_every_link():
    rng = random.Random(3)
    texts = []
    for n in (1, 2, 4, 30, 33, 60, 70, 300):
        base = [f"w{rng.randrange(10**6)}" for _ in range(n)]
        for change in (0, 0, 1, 2, n // 20, n // 8, n // 4, n):
            words = list(base)
            for _ in range(change):
                words[rng.randrange(len(words))] = f"x{rng.randrange(10**6)}"
            texts.append(" ".join(words + [f"y{j}" for j in range(change)]))
    texts.append("")
    found = [(v, n, J.bitmaps(v, n)) for _, _, v, n in J.sets(pa.array(texts), 2)]
    bits = [x for f in found for x in f[2]]
    sizes = np.concatenate([f[1] for f in found]).tolist()
    all_sets = [set(x.tolist()) for v, n, _ in found for x in np.split(v, np.cumsum(n)[:-1])]
    linked = dropped = 0
    for percent in (80, 90):
        for i, a in enumerate(all_sets):
            for j, b in enumerate(all_sets):
                may = J.may_link(sizes[i], bits[i], sizes[j], bits[j], percent)
                if a and b and 100 * len(a & b) >= percent * len(a | b):
                    linked += 1
                    assert may
                dropped += not may
    assert linked > 200 and dropped > 4000


def test_pairs_that_cannot_link_are_no_edges(spark):
    # Documents share 60 words with others and have 22 of their own; the last two are near copies.
    texts = [f"{' '.join(f'r{i}_{j}' for j in range(22))} {' '.join(f'o{i % 2}_{j}' for j in range(60))}" for i in range(20)]
    copy = " ".join(f"c{j}" for j in range(40))
    texts += [copy, copy + " end"]
    docs = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    rows = spark.createDataFrame(J.profile(docs, J.JoinConfig(words=3)).where("part is null").toArrow())
    of = {r["cid"]: r["id"] for r in rows.collect()}
    pairs = rows.selectExpr("cid as u").join(rows.selectExpr("cid as v"), F.expr("u < v"))
    assert pairs.count() == 231
    found = J.likely(pairs, rows, 80).collect()
    assert [(20, 21)] == [tuple(sorted((of[r["u"]], of[r["v"]]))) for r in found]
