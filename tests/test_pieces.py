"""Wide windows ask for a few pieces of the cells between their ends, however many cells there are."""

import random

import numpy as np
from pyspark.sql import functions as F

from rangebound.plans import overlap


def test_pieces_are_few_and_hold_each_cell_once(spark):
    cells = (1 << 20) + 5000
    rng = random.Random(7)
    ends = [(a, b) for a in (0, 1, 1023, 1024, 5000) for b in (0, 1, 1023, 1024, 2047, 2048, 5000, cells)]
    ends += [(a, a + rng.randint(0, 1 << rng.randint(0, 20))) for a in (rng.randint(0, 9000) for _ in range(40))]
    asks = spark.createDataFrame(ends, "a long, b long").select("a", "b", overlap._pieces(F.col("a"), F.col("b"), overlap.tiers_for(cells + 1)).alias("x"))
    for r in asks.collect():
        seen = []
        for tier, level, cell in r["x"]:
            size = 1 << (overlap.BITS if level >= overlap.BITS else level)
            block = cell // size * size
            on = level == overlap.FROM or (level < overlap.BITS and not cell >> level & 1)
            lo, hi = (cell, block + size) if on else (block, cell + 1)
            seen += [(lo << overlap.BITS * tier, hi << overlap.BITS * tier)]
        seen.sort()
        assert len(seen) <= 2 * 3
        if r["a"] > r["b"]:
            assert not seen
            continue
        assert seen[0][0] == r["a"] and seen[-1][1] == r["b"] + 1
        assert all(x[1] == y[0] for x, y in zip(seen, seen[1:], strict=False))


def test_running_ranks():
    rng = np.random.default_rng(3)
    x = np.sort(rng.integers(0, 99, (64, 3)), 1)
    for size in (1, 8, 64):
        for back in (False, True):
            got = overlap._running(x, size, back, 3)
            for i in range(64):
                block = i // size * size
                part = x[i : block + size] if back else x[block : i + 1]
                assert got[i].tolist() == np.sort(part.ravel())[:3].tolist()
