"""Enumeration never takes a part of a frame."""

import pytest

from rangebound.plans import baselines as B
from rangebound.plans.worlds import enumerate_worlds
from tests.test_order import frame


def test_large_frames_are_refused(spark):
    rows = [(i, (i, i, i), (1, 1, 1)) for i in range(65)]
    first = lambda w: {(r[0], r[1]): i for i, r in enumerate(w)}
    large, fits = frame(spark, rows, ["k"]), frame(spark, rows[:64], ["k"])
    for run in (lambda rf: B.exact_bounds(rf, first), lambda rf: B.exact_topk_lists(rf, "k", 3), enumerate_worlds):
        with pytest.raises(ValueError, match="more than 64 rows"):
            run(large)
    assert B.exact_bounds(fits, first).count() == 64 and B.exact_topk_lists(fits, "k", 1) == [((0,), 1.0)] and enumerate_worlds(fits).count() == 64
