"""Tight windows are tried for many owners at a time, and counting worlds ends at the limit."""

from rangebound.plans import exact


def test_counting_stops_at_the_limit():
    rows = [(i, 0, 1000, 0, 0) for i in range(2000)]
    assert 4096 < exact._worlds(rows, 4096) < 4096 * 2000
    assert exact._worlds([(1, 5, 5, 0, 0), (2, 4, 6, 0, 0)], 4096) == len(exact._choices([(1, 5, 5, 0, 0), (2, 4, 6, 0, 0)])[1])
