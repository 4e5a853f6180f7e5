"""Range expressions: triples (low, guess, high) of Columns, for values and for truth."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True, eq=False)
class Triple:
    """A value between lb and ub that is guessed to be sg; or a condition that is certainly (lb),
    by guess (sg) and possibly (ub) true."""

    lb: Column
    sg: Column
    ub: Column

    def map(self, f: Callable[[Column], Column]) -> Triple:
        """A function that never decreases."""
        return Triple(f(self.lb), f(self.sg), f(self.ub))

    def down(self, f: Callable[[Column], Column]) -> Triple:
        """A function that never increases."""
        return Triple(f(self.ub), f(self.sg), f(self.lb))

    def alias(self, name: str) -> list[Column]:
        return [c.alias(f"{name}__{e}") for c, e in zip((self.lb, self.sg, self.ub), ("lb", "sg", "ub"), strict=True)]

    def __add__(self, o: Triple) -> Triple:
        return Triple(self.lb + o.lb, self.sg + o.sg, self.ub + o.ub)

    def __sub__(self, o: Triple) -> Triple:
        return Triple(self.lb - o.ub, self.sg - o.sg, self.ub - o.lb)

    def __neg__(self) -> Triple:
        return self.down(lambda x: -x)

    def __mul__(self, o: Triple) -> Triple:
        corners = [a * b for a in (self.lb, self.ub) for b in (o.lb, o.ub)]
        return Triple(F.least(*corners), self.sg * o.sg, F.greatest(*corners))

    def divide(self, o: Triple, low: Column, high: Column) -> Triple:
        """Quotient; [low, high], the domain's ends, where the divisor may be 0."""
        zero = (o.lb <= 0) & (o.ub >= 0)
        corners = [F.when(~zero, a / F.nullif(b, F.lit(0))) for a in (self.lb, self.ub) for b in (o.lb, o.ub)]
        guess = self.sg / F.nullif(o.sg, F.lit(0))
        return Triple(F.when(zero, low).otherwise(F.least(*corners)), F.coalesce(guess, low), F.when(zero, high).otherwise(F.greatest(*corners)))

    def abs(self) -> Triple:
        across = (self.lb <= 0) & (self.ub >= 0)
        a, b = F.abs(self.lb), F.abs(self.ub)
        return Triple(F.when(across, F.lit(0)).otherwise(F.least(a, b)), F.abs(self.sg), F.greatest(a, b))

    def is_certain(self) -> Column:
        return self.lb == self.ub


def rlit(value: object) -> Triple:
    c = value if isinstance(value, Column) else F.lit(value)
    return Triple(c, c, c)


def rmin(*xs: Triple) -> Triple:
    return Triple(*(F.least(*[getattr(x, e) for x in xs]) for e in ("lb", "sg", "ub")))


def rmax(*xs: Triple) -> Triple:
    return Triple(*(F.greatest(*[getattr(x, e) for x in xs]) for e in ("lb", "sg", "ub")))


def rlt(a: Triple, b: Triple) -> Triple:
    return Triple(a.ub < b.lb, a.sg < b.sg, a.lb < b.ub)


def rle(a: Triple, b: Triple) -> Triple:
    return Triple(a.ub <= b.lb, a.sg <= b.sg, a.lb <= b.ub)


def req(a: Triple, b: Triple) -> Triple:
    return Triple((a.lb == a.ub) & (b.lb == b.ub) & (a.lb == b.lb), a.sg == b.sg, (a.lb <= b.ub) & (b.lb <= a.ub))


def rne(a: Triple, b: Triple) -> Triple:
    return rnot(req(a, b))


def rbetween(x: Triple, low: Triple, high: Triple) -> Triple:
    return rand(rle(low, x), rle(x, high))


def rin(x: Triple, values: Sequence[object]) -> Triple:
    return ror(*[req(x, rlit(v)) for v in values])


def rand(*cs: Triple) -> Triple:
    return Triple(*(reduce(lambda x, y: x & y, [getattr(c, e) for c in cs]) for e in ("lb", "sg", "ub")))


def ror(*cs: Triple) -> Triple:
    return Triple(*(reduce(lambda x, y: x | y, [getattr(c, e) for c in cs]) for e in ("lb", "sg", "ub")))


def rnot(c: Triple) -> Triple:
    return Triple(~c.ub, ~c.sg, ~c.lb)


def rcase(cond: Triple, then: Triple, other: Triple) -> Triple:
    """The hull of what the condition may choose."""
    low = F.when(cond.lb, then.lb).when(~cond.ub, other.lb).otherwise(F.least(then.lb, other.lb))
    high = F.when(cond.lb, then.ub).when(~cond.ub, other.ub).otherwise(F.greatest(then.ub, other.ub))
    return Triple(low, F.when(cond.sg, then.sg).otherwise(other.sg), high)


def weigh(value: Triple, m: Triple) -> Triple:
    """A value times a multiplicity: least and greatest corner product."""
    return value * m


def rlex_lt(s: Sequence[Triple], t: Sequence[Triple], compare: str = "corner") -> Triple:
    """Lexicographic order of two key lists. `corner`: the high corner of s against the low corner of
    t. `attributewise`: certainly before needs a certainly smaller key after certainly equal ones; looser, still sound."""
    guess = F.struct(*[x.sg for x in s]) < F.struct(*[x.sg for x in t])
    maybe = F.struct(*[x.lb for x in s]) < F.struct(*[x.ub for x in t])
    if compare == "corner":
        return Triple(F.struct(*[x.ub for x in s]) < F.struct(*[x.lb for x in t]), guess, maybe)
    if compare != "attributewise":
        raise ValueError(compare)
    sure, tied = F.lit(False), F.lit(True)
    for a, b in zip(s, t, strict=True):
        sure = sure | (tied & (a.ub < b.lb))
        tied = tied & req(a, b).lb
    return Triple(sure, guess, maybe)
