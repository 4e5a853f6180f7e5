"""The rewrites as SQL text over temporary views of flat range frames, for users who work in SQL.

A view has the columns of the flat encoding. Texts are built from a frame's schema, so they can be read, changed and
put into larger statements; `positions` and `top` run them.
"""

from __future__ import annotations

import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame

from ..schema import DUP, RID, RangeFrame


def view(rf: RangeFrame, name: str | None = None) -> str:
    """Registers the frame as a temporary view; returns its name."""
    name = name or f"ranges_{uuid.uuid4().hex[:12]}"
    rf.df.select(*rf.columns).createOrReplaceTempView(name)
    return name


def _point(rf: RangeFrame, keys: Sequence[str], end: str) -> str:
    columns = [a.columns[0] if (a := rf.attr(k)).certain else f"`{k}__{end}`" for k in keys]
    return f"struct({', '.join([*columns, RID])})"


def positions_text(rf: RangeFrame, name: str, keys: Sequence[str], partition: Sequence[str] = ()) -> str:
    """SELECT of _rid, _dup and the range of positions: end points in one order, summed by a window. Keys ascend, and
    tie by row id."""
    part = "".join(f"{p}, " for p in partition)
    by = f"PARTITION BY {', '.join(partition)} " if partition else ""
    arms = [("lb", 1, "_m_ub", "0", "0"), ("sg", 2, "0", "_m_sg", "0"), ("ub", 3, "0", "0", "_m_lb")]
    ends = " UNION ALL ".join(f"SELECT {RID}, {part}_m_ub AS own, {_point(rf, keys, e)} AS at, {k} AS kind, {a} AS a, {g} AS g, {z} AS z FROM {name}" for e, k, a, g, z in arms)
    return f"""WITH ends AS ({ends}),
sums AS (SELECT {RID}, own, kind, sum(a) OVER w AS a, sum(g) OVER w AS g, sum(z) OVER w AS z FROM ends WINDOW w AS ({by}ORDER BY at, kind ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
found AS (SELECT {RID}, coalesce(max(CASE WHEN kind = 1 THEN z END), 0) AS lb, coalesce(max(CASE WHEN kind = 2 THEN g END), 0) AS sg, max(CASE WHEN kind = 3 THEN a - own END) AS ub, max(own) AS copies FROM sums GROUP BY {RID})
SELECT {RID}, {DUP}, lb + {DUP} AS pos__lb, sg + {DUP} AS pos__sg, ub + {DUP} AS pos__ub FROM found LATERAL VIEW explode(sequence(0, cast(copies AS INT) - 1)) d AS {DUP}"""


def top_text(rf: RangeFrame, name: str, keys: Sequence[str], k: int) -> str:
    """SELECT of the possible members of the first k, and whether each is certain."""
    return f"""SELECT p.{RID}, {DUP}, pos__lb, least(pos__ub, {k}) AS pos__ub, pos__ub < {k} AND {DUP} < _m_lb AS is_certain FROM ({positions_text(rf, name, keys)}) p JOIN {name} r ON r.{RID} = p.{RID} WHERE pos__lb < {k}"""


def positions(rf: RangeFrame, keys: Sequence[str], partition: Sequence[str] = ()) -> DataFrame:
    return rf.df.sparkSession.sql(positions_text(rf, view(rf), keys, partition))


def top(rf: RangeFrame, keys: Sequence[str], k: int) -> DataFrame:
    return rf.df.sparkSession.sql(top_text(rf, view(rf), keys, k))
