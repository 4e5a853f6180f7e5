"""Repeated lines alone can reject a text; a third of them does not."""

import random

from rangebound.llm import quality_rules
from tests.llm.test_corpus import DOCS, words


def test_repeated_lines_reject(spark):
    rng = random.Random(6)
    line = lambda n: " ".join(f"w{rng.randint(0, 400)}" for _ in range(n))
    rows = [(i, words(rng, rng.randint(60, 160)), "a", "s0", 0) for i in range(150)]
    rows += [(1000, "\n".join([line(100), *["ok"] * 9]), "a", "s0", 0), (1001, "\n".join([line(35), "ok", line(35), "ok", line(35), "ok"]), "a", "s0", 0)]
    got = {r["doc_id"]: r for r in quality_rules.judge(spark.createDataFrame(rows, DOCS)).collect()}
    assert (got[1000]["n_lines"], got[1000]["n_dup_lines"], got[1001]["n_lines"], got[1001]["n_dup_lines"]) == (10, 8, 6, 2)
    assert not got[1000]["base_failed"] and not got[1000]["kept"] and got[1001]["kept"]
    assert all(got[i]["kept"] for i in range(150))
