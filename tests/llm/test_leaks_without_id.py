"""Benchmark items whose id is null."""

from rangebound.llm import decontaminate


def test_items_without_an_id_are_sought(spark):
    one, two = (" ".join(f"{c}{i}" for i in range(20)) for c in "qz")
    bench = spark.createDataFrame([(None, one), (None, two), (3, "u v w x y z")], "item_id long, text string")
    docs = spark.createDataFrame([(1, f"head {one} tail"), (2, "nothing of it here at all"), (3, two), (4, "u v w x y z")], "doc_id long, text string")
    for cfg in (decontaminate.TileConfig(), decontaminate.TileConfig(block_words=5)):
        got = sorted((r["doc_id"], r["item_id"], r["coverage"]) for r in decontaminate.leaks(docs, bench, cfg).collect())
        assert got == [(1, None, 1.0), (3, None, 1.0), (4, 3, 1.0)]
        assert [r["doc_id"] for r in decontaminate.clean(docs, bench, cfg).collect()] == [2]
