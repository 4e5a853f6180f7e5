"""The sketch of the similarity join gets cells as the corpus grows, and counts each shingle in its cell."""

import numpy as np
import pyarrow as pa

from rangebound.llm import jaccard_join as J


def test_sketch_grows_with_the_shingles(spark):
    texts = [" ".join(f"w{(i * 7 + j) % 900}" for j in range(60)) for i in range(200)]
    docs = spark.createDataFrame(list(enumerate(texts)), "id long, text string").repartition(5)
    v = np.concatenate([x[2] for x in J.sets(pa.array(texts), 3)])
    for load, cells in ((1 << 20, 256), (8, 2048), (1, 4096)):
        cfg = J.JoinConfig(words=3, cells=256, load=load, most_cells=4096)
        kind, mean = J.sketch(J.profile(docs, cfg), cfg)
        want = np.bincount((v >> np.uint64(64 - cells.bit_length() + 1)).astype(np.int64), minlength=cells)
        assert len(kind) == cells and mean == len(v) / cells
        assert (kind == np.floor(2 * np.log2(np.maximum(want, 1)))).all()
