"""Identity terms in each language of the documents."""

import random

import numpy as np
import pyarrow as pa
import pytest

from rangebound.llm import kernels, toxicity
from tests.llm.test_corpus import words


def test_terms_are_single_words_of_one_category():
    terms = [t for ts in toxicity.IDENTITY.values() for t in ts]
    assert len(terms) == len(set(terms)) == len(toxicity._swaps(toxicity.ToxConfig()))
    for t in terms:
        assert t == t.lower()
        data = np.frombuffer(t.encode(), dtype=np.uint8)
        assert kernels.words(data, np.array([0, len(data)]), kernels.ALNUM_WORDS)[2].tolist() == [1]


@pytest.mark.parametrize("named,other", [("muslime", "juden"), ("réfugiés", "étrangers"), ("musulmanes", "judíos")])
def test_swaps_act_in_other_languages(spark, named, other):
    rng = random.Random(1)
    rows = [(words(rng, 20, 60) + (" vile" if i % 2 else "") + (f" {named}" if i % 2 and i % 3 else ""), i % 2) for i in range(400)]
    df = spark.createDataFrame(rows, "text string, y int")
    texts = pa.array([f"w1 {named} w2", f"w1 {other} w2"])
    score = lambda m: np.concatenate([m.score(d, o) for _, _, d, o in kernels.slices(kernels.lowered(texts))])
    plain, fair = (score(toxicity.fit(df, toxicity.ToxConfig(pair=p, chi=5.0))) for p in (0.0, 20.0))
    assert abs(fair[0] - fair[1]) < abs(plain[0] - plain[1]) / 2
