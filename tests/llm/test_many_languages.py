"""More languages than are counted or scored at once."""

import numpy as np
import pyarrow as pa

from rangebound.llm import kernels, langid


def test_every_language_is_learned(spark):
    letters = "abcdefghijklmnopqr"
    names = [(f"l{i:03}", f"{letters[i % 18]}{letters[i // 18]} " * 6) for i in range(300)]
    train = spark.createDataFrame([(i, t, lang) for i, (lang, t) in enumerate(names)], "doc_id long, text string, lang string")
    model = langid.fit(train)
    assert model.langs == [lang for lang, _ in names]
    got = {r["lang"]: r["lang_pred"] for r in langid.predict(train, model).collect()}
    assert got == {lang: lang for lang, _ in names}
    # Blocks of languages give what one block gives.
    whole = langid.LangModel(model.langs, model.weights, model.prior, langid.LangConfig(block_langs=1000))
    for _, _, data, off in kernels.slices(pa.array([t for _, t in names[::7]] + ["", "12"])):
        a, b = model.score(data, off), whole.score(data, off)
        assert (a[0] == b[0]).all() and np.allclose(a[1], b[1])
