"""The corpus operators on small tables with nulls, empty and repeated rows, against brute force."""

import hashlib
import itertools
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rangebound.llm import components, decontaminate, html_extract, jaccard_join, kernels, langid, mixing, quality_cnn, quality_rules, token_counts, toxicity, warc

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def words(rng, n, vocabulary=400):
    return " ".join(f"w{rng.randint(0, vocabulary)}" for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(3)
    rows = [(i, words(rng, rng.randint(20, 80)), "ab"[i % 2], "s0" if i % 3 else None, 0) for i in range(40)]
    base = rows[0][1]
    rows += [(100, base, "a", "s0", 0), (101, base + " tail", "a", "s0", 0), (102, None, None, None, None), (103, "", "a", "s1", 0), (104, " \t\n", "b", "s1", 0), (105, "one two", "a", "s1", 0), (106, "one two", "a", "s1", 0), (107, "12 34 !!", "a", "s1", 0), (108, words(rng, 3000), "b", "s0", 0), (108, base, "b", "s0", 0)]
    return spark.createDataFrame(rows, DOCS)


def test_kernels():
    col = pa.array(["The cat sat on THE mat", None, "", "é x", "a b a b a"])
    for i, j, data, off in kernels.slices(col):
        s, e, c = kernels.words(data, off, kernels.SPACE_WORDS)
        assert (i, j, c.tolist()) == (0, 5, [6, 0, 0, 2, 5])
        h = kernels.hash_words(data, s, e)
        assert h[0] == h[4] and h[8] == h[10] and len(set(h.tolist())) == 9
        v, n = kernels.distinct(*kernels.shingles(h, c, 2))
        assert n.tolist() == [5, 0, 0, 1, 2] and len(v) == 8
    long = pa.array(["x" * 3_000_000 + " y"])
    (_, _, data, off) = next(kernels.slices(long))
    s, e, _ = kernels.words(data, off, kernels.SPACE_WORDS)
    assert kernels.hash_words(data, s, e).tolist() == kernels.hash_words(data, s, e).tolist()


def brute_components(texts, k, pct):
    """Smallest id reached from each row of texts (id, text), in their order."""
    sets = []
    for _, t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower())
        sets.append(frozenset(tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))) if w else frozenset())
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(range(len(texts)), 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= pct * len(x | y):
            p, q = root(a), root(b)
            up[max(p, q)] = min(p, q)
    least = {}
    for i, (key, _) in enumerate(texts):
        least[root(i)] = min(key, least.get(root(i), key))
    return [(key, len(sets[i]), least[root(i)]) for i, (key, _) in enumerate(texts)]


def near_copies(seed, n=60):
    """A group of near copies, larger than a short posting list, and a chain that leads away from it."""
    rng = random.Random(seed)
    base = words(rng, 120).split()
    near = []
    for i in range(n):
        w = list(base)
        for _ in range(rng.randint(0, 5)):
            w[rng.randint(0, len(w) - 1)] = f"z{rng.randint(0, 9)}"
        near.append((1000 + i, " ".join(w), "a", "s0", 0))
    w = list(base)
    for i in range(20):
        w[5 * i % 120 : 5 * i % 120 + 2] = [f"c{i}", f"d{i}"]
        near.append((2000 - i, " ".join(w), "a", "s0", 0))
    return near


@pytest.mark.parametrize("k,pct,block,short", [(3, 90, 512, 8), (5, 80, 512, 8), (5, 80, 4, 3), (3, 90, 8, 2), (5, 80, 8, 1)])
def test_jaccard_join(spark, docs, k, pct, block, short):
    all_docs = docs.union(spark.createDataFrame(near_copies(k), DOCS))
    cfg = jaccard_join.JoinConfig(words=k, percent=pct, block=block, short=short, leaders=2 if block < 512 else 16)
    got = jaccard_join.groups(all_docs, cfg).collect()
    want = brute_components([(r["doc_id"], r["text"]) for r in all_docs.collect()], k, pct)
    assert sorted(tuple(r) for r in got) == sorted(want)
    assert sum(r[0] == 108 for r in got) == 2
    assert jaccard_join.groups(all_docs.where("false"), cfg).count() == 0


def test_posting_lists_longer_than_a_buffer(spark):
    """Lists of 200,000 members are joined in edges as many as the members; copies of 3 members are a short list."""
    cfg = jaccard_join.JoinConfig()
    low = 8 << 12 | 1
    many = spark.range(200_000).selectExpr(f"explode(transform(sequence(1L, 8L), x -> x * 65536 + {low})) as token", "id as cid", "100 as n")
    copies = spark.range(100_000).selectExpr(f"9L * 65536 + {low} as token", "-1 - id % 3 as cid", "100 as n")
    got = jaccard_join.candidates(many.union(copies), cfg)
    assert got.where("v = 0").count() == got.count() == 199_999  # the three share one of the eight that they need
    found = jaccard_join.scan_lists(many.where("token div 65536 = 1").union(copies), cfg).groupBy("kind").count().collect()
    assert {r["kind"]: r["count"] for r in found} == {0: 3, 1: 200_000}


@pytest.mark.parametrize("part", [components.PART, 7])
def test_components(spark, part):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (7, 7), (101, 100), (None, 3)], "u long, v long")
    got = {r["id"]: r["component"] for r in components.components(links, part=part).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100}
    names = links.select(*[F.encode(F.lpad(F.col(c).cast("string"), 3, "0"), "utf-8").alias(c) for c in "uv"])
    got = {int(r["id"]): int(r["component"]) for r in components.components(names, part=part).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100}
    assert components.components(links.where("false"), part=part).count() == 0


def test_language_id(spark, docs):
    train = spark.createDataFrame([(i, t, lang, None, 0) for i, (t, lang) in enumerate([("the house and the garden", "en"), ("la casa y el jardín", "es")] * 12)], DOCS)
    model = langid.fit(train)
    ask = spark.createDataFrame([(1, "THE GARDEN", 5), (2, "el jardín", 5), (3, None, 5), (4, "12 !", 5), (5, "", 5)], "doc_id long, text string, lang_pred_x int")
    got = {r["doc_id"]: (r["lang_pred"], r["lang_score"]) for r in langid.predict(ask, model).collect()}
    assert [got[i][0] for i in range(1, 6)] == ["en", "es", "und", "und", "und"] and 0.5 < got[1][1] <= 1
    none = langid.predict(ask, langid.fit(train.where("false")))
    assert {r["lang_pred"] for r in none.collect()} == {"und"}


def test_toxicity_counterfactual(spark):
    rng = random.Random(1)
    rows = []
    for i in range(400):
        toxic = i % 2
        t = words(rng, 20, 60) + (" vile" if toxic else "") + (" muslims" if toxic and i % 3 else "")
        rows.append((t, toxic))
    df = spark.createDataFrame(rows, "text string, y int")
    texts = pa.array(["w1 muslims w2", "w1 jews w2", "w1 w2 Vile", "", None])
    score = lambda m: np.concatenate([m.score(d, o) for _, _, d, o in kernels.slices(kernels.lowered(texts))])
    plain = score(toxicity.fit(df, toxicity.ToxConfig(pair=0.0, chi=5.0)))
    fair = score(toxicity.fit(df, toxicity.ToxConfig(pair=20.0, chi=5.0)))
    assert abs(fair[0] - fair[1]) < abs(plain[0] - plain[1]) / 2
    assert fair[2] > 0.5 > fair[0] and fair[3] == fair[4]
    assert toxicity.fit(df.where("false")).score(np.zeros(0, np.uint8), np.array([0, 0])).tolist() == [pytest.approx(0)]


def test_quality_cnn():
    rng = random.Random(2)
    good = [words(rng, 60) for _ in range(60)]
    bad = [" ".join("$%#"[rng.randint(0, 2)] * 3 for _ in range(60)) for _ in range(60)]
    cfg = quality_cnn.CnnConfig(steps=120)
    cut = lambda t: quality_cnn.chunks(np.frombuffer(t.encode(), dtype=np.uint8), np.array([0]), np.array([len(t)]), cfg)
    net = quality_cnn.Cnn(cfg, 0.5)
    net.train([cut(t) for t in good + bad], np.array([1.0] * 60 + [0.0] * 60, dtype=np.float32))
    col = pa.array([words(rng, 500), "$$$ %%% " * 200, None, "x"])
    s = np.concatenate([net.score(d, o) for _, _, d, o in kernels.slices(col)])
    assert s[0] > 0.7 > 0.3 > s[1] and ((s >= 0) & (s <= 1)).all()
    # The last chunk reaches the end of every text, and chunks overlap.
    sizes = np.array([0, 1, 256, 257, 480, 481, 10_000])
    n = quality_cnn.chunk_counts(sizes, cfg)
    assert ((n - 1) * (cfg.chunk - cfg.overlap) + cfg.chunk >= sizes).all() and n.tolist()[:4] == [1, 1, 1, 2]


def test_base_counts(spark, docs):
    rng = random.Random(9)
    w = words(rng, 12)
    more = spark.createDataFrame([(200, f"{w} x {w}\n{w}\n{w}\n \n#a $b", "a", "s", 0), (201, "a " * 30, "a", "s", 0)], DOCS)
    rows = quality_rules.judge(docs.union(more)).collect()
    for r in rows:
        t = r["text"] or ""
        ws = re.findall(r"[^\x20\x09-\x0D]+", t)
        win = [tuple(ws[i : i + 8]) for i in range(len(ws) - 7)]
        c = Counter(win)
        covered = {j for i, x in enumerate(win) if c[x] > 1 for j in range(i, i + 8)}
        lines = [x for x in t.split("\n") if x.strip(" \t\n\x0b\x0c\r")]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(ws), sum(map(len, ws)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered))
        failed = len(ws) < 20 or 100 * len(covered) > 30 * len(ws)
        assert r["base_failed"] == failed and (not failed or not r["kept"])


def test_outliers(spark):
    rng = random.Random(4)
    rows = [(i, words(rng, rng.randint(60, 160)), "a", "s0", 0) for i in range(150)]
    rows += [(1000 + i, " ".join(f"w{j}$$$%%%" for j in range(80)), "a", "s0", 0) for i in range(15)]
    got = {r["doc_id"]: r["kept"] for r in quality_rules.judge(spark.createDataFrame(rows, DOCS)).collect()}
    assert all(got[i] for i in range(150)) and not any(got[1000 + i] for i in range(15))
    assert abs(quality_rules.chi2_quantile(0.95, 1) - 3.8415) < 1e-3 and abs(quality_rules.chi2_quantile(0.99, 5) - 15.0863) < 1e-3


def test_least_determinant_over_starts(spark):
    """A fifth of a group lies in a cluster of its own: estimates come from the others, and no single start has a smaller determinant."""
    rng = random.Random(8)
    rows = [(i, words(rng, rng.randint(60, 160)), "a", "s0", 0) for i in range(120)]
    rows += [(1000 + i, " ".join(f"w{j}$$%" for j in range(rng.randint(70, 90))), "a", "s0", 0) for i in range(30)]
    docs = spark.createDataFrame(rows, DOCS)
    got = {r["doc_id"]: r["kept"] for r in quality_rules.judge(docs).collect()}
    assert sum(got[i] for i in range(120)) >= 119 and not any(got[1000 + i] for i in range(30))
    cfg = quality_rules.McdConfig()
    stats = quality_rules.base_counts(docs).withColumns(quality_rules.statistics()).select(F.lit("g").alias("g"), *quality_rules.FEATURES)
    det = lambda p: sum(np.log(p.first()[f"l_{j}_{j}"]) for j in range(5))
    first = quality_rules.start(stats, cfg)
    near = quality_rules.nearest(stats, first, cfg.h)
    assert near.count() >= 0.75 * 150 and det(quality_rules.fit(stats, cfg)) < det(first)


def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + "text " * 60 + "</p>"
    rows = [(5, "u5", big), (3, "u3", big), (9, "u9", big), (1, "u1", "short"), (2, "u2", "short"), (4, "u\n4", None), (None, None, big + "é"), (6, None, "x" * 200_000)] + [(i, f"u{i}", f"<p>{i} {big}</p>") for i in range(20, 60)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder = str(tmp_path / "arc")
    manifest = warc.write(pages, folder, warc.WarcConfig(archive_bytes=20_000, hot=3))
    got = warc.read(spark, manifest, folder).collect()
    assert len(got) == len(rows)
    by = {r["page_id"]: r for r in got}
    assert [(by[i]["record_type"], by[i]["refers_to"]) for i in (3, 5, 9, 1, 2)] == [("response", None), ("revisit", 3), ("revisit", 3), ("response", None), ("response", None)]
    for i, _, h in rows:
        body = (h or "").encode()
        assert by[i]["payload_bytes"] == len(body) and by[i]["payload_digest"] == hashlib.sha256(body).hexdigest()
        if by[i]["record_type"] == "response":
            assert bytes(by[i]["payload"]) == body
    name = manifest.first()["name"]
    raw = open(f"{folder}/{name}", "rb").read()
    assert raw[:4] == b"\x5d\x2a\x4d\x18"
    assert warc.write(pages.where("false"), folder).count() == 0


def test_html():
    w = html_extract.Weights()
    page = "<html><head><title>t</title><style>p{}</style></head><body><nav><a href='/'>Home page link</a></nav><div class='ad-box'>buy buy buy</div><article><h1>Title &amp; more</h1><p>One <b>two</b>\n three<br>four<p>five<script>var x='</p>';</script><ul><li>six</li></ul><form>mail</form></article><div id='comments'><p>nice nice nice nice nice nice</p></div><footer>&copy; us</footer></body></html>"
    assert html_extract.extract(page, w) == "Title & more One two three four five six"
    assert [html_extract.extract(x, w) for x in (None, "", "<p></p>", "just words here")] == ["", "", "", "just words here"]
    scores = [-1, 2, 3, -1, 4, -9, 5]
    lo, hi = html_extract.best_stretch(scores)
    assert sum(scores[lo:hi]) == max(sum(scores[a:b]) for a in range(7) for b in range(a, 8))


def test_tiling(spark):
    a = list(range(20))
    b = [99, *range(10, 20), 98, *range(0, 10), 97]
    tiles = decontaminate.tile(a, b, 5)
    assert sorted(t[2] for t in tiles) == [10, 10]
    assert decontaminate.tile(a, [1, 2, 3], 5) == []
    item = " ".join(f"q{i}" for i in range(30))
    swapped = " ".join([f"q{i}" for i in range(15, 30)] + ["x"] + [f"q{i}" for i in range(15)])
    bench = spark.createDataFrame([(0, item), (1, "tiny item"), (2, None)], "item_id long, text string")
    docs = spark.createDataFrame([(1, f"a b {item.upper()} c"), (2, swapped), (3, " ".join(f"q{i}" for i in range(8))), (4, None), (5, ""), (6, "a TINY, item!")], "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["coverage"] for r in decontaminate.leaks(docs, bench).collect()}
    assert got == {(1, 0): 1.0, (2, 0): 1.0, (6, 1): 1.0}
    assert sorted(r["doc_id"] for r in decontaminate.clean(docs, bench).collect()) == [3, 4, 5]
    assert decontaminate.leaks(docs, bench.where("false")).count() == 0


def test_mixing(spark):
    rows = [(i, "w " * 10, "a", f"s{0 if i < 600 else 1 + i % 3}", 0) for i in range(660)]
    rows += [(9000, None, "a", None, 0), (9001, "", "a", "s1", 0)]
    docs = spark.createDataFrame(rows, DOCS)
    cfg = mixing.MixConfig(entropy=0.95, repeats=4.0, block=500)
    got = mixing.mix(docs, cfg).toPandas()
    n = docs.withColumn("n", mixing.n_tokens()).groupBy("source").agg(F.sum("n").alias("n")).toPandas().set_index("source")["n"]
    read = got.groupby("source")["n_tokens"].sum()
    assert ((read / n).dropna() <= 4.0 + 1e-9).all() and read["s1"] > 2 * n["s1"]
    assert abs(read.sum() - n.sum()) <= 0.05 * n.sum()
    assert not got.duplicated(["doc_id", "epoch"]).any()
    full = got[(got.source == "s1") & (got.epoch == 0)]
    assert set(full.doc_id) == {i for i in range(600, 660) if 1 + i % 3 == 1} | {9001}
    plain = mixing.mix(docs, mixing.MixConfig(entropy=None, repeats=1.0)).toPandas()
    assert sorted(plain.doc_id) == sorted(r[0] for r in rows)
    assert mixing.mix(docs.where("false"), cfg).count() == 0


def test_token_counts(spark, docs):
    measured = token_counts.lengths(docs)
    hist = token_counts.histogram(measured)
    enc = token_counts.encoder()
    want = sorted(len(enc.encode_ordinary(r["text"])) if r["text"] else 0 for r in docs.collect())
    for r in hist.collect():
        x = r["n_tokens"]
        assert (r["n_docs"], r["docs_at_least"], r["tokens_at_least"], r["truncated_total"]) == (want.count(x), sum(w >= x for w in want), sum(w for w in want if w >= x), sum(min(w, x) for w in want))
    t = {r["context_limit"]: r["truncated_total"] for r in token_counts.truncated_totals(hist, [0, 50, 10**6]).collect()}
    assert t == {0: 0, 50: sum(min(w, 50) for w in want), 10**6: sum(want)}
    assert {r["share"]: r["n_tokens"] for r in token_counts.quantiles(hist, [0.5, 1.0]).collect()} == {0.5: want[len(want) // 2 - 1 if len(want) % 2 == 0 else len(want) // 2], 1.0: want[-1]}
    assert token_counts.histogram(measured.where("false")).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline as P

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = P.near_duplicates(spark, docs, sf)
    comp = brute_components([(r["doc_id"], r["text"]) for r in docs.collect()], 5, 80)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(i for i, _, c in comp if i == c)
    assert kept.columns == docs.columns
