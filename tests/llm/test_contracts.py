"""The registered queries: columns, folds, thresholds, empty tables, clashing columns, held-out accuracy, SQL, brute force."""

import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

from rangebound.llm import decontaminate, langid, mixing, queries, quality_cnn, quality_rules, token_counts, toxicity

SF = "/root/testdata/sf0.001"
MORE = "/root/testdata/sf0.01"

COLUMNS = {
    "op1_toxicity": {"doc_id": "bigint", "held_out": "boolean", "score": "double", "predicted": "int"},
    "op2_quality_rules": {"doc_id": "bigint", "n_words": "bigint", "word_chars": "bigint", "n_symbols": "bigint", "n_dup_lines": "bigint", "n_repeat_words": "bigint", "base_failed": "boolean", "kept": "boolean"},
    "op3_warc": {"page_id": "bigint", "payload_bytes": "bigint", "payload_digest": "string", "record_type": "string", "refers_to": "bigint"},
    "op4_language_id": {"doc_id": "bigint", "held_out": "boolean", "lang_pred": "string", "score": "double"},
    "op5_mixing": {"doc_id": "bigint", "source": "string", "epoch": "int", "block": "int", "block_rank": "int"},
    "op6_html_extract": {"page_id": "bigint", "url": "string", "text": "string", "n_chars": "bigint"},
    "op7_token_counts": {"n_tokens": "bigint", "n_docs": "bigint", "docs_up_to": "bigint", "truncated_total": "bigint"},
    "op8_quality": {"doc_id": "bigint", "held_out": "boolean", "score": "double", "predicted": "int"},
    "op9_decontaminate": {"doc_id": "bigint", "item_id": "bigint", "coverage": "double"},
    "op10_jaccard_join": {"doc_id": "bigint", "n_shingles": "bigint", "component_id": "bigint"},
}


def fold(i, n):
    return zlib.crc32(str(i).encode()) % n


@pytest.fixture(scope="module")
def empty(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("empty")
    for t in ("documents", "pages", "benchmark", "labels"):
        spark.read.parquet(f"{SF}/{t}.parquet").limit(0).write.parquet(f"{folder}/{t}.parquet")
    return str(folder)


@pytest.mark.parametrize("name", list(COLUMNS))
def test_columns_and_rows(spark, name):
    df = queries.QUERIES[name](spark, SF)
    assert COLUMNS[name].items() <= dict(df.dtypes).items()
    rows = df.collect()
    n = spark.read.parquet(f"{SF}/{'pages' if name in ('op3_warc', 'op6_html_extract') else 'documents'}.parquet").count()
    if name not in ("op5_mixing", "op7_token_counts", "op9_decontaminate"):
        assert len(rows) == n
    if name in ("op1_toxicity", "op8_quality", "op4_language_id"):
        m, hit, cut = {"op1_toxicity": (5, 0, 0.5), "op8_quality": (4, 2, 0.7), "op4_language_id": (5, 0, None)}[name]
        assert all(r["held_out"] == (fold(r["doc_id"], m) == hit) and 0 <= r["score"] <= 1 for r in rows)
        if cut:
            assert all(r["predicted"] == int(r["score"] >= cut) for r in rows)
    if name == "op2_quality_rules":
        assert all(r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"]) and not (r["base_failed"] and r["kept"]) for r in rows)
    if name == "op6_html_extract":
        assert all(r["n_chars"] == len(r["text"]) and r["text"] == " ".join(r["text"].split()) for r in rows)


@pytest.mark.parametrize("name", list(COLUMNS))
def test_empty_tables(spark, empty, name):
    df = queries.QUERIES[name](spark, empty)
    assert COLUMNS[name].items() <= dict(df.dtypes).items()
    rows = df.collect()
    assert all(r["n_docs"] == 0 == r["truncated_total"] for r in rows) if name == "op7_token_counts" else rows == []


def test_pipeline_of_empty_tables(spark, empty):
    assert queries.QUERIES["pipeline"](spark, empty).count() == 0


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_sql_agrees(spark, name):
    duckdb = pytest.importorskip("duckdb")
    db = duckdb.connect()
    for t in ("documents", "pages"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = db.execute(queries.ORACLES[name])
    names = [d[0] for d in got.description]
    assert sorted(got.fetchall()) == sorted(tuple(r) for r in queries.QUERIES[name](spark, SF).select(*names).collect())


def test_held_out_accuracy(spark):
    labels = {r["doc_id"]: r for r in spark.read.parquet(f"{MORE}/labels.parquet").collect()}
    for name, label in (("op1_toxicity", "toxic"), ("op8_quality", "quality")):
        asked = [(r["predicted"], labels[r["doc_id"]][label]) for r in queries.QUERIES[name](spark, MORE).collect() if r["held_out"] and r["doc_id"] in labels]
        assert len(asked) > 50 and sum(p == y for p, y in asked) >= 0.95 * len(asked), name
    lang = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{MORE}/documents.parquet").select("doc_id", "lang").collect()}
    asked = [(r["lang_pred"], lang[r["doc_id"]]) for r in queries.QUERIES["op4_language_id"](spark, MORE).collect() if r["held_out"] and lang[r["doc_id"]] and r["lang_pred"] != "und"]
    assert len(asked) > 100 and sum(p == y for p, y in asked) >= 0.97 * len(asked)


def test_scores_do_not_depend_on_the_order_of_rows(spark):
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    out = []
    for d in (docs, docs.orderBy(F.desc("doc_id")).repartition(5)):
        rows = toxicity.training_rows(d.select("doc_id", "text"), labels, "toxic", F.lit(True), 1000)
        m = toxicity.fit(rows, toxicity.ToxConfig(chi=3.0))
        out.append((m.hashes.tolist(), m.weights.tolist(), m.bias))
    assert out[0] == out[1] and len(out[0][0]) > 0


CLASH = ("lang_pred", "lang_score", "n_words", "kept", "distance", "f_length", "toxicity", "quality", "n_tokens", "_bitmap", "_hit", "_id", "id", "component", "doc_key", "m_0", "row", "Kept")


@pytest.fixture(scope="module")
def clashing(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [c for c in CLASH if c != "Kept"]
    return docs.select("*", *[F.concat(F.lit(f"{c}-"), F.col("doc_id").cast("string")).alias(c) for c in names])


def test_stages_keep_clashing_columns(spark, clashing):
    import corpus_pipeline as P

    rows = clashing
    for _, stage in P.STAGES[:-1]:
        rows = stage(spark, rows, SF)
        assert rows.columns == clashing.columns
    got = rows.collect()
    assert got and all(r[c] == f"{c}-{r['doc_id']}" for r in got for c in clashing.columns if c in CLASH)


def test_results_take_the_place_of_columns_of_their_names(spark, clashing):
    some = clashing.limit(20)
    assert "lang_pred" in langid.predict(some, langid.fit(some)).columns
    assert quality_rules.judge(some).select("n_words", "kept").dtypes == [("n_words", "bigint"), ("kept", "boolean")]
    assert dict(token_counts.lengths(some).dtypes)["n_tokens"] == "bigint"
    tox = toxicity.fit(some.limit(0).selectExpr("text", "1 as y"))
    assert dict(toxicity.score(some, tox).dtypes)["toxicity"] == "double" and toxicity.score(some, tox).count() == 20
    net = quality_cnn.fit(some.limit(0).selectExpr("text", "1 as y"))
    assert dict(quality_cnn.score(some, net).dtypes)["quality"] == "double" and quality_cnn.score(some, net).count() == 20


def test_token_histogram_by_brute_force(spark):
    enc = token_counts.encoder()
    lengths = [len(enc.encode_ordinary(r["text"] or "")) for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").collect()]
    got = {r["n_tokens"]: r for r in queries.QUERIES["op7_token_counts"](spark, SF).collect()}
    assert set(got) == {*lengths, *token_counts.CONTEXT_LIMITS}
    for n, r in got.items():
        assert (r["n_docs"], r["docs_up_to"], r["docs_at_least"], r["tokens_at_least"], r["truncated_total"]) == (lengths.count(n), sum(x <= n for x in lengths), sum(x >= n for x in lengths), sum(x for x in lengths if x >= n), sum(min(x, n) for x in lengths))


def scatter(x, salt):
    p = mixing.P
    a = ((x or 0) % p * 48271 + salt * 69621 + 11) % p
    b = (a * 16807 + a % 65537 * 40692) % p
    return (b * 39373 + b // 32768) % p


@pytest.mark.parametrize("run", [2, 4096])
def test_block_permutations_by_brute_force(spark, run):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    cfg = mixing.MixConfig(block=500, run=run)
    got = mixing.mix(docs, cfg).collect()
    rows = docs.select("doc_id", "source", mixing.n_tokens().alias("n")).collect()
    for source in {r["source"] for r in rows}:
        mine = [r for r in rows if r["source"] == source]
        total = sum(r["n"] for r in mine)
        blocks = max(1, -(-total // cfg.block))
        block = {r["doc_id"]: scatter(r["doc_id"], cfg.seed) % blocks for r in mine}
        held = Counter()
        for r in mine:
            held[block[r["doc_id"]]] += r["n"]
        out = [r for r in got if r["source"] == source]
        last = max(r["epoch"] for r in out)
        for epoch in range(last + 1):
            order = sorted(held, key=lambda b: (scatter(b, epoch + cfg.seed), b))
            part = [r for r in out if r["epoch"] == epoch]
            assert all(order[r["block_rank"] - 1] == r["block"] == block[r["doc_id"]] for r in part)
            if epoch < last:
                assert sorted(r["doc_id"] for r in part) == sorted(r["doc_id"] for r in mine)


def test_stages_by_brute_force(spark):
    """Language ID, rules and decontamination as stages keep what their operators say, row by row."""
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    ids = lambda df: sorted(r["doc_id"] for r in df.select("doc_id").collect())
    langs = langid.predict(docs, langid.fit(docs)).collect()
    assert ids(P.language_id(spark, docs, SF)) == sorted(r["doc_id"] for r in langs if r["lang_pred"] != "und" and r["lang_score"] >= P.LEAST_POSTERIOR)
    assert ids(P.rules(spark, docs, SF)) == sorted(r["doc_id"] for r in quality_rules.judge(docs).collect() if r["kept"])
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    cfg = decontaminate.TileConfig()
    items = [(r["text"] or "").lower().split() for r in bench.collect()]
    kept = set(ids(P.benchmark_leaks(spark, docs, SF)))
    whole = [" ".join(x) for x in items if len(x) >= cfg.least]
    for r in docs.collect():
        text = " ".join((r["text"] or "").lower().split())
        if any(x in text for x in whole):
            assert r["doc_id"] not in kept  # an item that is there whole covers itself
        elif not any(set(x) & set(text.split()) for x in items):
            assert r["doc_id"] in kept
