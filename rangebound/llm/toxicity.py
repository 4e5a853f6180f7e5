"""Toxicity: a logistic classifier regularised by counterfactual identity swaps.

Each labelled text that names a group is paired with copies in which every identity term is swapped
for another of its category, a copy for each other term. Training adds to the log loss a penalty on the squared
difference of the two logits, also for a copy that names none, so that naming a group does not move the score by itself, and an
L1 penalty, so that words without evidence weigh nothing however long a text is. Features are
hashed words and word beginnings, present or absent.

Training takes at most `sample` labelled rows. Their features are counted on the executors, over whole texts; the
driver gets the `keep` most telling ones, and then only these of each row. Defined results: null and empty texts get the
bias alone; with no labelled row the score is 0; labels given more than once for a document count once, as their
maximum; a column named toxicity gives way to the score.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import bounded_sample, fold, free_of, table

#: Terms that name groups, by category and language; a term is swapped for the others of its category. No term is in two.
IDENTITY: dict[str, tuple[str, ...]] = {
    "gender": ("women", "men", "woman", "man", "girls", "boys", "transgender"),
    "religion": ("muslims", "christians", "jews", "hindus", "buddhists", "sikhs", "atheists"),
    "faith": ("muslim", "christian", "jewish", "hindu", "buddhist", "sikh", "atheist"),
    "origin": ("african", "asian", "european", "arab", "american", "mexican", "indian"),
    "colour": ("black", "white", "brown"),
    "orientation": ("gay", "straight", "lesbian", "bisexual", "heterosexual"),
    "status": ("immigrants", "refugees", "natives", "foreigners"),
    "ability": ("disabled", "blind", "deaf", "autistic"),
    "gender_de": ("frauen", "männer", "frau", "mann", "mädchen", "jungen"),
    "religion_de": ("muslime", "christen", "juden", "buddhisten", "atheisten"),
    "faith_de": ("muslimische", "christliche", "jüdische", "hinduistische", "buddhistische", "atheistische"),
    "origin_de": ("afrikanische", "asiatische", "europäische", "arabische", "amerikanische", "mexikanische", "indische"),
    "colour_de": ("schwarze", "weiße", "braune"),
    "orientation_de": ("schwule", "lesbische", "bisexuelle", "heterosexuelle"),
    "status_de": ("einwanderer", "flüchtlinge", "einheimische", "ausländer"),
    "ability_de": ("behinderte", "blinde", "gehörlose", "autistische"),
    "gender_fr": ("femmes", "hommes", "femme", "homme", "filles", "garçons"),
    "religion_fr": ("musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées"),
    "faith_fr": ("musulman", "chrétien", "juif", "hindou", "bouddhiste", "athée"),
    "origin_fr": ("africain", "asiatique", "européen", "arabe", "américain", "mexicain", "indien"),
    "colour_fr": ("noirs", "blancs", "bruns"),
    "orientation_fr": ("homosexuels", "lesbiennes", "bisexuels", "hétérosexuels"),
    "status_fr": ("immigrés", "réfugiés", "autochtones", "étrangers"),
    "ability_fr": ("handicapés", "aveugles", "sourds", "autistes"),
    "gender_es": ("mujeres", "hombres", "mujer", "hombre", "niñas", "niños"),
    "religion_es": ("musulmanes", "cristianos", "judíos", "hindúes", "budistas", "ateos"),
    "faith_es": ("musulmán", "cristiano", "judío", "hindú", "budista", "ateo"),
    "origin_es": ("africano", "asiático", "europeo", "árabe", "americano", "mexicano", "indio"),
    "colour_es": ("negros", "blancos", "morenos"),
    "orientation_es": ("homosexuales", "lesbianas", "bisexuales", "heterosexuales"),
    "status_es": ("inmigrantes", "refugiados", "nativos", "extranjeros"),
    "ability_es": ("discapacitados", "ciegos", "sordos", "autistas"),
}


@dataclass(frozen=True)
class ToxConfig:
    """sample: most labelled rows; prefixes: lengths in bytes of word beginnings; min_docs: a
    feature needs so many training documents; keep: most features, by chi-square; pair: weight of
    the counterfactual penalty; l1 (over the root of the rows), l2: other penalties; chi: least
    chi-square of a feature; steps, rate: gradient steps."""

    sample: int = 12_000
    prefixes: tuple[int, ...] = (4, 5, 6)
    min_docs: int = 3
    keep: int = 4000
    pair: float = 1.0
    l1: float = 0.003
    chi: float = 20.0
    l2: float = 1e-6
    steps: int = 400
    rate: float = 0.3


def _features(data: np.ndarray, offsets: np.ndarray, cfg: ToxConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature hashes, the document of each, and the hashes of whole words alone (first block)."""
    s, e, counts = K.words(data, offsets, K.ALNUM_WORDS)
    whole = K.hash_words(data, s, e)
    doc = np.repeat(np.arange(len(counts)), counts)
    out, docs = [whole], [doc]
    for p in cfg.prefixes:
        longer = e - s > p
        out.append(K.mix(K.hash_words(data, s[longer], s[longer] + p) + np.uint64(p)))
        docs.append(doc[longer])
    return np.concatenate(out), np.concatenate(docs), whole


def _swaps(cfg: ToxConfig) -> dict[int, tuple[np.ndarray, list[np.ndarray]]]:
    """Hash of each identity term -> all its features, and those of each term that may replace it."""
    out = {}
    for terms in IDENTITY.values():
        feats = []
        for t in terms:
            data = np.frombuffer(t.encode(), dtype=np.uint8)
            feats.append(_features(data, np.array([0, len(data)]), cfg)[0])
        for i, x in enumerate(feats):
            out[int(x[0])] = (x, [y for j, y in enumerate(feats) if j != i])
    return out


def training_rows(docs: DataFrame, labels: DataFrame, label: str, keep: Column, n: int) -> DataFrame:
    """(text, y) of at most n labelled documents, taken by a hash of the id; `keep` holds of the
    ids that may be learned from. The picked labels are at most n rows, so they are broadcast."""
    picked = bounded_sample(labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).where(keep).groupBy("doc_id").agg(F.max(label).alias("y")), F.col("doc_id"), n)
    return docs.join(F.broadcast(picked), "doc_id").where("text is not null").select("text", F.col("y").cast("int").alias("y"))


@dataclass
class ToxModel:
    hashes: np.ndarray  # sorted
    weights: np.ndarray
    bias: float
    cfg: ToxConfig

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        n = len(offsets) - 1
        z = np.full(n, self.bias)
        if len(self.hashes):
            h, doc, _ = _features(data, offsets, self.cfg)
            hit = self._maybe[(h & np.uint64(0xFFFF)).astype(np.int64)]
            h, doc = h[hit], doc[hit]
            at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
            ok = self.hashes[at] == h
            pair = np.unique(doc[ok] * len(self.hashes) + at[ok])
            z += np.bincount(pair // len(self.hashes), weights=self.weights[pair % len(self.hashes)], minlength=n)
        return 1 / (1 + np.exp(-np.clip(z, -500, 500)))

    def __post_init__(self) -> None:
        self._maybe = np.zeros(1 << 16, dtype=bool)
        self._maybe[(self.hashes & np.uint64(0xFFFF)).astype(np.int64)] = True


def _documents(column: pa.Array, cfg: ToxConfig) -> Iterator[tuple[int, np.ndarray]]:
    """(row, distinct features) of each text."""
    for i, j, data, off in K.slices(K.lowered(column)):
        h, doc, _ = _features(data, off, cfg)
        order = np.argsort(doc, kind="stable")
        h, cut = h[order], np.searchsorted(doc[order], np.arange(j - i + 1))
        for k in range(j - i):
            yield i + k, np.unique(h[cut[k] : cut[k + 1]])


def vocabulary(rows: DataFrame, n: int, pos: int, cfg: ToxConfig) -> np.ndarray:
    """Sorted features: the cfg.keep of greatest chi-square among n rows, pos of them positive, and those of all terms."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            y = b.column(1).to_numpy().astype(np.int64)
            got = [(x, np.full(len(x), y[i])) for i, x in _documents(b.column(0), cfg)]
            every, inv = np.unique(np.concatenate([np.zeros(0, np.uint64), *[x for x, _ in got]]), return_inverse=True)
            ones = np.concatenate([np.zeros(0, np.int64), *[t for _, t in got]])
            df, dp = np.bincount(inv, minlength=len(every)), np.bincount(inv, weights=ones, minlength=len(every)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(every.view(np.int64)), pa.array(df.astype(np.int64)), pa.array(dp)], ["f", "df", "dp"])

    ids = np.unique(np.concatenate([x[0] for x in _swaps(cfg).values()]))
    seen = rows.mapInArrow(count, "f long, df long, dp long").groupBy("f").agg(F.sum("df").cast("double").alias("df"), F.sum("dp").cast("double").alias("dp"))
    a, b = F.col("dp"), F.col("df") - F.col("dp")
    c, d = float(pos) - F.col("dp"), float(n - pos) - (F.col("df") - F.col("dp"))
    chi = float(n) * (a * d - b * c) * (a * d - b * c) / F.greatest((a + b) * (c + d) * (a + c) * (b + d), F.lit(1.0))
    best = seen.where(F.col("df") >= cfg.min_docs).withColumn("chi", chi).where(F.col("chi") >= cfg.chi).orderBy(F.desc("chi"), "f").limit(cfg.keep).select("f").collect()
    return np.union1d(np.array([r["f"] for r in best], dtype=np.int64).view(np.uint64), ids)


def fit(rows: DataFrame, cfg: ToxConfig = ToxConfig()) -> ToxModel:
    """Learns from a bounded frame of (text, y)."""
    sizes = rows.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("y"), F.lit(0)).alias("pos")).first()
    n, pos = sizes["n"], sizes["pos"]
    if not n or pos in (0, n):
        return ToxModel(np.zeros(0, np.uint64), np.zeros(0), 500.0 if n and pos else -500.0, cfg)
    vocab = vocabulary(rows, n, pos, cfg)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        swaps = _swaps(cfg)
        ids = np.array(sorted(swaps), dtype=np.uint64)
        known = lambda x: np.flatnonzero(np.isin(vocab, x)).astype(np.int32).tobytes()
        for b in batches:
            y = b.column(1).to_pylist()
            ys, feats, twins = [], [], []
            for i, own in _documents(b.column(0), cfg):
                named = own[np.isin(own, ids)].tolist()
                more = []
                if named:
                    # The t-th twin swaps every term named in the text for the t-th other of its category.
                    rest = own[~np.isin(own, np.concatenate([swaps[x][0] for x in named]))]
                    more = [known(np.concatenate([rest, *[swaps[x][1][t % len(swaps[x][1])] for x in named]])) for t in range(max(len(swaps[x][1]) for x in named))]
                    more.append(known(rest))  # and one twin names no group at all
                ys.append(y[i])
                feats.append(known(own))
                twins.append(more)
            yield pa.RecordBatch.from_arrays([pa.array(ys, pa.int32()), pa.array(feats, pa.binary()), pa.array(twins, pa.list_(pa.binary()))], ["y", "f", "twins"])

    got = rows.mapInArrow(encode, "y int, f binary, twins array<binary>").collect()
    got.sort(key=lambda r: (r["y"], bytes(r["f"]), [bytes(t) for t in r["twins"]]))  # the order of arrival differs from run to run
    read = lambda x: np.frombuffer(bytes(x), dtype=np.int32)
    return train([read(r["f"]) for r in got], np.array([float(r["y"]) for r in got]), [[read(t) for t in r["twins"]] for r in got], vocab, cfg)


def _sparse(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.repeat(np.arange(len(docs)), [len(x) for x in docs]), np.concatenate([*docs, np.zeros(0, np.int32)]).astype(np.int64)


def train(docs: list[np.ndarray], y: np.ndarray, twins: list[list[np.ndarray]], vocab: np.ndarray, cfg: ToxConfig) -> ToxModel:
    """Proximal gradient descent on log loss + pair * squared logit gap + L2, with an L1 step. docs, twins: places in vocab."""
    n, pos = len(docs), float(y.sum())
    r, col = _sparse(docs)
    pair_of = np.repeat(np.arange(n), [len(t) for t in twins])
    tr, tc = _sparse([t for ts in twins for t in ts])
    m = len(pair_of)
    w, bias = np.zeros(len(vocab)), float(np.log(pos / (n - pos)))
    share = np.where(y > 0, 0.5 / pos, 0.5 / (n - pos))  # classes weigh alike
    g2, gb = np.full(len(w), 1e-8), 1e-8
    l1 = cfg.l1 / np.sqrt(n)
    for _ in range(cfg.steps):
        z = np.bincount(r, weights=w[col], minlength=n) + bias
        p = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
        gz = (p - y) * share
        gw = np.zeros(len(w))
        if m:
            gap = z[pair_of] - (np.bincount(tr, weights=w[tc], minlength=m) + bias)
            gp = 2 * cfg.pair * gap / m
            gw -= np.bincount(tc, weights=gp[tr], minlength=len(w))
            gz = gz + np.bincount(pair_of, weights=gp, minlength=n)
        gw += np.bincount(col, weights=gz[r], minlength=len(w)) + cfg.l2 * w
        g2 += gw**2
        gb += float(gz.sum()) ** 2
        step = cfg.rate / np.sqrt(g2)
        w = w - step * gw
        w = np.sign(w) * np.maximum(np.abs(w) - step * l1, 0)
        bias -= cfg.rate * float(gz.sum()) / np.sqrt(gb)
    live = w != 0
    return ToxModel(vocab[live], w[live], bias, cfg)


def score(docs: DataFrame, model: ToxModel, text: str = "text") -> DataFrame:
    """All columns of docs, with toxicity (0 to 1)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = free_of(docs, ["toxicity"])
    fields = docs.schema.fieldNames()
    where = fields.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = np.zeros(b.num_rows)
            for i, j, data, off in K.slices(K.lowered(b.column(where))):
                out[i:j] = shared.value.score(data, off)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out)], [*fields, "toxicity"])

    return docs.mapInArrow(run, docs.select("*", F.lit(0.0).alias("toxicity")).schema)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    cfg = ToxConfig()
    model = fit(training_rows(docs, table(spark, sf_dir, "labels"), "toxic", fold("doc_id", 5) != 0, cfg.sample), cfg)
    out = score(docs, model)
    return out.select("doc_id", F.coalesce(fold("doc_id", 5) == 0, F.lit(False)).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"))
