"""Exact length histogram: documents by encoded length, and suffix sums over it.

Texts are encoded whole by a public byte-pair vocabulary (its path is a parameter); only lengths
leave the encoder. The histogram has a row for each length that occurs. Suffix sums answer, for
every context limit, how many documents are at least so long, how many tokens they have, and how
many tokens remain if all texts are cut at the limit. Limits that are asked for have a row of their own, with no
documents if no text is so long. A quantile is the least length whose docs_up_to reaches its share of all. Sums run
within ranges of lengths and over the ranges' totals, so no task sees the whole histogram.

Defined results: null and empty texts have length 0; an empty table has an empty histogram, or nothing
but zeros at the limits; repeated rows count each. A column n_tokens of the input gives way to the count.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import free_of, materialise, table

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: Fixed value: the split before merging that belongs to this vocabulary.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
RANGE = 1024
#: Context limits that the query answers besides the lengths that occur.
CONTEXT_LIMITS = tuple(1 << k for k in range(9, 18))


def encoder(path: str = VOCABULARY, pattern: str = PATTERN):
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def lengths(docs: DataFrame, text: str = "text", path: str = VOCABULARY, pattern: str = PATTERN) -> DataFrame:
    """All columns of docs but the text, with n_tokens."""
    keep = [c for c in free_of(docs, ["n_tokens"]).columns if c != text]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, pattern)
        for b in batches:
            n = np.zeros(b.num_rows, dtype=np.int64)
            column = b.column(b.num_columns - 1)
            for i in range(b.num_rows):
                if t := column[i].as_py():
                    n[i] = len(enc.encode_ordinary(t))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(n)], [*keep, "n_tokens"])

    return docs.select(*keep, text).mapInArrow(run, docs.select(*keep, F.lit(0).cast("long").alias("n_tokens")).schema)


def histogram(measured: DataFrame, limits: tuple[int, ...] = ()) -> DataFrame:
    """From rows with n_tokens: n_tokens, n_docs, docs_up_to, docs_at_least, tokens_at_least, truncated_total. The counts
    are written once to the shared folder, so texts are encoded once."""
    h = measured.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n_docs"))
    if limits:
        asked = measured.sparkSession.createDataFrame([(x, 0) for x in sorted(set(limits))], "n_tokens long, n_docs long")
        h = h.union(asked).groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))
    h = materialise(h).withColumn("range", F.floor(F.col("n_tokens") / RANGE))
    later = W.orderBy("range").rowsBetween(1, W.unboundedFollowing)
    all_ = W.orderBy("range").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    totals = h.groupBy("range").agg(F.sum("n_docs").alias("d"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("t"))
    above = totals.select("range", F.coalesce(F.sum("d").over(later), F.lit(0)).alias("d_above"), F.coalesce(F.sum("t").over(later), F.lit(0)).alias("t_above"), F.sum("t").over(all_).alias("t_all"), F.sum("d").over(all_).alias("d_all"))
    own = W.partitionBy("range").orderBy("n_tokens").rowsBetween(0, W.unboundedFollowing)
    h = h.join(above, "range").withColumns({"docs_at_least": F.sum("n_docs").over(own) + F.col("d_above"), "tokens_at_least": F.sum(F.col("n_docs") * F.col("n_tokens")).over(own) + F.col("t_above")})
    return h.select("n_tokens", "n_docs", (F.col("d_all") - F.col("docs_at_least") + F.col("n_docs")).alias("docs_up_to"), "docs_at_least", "tokens_at_least", (F.col("t_all") - F.col("tokens_at_least") + F.col("n_tokens") * F.col("docs_at_least")).alias("truncated_total"))


def truncated_totals(hist: DataFrame, limits: list[int]) -> DataFrame:
    """(context_limit, truncated_total, docs_cut, tokens_cut) for any limits."""
    cut = F.greatest(F.lit(0), F.col("n_tokens") - F.col("context_limit"))
    lim = hist.sparkSession.createDataFrame([(x,) for x in limits], "context_limit long")
    every = hist.select("n_tokens", "n_docs", F.explode(F.array(*[F.lit(x).cast("long") for x in limits])).alias("context_limit"))
    got = every.groupBy("context_limit").agg(F.sum(F.col("n_docs") * F.least("n_tokens", "context_limit")).alias("truncated_total"), F.sum(F.when(cut > 0, F.col("n_docs")).otherwise(0)).alias("docs_cut"), F.sum(F.col("n_docs") * cut).alias("tokens_cut"))
    return lim.join(got, "context_limit", "left").fillna(0)


def quantiles(hist: DataFrame, shares: list[float]) -> DataFrame:
    """(share, n_tokens): the least length that at least this share of documents does not exceed."""
    total = hist.agg(F.sum("n_docs").alias("all"))
    below = hist.crossJoin(F.broadcast(total)).withColumn("up_to", F.col("all") - F.col("docs_at_least") + F.col("n_docs"))
    each = below.select("n_tokens", "up_to", "all", F.explode(F.array(*[F.lit(float(x)) for x in shares])).alias("share"))
    return each.where(F.col("up_to") >= F.ceil(F.col("share") * F.col("all"))).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return histogram(lengths(table(spark, sf_dir, "documents").select("text")), CONTEXT_LIMITS)
