"""Mixing sources by temperature, realised as budgeted block permutations.

A source's weight is its token share to the power a, normalised. The exponent is bisected between 1 (shares
as they are) and 0 (all sources alike) until the mix has the target entropy, or as near as the
repetition limit allows: no source is read more often than that. A source's budget is its weight of the
token budget; it is met by whole passes over the source and a part of one. Each pass permutes the
source's blocks, and the documents within each block; the part is the first blocks of its
permutation, and of the block that crosses the budget, the first documents that fit.

All of it is DataFrame expressions. Per source there is one row, per block one; a hot source
is many blocks, never one task. Defined results: a null source is a source of its own; a text
without words costs nothing and is taken in each whole pass; sources without tokens have weight 0
and are read once; an empty table gives no rows; repeated rows count each and tie, in any order; a column to be carried
must not have the name of a result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise, table
from .quality_rules import SPACE, WORD_GAP

P = 2147483647


@dataclass(frozen=True)
class MixConfig:
    """entropy: wanted, as a share of the most there can be (None: only the limit counts); repeats:
    most passes over a source; budget: tokens, as a multiple of all there are; block: tokens of a
    block, about; run: blocks that are ranked in one task, about; seed: of the permutations; rounds: of the bisection."""

    entropy: float | None = 0.95
    repeats: float = 4.0
    budget: float = 1.0
    block: int = 200_000
    run: int = 4096
    seed: int = 1
    rounds: int = 50


def scatter(x: Column, salt: Column) -> Column:
    """A hash in whole-number arithmetic that any SQL engine repeats; below 2^31 - 1."""
    a = F.pmod(F.pmod(F.coalesce(x.cast("long"), F.lit(0)), F.lit(P)) * 48271 + salt.cast("long") * 69621 + 11, F.lit(P))
    b = F.pmod(a * 16807 + F.pmod(a, F.lit(65537)) * 40692, F.lit(P))
    return F.pmod(b * 39373 + F.floor(b / 32768), F.lit(P)).cast("long")


def n_tokens(text: str = "text") -> Column:
    """Words of a text, the measure of its tokens here."""
    t = F.btrim(F.coalesce(F.col(text), F.lit("")), F.lit(SPACE))
    return F.when(t == "", 0).otherwise(F.size(F.split(t, WORD_GAP))).cast("long")


def weights(sizes: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """sizes: (source, tokens), a row for each source. Adds exponent, weight, target, passes and rest."""
    one = sizes.where("tokens > 0").agg(F.sort_array(F.collect_list(F.log(F.col("tokens").cast("double")))).alias("logs"), F.sum("tokens").alias("all"))
    one = one.withColumn("top", F.array_max("logs"))
    add = lambda arr: F.aggregate(arr, F.lit(0.0), lambda s, x: s + x)
    w = lambda a: F.transform("logs", lambda x: F.exp(a * (x - F.col("top"))))
    z = lambda a: add(w(a))
    # H = ln z - sum(w ln w) / z
    entropy = lambda a: F.log(z(a)) - add(F.transform("logs", lambda x: F.exp(a * (x - F.col("top"))) * a * (x - F.col("top")))) / z(a)
    # Most passes: the smallest source's, budget * weight / tokens.
    passes = lambda a: cfg.budget * F.col("all") * F.exp(a * (F.array_min("logs") - F.col("top"))) / z(a) / F.exp(F.array_min("logs"))
    fits = lambda a: (passes(a) <= cfg.repeats) & (F.lit(True) if cfg.entropy is None else (entropy(a) <= cfg.entropy * F.log(F.size("logs").cast("double"))))

    def halve(acc: Column, _: Column) -> Column:
        mid = (acc["lo"] + acc["hi"]) / 2
        ok = fits(mid)
        return F.struct(F.when(ok, acc["lo"]).otherwise(mid).alias("lo"), F.when(ok, mid).otherwise(acc["hi"]).alias("hi"))

    found = F.aggregate(F.sequence(F.lit(1), F.lit(cfg.rounds)), F.struct(F.lit(0.0).alias("lo"), F.lit(1.0).alias("hi")), halve, lambda acc: acc["hi"])
    one = one.select("all", "top", F.when(F.size("logs") == 0, F.lit(1.0)).otherwise(found).alias("exponent"), "logs").select("all", "top", "exponent", z(F.col("exponent")).alias("z"))
    got = sizes.crossJoin(F.broadcast(one))  # one row
    got = got.withColumn("weight", F.when(F.col("tokens") > 0, F.exp(F.col("exponent") * (F.log(F.col("tokens").cast("double")) - F.col("top"))) / F.col("z")).otherwise(0.0))
    got = got.withColumn("target", F.floor(cfg.budget * F.col("all") * F.col("weight") + 1e-6).cast("long"))
    got = got.withColumn("passes", F.when(F.col("tokens") > 0, F.floor(F.col("target") / F.col("tokens"))).otherwise(1).cast("int"))
    return got.withColumn("rest", F.when(F.col("tokens") > 0, F.col("target") - F.col("passes") * F.col("tokens")).otherwise(0)).drop("all", "top", "z")


def mix(docs: DataFrame, cfg: MixConfig = MixConfig(), key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """Rows (doc_id, source, n_tokens, what is in carry, epoch, block, block_rank, doc_key): a document once for each pass that
    takes it. Read in order of epoch, block_rank, doc_key, id, a source is a permutation of blocks in each pass."""
    slim = docs.select(F.col(key).alias("doc_id"), F.col("source"), n_tokens(text).alias("n_tokens"), *carry)
    slim = materialise(slim.withColumn("_s", F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("-"))))
    sizes = slim.groupBy("_s").agg(F.sum("n_tokens").alias("tokens"))
    plan = materialise(weights(sizes, cfg).withColumn("blocks", F.greatest(F.lit(1), F.ceil(F.col("tokens") / cfg.block)).cast("int")))
    # One row for each source: Spark broadcasts it while it is small.
    placed = slim.join(plan.select("_s", "blocks", "passes", "rest"), "_s")
    placed = placed.withColumn("block", F.pmod(scatter(F.col("doc_id"), F.lit(cfg.seed)), F.col("blocks")).cast("int"))
    held = placed.groupBy("_s", "block").agg(F.sum("n_tokens").alias("t"), F.first("passes").alias("passes"), F.first("rest").alias("rest"), F.first("blocks").alias("blocks"))
    turns = held.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("passes"))))
    # A permutation's keys are spread evenly, so stretches of them hold about cfg.run blocks each: ranks and sums run within
    # a stretch, and start from the totals of those before.
    turns = turns.withColumn("key", scatter(F.col("block"), F.col("epoch") + cfg.seed)).withColumn("stretch", F.floor(F.col("key") / F.ceil(F.lit(P) / F.ceil(F.col("blocks") / cfg.run))))
    totals = turns.groupBy("_s", "epoch", "stretch").agg(F.count(F.lit(1)).alias("n"), F.sum("t").alias("sum"))
    earlier = W.partitionBy("_s", "epoch").orderBy("stretch").rowsBetween(W.unboundedPreceding, -1)
    totals = totals.select("_s", "epoch", "stretch", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("n0"), F.coalesce(F.sum("sum").over(earlier), F.lit(0)).alias("t0"))
    order = W.partitionBy("_s", "epoch", "stretch").orderBy("key", "block")
    turns = turns.withColumn("own", F.row_number().over(order)).withColumn("run", F.sum("t").over(order.rowsBetween(W.unboundedPreceding, 0)))
    turns = turns.join(totals, ["_s", "epoch", "stretch"]).withColumns({"block_rank": (F.col("n0") + F.col("own")).cast("int"), "before": F.col("t0") + F.col("run") - F.col("t")})
    part = F.col("epoch") == F.col("passes")
    turns = turns.withColumn("room", F.when(part, F.col("rest") - F.col("before"))).where(~part | (F.col("room") > 0))
    turns = materialise(turns.select("_s", "block", "epoch", "block_rank", "t", "room"))
    out = ["doc_id", "source", "n_tokens", *carry, "epoch", "block", "block_rank", "doc_key"]
    both = placed.join(turns, ["_s", "block"]).withColumn("doc_key", scatter(F.col("doc_id"), F.col("epoch") + cfg.seed + 7919))
    whole = both.where(F.col("room").isNull() | (F.col("room") >= F.col("t")))
    crossing = both.where(F.col("room") < F.col("t"))  # one block of each source at most
    crossing = crossing.withColumn("run", F.sum("n_tokens").over(W.partitionBy("_s", "block").orderBy("doc_key", "doc_id", "n_tokens").rowsBetween(W.unboundedPreceding, 0)))
    return whole.select(*out).union(crossing.where(F.col("run") <= F.col("room")).select(*out))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))
