"""ra_join_overlap on sizes that very many parts share: equal ranges are joined once."""

from pyspark.sql import functions as F

from rangebound import queries as q


def test_many_parts_of_one_size(spark, tmp_path):
    n = 100_000  # as pairs, 10^10
    spark.range(n).select(F.col("id").alias("p_partkey"), F.lit(7).alias("p_size")).write.parquet(f"{tmp_path}/part.parquet")
    got = q.QUERIES["ra_join_overlap"](spark, str(tmp_path))
    assert got.agg(F.sum("_m_sg"), F.max("_m_ub") <= n * n).first()[:] == (n * n, True)
