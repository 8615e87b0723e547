"""Cost and accuracy measures as expressions and small frames; SQL functions and table functions."""

from __future__ import annotations

import time
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def split_of(seq_id: Column) -> Column:
    """70 / 20 / 10 by id."""
    k = F.pmod(seq_id, F.lit(10))
    return F.when(k < 7, "train").when(k < 9, "val").otherwise("test")


def bpb(container: DataFrame) -> DataFrame:
    """Compressed bits a base, by corpus and codec."""
    return container.groupBy("corpus", "codec").agg(
        F.sum("n_bases").cast("long").alias("n_bases"), F.sum("n_bits").alias("n_bits"), (F.sum("n_bits") / F.sum("n_bases")).alias("bpb")
    )


def bpb_with_model(container: DataFrame, params: int, bits_per_weight: int = 32) -> DataFrame:
    return bpb(container).withColumn("bpb_with_model", (F.col("n_bits") + params * bits_per_weight) / F.col("n_bases"))


def ratio(container: DataFrame, bits_per_base: int = 8) -> DataFrame:
    """Original size over compressed size, one byte a base."""
    return bpb(container).withColumn("ratio", F.lit(float(bits_per_base)) / F.col("bpb"))


def fragment_overhead(container: DataFrame, context: int = 64) -> DataFrame:
    return container.groupBy("corpus").agg((F.count("*") * 2 * context / F.sum("n_bases")).alias("overhead"))


def relative(results: DataFrame, baseline: str) -> DataFrame:
    """bpb of each method over that of the baseline, and the saving."""
    b = results.where(F.col("method") == baseline).select("corpus", F.col("bpb").alias("base_bpb"), F.col("seconds").alias("base_s"))
    j = results.join(b, "corpus")
    return j.select("corpus", "method", (F.col("bpb") / F.col("base_bpb")).alias("ratio"), (1 - F.col("bpb") / F.col("base_bpb")).alias("saving"), (F.col("base_s") / F.col("seconds")).alias("speedup"))


def generalisation(dedicated: DataFrame, hybrid: DataFrame) -> DataFrame:
    """bpb of hybrid training less that of dedicated training."""
    h = hybrid.select("corpus", "method", F.col("bpb").alias("hybrid"))
    return dedicated.join(h, ["corpus", "method"]).withColumn("gap", F.col("hybrid") - F.col("bpb"))


def throughput(results: DataFrame) -> DataFrame:
    return results.withColumn("bases_per_s", F.col("n_bases") / F.col("seconds"))


def ideal_bits(rows: DataFrame) -> DataFrame:
    """Sum of -log2 p of rows (seq_id, p): code length without coding."""
    return rows.groupBy("seq_id").agg(F.sum(-F.log2("p")).alias("bits"), F.count("*").alias("n"))


def cross_entropy(rows: DataFrame) -> DataFrame:
    """Mean loss a symbol, in bits and in nats."""
    return rows.agg(F.avg(-F.log2("p")).alias("bits"), F.avg(-F.log("p")).alias("nats"))


def lossless(before: DataFrame, after: DataFrame) -> DataFrame:
    d = lambda df, n: df.select("seq_id", F.md5(F.col("bases").cast("binary")).alias(n))
    return d(before, "a").join(d(after, "b"), "seq_id", "full").select("seq_id", F.col("a").eqNullSafe(F.col("b")).alias("lossless"))


def timed(fn: Callable[[], object]) -> tuple[object, float]:
    """Result and wall seconds."""
    t = time.perf_counter()
    return fn(), time.perf_counter() - t


@udtf(returnType="pos bigint, kmer string")
class Kmers:
    def eval(self, bases: str, k: int):
        for i in range(len(bases) - k + 1):
            yield i, bases[i : i + k]


@udtf(returnType="group_id int, start bigint, bases string")
class Groups:
    def eval(self, bases: str, size: int):
        for g, i in enumerate(range(0, len(bases), size)):
            yield g, i, bases[i : i + size]


@udtf(returnType="pos bigint, base string")
class Bases:
    def eval(self, bases: str):
        yield from enumerate(bases)


def register(spark: SparkSession) -> None:
    """Installs the functions, so that SQL can call them."""
    spark.udtf.register("kmers", Kmers)
    spark.udtf.register("base_groups", Groups)
    spark.udtf.register("explode_bases", Bases)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION raw_bits(bases STRING) RETURNS BIGINT RETURN 2 * length(replace(bases, 'N', ''))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bits_per_base(bits BIGINT, n BIGINT) RETURNS DOUBLE RETURN bits / n")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rev_comp(bases STRING) RETURNS STRING RETURN reverse(translate(bases, 'AGCTN', 'TCGAN'))")


def udtf_kmers(df: DataFrame, k: int) -> DataFrame:
    spark = df.sparkSession
    register(spark)
    df.createOrReplaceTempView("kmer_source")
    return spark.sql(f"SELECT s.seq_id, t.pos, t.kmer FROM kmer_source s, LATERAL kmers(s.bases, {k}) t")


def udaf_bits(rows: DataFrame) -> DataFrame:
    """Order-0 entropy of each sequence by a grouped-aggregate function."""
    @F.pandas_udf("double")
    def bits(codes: pd.Series) -> float:
        import numpy as np

        n = codes.value_counts().to_numpy()
        return float(-(n * np.log2(n / n.sum())).sum() / n.sum())

    return rows.groupBy("seq_id").agg(bits("code").alias("bits")).select("seq_id", F.round("bits", 6).alias("bits"))


def sql_bpb(spark: SparkSession, df: DataFrame) -> DataFrame:
    register(spark)
    df.createOrReplaceTempView("sequences")
    return spark.sql("SELECT seq_id, CAST(length(bases) AS BIGINT) AS n_bases, round(bits_per_base(raw_bits(bases), length(bases)), 6) AS raw_bpb, rev_comp(bases) AS rc FROM sequences")
