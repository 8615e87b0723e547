"""Published figures of the compared methods, as rows, and what follows from them.

Fixed values: (method, human bpb, human seconds, fish bpb, fish seconds); 0.0100 stands for the misprinted 0.0010.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROWS = [
    ("deflate", 1.4232, 0.15, 2.4460, 0.62),
    ("lzma", 0.0910, 0.38, 1.2371, 3.43),
    ("bwt", 0.3558, 0.22, 2.0303, 0.44),
    ("context", 1.5572, 1.56, 1.4119, 5.44),
    ("field_aware", 0.1360, 2.36, 1.2869, 1.87),
    ("conv_lstm", 0.0336, 2993.0, 1.3591, 7994.0),
    ("conv_bilstm", 0.0145, 3407.0, 0.7036, 8794.0),
    ("carry", 0.0097, 4938.0, 0.6587, 13977.0),
    ("byte", 0.0075, 5074.0, 0.4085, 13747.0),
    ("multilevel", 0.0100, 684.0, 0.4794, 1809.0),
]
HUMAN_BASES, FISH_BASES = 1_691_705, 4_564_117


def published(spark: SparkSession) -> DataFrame:
    rows = [(m, c, b, s) for m, hb, hs, fb, fs in ROWS for c, b, s in (("human", hb, hs), ("fish", fb, fs))]
    return spark.createDataFrame(rows, "method string, corpus string, bpb double, seconds double")


def relative(spark: SparkSession) -> DataFrame:
    """Against the strongest earlier learned coder and the ungrouped carry coder."""
    p = published(spark)
    a = p.where("method = 'conv_bilstm'").select("corpus", F.col("bpb").alias("b"))
    t = p.where("method = 'carry'").select("corpus", F.col("seconds").alias("t"))
    n = F.when(F.col("corpus") == "human", HUMAN_BASES).otherwise(FISH_BASES)
    return p.join(a, "corpus").join(t, "corpus").select(
        "method", "corpus", F.round(F.col("bpb") / F.col("b"), 6).alias("ratio"), F.round(F.col("t") / F.col("seconds"), 6).alias("speedup"), F.round(n / F.col("seconds"), 3).alias("bases_per_s")
    )


_VALUES = ", ".join(f"('{m}', '{c}', {b}::DOUBLE, {s}::DOUBLE)" for m, hb, hs, fb, fs in ROWS for c, b, s in (("human", hb, hs), ("fish", fb, fs)))
RELATIVE_SQL = f"""WITH p AS (SELECT * FROM (VALUES {_VALUES}) t(method, corpus, bpb, seconds)), a AS (SELECT corpus, bpb AS b FROM p WHERE method = 'conv_bilstm'), t AS (SELECT corpus, seconds AS t FROM p WHERE method = 'carry')
  SELECT method, corpus, round(bpb / b, 6) AS ratio, round(t / seconds, 6) AS speedup, round(CASE corpus WHEN 'human' THEN {HUMAN_BASES} ELSE {FISH_BASES} END / seconds, 3) AS bases_per_s FROM p JOIN a USING (corpus) JOIN t USING (corpus)"""
