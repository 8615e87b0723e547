"""Attention as joins: plain, with memory of features over one or more segments, with carried outputs; positions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def dot(x, y):
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)


def scores(queries: DataFrame, keys: DataFrame, scale: float = 8.0) -> DataFrame:
    """queries (seg, i, q), keys (seg, j, k): scaled products inside a segment by an equi-join."""
    return queries.join(keys, "seg").withColumn("s", dot(F.col("q"), F.col("k")) / scale)


def attend(queries: DataFrame, keys: DataFrame, scale: float = 8.0) -> DataFrame:
    """(seg, i, d, o): softmax over the keys of the segment, weighted sum of the keys by component."""
    s = scores(queries, keys, scale)
    w = Window.partitionBy("seg", "i")
    s = s.withColumn("e", F.exp(F.col("s") - F.max("s").over(w)))
    s = s.withColumn("a", F.col("e") / F.sum("e").over(w))
    return s.select("seg", "i", "a", F.posexplode("k").alias("d", "x")).groupBy("seg", "i", "d").agg(F.sum(F.col("a") * F.col("x")).alias("o"))


def with_memory(seg: DataFrame, m: int) -> DataFrame:
    """Keys (seg, j, k): every row is offered to its own segment and the m that follow; no range predicate."""
    later = F.explode(F.array(*[F.col("seg") + t for t in range(m + 1)]))
    return seg.select(later.alias("seg"), (F.col("i") + F.lit(0)).alias("j"), F.col("seg").alias("from_seg"), F.col("vec").alias("k"))


def attend_memory(seg: DataFrame, m: int) -> DataFrame:
    q = seg.select("seg", "i", F.col("vec").alias("q"))
    return attend(q, with_memory(seg, m))


def gather(o: DataFrame) -> DataFrame:
    """(seg, i, vec) from (seg, i, d, o)."""
    parts = F.sort_array(F.collect_list(F.struct("d", "o")))
    return o.groupBy("seg", "i").agg(F.transform(parts, lambda x: x["o"]).alias("vec"))


def attend_latent_whole(seg: DataFrame, scale: float = 8.0) -> DataFrame:
    """Carried outputs over all segments in order: the output of one stands before the next. One chain: every output needs
    the one before, so one task holds one segment and one state at a time. A missing segment ends the chain."""
    import numpy as np
    import pandas as pd

    def run(batches):
        now, rows, last, state = None, [], None, None

        def close():
            nonlocal last, state
            q = np.array([v for _, v in rows], float)
            keys = np.concatenate((state, q)) if state is not None and last == now - 1 else q
            a = q @ keys.T / scale
            a = np.exp(a - a.max(axis=1, keepdims=True))
            last, state = now, a / a.sum(axis=1, keepdims=True) @ keys
            return pd.DataFrame({"seg": now, "i": [i for i, _ in rows], "o": list(state)})

        for b in batches:
            for s, i, v in zip(b["seg"], b["i"], b["vec"], strict=True):
                if s != now and rows:
                    yield close()
                    rows = []
                now = s
                rows.append((i, v))
        if rows:
            yield close()

    one = seg.select(F.col("seg").cast("long").alias("seg"), F.col("i").cast("long").alias("i"), "vec").repartition(1).sortWithinPartitions("seg", "i")
    return one.mapInPandas(run, "seg long, i long, o array<double>").select("seg", "i", F.posexplode("o").alias("d", "o"))


def sinusoid_df(spark: SparkSession, n: int = 13, d: int = 64, freq_base: float = 10000.0, first: int = 0) -> DataFrame:
    """(i, d, g): sines on even components, cosines on odd ones."""
    grid = spark.range(first, first + n).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(d - 1))).alias("d"))
    angle = F.col("i") / F.pow(F.lit(freq_base), F.expr("(d div 2) * 2") / d)
    return grid.withColumn("g", F.when(F.col("d") % 2 == 0, F.sin(angle)).otherwise(F.cos(angle)))


def position_vectors(spark: SparkSession, n: int, d: int, first: int = 0) -> DataFrame:
    parts = F.sort_array(F.collect_list(F.struct("d", "g")))
    return sinusoid_df(spark, n, d, first=first).groupBy("i").agg(F.transform(parts, lambda x: x["g"]).alias("g"))


def add(x, y):
    return F.zip_with(x, y, lambda a, b: a + b)


def scores_absolute(seg: DataFrame, n: int = 13, d: int = 64) -> DataFrame:
    """(seg, i, j, a) with absolute codes added to both sides."""
    g = F.broadcast(position_vectors(seg.sparkSession, n, d))  # n rows
    coded = seg.join(g, "i").select("seg", "i", add("vec", "g").alias("x"))
    keys = coded.select("seg", F.col("i").alias("j"), F.col("x").alias("k"))
    return scores(coded.select("seg", "i", F.col("x").alias("q")), keys, 1.0).select("seg", "i", "j", F.col("s").alias("a"))


def scores_relative(seg: DataFrame, n: int = 13, d: int = 64, u: float = 0.125, v: float = -0.25) -> DataFrame:
    """(seg, i, j, a): content with bias u, offset code i - j with bias v; the offset table has 2n - 1 rows."""
    g = position_vectors(seg.sparkSession, 2 * n - 1, d, first=-(n - 1)).withColumnRenamed("i", "delta")
    pairs = seg.select("seg", "i", F.col("vec").alias("q")).join(seg.select("seg", F.col("i").alias("j"), F.col("vec").alias("k")), "seg")
    pairs = pairs.withColumn("delta", F.col("i") - F.col("j")).join(F.broadcast(g), "delta")
    shift = lambda x, c: F.transform(x, lambda a: a + F.lit(c))
    a = dot(shift(F.col("q"), u), F.col("k")) + dot(shift(F.col("q"), v), F.col("g"))
    return pairs.select("seg", "i", "j", a.alias("a"))


def layer_norm_df(seg: DataFrame, eps: float = 1e-5) -> DataFrame:
    rows = seg.select("seg", "i", F.posexplode("vec").alias("d", "x"))
    w = Window.partitionBy("seg", "i")
    return rows.withColumn("y", (F.col("x") - F.avg("x").over(w)) / F.sqrt(F.var_pop("x").over(w) + eps))
