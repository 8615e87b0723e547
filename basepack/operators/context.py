"""Statistical baselines as windows: adaptive and static context models, competition and mixing."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def with_context(rows: DataFrame, k: int, name: str = "ctx") -> DataFrame:
    """The k codes before each base as one number; null where there are fewer."""
    w = Window.partitionBy("seq_id").orderBy("pos")
    total = F.lit(0).cast("long")
    for i in range(1, k + 1):
        total = total + F.lag("code", i).over(w) * 5 ** (i - 1)
    return rows.withColumn(name, total)


def adaptive(rows: DataFrame, k: int, alpha: float = 1.0, symbols: int = 5) -> DataFrame:
    """rows plus bits: cost of each base under counts of what came before in its sequence; one exchange for all windows."""
    d = with_context(rows, k).where("ctx IS NOT NULL")
    before = lambda *keys: Window.partitionBy("seq_id", *keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    hit, seen = F.count("*").over(before("ctx", "code")), F.count("*").over(before("ctx"))
    return d.withColumn("p", (hit + alpha) / (seen + alpha * symbols)).withColumn("bits", -F.log2("p"))


def entropy(rows: DataFrame, k: int) -> DataFrame:
    """(n, bits): empirical entropy of order k over all rows."""
    counts = with_context(rows, k).where("ctx IS NOT NULL").groupBy("ctx", "code").agg(F.count("*").alias("n"))
    totals = counts.groupBy("ctx").agg(F.sum("n").alias("t"))
    j = counts.join(totals, "ctx")
    return j.agg(F.sum("n").alias("n"), (F.sum(-F.col("n") * F.log2(F.col("n") / F.col("t"))) / F.sum("n")).alias("h"))


def competing(rows: DataFrame, orders=(0, 1, 2, 3)) -> DataFrame:
    """(seq_id, order, bits) of the order that serves each sequence best; ties to the lower order."""
    parts = [adaptive(rows, k).groupBy("seq_id").agg((F.sum("bits") / F.count("*")).alias("bits")).withColumn("k", F.lit(k)) for k in orders]
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    best = F.min_by(F.struct("k", "bits"), F.struct(F.round("bits", 9), "k")).alias("b")
    return every.groupBy("seq_id").agg(best).select("seq_id", "b.k", "b.bits")


def blended(rows: DataFrame, ks=(1, 2), weights=(0.5, 0.5)) -> DataFrame:
    """Several matching distances blended to one prediction per base."""
    out = None
    for k, w in zip(ks, weights, strict=True):
        a = adaptive(rows, k).select("seq_id", "pos", (F.col("p") * w).alias(f"p{k}"))
        out = a if out is None else out.join(a, ["seq_id", "pos"])
    total = sum((F.col(f"p{k}") for k in ks[1:]), F.col(f"p{ks[0]}"))
    return out.withColumn("bits", -F.log2(total))


def word_counts(df: DataFrame, width: int) -> DataFrame:
    """(word, n): how often each word of `width` bases occurs in sequences (bases of A, G, C, T), as a number in base 4; each task counts
    in a table of 4^width numbers and sends the words it has seen."""
    import numpy as np
    import pyarrow as pa

    from ..functions.alphabet import _CODE

    if not 1 <= width <= 10:
        raise ValueError("width from 1 to 10")

    def run(batches):
        total = np.zeros(4**width, np.int64)
        for b in batches:
            for s in b.column(0).to_pylist():
                c = _CODE[np.frombuffer(s.encode(), np.uint8)]
                for a in range(0, len(c) - width + 1, 1 << 20):
                    part = c[a : a + (1 << 20) + width - 1]
                    key = np.zeros(len(part) - width + 1, np.int64)
                    for i in range(width):
                        key = key * 4 + part[i : i + len(key)]
                    total += np.bincount(key, minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["word", "n"])

    known = df.where("bases IS NOT NULL").select("bases")
    return known.mapInArrow(run, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


def em_mixture(rows: DataFrame, ks=(0, 1, 2), iters: int = 3) -> list[float]:
    """Mixture weights of adaptive orders by expectation-maximisation; each round is one aggregation."""
    out = None
    for k in ks:
        a = adaptive(rows, k).select("seq_id", "pos", F.col("p").alias(f"p{k}"))
        out = a if out is None else out.join(a, ["seq_id", "pos"])
    w = [1 / len(ks)] * len(ks)
    for _ in range(iters):
        mix = sum((F.lit(w[i]) * F.col(f"p{k}") for i, k in enumerate(ks[1:], 1)), F.lit(w[0]) * F.col(f"p{ks[0]}"))
        row = out.agg(*[F.avg(F.lit(w[i]) * F.col(f"p{k}") / mix).alias(f"w{k}") for i, k in enumerate(ks)]).first()
        w = [row[f"w{k}"] for k in ks]
    return w
