"""Fixed-length groups, initial fragments, n-gram words, byte grouping, lanes and their combination."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

FRAGMENT = 64
GROUP = 213_000


def fixed_groups(df: DataFrame, length: int = GROUP) -> DataFrame:
    """(corpus, seq_id, group_id, start, n_bases, bases): equal groups, a row each; narrow, no shuffle."""
    n = F.length("bases")
    # Bases are a byte each; in a string the way to a group would be walked anew for every group.
    cut = df.withColumn("n", n).where("n > 0").withColumn("raw", F.col("bases").cast("binary")).withColumn("start", F.explode(F.sequence(F.lit(0), F.col("n") - 1, F.lit(length))))
    return cut.select(
        "corpus", "seq_id", F.expr(f"cast(start div {length} as int)").alias("group_id"), F.col("start").cast("long").alias("start"),
        F.least(F.lit(length), F.col("n") - F.col("start")).cast("int").alias("n_bases"),
        F.substring("raw", F.col("start") + 1, F.lit(length)).cast("string").alias("bases"),
    )


def fixed_count(rows: DataFrame, n_groups: int) -> DataFrame:
    """A given number of groups for each sequence, whatever its length (the ad-hoc way)."""
    return rows.withColumn("bucket", F.ntile(n_groups).over(Window.partitionBy("seq_id").orderBy("pos")))


def length_for_budget(extra_bpb: float, context: int = FRAGMENT) -> int:
    """Shortest group whose two-bit fragment costs no more than extra_bpb bits a base."""
    return math.ceil(round(2 * context / extra_bpb, 6))


def budget_length(extra_bpb: Column, context: int = FRAGMENT) -> Column:
    """length_for_budget of a column."""
    return F.ceil(F.round(2 * context / extra_bpb, 6)).cast("long")


def initial_fragment(df: DataFrame, context: int = FRAGMENT) -> DataFrame:
    """(.., at, fragment): first stretch of known bases of that length, 0-based; null if there is none."""
    at = F.regexp_instr("bases", F.lit(f"[AGCT]{{{context}}}"))
    return df.withColumn("at", F.when(at > 0, at - 1).cast("long")).withColumn(
        "fragment", F.when(at > 0, F.substring("bases", at, F.lit(context)))
    )


def ngram_words(df: DataFrame, n: int) -> DataFrame:
    """(seq_id, i, word): words side by side; a tail shorter than n is left out of the words."""
    words = F.regexp_extract_all("bases", F.lit(f"(.{{{n}}})"), F.lit(1))  # one walk over the sequence
    return df.select("seq_id", F.posexplode(words).alias("i", "word")).select("seq_id", F.col("i").cast("long").alias("i"), "word")


def ngram_vocab(spark: SparkSession, n: int) -> DataFrame:
    """All 4^n words with their codes; n is at most 8."""
    if not 1 <= n <= 8:
        raise ValueError("n from 1 to 8")
    word, rest = F.lit(""), F.col("id")
    for k in range(n):
        digit = F.expr(f"cast(id div {4 ** (n - 1 - k)} % 4 as int)")
        word = F.concat(word, F.substring(F.lit("AGCT"), digit + 1, F.lit(1)))
    return spark.range(4**n).select(word.alias("word"), rest.alias("code"))


def byte_group_df(df: DataFrame, g: int) -> DataFrame:
    """(seg, r, vec): g neighbours of each segment side by side as one wider vector."""
    parts = F.sort_array(F.collect_list(F.struct("i", "vec")))
    return df.groupBy("seg", F.expr(f"i div {g}").alias("r")).agg(F.flatten(F.transform(parts, lambda x: x["vec"])).alias("vec"))


def byte_group(x, g: int):
    """(.., length, h) to (.., length / g, h * g)."""
    return x.reshape(*x.shape[:-2], x.shape[-2] // g, x.shape[-1] * g)


def lane_batches(groups: DataFrame, lanes: int = 64, shards: int = 8) -> DataFrame:
    """Batch and lane numbers: groups of like length step together; windows are per shard, never global."""
    shard = F.expr(f"cast((seq_id * 31 + group_id) % {shards} as int)")
    w = Window.partitionBy("shard").orderBy("n_bases", "seq_id", "group_id")
    numbered = groups.withColumn("shard", shard).withColumn("k", F.row_number().over(w) - 1)
    return numbered.withColumn("batch", F.expr(f"k div {lanes}")).withColumn("lane", F.col("k") % lanes).drop("k")


def concat_corpus(df: DataFrame, by: str) -> DataFrame:
    """Offsets of sequences if all of one key stand one after the other."""
    w = Window.partitionBy(by).orderBy("seq_id").rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn("offset", F.coalesce(F.sum(F.length("bases")).over(w), F.lit(0)).cast("long"))


@dataclass(frozen=True)
class MultiLevelPlan:
    """Fixed groups, then words, then byte grouping, in this order; 0 or 1 leaves a level out."""

    fg: int = 0
    ng: int = 1
    bg: int = 1
    mode: str = "extend_context"

    def shapes(self, context: int = 64, kernel: int = 24, pool: int = 3) -> dict[str, int]:
        """Tensor lengths on the way to the encoder for one window."""
        raw = context * (self.bg if self.mode == "extend_context" else 1)
        words = raw // self.ng
        length = words // self.bg
        conv = max(0, length - kernel + 1)
        return {"raw": raw, "words": words, "length": length, "conv": conv, "n": conv // pool}

    def apply(self, df: DataFrame) -> DataFrame:
        out = fixed_groups(df, self.fg) if self.fg else df.withColumn("group_id", F.lit(0)).withColumn("start", F.lit(0).cast("long")).withColumn("n_bases", F.length("bases"))
        return out.withColumn("n_words", F.expr(f"n_bases div {self.ng}")).withColumn("n_rows", F.expr(f"n_words div {self.bg}"))


def ablation_grid(fg: int = GROUP) -> dict[str, MultiLevelPlan]:
    return {"none": MultiLevelPlan(), "byte": MultiLevelPlan(bg=2), "byte_ngram": MultiLevelPlan(bg=2, ng=2), "all": MultiLevelPlan(fg, 2, 2)}
