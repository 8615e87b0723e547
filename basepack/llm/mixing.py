"""Mixing sources to target weights with hash-threshold histograms, in DataFrame functions alone.

Every document gets a 60-bit hash of its id and text. Per source, the words of all documents are summed
into 4 096 hash buckets (map-side combined, so a hot source costs one row a bucket and task).
A running sum over the buckets finds where the word budget runs out; only that boundary bucket is
read again at the next 12 bits, until five levels have fixed the threshold to one hash value.
Documents are then kept by comparing their hash with the threshold of their source: no sort of
documents, and nested budgets keep nested sets.

A source whose target exceeds its size is taken whole once and its remainder by threshold; a
document is never taken more than twice.

Defined results: null text or text without words has size 0; a null source is a source of its own,
ordered last; a null id hashes as the text 'null', and since the text is hashed with it, only rows equal in both share a
hash and move together; very long texts are counted whole; an empty table gives an empty result; extra columns are kept by `mix`,
whose own columns (mix_...) replace those of the input.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, native_size

WEIGHTS = (3, 1, 2)
SHARE = 1.5
CAP = 2
LEVELS = 5
LEVEL_BITS = 12
#: Sources up to this many are joined by broadcast; more are joined by shuffle.
BROADCAST_SOURCES = 20_000


def mix_hash(doc_id: Column, text: Column) -> Column:
    """60 bits of md5 of the id as text and the text."""
    both = F.concat(F.coalesce(doc_id.cast("string"), F.lit("null")), F.lit("|"), F.coalesce(text, F.lit("")))
    return F.conv(F.substring(F.md5(both.cast("binary")), 1, 15), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: int = CAP) -> DataFrame:
    """(source, source_size) -> target: the share dealt by weight, never over cap times the size.

    The level at which uncapped sources stand is found from running sums over the sources in the order
    in which they reach their caps; the result is the fixed point of dealing the excess again and again.
    One row a source, so these windows hold the list of sources, not documents.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("rank") % len(weights) + 1).cast("int"))
    cut = Window.orderBy("ratio", "rank")
    every = Window.partitionBy()
    limit = (F.lit(cap) * F.col("source_size")).cast("double")
    before = cut.rowsBetween(Window.unboundedPreceding, -1)
    d = (
        sizes.withColumn("rank", F.row_number().over(order) - 1)
        .withColumn("w", w)
        .withColumn("limit", limit)
        .withColumn("ratio", F.col("limit") / F.col("w"))
        .withColumn("budget", F.sum("source_size").over(every) * F.lit(share))
        .withColumn("all_w", F.sum("w").over(every))
        .withColumn("cap_before", F.coalesce(F.sum("limit").over(before), F.lit(0.0)))
        .withColumn("w_before", F.coalesce(F.sum("w").over(before), F.lit(0.0)))
    )
    level = (F.col("budget") - F.col("cap_before")) / (F.col("all_w") - F.col("w_before"))
    d = d.withColumn("level", level)
    free = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "rank", "level"))).over(every)
    d = d.withColumn("free", free["level"])
    target = F.when(F.col("free").isNull() | (F.col("ratio") <= F.col("free")), F.col("limit")).otherwise(
        F.col("free") * F.col("w")
    )
    return d.select("source", "source_size", target.alias("target"))


def _keyed(df: DataFrame) -> DataFrame:
    return df.withColumn("source_key", F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("")))


def _small(df: DataFrame, n_sources: int) -> DataFrame:
    return F.broadcast(df) if n_sources <= BROADCAST_SOURCES else df


def thresholds(hashed: DataFrame, plan: DataFrame, n_sources: int) -> DataFrame:
    """Per source the largest hash that is taken (source_key, upto, -1 for none).

    hashed: (source_key, size, h); plan: (source_key, wanted) words to take by threshold.
    Per level one histogram over the documents that still lie in their source's boundary bucket.
    """
    bits = LEVELS * LEVEL_BITS
    state = plan.select("source_key", "wanted", F.lit(0).cast("long").alias("prefix"), F.lit(0).cast("long").alias("taken"))
    for level in range(1, LEVELS + 1):
        shift = bits - level * LEVEL_BITS
        cells = (
            hashed.join(_small(state, n_sources), "source_key")
            .where(F.shiftright("h", shift + LEVEL_BITS) == F.col("prefix"))
            .groupBy("source_key", F.shiftright("h", shift).alias("bucket"))
            .agg(F.sum("size").alias("words"))
        )
        run = Window.partitionBy("source_key").orderBy("bucket")
        cells = cells.withColumn("upto", F.sum("words").over(run))
        here = cells.join(_small(state, n_sources), "source_key").where(F.col("taken") + F.col("upto") > F.col("wanted"))
        edge = here.groupBy("source_key").agg(F.min(F.struct("bucket", "upto", "words")).alias("edge"))
        state = materialise(
            state.join(edge, "source_key", "left").select(
                "source_key",
                "wanted",
                # No boundary (the budget covers all that is left): a prefix past every bucket.
                F.coalesce(F.col("edge.bucket"), F.lit(1 << (level * LEVEL_BITS)).cast("long")).alias("prefix"),
                (F.col("taken") + F.coalesce(F.col("edge.upto") - F.col("edge.words"), F.lit(0))).alias("taken"),
                F.col("edge.words").alias("edge_words"),
            ),
            "mix-level",
        )
    # The boundary is one hash value now: it is taken if that comes nearer to the budget than leaving it.
    nearer = F.col("edge_words").isNotNull() & (
        F.col("taken") + F.col("edge_words") - F.col("wanted") < F.col("wanted") - F.col("taken")
    )
    return state.select("source_key", F.when(nearer, F.col("prefix")).otherwise(F.col("prefix") - 1).alias("upto"))


def mix(docs: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: int = CAP) -> DataFrame:
    """docs plus mix_size, mix_source_size, mix_target, mix_copies, mix_taken for every document."""
    docs = docs.drop("mix_size", "mix_source_size", "mix_target", "mix_copies", "mix_taken", "mix_whole", "mix_upto", "source_key")  # own names win
    slim = materialise(
        _keyed(docs).select("source", "source_key", native_size(F.col("text")).alias("size"), mix_hash(F.col("doc_id"), F.col("text")).alias("h")),
        "mix-sizes",
    )
    sizes = slim.groupBy("source", "source_key").agg(F.sum("size").cast("long").alias("source_size"))
    plan = source_targets(sizes.select("source", "source_size"), weights, share, cap)
    ratio = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
    plan = _keyed(plan).withColumn("whole", F.least(ratio, F.lit(cap)).cast("long"))
    plan = materialise(plan.withColumn("wanted", F.col("target") - F.col("whole") * F.col("source_size")), "mix-plan")
    n_sources = plan.count()
    cut = thresholds(slim, plan, n_sources)
    facts = plan.join(cut, "source_key").select(
        "source_key",
        F.col("source_size").alias("mix_source_size"),
        F.col("target").alias("mix_target"),
        F.col("whole").alias("mix_whole"),
        F.col("upto").alias("mix_upto"),
    )
    copies = F.least(F.col("mix_whole") + (mix_hash(F.col("doc_id"), F.col("text")) <= F.col("mix_upto")).cast("long"), F.lit(cap))
    return (
        _keyed(docs)
        .withColumn("mix_size", native_size(F.col("text")))
        .join(_small(facts, n_sources), "source_key")
        .withColumn("mix_copies", copies)
        .withColumn("mix_taken", F.col("mix_copies") * F.col("mix_size"))
        .drop("source_key", "mix_whole", "mix_upto")
    )


def mix_report(docs: DataFrame) -> DataFrame:
    """The contract's columns for every document."""
    return mix(docs.select("doc_id", "text", "source")).select(
        "doc_id",
        F.col("mix_size").alias("size"),
        F.col("mix_source_size").alias("source_size"),
        F.col("mix_target").alias("target"),
        F.col("mix_taken").alias("taken"),
    )


#: DuckDB form: the same rule by sorting, which the thresholds avoid. `{docs}` is the input relation.
MIX_SQL = r"""
, sized AS (
  SELECT *, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || '|' || coalesce(text, '')), 1, 15))::UBIGINT AS h,
         CASE WHEN source IS NULL THEN '' ELSE '=' || source END AS source_key
  FROM {docs}),
sources AS (SELECT source, source_key, sum(size)::BIGINT AS source_size FROM sized GROUP BY ALL),
weighed AS (
  SELECT *, [3.0::DOUBLE, 1.0::DOUBLE, 2.0::DOUBLE][(row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1] AS w,
         row_number() OVER (ORDER BY source IS NULL, source) AS rank, (2 * source_size)::DOUBLE AS cap
  FROM sources),
levelled AS (
  SELECT *, cap / w AS ratio,
    ((sum(source_size) OVER ())::DOUBLE * 1.5::DOUBLE - coalesce(sum(cap) OVER prev, 0.0::DOUBLE))
      / (sum(w) OVER () - coalesce(sum(w) OVER prev, 0.0::DOUBLE)) AS level
  FROM weighed WINDOW prev AS (ORDER BY cap / w, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
free AS (SELECT level AS free FROM levelled WHERE level <= ratio ORDER BY ratio, rank LIMIT 1),
planned AS (
  SELECT l.*, CASE WHEN f.free IS NULL OR l.ratio <= f.free THEN l.cap ELSE f.free * l.w END AS target
  FROM levelled l LEFT JOIN free f ON true),
wanted AS (
  SELECT *, CASE WHEN source_size > 0 THEN least(floor(target / source_size), 2) ELSE 0 END::BIGINT AS whole,
         target - (CASE WHEN source_size > 0 THEN least(floor(target / source_size), 2) ELSE 0 END) * source_size AS wanted
  FROM planned),
hashes AS (SELECT source_key, h, sum(size)::BIGINT AS words FROM sized GROUP BY ALL),
running AS (
  SELECT source_key, h, words, (sum(words) OVER (PARTITION BY source_key ORDER BY h))::BIGINT AS upto FROM hashes),
chosen AS (
  SELECT r.source_key, r.h,
    CASE WHEN r.upto <= w.wanted THEN true
         WHEN r.upto - r.words > w.wanted THEN false
         ELSE row_number() OVER (PARTITION BY r.source_key, r.upto > w.wanted ORDER BY r.h) = 1
              AND r.upto - w.wanted < w.wanted - (r.upto - r.words) END AS part
  FROM running r JOIN wanted w USING (source_key))
"""

REPORT_SQL = (
    "WITH docs AS (SELECT doc_id, text, source FROM documents)"
    + MIX_SQL.replace("{docs}", "docs")
    + """
SELECT s.doc_id, s.size, w.source_size, w.target, s.size * least(w.whole + c.part::BIGINT, 2) AS taken
FROM sized s JOIN wanted w USING (source_key) JOIN chosen c ON c.source_key = s.source_key AND c.h = s.h
"""
)
