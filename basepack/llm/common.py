"""Helpers shared by the training-data operators: tables, shared storage, byte-level words."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text handled at once by the vectorised kernels inside one Arrow batch.
BLOCK_BYTES = 2 << 20

#: A-Z to a-z on UTF-8 bytes; every other byte stays.
ASCII_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))

#: As ASCII_LOWER, and every ASCII byte that is neither digit nor letter becomes a space.
ALNUM_LOWER = bytes(
    c + 32 if 65 <= c <= 90 else c if c >= 0x80 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256)
)

#: Java regex of what separates words in the white-space word rule.
SPACES = "[\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; local sessions without one get a folder of their own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return "file:///tmp/checkpoints/basepack"


#: Spark deletes the shuffles of a query when it has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, tag: str, clean: bool = False) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage and survives lost executors. `clean`: its shuffles, which
    nothing reads any more, are deleted at once and not when the driver happens to collect garbage."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true" if clean else before)
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def words_of(data: bytes | None) -> list[bytes]:
    """Words `[^\\x20\\x09-\\x0D]+` of a UTF-8 text, A-Z lower-cased; null has none."""
    return data.translate(ASCII_LOWER).split() if data else []


def alnum_words(data: bytes | None) -> list[bytes]:
    """Words of digits, letters and non-ASCII characters, A-Z lower-cased; null has none."""
    return data.translate(ALNUM_LOWER).split() if data else []


def native_size(col) -> F.Column:
    """Number of white-space separated words as a Catalyst expression; null counts 0."""
    text = F.regexp_replace(F.coalesce(col, F.lit("")), f"^{SPACES}|{SPACES}$", "")
    return F.when(text == "", F.lit(0)).otherwise(F.size(F.split(text, SPACES))).cast("long")


def packed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, rest): all other columns in one struct, so that none clashes with the names an operator uses."""
    others = [F.col(f"`{c}`") for c in docs.columns if c not in ("doc_id", "text")]
    return docs.select("doc_id", "text", F.struct(F.lit(0).alias("_"), *others).alias("rest"))


def unpacked(df: DataFrame, columns: list[str]) -> DataFrame:
    """The columns that `packed` put away."""
    return df.select(*[F.col(c) if c in ("doc_id", "text") else F.col("rest").getField(c).alias(c) for c in columns])


def byte_column(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    return batch.column(batch.schema.get_field_index(name)).cast(pa.binary()).to_pylist()


def blocks(sizes: list[int], limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Cut a batch into runs of rows of at most `limit` bytes (one longer row makes a run of its own)."""
    start = total = 0
    for i, n in enumerate(sizes):
        if i > start and total + n > limit:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield start, len(sizes)


def map_rows(df: DataFrame, schema: str, fn: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]]) -> DataFrame:
    """mapInArrow with a function of one batch."""

    def run(batches):
        for b in batches:
            yield from fn(b)

    return df.mapInArrow(run, schema)


#: A key with over a 4096th of all rows is heavy; there are fewer than 4096 such keys, whatever the input.
HEAVY = 4096


def join_uneven(left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int, how: str = "inner", by: str | None = None, heavy: int = HEAVY) -> DataFrame:
    """left joined with right on keys, without a task that gets all rows of a frequent key.

    `weight` is a column of right: how many rows of left have the key; `total`: rows of left. Heavy keys are broadcast (fewer
    than `heavy` of them, by their weight) and their rows stay where they are; all others are joined by shuffle. left
    and right are read twice, so they should be written tables. how: inner or left_semi. by: hint for the join by shuffle, so that
    it is one at any size and figures of small inputs hold for large ones."""
    hot = F.broadcast(right.where(F.col(weight) * heavy > total).drop(weight))
    rest = left.join(hot.select(*keys).distinct().hint("broadcast"), keys, "left_anti")
    light = right.where(F.col(weight) * heavy <= total).drop(weight)
    return left.join(hot, keys, how).unionByName(rest.join(light.hint(by) if by else light, keys, how))


#: Bits of the filter of `with_marks`: for each key, and at most.
BITS_A_KEY, MOST_BITS = 16, 1 << 26


def with_marks(df: DataFrame, some: DataFrame, keys: list[str], name: str = "marked") -> DataFrame:
    """df plus a boolean that is true for all rows whose keys (without nulls) are in `some`, and for few others: what is not
    marked needs no shuffle to be known as alone. One bit a key, in at most 8 MB that are broadcast; more keys than that serves only mark
    more rows. some: a written table."""
    bits = 1 << 15
    while bits < min(MOST_BITS, BITS_A_KEY * some.count()):
        bits *= 2
    spot = F.pmod(F.xxhash64(*keys), F.lit(bits)) + 1
    maps = some.select(spot.alias("spot")).groupBy(F.expr("bitmap_bucket_number(spot)").alias("bucket_of_marks"))
    maps = maps.agg(F.expr("bitmap_construct_agg(bitmap_bit_position(spot))").alias("map_of_marks"))
    at = F.bitmap_bit_position(spot)
    byte = F.conv(F.hex(F.substring("map_of_marks", (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    found = F.coalesce(F.getbit(byte, (at % 8).cast("int")) == 1, F.lit(False))
    joined = df.withColumn("bucket_of_marks", F.bitmap_bucket_number(spot)).join(F.broadcast(maps), ["bucket_of_marks"], "left")
    return joined.withColumn(name, found).drop("bucket_of_marks", "map_of_marks")


def fold(col: str, mod: int) -> F.Column:
    """crc32 of the id as text, modulo mod; a null id belongs to fold 0."""
    return F.coalesce(F.crc32(F.col(col).cast("string").cast("binary")) % mod, F.lit(0))
