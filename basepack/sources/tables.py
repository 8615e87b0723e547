"""Sequence views over the given tables, and a FASTA-like data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions import alphabet as A


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; local sessions without one get a folder of their own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return (found or "file:///tmp/checkpoints/basepack").rstrip("/")


def even(df: DataFrame, key: str) -> DataFrame:
    """A table of fewer files than shuffle partitions is read by few tasks: its rows are dealt by key. Others stay as they are."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, key) if len(df.inputFiles()) < n else df


def doc_quad(spark, sf_dir) -> DataFrame:
    d = even(load(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id")
    return d.select(F.lit("doc_quad").alias("corpus"), F.col("doc_id").alias("seq_id"), A.quad_map(F.col("text")).alias("bases"))


def doc_letter(spark, sf_dir) -> DataFrame:
    d = even(load(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id")
    return d.select(F.lit("doc_letter").alias("corpus"), F.col("doc_id").alias("seq_id"), A.letter_map(F.col("text")).alias("bases"))


def page_quad(spark, sf_dir) -> DataFrame:
    d = even(load(spark, sf_dir, "pages").select("page_id", "html"), "page_id")
    return d.select(F.lit("page_quad").alias("corpus"), F.col("page_id").alias("seq_id"), A.quad_map(F.col("html")).alias("bases"))


def bench_quad(spark, sf_dir) -> DataFrame:
    d = load(spark, sf_dir, "benchmark")
    return d.select(F.lit("benchmark").alias("corpus"), F.col("item_id").alias("seq_id"), A.quad_map(F.col("text")).alias("bases"))


def _ordered(df: DataFrame, key: str, order: list[str], corpus: str) -> DataFrame:
    listed = F.sort_array(F.collect_list(F.struct(*order, "base")))
    bases = F.array_join(F.transform(listed, lambda x: x["base"]), "")
    return df.groupBy(F.col(key).alias("seq_id")).agg(bases.alias("bases")).select(F.lit(corpus).alias("corpus"), "seq_id", "bases")


def event_seq(spark, sf_dir) -> DataFrame:
    e = load(spark, sf_dir, "events").withColumn("base", A.event_base(F.col("event_type")))
    return _ordered(e, "user_id", ["ts", "event_id"], "events")


def order_seq(spark, sf_dir) -> DataFrame:
    first = F.substring("o_orderpriority", 1, 1)
    o = load(spark, sf_dir, "orders").withColumn("base", F.translate(first, "12345", A.ALPHABET))
    return _ordered(o, "o_custkey", ["o_orderdate", "o_orderkey"], "orders")


def event_rows(spark, sf_dir) -> DataFrame:
    return A.base_rows(event_seq(spark, sf_dir)).drop("corpus")


def segments(spark, sf_dir, size: int = 13) -> DataFrame:
    e = load(spark, sf_dir, "embeddings")
    return e.select(
        F.expr(f"vec_id div {size}").alias("seg"), (F.col("vec_id") % size).alias("i"), F.col("embedding").cast("array<double>").alias("vec")
    )


class FastaPart(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class FastaReader(DataSourceReader):
    """One partition a file. Records are `>name` lines followed by lines of bases."""

    def __init__(self, options) -> None:
        self.paths = [p for p in options.get("path", "").split(",") if p]

    def partitions(self):
        return [FastaPart(p) for p in self.paths]

    def read(self, partition):
        name, parts = None, []
        with open(partition.path) as f:
            for line in f:
                line = line.strip()
                if line.startswith(">"):
                    if name is not None:
                        yield name, "".join(parts)
                    name, parts = line[1:], []
                elif line:
                    parts.append(line.upper())
        if name is not None:
            yield name, "".join(parts)


class FastaDataSource(DataSource):
    """spark.read.format('fasta').load('a.fa,b.fa') on files that the executors can open."""

    @classmethod
    def name(cls):
        return "fasta"

    def schema(self):
        return "name string, bases string"

    def reader(self, schema):
        return FastaReader(self.options)


def read_fasta_text(spark: SparkSession, path: str) -> DataFrame:
    """The same records from any store that Spark reads: one row a record, split at '>' by the text reader."""
    lines = spark.read.option("lineSep", ">").text(path).where("length(trim(value)) > 0")
    name = F.regexp_extract("value", "^([^\\r\\n]*)", 1)
    bases = F.upper(F.regexp_replace(F.regexp_replace("value", "^[^\\r\\n]*", ""), "[\\r\\n\\s]", ""))
    return lines.select(name.alias("name"), bases.alias("bases"))


def write_fasta(df: DataFrame, path: str) -> None:
    df.select(F.concat(F.lit(">"), F.col("seq_id").cast("string"), F.lit("\n"), F.col("bases"))).write.text(path)


def read_records(spark: SparkSession, path: str) -> DataFrame:
    """Three-field read records, tab separated: id, bases, qual."""
    return spark.read.schema("id string, bases string, qual string").option("sep", "\t").csv(path)
