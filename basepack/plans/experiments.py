"""Experiment workloads: methods side by side, groupings, mixed training, training curve, container on disk.

Sequences are split 70 / 20 / 10 by id: learned coders train on the first part, choose their epoch on the second, and
every method, archivers included, is measured on the third.
"""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import codec, general
from ..sources import tables as S
from . import measures, model, train

SCHEMA = "corpus string, method string, n_bases long, n_bits long, bpb double, seconds double, params long"


def _corpora(spark, sf_dir):
    from ..functions import alphabet as A

    fish = A.split_unknown(S.event_seq(spark, sf_dir)).select(F.lit("fish").alias("corpus"), "seq_id", "bases")
    human = S.bench_quad(spark, sf_dir).withColumn("corpus", F.lit("human"))
    return {"human": human, "fish": fish}


def _one_stream(df: DataFrame) -> DataFrame:
    """A small corpus as one sequence, as an archiver would see one file."""
    parts = F.sort_array(F.collect_list(F.struct("seq_id", "bases")))
    text = F.array_join(F.transform(parts, lambda x: x["bases"]), "")
    return df.groupBy("corpus").agg(text.alias("bases")).select("corpus", F.lit(0).cast("long").alias("seq_id"), "bases")


def _measure(df, name, coder, group=4096, lanes=64):
    def run():
        return measures.bpb(codec.compress(df, coder, group, lanes)).first()

    row, seconds = measures.timed(run)
    params = sum(v.size for v in coder.weights.values()) if coder.weights else 0
    return row["n_bases"], row["n_bits"], row["bpb"], seconds, params


def _parts(df: DataFrame) -> dict[str, DataFrame]:
    split = measures.split_of(F.col("seq_id"))
    return {k: df.where(split == k) for k in ("train", "val", "test")}


LEARNED = {"carry": model.TINY, "byte": model.BYTE, "multilevel": model.MULTI, "conv_lstm": model.LSTM, "conv_bilstm": model.BILSTM}


def _trained(parts: dict[str, dict[str, DataFrame]]) -> dict:
    """(weights, statistics) of every learned method on every corpus, each epoch over the whole training part. Trainings don't depend on each other and have two tasks each, so
    they run side by side, and before anything is timed."""

    def one(key):
        corpus, name = key
        cfg = replace(LEARNED[name], block_order="standard")
        w, stats, _ = train.fit(parts[corpus]["train"], parts[corpus]["val"], cfg, epochs=2, steps=None, lanes=32, rate=3e-3, partitions=2)
        return w, stats

    keys = [(corpus, name) for name in reversed(LEARNED) for corpus in parts]  # the longest first
    with ThreadPoolExecutor(len(keys)) as pool:
        return dict(zip(keys, pool.map(one, keys), strict=True))


def scores(spark, sf_dir) -> DataFrame:
    """Bits a base and seconds of every method on the test part of both small corpora."""
    rows = []
    parts = {corpus: _parts(df) for corpus, df in _corpora(spark, sf_dir).items()}
    trained = _trained(parts)
    for corpus, part in parts.items():
        test = part["test"]
        whole = _one_stream(test)
        for c in general.CODECS:
            r, s = measures.timed(lambda w=whole, c=c: general.encode(w, c).agg(F.sum("n_bases"), F.sum("n_bits")).first())
            rows.append((corpus, c, r[0], r[1], r[1] / r[0], s, 0))
        rows.append((corpus, "context", *_measure(whole, "context", codec.order_coder((1, 2, 3, 4, 6, 8)), 1 << 20, 1)))
        for name, cfg in LEARNED.items():
            cfg, (w, stats) = replace(cfg, block_order="standard"), trained[corpus, name]
            rows.append((corpus, name, *_measure(test, name, codec.model_coder(cfg, name, weights=w, stats=stats))))
    return spark.createDataFrame(rows, SCHEMA)


def memory_scores(spark, sf_dir) -> DataFrame:
    """Test bits a base of the four cells of carry and cut, trained alike on the passages."""
    part = _parts(_corpora(spark, sf_dir)["human"])
    rows = []
    for name, cfg in model.memory_grid().items():
        cfg = replace(cfg, block_order="standard")
        w, stats, _ = train.fit(part["train"], part["val"], cfg, epochs=2, steps=60, lanes=32, rate=3e-3, partitions=2)
        rows.append(("human", name, *_measure(part["test"], name, codec.model_coder(cfg, name, weights=w, stats=stats))))
    return spark.createDataFrame(rows, SCHEMA)


def grouping_scores(spark, sf_dir) -> DataFrame:
    """Time and bits of the grouping ablation on the training part, the largest; weights trained alike for each configuration."""
    part = _parts(_corpora(spark, sf_dir)["human"])
    rows, trained = [], {}
    for name, cfg, group, lanes in (("none", model.TINY, 1 << 20, 8), ("byte", model.BYTE, 1 << 20, 8), ("byte_ngram", model.MULTI, 1 << 20, 8), ("all", model.MULTI, 512, 64)):
        cfg = replace(cfg, block_order="standard")
        if cfg not in trained:
            trained[cfg] = train.fit(part["train"], part["val"], cfg, epochs=2, steps=60, lanes=32, rate=3e-3, partitions=2)
        w, stats, _ = trained[cfg]
        rows.append(("human", name, *_measure(part["train"], name, codec.model_coder(cfg, name, weights=w, stats=stats), group, lanes)))
    return spark.createDataFrame(rows, SCHEMA)


def hybrid_scores(spark, sf_dir) -> DataFrame:
    """Validation bits a base of dedicated and of mixed training."""
    parts = {k: _parts(df) for k, df in _corpora(spark, sf_dir).items()}
    cfg = replace(model.MULTI, block_order="standard")
    rows = []
    for corpus, p in parts.items():
        _, _, h = train.fit(p["train"], p["val"], cfg, epochs=2, steps=60, lanes=32, rate=3e-3, partitions=2)
        rows.append((corpus, "dedicated", min(x[2] for x in h)))
    _, _, h = train.fit_mixed({k: p["train"] for k, p in parts.items()}, {k: p["val"] for k, p in parts.items()}, cfg, epochs=2, steps=60, partitions=2)
    rows.append(("both", "hybrid", min(x[2] for x in h)))
    return spark.createDataFrame(rows, "corpus string, training string, bpb double")


def train_history(spark, sf_dir) -> DataFrame:
    df = S.doc_quad(spark, sf_dir)
    split = measures.split_of(F.col("seq_id"))
    cfg = replace(model.MULTI, block_order="standard")
    _, _, h = train.fit(df.where(split == "train"), df.where(split == "val"), cfg, epochs=3, steps=60, rate=3e-3)
    return spark.createDataFrame(h, "epoch int, loss double, val_bpb double")


def container_roundtrip(spark, sf_dir) -> DataFrame:
    """Container written as Parquet by corpus and shard, and decoded from there."""
    path = f"{S.shared_dir(spark)}/container-{uuid.uuid4().hex}"
    from ..functions import alphabet as A

    src = A.split_unknown(S.event_seq(spark, sf_dir))
    c = codec.model_coder(model.MULTI, "multilevel")
    codec.compress(src.select("corpus", "seq_id", "bases"), c, 512, 64).write.partitionBy("corpus", "shard").parquet(path)
    back = codec.decompress(spark.read.parquet(path), c, 64).select("seq_id", F.col("bases").alias("b"))
    joined = src.select("seq_id", "unknown").join(back, "seq_id", "left").withColumn("bases", F.coalesce("b", F.lit("")))
    return general.digests(A.merge_unknown(joined))
