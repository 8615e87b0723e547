"""General archivers over sequences, raw packing, and choosing the cheaper of two."""

from __future__ import annotations

import bz2
import lzma
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import alphabet as A

CODECS = {
    "deflate": (lambda b: zlib.compress(b, 9), zlib.decompress),
    "lzma": (lambda b: lzma.compress(b, preset=6), lzma.decompress),
    "bwt": (lambda b: bz2.compress(b, 9), bz2.decompress),
}


def encode(df: DataFrame, codec: str) -> DataFrame:
    """(seq_id, n_bases, payload, n_bits): one ASCII byte a base goes in, as a text of the sequence would."""
    def run(batches):
        press = CODECS[codec][0]
        for b in batches:
            out = [press(x.encode()) for x in b.column(1).to_pylist()]
            n = [len(x) for x in b.column(1).to_pylist()]
            cols = [b.column(0), pa.array(n, pa.int64()), pa.array(out, pa.binary()), pa.array([8 * len(x) for x in out], pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, ["seq_id", "n_bases", "payload", "n_bits"])

    return df.select(F.col("seq_id").cast("long"), F.coalesce("bases", F.lit("")).alias("bases")).mapInArrow(run, "seq_id long, n_bases long, payload binary, n_bits long")


def decode(df: DataFrame, codec: str) -> DataFrame:
    def run(batches):
        open_ = CODECS[codec][1]
        for b in batches:
            cols = [b.column(0), pa.array([open_(x).decode() for x in b.column(1).to_pylist()], pa.string())]
            yield pa.RecordBatch.from_arrays(cols, ["seq_id", "bases"])

    return df.select("seq_id", "payload").mapInArrow(run, "seq_id long, bases string")


def digests(df: DataFrame) -> DataFrame:
    return df.select("seq_id", F.length("bases").cast("long").alias("n_bases"), F.md5(F.col("bases").cast("binary")).alias("digest"))


def round_trip(df: DataFrame, codec: str) -> DataFrame:
    return digests(decode(encode(df, codec), codec))


def raw2(df: DataFrame) -> DataFrame:
    """Two bits a base and the runs of unknown ones; Catalyst only."""
    known = A.split_unknown(df)
    n = F.length("bases")
    return known.select("seq_id", n.cast("long").alias("n_known"), A.pack(A.padded(F.col("bases"))).alias("payload"), "unknown")


def raw2_back(df: DataFrame) -> DataFrame:
    bases = F.substring(A.unpack(F.col("payload")), F.lit(1), F.col("n_known").cast("int"))
    return A.merge_unknown(df.withColumn("bases", bases)).select("seq_id", "bases")


def bwt_blocks(df: DataFrame, size: int = 60) -> DataFrame:
    """(seq_id, block, last): block-sorting transform spelled out: sorted rotations of each block of each sequence with an
    end mark. An empty sequence is one empty block."""
    blocks = F.sequence(F.lit(0), F.greatest(F.ceil(F.length("bases") / size).cast("int"), F.lit(1)) - 1)
    cut = df.select("seq_id", "bases", F.explode(blocks).alias("block"))
    s = F.concat(F.substring("bases", F.col("block") * size + 1, F.lit(size)), F.lit("$"))
    rot = cut.select("seq_id", F.col("block").cast("long").alias("block"), s.alias("s"))
    rot = rot.select("seq_id", "block", "s", F.explode(F.sequence(F.lit(0), F.length("s") - 1)).alias("i"))
    rot = rot.select("seq_id", "block", F.concat(F.substring("s", F.col("i") + 1, F.length("s")), F.substring("s", F.lit(1), F.col("i"))).alias("r"))
    ordered = F.sort_array(F.collect_list("r"))
    return rot.groupBy("seq_id", "block").agg(F.array_join(F.transform(ordered, lambda x: F.right(x, F.lit(1))), "").alias("last"))


def bwt_inverse(last: str) -> str:
    order = sorted(range(len(last)), key=lambda i: (last[i], i))
    out, at = [], order[0]
    for _ in last:
        out.append(last[at])
        at = order[at]
    text = "".join(out)
    cut = text.index("$")
    return text[cut + 1 :] + text[:cut]


def pick_cheaper(a: DataFrame, b: DataFrame, names: tuple[str, str]) -> DataFrame:
    """(seq_id, chosen, n_bits) per sequence; ties to the first."""
    j = a.select("seq_id", F.col("n_bits").alias("x")).join(b.select("seq_id", F.col("n_bits").alias("y")), "seq_id")
    return j.select("seq_id", F.when(F.col("x") <= F.col("y"), names[0]).otherwise(names[1]).alias("chosen"), F.least("x", "y").alias("n_bits"))


def nml_blocks(df: DataFrame, block: int = 32) -> DataFrame:
    """(seq_id, bits): blocks coded by their agreement with the best earlier block (one regression parameter, two-part
    normalised likelihood), or by two bits a base where that is cheaper; sequential over a sequence."""
    from math import comb, log2

    def run(batches):
        c = log2(sum(comb(block, k) * (k / block) ** k * (1 - k / block) ** (block - k) for k in range(block + 1)))
        for b in batches:
            out = []
            for s in b.column(1).to_pylist():
                parts = [s[i : i + block] for i in range(0, len(s), block)]
                bits = 0.0
                for i, p in enumerate(parts):
                    plain = 2.0 * len(p)
                    if len(p) == block and i:
                        hits = max(sum(x == y for x, y in zip(p, q, strict=True)) for q in parts[:i])
                        r = hits / block
                        like = -(hits * log2(r) if hits else 0) - ((block - hits) * log2((1 - r) / 3) if hits < block else 0)
                        plain = min(plain, like + c + log2(i))
                    bits += plain + 1
                out.append(bits)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64())], ["seq_id", "bits"])

    return df.select(F.col("seq_id").cast("long"), "bases").mapInArrow(run, "seq_id long, bits double")


def field_aware(df: DataFrame) -> DataFrame:
    """(part, field, n, payload) of (id, bases, qual) records: ids as differences, each field's bytes by its own
    dictionary coder; a part is one Arrow batch of one task."""
    def run(batches):
        from pyspark import TaskContext

        for k, b in enumerate(batches):
            ids = b.column(0).to_pylist()
            fields = {"id": [y - x for x, y in zip([0, *ids], ids, strict=False)], "bases": b.column(1).to_pylist(), "qual": b.column(2).to_pylist()}
            data = [lzma.compress("\n".join(map(str, v)).encode(), preset=6) for v in fields.values()]
            part = (TaskContext.get().partitionId() << 32) + k
            cols = [pa.array([part] * 3, pa.int64()), pa.array(list(fields)), pa.array([len(ids)] * 3, pa.int64()), pa.array(data, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, ["part", "field", "n", "payload"])

    return df.mapInArrow(run, "part long, field string, n long, payload binary")


def field_aware_back(fields: DataFrame) -> DataFrame:
    """(id, bases, qual) records of every part."""
    def run(table: pa.Table) -> pa.Table:
        text = {f: lzma.decompress(x).decode().split("\n") for f, n, x in zip(*(table.column(c).to_pylist() for c in ("field", "n", "payload")), strict=True) if n}
        ids, at = [], 0
        for x in text.get("id", []):
            at += int(x)
            ids.append(at)
        return pa.table({"id": pa.array(ids, pa.int64()), "bases": pa.array(text.get("bases", []), pa.string()), "qual": pa.array(text.get("qual", []), pa.string())})

    return fields.groupBy("part").applyInArrow(run, "id long, bases string, qual string")
