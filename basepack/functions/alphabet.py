"""Bases, maps between text and bases, packing, unknown bases.

Fixed values: the order of the alphabet (A, G, C, T, N) and its complements.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, LongType, StringType

ALPHABET = "AGCTN"
COMPLEMENT = "TCGAN"
EVENT_BASES = {"click": "A", "view": "G", "purchase": "C", "signup": "T", "error": "N"}
PRIORITY_BASES = ("1", "2", "3", "4", "5")
HEX = "0123456789abcdef"


def base_pair(v: int) -> str:
    return ALPHABET[v >> 2] + ALPHABET[v & 3]


_CODE = np.zeros(256, np.uint8)
_CODE[list(ALPHABET[:4].encode())] = range(4)
_LETTER = np.frombuffer(ALPHABET[:4].encode(), np.uint8)
#: The four bases of each byte.
_QUADS = _LETTER[np.arange(256)[:, None] >> np.array([6, 4, 2, 0]) & 3]


def _bytes_of(a: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of an array of strings or binaries one after the other, and where each value begins and ends."""
    wide = pa.types.is_large_string(a.type) or pa.types.is_large_binary(a.type)
    _, cuts, raw = a.buffers()
    at = np.frombuffer(cuts, np.int64 if wide else np.int32)[a.offset : a.offset + len(a) + 1].astype(np.int64)
    return (np.frombuffer(raw, np.uint8) if raw else np.zeros(0, np.uint8))[at[0] : at[-1]], at - at[0]


def _array(kind: pa.DataType, data: np.ndarray, at: np.ndarray, like: pa.Array) -> pa.Array:
    out = pa.Array.from_buffers(kind, len(like), [None, pa.py_buffer(at.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])
    return pc.if_else(like.is_valid(), out, pa.scalar(None, kind)) if like.null_count else out


def quads_of(a: pa.Array) -> pa.Array:
    data, at = _bytes_of(a)
    return _array(pa.string(), _QUADS[data].reshape(-1), 4 * at, a)


def packed_of(a: pa.Array) -> pa.Array:
    """Values of lengths divisible by four, so that quadruples of the whole array are those of its values."""
    data, at = _bytes_of(a)
    if (at % 4).any():
        raise ValueError("only sequences of a length divisible by four can be packed")
    c = _CODE[data].reshape(-1, 4)
    return _array(pa.binary(), c[:, 0] << 6 | c[:, 1] << 4 | c[:, 2] << 2 | c[:, 3], at // 4, a)


# One table look-up over the buffer of a whole Arrow batch; built-in functions would need a pass for each of 16 digits.
@F.arrow_udf(StringType())
def _quads(a: pa.Array) -> pa.Array:
    return quads_of(a)


@F.arrow_udf(BinaryType())
def _packed(a: pa.Array) -> pa.Array:
    return packed_of(a)


@F.arrow_udf(ArrayType(LongType()))
def _counts(a: pa.Array) -> pa.Array:
    data, at = _bytes_of(a)
    letters = list(ALPHABET[:4].encode())
    rows = [np.bincount(data[i:j], minlength=128)[letters] for i, j in zip(at[:-1], at[1:], strict=True)]
    return pa.array(rows, pa.list_(pa.int64()))


def base_counts(bases: Column) -> Column:
    """How often A, G, C and T stand in each sequence; null has none."""
    return _counts(bases)


def quad_map(text: Column) -> Column:
    """Four bases for each UTF-8 byte, high bits first; reversible."""
    return _quads(text)


def quad_bytes(bases: Column) -> Column:
    """The bytes that quad_map made the bases from."""
    return pack(bases)


def letter_map(text: Column) -> Column:
    """One base for each letter a-z, N for other characters, white space dropped; not reversible."""
    letters = "abcdefghijklmnopqrstuvwxyz"
    out = F.regexp_replace(F.regexp_replace(F.lower(text), "[ \\t\\r\\n]", ""), "[^a-z]", "N")
    return F.translate(F.translate(out, letters, "".join("0123"[i % 4] for i in range(26))), "0123", "AGCT")


def letter_sql(text: str) -> str:
    inner = f"regexp_replace(regexp_replace(lower({text}), '[ \\t\\r\\n]', '', 'g'), '[^a-z]', 'N', 'g')"
    digits = "".join("0123"[i % 4] for i in range(26))
    return f"translate(translate({inner}, 'abcdefghijklmnopqrstuvwxyz', '{digits}'), '0123', 'AGCT')"


def quad_sql(text: str) -> str:
    out = f"lower(hex(encode({text})))"
    for v, digit in enumerate(HEX):
        out = f"replace({out}, '{digit}', '{base_pair(v)}')"
    return out


def pack(bases: Column) -> Column:
    """Two bits a base; only A, G, C, T, and a length divisible by four."""
    return _packed(bases)


def padded(bases: Column) -> Column:
    """Bases drawn out with A to a length divisible by four."""
    return F.rpad(bases, (F.ceil(F.length(bases) / 4) * 4).cast("int"), F.lit("A"))


def unpack(data: Column) -> Column:
    return _quads(data)


def reverse_complement(bases: Column) -> Column:
    return F.reverse(F.translate(bases, ALPHABET, COMPLEMENT))


def code(base: Column) -> Column:
    """0 to 4 in the order of the alphabet."""
    return F.position(base, F.lit(ALPHABET)) - 1


def event_base(kind: Column) -> Column:
    out = None
    for name, base in EVENT_BASES.items():
        out = F.when(kind == name, base) if out is None else out.when(kind == name, base)
    return out


def unknown_runs(bases: Column) -> Column:
    """[(pos, len)] of the maximal runs of N, positions from 0: run lengths of a split at every change."""
    runs = F.regexp_extract_all(bases, F.lit("(N+|[^N]+)"), F.lit(1))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<pos:bigint,len:int>>").alias("runs"))

    def step(acc, run):
        size = F.length(run)
        own = F.struct(acc["at"].alias("pos"), size.alias("len"))
        return F.struct(
            (acc["at"] + size).cast("long").alias("at"),
            F.when(run.startswith("N"), F.concat(acc["runs"], F.array(own))).otherwise(acc["runs"]).alias("runs"),
        )

    found = F.aggregate(runs, start, step, lambda acc: acc["runs"])
    return F.when(F.contains(bases, F.lit("N")), found).otherwise(F.array().cast("array<struct<pos:bigint,len:int>>"))


def split_unknown(df: DataFrame) -> DataFrame:
    """bases without N, and the runs that were taken out."""
    return df.withColumn("unknown", unknown_runs(F.col("bases"))).withColumn("bases", F.replace("bases", F.lit("N"), F.lit("")))


def merge_unknown(df: DataFrame) -> DataFrame:
    """Puts the runs back; they are in ascending order, so each position is right when its turn comes."""
    def step(acc, run):
        before = F.substring(acc, F.lit(1), run["pos"].cast("int"))
        after = F.substring(acc, (run["pos"] + 1).cast("int"), F.length(acc))
        return F.concat(before, F.repeat(F.lit("N"), run["len"]), after)

    return df.withColumn("bases", F.aggregate("unknown", F.col("bases"), step))


def base_rows(df: DataFrame) -> DataFrame:
    """One row for each base: (.., pos, base, code); no shuffle."""
    out = df.where(F.length("bases") > 0).select("*", F.posexplode(F.split("bases", "")).alias("pos", "base")).where("base <> ''")
    return out.withColumn("pos", F.col("pos").cast("long")).withColumn("code", code(F.col("base"))).drop("bases")
