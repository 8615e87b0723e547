"""Arithmetic coding: a real-valued interval fold as expressions, and an integer range coder over lanes."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOTAL_BITS = 16
TOTAL = 1 << TOTAL_BITS


def interval(steps: Column) -> Column:
    """struct(low, width) after an array of (below, share) structs, from the whole unit interval."""
    start = F.struct(F.lit(0.0).alias("low"), F.lit(1.0).alias("width"))
    return F.aggregate(
        steps, start,
        lambda acc, s: F.struct((acc["low"] + s["below"] * acc["width"]).alias("low"), (acc["width"] * s["share"]).alias("width")),
    )


#: A part of a block ends before its width falls below this: doubles then tell its tag from those of all other bases.
NARROWEST = 2.0**-40


def parts(steps: Column) -> Column:
    """[struct(low, width, n)] after an array of (below, share) structs: as `interval`, but begun anew from the unit interval
    whenever the width would fall below NARROWEST, so that no block is too improbable for doubles."""
    part = "struct<low:double,width:double,n:int>"
    start = F.struct(F.array().cast(f"array<{part}>").alias("done"), F.lit(0.0).alias("low"), F.lit(1.0).alias("width"), F.lit(0).alias("n"))

    def step(acc, s):
        full = (acc["n"] > 0) & (acc["width"] * s["share"] < NARROWEST)
        own = F.array(F.struct(acc["low"].alias("low"), acc["width"].alias("width"), acc["n"].alias("n")))
        return F.struct(
            F.when(full, F.concat(acc["done"], own)).otherwise(acc["done"]).alias("done"),
            F.when(full, s["below"]).otherwise(acc["low"] + s["below"] * acc["width"]).alias("low"),
            F.when(full, s["share"]).otherwise(acc["width"] * s["share"]).alias("width"),
            F.when(full, F.lit(1)).otherwise(acc["n"] + 1).alias("n"),
        )

    return F.aggregate(steps, start, step, lambda a: F.concat(a["done"], F.array(F.struct(a["low"].alias("low"), a["width"].alias("width"), a["n"].alias("n")))))


def shortest_tag(low: Column, width: Column) -> tuple[Column, Column]:
    """Bits of a binary fraction inside the interval, and the fraction."""
    bits = F.ceil(-F.log2(width)) + 1
    return bits, F.ceil(low * F.pow(F.lit(2.0), bits)) / F.pow(F.lit(2.0), bits)


def order0(rows: DataFrame) -> DataFrame:
    """(seq_id, code, below, share): frequencies of the bases of each sequence, in the order of the alphabet."""
    from pyspark.sql import Window

    counts = rows.groupBy("seq_id", "code").agg(F.count("*").alias("n"))
    w = Window.partitionBy("seq_id")
    run = w.orderBy("code").rowsBetween(Window.unboundedPreceding, -1)
    total = F.sum("n").over(w)
    return counts.select(
        "seq_id", "code", "n", (F.coalesce(F.sum("n").over(run), F.lit(0)) / total).alias("below"), (F.col("n") / total).alias("share")
    )


def quantise(p: np.ndarray) -> np.ndarray:
    """Rows of probabilities to rows of counts of at least 1 that sum to 2^16; ties go to the lowest code."""
    a = p.shape[-1]
    n = 1 + np.floor(p * (TOTAL - a)).astype(np.int64)
    top = n.argmax(axis=-1)
    np.put_along_axis(n, top[..., None], np.take_along_axis(n, top[..., None], -1) + TOTAL - n.sum(axis=-1, keepdims=True), -1)
    return n


def added(x: np.ndarray) -> np.ndarray:
    """Sum over the first axis, one after the other."""
    total = x[0]
    for y in x[1:]:
        total = total + y
    return total


#: Series, highest power first: of log2(m) in squares of (m - 1) / (m + 1), and of 2^f in f. Libraries give logarithms whose last bit
#: differs from machine to machine; sums and products in a fixed order don't, so that what one machine coded any other decodes.
LOG2 = [2 / math.log(2) / (2 * k + 1) for k in range(12, -1, -1)]
EXP2 = [math.log(2) ** k / math.factorial(k) for k in range(14, -1, -1)]


def log2_of(x: np.ndarray) -> np.ndarray:
    """log2 of positive numbers, to some 1e-16 of it or of 1."""
    m, e = np.frexp(x)
    low = m < 0.70710678118654757
    m, e = np.where(low, m + m, m), e - low
    s = (m - 1) / (m + 1)
    z = s * s
    y = np.full_like(z, LOG2[0])
    for c in LOG2[1:]:
        y *= z
        y += c
    return e + s * y


def exp2_of(x: np.ndarray) -> np.ndarray:
    """2^x for x from -1000 to 0."""
    n = np.rint(x)
    f = x - n
    y = np.full_like(f, EXP2[0])
    for c in EXP2[1:]:
        y *= f
        y += c
    return np.ldexp(y, n.astype(np.int32))


def quantise_columns(p: np.ndarray) -> np.ndarray:
    """quantise for probabilities (symbols, lanes)."""
    n = 1 + np.floor(p * (TOTAL - len(p))).astype(np.int64)
    most, top = n[0], np.zeros(n.shape[1], np.int64)
    for i in range(1, len(n)):
        more = n[i] > most
        most, top = np.where(more, n[i], most), np.where(more, i, top)
    n[top, np.arange(n.shape[1])] += TOTAL - added(n)
    return n


class LaneEncoder:
    """Range coders of many lanes in step: 32-bit low with carry, bytes out of each lane."""

    def __init__(self, lanes: int) -> None:
        self.low = np.zeros(lanes, np.uint64)
        self.range = np.full(lanes, 0xFFFFFFFF, np.uint64)
        self.out = np.zeros((lanes, 64), np.uint8)
        self.n = np.zeros(lanes, np.int64)

    def _put(self, at: np.ndarray) -> None:
        if len(at) and self.n[at].max() >= self.out.shape[1] - 1:
            self.out = np.concatenate((self.out, np.zeros_like(self.out)), axis=1)
        self.out[at, self.n[at]] = (self.low[at] >> np.uint64(24)).astype(np.uint8)
        self.n[at] += 1
        self.low[at] = (self.low[at] << np.uint64(8)) & np.uint64(0xFFFFFFFF)

    def encode(self, start: np.ndarray, freq: np.ndarray, on: np.ndarray) -> None:
        """Narrow the lanes numbered `on` by shares of 2^16."""
        r = self.range[on] >> np.uint64(TOTAL_BITS)
        low = self.low[on] + start.astype(np.uint64) * r
        self.range[on] = freq.astype(np.uint64) * r
        over = on[low >> np.uint64(32) > 0]
        self.low[on] = low & np.uint64(0xFFFFFFFF)
        at = self.n[over] - 1
        while len(over):  # carry into bytes that are out
            self.out[over, at] += 1
            more = self.out[over, at] == 0
            over, at = over[more], at[more] - 1
        while len(small := np.flatnonzero(self.range < (1 << 24))):
            self._put(small)
            self.range[small] <<= np.uint64(8)

    def finish(self) -> list[bytes]:
        every = np.arange(len(self.n))
        for _ in range(4):
            self._put(every)
        return [self.out[i, : self.n[i]].tobytes().rstrip(b"\0") for i in every]


class LaneDecoder:
    """The inverse, lane by lane in step; bytes past the end read as zero."""

    def __init__(self, data: list[bytes]) -> None:
        size = max(map(len, data), default=0) + 8
        self.data = np.zeros((len(data), size), np.uint8)
        for i, x in enumerate(data):
            self.data[i, : len(x)] = np.frombuffer(x, np.uint8)
        self.at = np.full(len(data), 4)
        self.code = np.zeros(len(data), np.uint64)
        for k in range(4):
            self.code = (self.code << np.uint64(8)) | self.data[:, k].astype(np.uint64)
        self.range = np.full(len(data), 0xFFFFFFFF, np.uint64)

    def decode(self, cum: np.ndarray, on: np.ndarray) -> np.ndarray:
        """cum: (lanes of `on`, symbols + 1) cumulated counts."""
        r = self.range[on] >> np.uint64(TOTAL_BITS)
        value = np.minimum(self.code[on] // r, TOTAL - 1).astype(np.int64)
        symbol, row = np.zeros(len(cum), np.int64), np.arange(len(cum))
        for i in range(1, cum.shape[1]):
            symbol += cum[:, i] <= value
        start = cum[row, symbol].astype(np.uint64)
        stop = cum[row, symbol + 1].astype(np.uint64)
        self.code[on] -= start * r
        self.range[on] = (stop - start) * r
        while len(small := np.flatnonzero(self.range < (1 << 24))):
            at = np.minimum(self.at[small], self.data.shape[1] - 1)
            self.code[small] = (self.code[small] << np.uint64(8)) | self.data[small, at].astype(np.uint64)
            self.at[small] += 1
            self.range[small] <<= np.uint64(8)
        return symbol


def cumulate(counts: np.ndarray) -> np.ndarray:
    out = np.zeros((*counts.shape[:-1], counts.shape[-1] + 1), np.int64)
    for i in range(counts.shape[-1]):
        np.add(out[..., i], counts[..., i], out=out[..., i + 1])
    return out


def encode_lanes(step, codes: np.ndarray, lengths: np.ndarray) -> list[bytes]:
    """codes: (lanes, steps). step(previous codes or None) gives counts (lanes, symbols) for the next base."""
    coder, prev = LaneEncoder(len(codes)), None
    for t in range(int(lengths.max(initial=0))):
        on = np.flatnonzero(lengths > t)
        cum = cumulate(step(prev))
        now = codes[:, t]
        start, stop = cum[on, now[on]], cum[on, now[on] + 1]
        coder.encode(start, stop - start, on)
        prev = np.where(lengths > t, now, 0)
    return coder.finish()


def decode_lanes(step, data: list[bytes], lengths: np.ndarray) -> np.ndarray:
    coder, prev = LaneDecoder(data), None
    out = np.zeros((len(data), int(lengths.max(initial=0))), np.int64)
    for t in range(out.shape[1]):
        on = np.flatnonzero(lengths > t)
        out[on, t] = coder.decode(cumulate(step(prev))[on], on)
        prev = np.where(lengths > t, out[:, t], 0)
    return out
