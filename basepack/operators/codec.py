"""Compression and decompression of sequences by learned and adaptive coders, groups in lock-step lanes.

A container row is one group: its fragment at two bits a base, its payload, the runs of unknown bases.
Groups are dealt to `spark.sql.shuffle.partitions` tasks and sorted there by length; each task cuts its groups into lane
batches. Batches always have exactly `lanes` lanes (short ones are filled up), and task (shard), batch and lane of a group are
stored, so the same arrays meet at both ends; in grid mode all sums are exact besides. Decoding yields groups as
rows; only what asks for whole sequences puts them together.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import alphabet as A
from ..functions import jvm
from ..functions.coder import added, decode_lanes, encode_lanes, exp2_of, log2_of, quantise, quantise_columns
from ..plans.model import ModelConfig
from . import nn
from .grouping import fixed_groups

_CODE = np.zeros(256, np.int64)
for _i, _b in enumerate(b"AGCT"):
    _CODE[_b] = _i
_BASE = np.frombuffer(b"AGCT", np.uint8)

ROWS = (
    "corpus string, seq_id long, group_id int, start long, n_bases int, shard int, batch long, lane long, fragment binary, "
    "payload binary, n_bits long, codec string, config_hash string"
)


def codes_of(bases: str) -> np.ndarray:
    return _CODE[np.frombuffer(bases.encode(), np.uint8)]


def bases_of(codes: np.ndarray) -> str:
    return _BASE[codes].tobytes().decode()


def pack2(codes: np.ndarray) -> bytes:
    c = np.concatenate((codes, np.zeros(-len(codes) % 4, np.int64))).reshape(-1, 4)
    return (c @ np.array([64, 16, 4, 1])).astype(np.uint8).tobytes()


def unpack2(data: bytes, n: int) -> np.ndarray:
    b = np.frombuffer(data, np.uint8).astype(np.int64)
    return np.stack([(b >> s) & 3 for s in (6, 4, 2, 0)], axis=1).reshape(-1)[:n]


#: Contexts of one table over all lanes of a batch.
SLOTS = 1 << 20


def slots_of(lanes: int) -> int:
    """Contexts of higher orders share slots, fewer the more lanes there are: some 32 MB a table at most."""
    return 4 ** max(5, min(8, (SLOTS // lanes).bit_length() // 2))


#: What a context has seen of each base before it has seen any, and how fast an order's past success is forgotten.
ALPHA, DECAY = 1 / 16, 0.98


class ModelStep:
    """Counts for the next base of every lane, from a learned model over the bases before."""

    def __init__(self, weights, stats, cfg: ModelConfig, first: np.ndarray) -> None:
        self.w, self.stats, self.cfg = weights, stats, cfg
        self.window = first[:, -cfg.raw_context :].copy()
        self.state = None

    def __call__(self, prev):
        if prev is not None:
            self.window = np.concatenate((self.window[:, 1:], prev[:, None]), axis=1)
        logits, self.state = nn.step(self.window, self.state, self.w, self.cfg, self.stats)
        return quantise(nn.softmax(logits))


class OrderStep:
    """Adaptive finite-context models of several orders; each lane mixes them by how well they did."""

    def __init__(self, orders, lanes: int, first: np.ndarray, alpha: float = ALPHA, decay: float = DECAY) -> None:
        self.orders, self.alpha, self.decay = orders, alpha, decay
        self.slots = slots_of(lanes)
        sizes = [min(4**k, self.slots) for k in orders]
        self.tables = [np.zeros((lanes * n, 4), np.float32) for n in sizes]
        self.flat = [t.reshape(-1) for t in self.tables]
        self.score = np.zeros((len(orders), lanes))
        self.past = np.zeros(lanes, np.int64)  # the bases of the longest context as one number
        self.mask = 4 ** max(orders, default=0) - 1
        self.rows = np.arange(lanes)
        self.begin = [self.rows * n for n in sizes]
        # By base, order and lane, so that sums over bases and orders run along lanes.
        self.probs = None
        self.at = np.arange(len(orders))[:, None]
        self.keys = None
        for t in range(first.shape[1]):
            self(first[:, t], quiet=True)

    def __call__(self, prev, quiet=False):
        if prev is not None:
            if self.probs is not None:
                self.score *= self.decay
                self.score += log2_of(self.probs[prev, self.at, self.rows])
            if self.keys is not None:
                for t, k in zip(self.flat, self.keys, strict=True):
                    t[k * 4 + prev] += 1
            self.past = (self.past * 4 + prev) & self.mask
        self.keys = []
        probs = np.empty((4, len(self.orders), len(self.rows)))
        for i, (k, t, begin) in enumerate(zip(self.orders, self.tables, self.begin, strict=True)):
            key = self.past & (4**k - 1)
            key = begin + (key if 4**k <= self.slots else (key * 2654435761 >> 7) % self.slots)
            self.keys.append(key)
            probs[:, i] = t.take(key, axis=0).T
        probs += self.alpha
        probs /= added(probs)
        self.probs = probs
        if quiet:
            return None
        weight = exp2_of(np.clip(self.score - self.score.max(axis=0), -40, 0))
        p = added((probs * weight).swapaxes(0, 1)) / added(weight)
        p = np.rint(p * 65536) / 65536
        return quantise_columns(p / added(p)).T


class Coder:
    """What goes to the executors: how to make a step for a batch of lanes."""

    def __init__(self, codec: str, cfg: ModelConfig | None = None, weights=None, stats=None, orders=(1, 2, 4, 8)) -> None:
        self.codec, self.cfg, self.weights, self.orders = codec, cfg, weights, orders
        self.stats = stats if stats is not None else (nn.running(cfg) if cfg else None)
        if cfg and cfg.numeric_mode == "grid":
            self.weights = {k: nn.snap(v) for k, v in weights.items()}

    @property
    def fragment(self) -> int:
        return self.cfg.raw_context if self.cfg else 0

    def in_jvm(self, spark) -> bool:
        """Whether lanes are coded by functions of the JVM, each alone: by contexts, to the same bytes as here."""
        return self.cfg is None and 0 < max(self.orders, default=0) <= jvm.LONGEST and len(self.orders) <= jvm.MOST and jvm.ready(spark)

    def contexts(self, lanes: int):
        return self.orders, slots_of(lanes), ALPHA, DECAY

    def digest(self) -> str:
        return self.cfg.digest() if self.cfg else "-".join(map(str, self.orders))

    def step(self, lanes: int, first: np.ndarray):
        return ModelStep(self.weights, self.stats, self.cfg, first) if self.cfg else OrderStep(self.orders, lanes, first)


def model_coder(cfg: ModelConfig, codec: str = "carry", seed: int = 42, weights=None, stats=None) -> Coder:
    return Coder(codec, cfg, weights if weights is not None else nn.init(cfg, seed), stats)


def order_coder(orders=(1, 2, 4, 8)) -> Coder:
    return Coder("context", orders=orders)


def encode_batch(coder: Coder, sequences: list[str], lanes: int) -> list[tuple[bytes, bytes]]:
    """(fragment, payload) of up to `lanes` groups."""
    f = coder.fragment
    codes = [codes_of(s) for s in sequences]
    frags = [pack2(c[:f]) for c in codes]
    lengths = np.array([max(0, len(c) - f) for c in codes] + [0] * (lanes - len(codes)))
    body, first = np.zeros((lanes, lengths.max(initial=0)), np.int64), np.zeros((lanes, f), np.int64)
    for i, c in enumerate(codes):
        body[i, : lengths[i]] = c[f:]
        first[i, : min(f, len(c))] = c[:f]
    data = encode_lanes(coder.step(lanes, first), body, lengths)
    return list(zip(frags, data[: len(codes)], strict=True))


def decode_batch(coder: Coder, rows: list[tuple[bytes, bytes, int]], lanes: int) -> list[str]:
    """rows: (fragment, payload, bases)."""
    f = coder.fragment
    lengths = np.array([max(0, n - f) for _, _, n in rows] + [0] * (lanes - len(rows)))
    first = np.zeros((lanes, f), np.int64)
    heads = []
    for i, (frag, _, n) in enumerate(rows):
        heads.append(unpack2(frag, min(f, n)))
        first[i, : len(heads[-1])] = heads[-1]
    data = [p for _, p, _ in rows] + [b""] * (lanes - len(rows))
    body = decode_lanes(coder.step(lanes, first), data, lengths)
    return [bases_of(np.concatenate((h, body[i, : lengths[i]]))) for i, h in enumerate(heads)]


def compress(df: DataFrame, coder: Coder, group: int = 1024, lanes: int = 512) -> DataFrame:
    """(corpus, seq_id, bases of A, G, C, T) to container rows; one shuffle, of the groups."""
    spark = df.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    casts = [F.col(n).cast(t).alias(n) for n, t in (("corpus", "string"), ("seq_id", "long"), ("group_id", "int"), ("start", "long"), ("n_bases", "int"))]
    groups = fixed_groups(df, group).select(*casts, "bases")
    dealt = groups.repartition(tasks, "seq_id", "group_id").sortWithinPartitions("n_bases", "corpus", "seq_id", "group_id")
    names = ("corpus", "seq_id", "group_id", "start", "n_bases")
    if coder.in_jvm(spark):
        number = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))  # of the row in its task
        rows = dealt.select(*names, "bases", F.spark_partition_id().alias("shard"), number.alias("k"))
        place = (F.expr(f"k div {lanes}").alias("batch"), (F.col("k") % lanes).alias("lane"))
        rows = rows.select(*names, "shard", *place, F.expr("X''").alias("fragment"), jvm.encoded(F.col("bases"), *coder.contexts(lanes)).alias("payload"))
        more = (F.lit(coder.codec).alias("codec"), F.lit(coder.digest()).alias("config_hash"))
        return rows.select("*", (8 * F.length("payload")).cast("long").alias("n_bits"), *more)
    shared = spark.sparkContext.broadcast(coder)

    def encode(rows: pa.Table, shard: int, batch: int) -> pa.RecordBatch:
        c, k = shared.value, rows.num_rows
        out = encode_batch(c, rows.column("bases").to_pylist(), lanes)
        bits = [2 * min(c.fragment, n) + 8 * len(p) for (_, p), n in zip(out, rows.column("n_bases").to_pylist(), strict=True)]
        cols = [rows.column(n).combine_chunks() for n in names]
        cols += [pa.array([shard] * k, pa.int32()), pa.array([batch] * k, pa.int64()), pa.array(range(k), pa.int64())]
        cols += [pa.array([f for f, _ in out], pa.binary()), pa.array([p for _, p in out], pa.binary()), pa.array(bits, pa.int64())]
        cols += [pa.array([c.codec] * k, pa.string()), pa.array([c.digest()] * k, pa.string())]
        more = ("shard", "batch", "lane", "fragment", "payload", "n_bits", "codec", "config_hash")
        return pa.RecordBatch.from_arrays(cols, [*names, *more])

    def run(batches):
        from pyspark import TaskContext

        shard, number, rest = TaskContext.get().partitionId(), 0, None
        for b in batches:
            t = pa.Table.from_batches([b])
            rest = t if rest is None else pa.concat_tables([rest, t])
            while rest.num_rows >= lanes:
                yield encode(rest.slice(0, lanes), shard, number)
                rest, number = rest.slice(lanes), number + 1
        if rest is not None and rest.num_rows:
            yield encode(rest, shard, number)

    return dealt.mapInArrow(run, ROWS)


def decode_groups(container: DataFrame, coder: Coder, lanes: int = 512) -> DataFrame:
    """Container rows to (corpus, seq_id, group_id, start, bases), a row each; a task per lane batch."""
    # The bytes are few and the work is much: a fixed number of tasks, which is not coalesced by size.
    tasks = int(container.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = container.repartition(tasks, "shard", "batch")
    if coder.in_jvm(container.sparkSession):
        other = F.raise_error(F.lit("the container was written with another configuration"))
        bases = jvm.decoded(F.col("payload"), F.col("n_bases"), *coder.contexts(lanes))
        return dealt.select("corpus", "seq_id", "group_id", "start", F.when(F.col("config_hash") == coder.digest(), bases).otherwise(other.cast("string")).alias("bases"))
    shared = container.sparkSession.sparkContext.broadcast(coder)

    def run(table: pa.Table) -> pa.Table:
        c = shared.value
        if set(table.column("config_hash").to_pylist()) != {c.digest()}:
            raise ValueError("the container was written with another configuration")
        t = table.sort_by("lane")
        rows = list(zip(t.column("fragment").to_pylist(), t.column("payload").to_pylist(), t.column("n_bases").to_pylist(), strict=True))
        cols = {n: t.column(n).combine_chunks() for n in ("corpus", "seq_id", "group_id", "start")}
        return pa.table(cols | {"bases": pa.array(decode_batch(c, rows, lanes), pa.string())})

    return dealt.groupBy("shard", "batch").applyInArrow(run, "corpus string, seq_id long, group_id int, start long, bases string")


def _joined() -> F.Column:
    return F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("start", "bases"))), lambda x: x["bases"]), "")


def decompress(container: DataFrame, coder: Coder, lanes: int = 512) -> DataFrame:
    """Container rows to (corpus, seq_id, bases), for sequences that fit a row (2 GB); decode_groups has no such bound."""
    return decode_groups(container, coder, lanes).groupBy("corpus", "seq_id").agg(_joined().alias("bases"))


def read_range(container: DataFrame, coder: Coder, seq_id: int, start: int, stop: int, group: int, lanes: int = 512) -> DataFrame:
    """Bases [start, stop) of one sequence: only the lane batches that hold its groups are decoded."""
    low, high = start // group, max(start, stop - 1) // group
    mine = (F.col("seq_id") == seq_id) & F.col("group_id").between(low, high)
    wanted = container.where(mine).select("shard", "batch").distinct()  # at most as many rows as the range has groups
    batches = container.join(F.broadcast(wanted), ["shard", "batch"], "left_semi")
    seq = decode_groups(batches, coder, lanes).where(mine).groupBy("corpus", "seq_id").agg(_joined().alias("bases"))
    return seq.select("seq_id", F.substring("bases", F.lit(start - low * group + 1), F.lit(max(0, stop - start))).alias("piece"))


class StaticStep:
    """The same counts at every step: static arithmetic coding of each lane under its own frequencies."""

    def __init__(self, freq: np.ndarray) -> None:
        self.counts = quantise((freq + 1e-9) / (freq + 1e-9).sum(axis=1, keepdims=True))

    def __call__(self, prev):
        return self.counts


def static_encode(df: DataFrame) -> DataFrame:
    """(seq_id, n, freq, payload) of short sequences (seq_id, bases of A, G, C, T): frequencies, then the coded bases."""
    def run(batches):
        for b in batches:
            codes = [codes_of(s) for s in b.column(1).to_pylist()]
            n = np.array([len(c) for c in codes], np.int64)
            body, freq = np.zeros((len(codes), n.max(initial=0)), np.int64), np.zeros((len(codes), 4), np.int64)
            for i, c in enumerate(codes):
                body[i, : n[i]] = c
                freq[i] = np.bincount(c, minlength=4)
            data = encode_lanes(StaticStep(freq), body, n) if len(codes) else []
            cols = [b.column(0), pa.array(n), pa.array(freq.tolist(), pa.list_(pa.int64())), pa.array(data, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, ["seq_id", "n", "freq", "payload"])

    return df.select(F.col("seq_id").cast("long").alias("seq_id"), "bases").mapInArrow(run, "seq_id long, n long, freq array<long>, payload binary")


def static_decode(coded: DataFrame) -> DataFrame:
    """(seq_id, bases) of static_encode's rows; batches need not be the same."""
    def run(batches):
        for b in batches:
            n = np.array(b.column(1).to_pylist(), np.int64)
            freq = np.array(b.column(2).to_pylist(), np.int64).reshape(len(n), 4)
            body = decode_lanes(StaticStep(freq), b.column(3).to_pylist(), n)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([bases_of(body[i, : n[i]]) for i in range(len(n))], pa.string())], ["seq_id", "bases"])

    return coded.select("seq_id", "n", "freq", "payload").mapInArrow(run, "seq_id long, bases string")


def round_trip(df: DataFrame, coder: Coder, group: int = 1024, lanes: int = 512) -> DataFrame:
    """(seq_id, n_bases, md5): of what comes back; unknown bases travel beside the payload."""
    known = A.split_unknown(df)
    back = decompress(compress(known.select("corpus", "seq_id", "bases"), coder, group, lanes), coder, lanes)
    side = known.select("corpus", "seq_id", "unknown")
    joined = side.join(back, ["corpus", "seq_id"], "left").withColumn("bases", F.coalesce("bases", F.lit("")))
    whole = A.merge_unknown(joined)
    return whole.select("seq_id", F.length("bases").cast("long").alias("n_bases"), F.md5(F.col("bases").cast("binary")).alias("digest"))
