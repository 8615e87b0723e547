"""Training: lanes walk sequences in order, gradients are averaged over tasks, RMSProp steps on the driver.

sync='step' sums gradients of all partitions for every update; sync='epoch' lets each partition take its
own steps and averages the weights after the epoch. What returns to the driver is one model per partition.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import nn
from ..operators.codec import codes_of
from .model import ModelConfig


class RMSProp:
    def __init__(self, rate: float = 1e-3, decay: float = 0.99, eps: float = 1e-8) -> None:
        self.rate, self.decay, self.eps, self.mean = rate, decay, eps, {}

    def step(self, w: dict, grad: dict) -> None:
        for k, g in grad.items():
            m = self.mean[k] = self.decay * self.mean.get(k, 0.0) + (1 - self.decay) * g * g
            w[k] = w[k] - self.rate * g / (np.sqrt(m) + self.eps)


def lane_text(sequences: list[str], lanes: int, context: int) -> np.ndarray:
    """(lanes, steps): all sequences one after the other, cut into equal lanes; the last lane is filled up from the start, so
    that no base is left out."""
    codes = np.concatenate([codes_of(s).astype(np.uint8) for s in sequences] or [np.zeros(0, np.uint8)])
    width = max(context + 1, -(-len(codes) // lanes))
    return np.resize(codes, lanes * width).reshape(lanes, width) if len(codes) else np.zeros((lanes, context + 1), np.uint8)


def side_by_side(parts: dict[str, list[str]], lanes: int, context: int) -> np.ndarray:
    """`lanes` lanes of each corpus one under the other; shorter ones start again, so that every step has them all."""
    texts = [lane_text(x, lanes, context) for _, x in sorted(parts.items())]
    width = max(t.shape[1] for t in texts)
    return np.concatenate([np.resize(t, (lanes, width)) if t.shape[1] == width else np.stack([np.resize(row, width) for row in t]) for t in texts])


def gradients(w, stats, cfg: ModelConfig, window, target, state, rng):
    t = {k: nn.Tensor(v) for k, v in w.items()}
    logits, keep = nn.step(window, state, t, cfg, stats, rng)
    value = nn.loss(logits, target)
    value.backward()
    return float(value.data), {k: v.grad for k, v in t.items() if v.grad is not None}, keep


def walk(text: np.ndarray, w, stats, cfg: ModelConfig, steps: int | None, rate: float, seed: int = 0, start: int = 0):
    """Local epoch of `steps` updates over lanes of text from position `start` on, round and round: weights and mean loss in bits.
    steps=None: the whole text, once."""
    rng, opt, state, total = np.random.default_rng(seed), RMSProp(rate), None, 0.0
    last = text.shape[1] - cfg.raw_context
    start, steps = (0, last) if steps is None else (start, min(steps, last))
    for k in range(steps):
        t = (start + k) % last
        if t == 0:
            state = None
        window, target = text[:, t : t + cfg.raw_context], text[:, t + cfg.raw_context]
        value, grad, state = gradients(w, stats, cfg, window, target, state, rng)
        opt.step(w, grad)
        total += value
    return w, total / max(1, steps)


#: Places of a lane whose features are computed at once, and numbers of their windows at most.
AHEAD = 256
NUMBERS = 1 << 20


def validate_all(text: np.ndarray, models: list, cfg: ModelConfig) -> tuple[list[float], int]:
    """Code length in bits under each (weights, statistics), and number of bases, over whole lanes; all models walk in step."""
    last, bits = text.shape[1] - cfg.raw_context, np.zeros(len(models))
    ahead = max(1, min(AHEAD, NUMBERS // (len(models) * len(text) * cfg.rows * cfg.d_model)))
    walk = nn.walker([w for w, _ in models], cfg, len(text))
    for a in range(0, last, ahead):
        b = min(a + ahead, last)
        part = text[:, a : b - 1 + cfg.raw_context]
        logits = walk(np.stack([nn.every_window(nn.track(part, w, cfg, stats), b - a, cfg) for w, stats in models]))
        target = text[:, a + cfg.raw_context : b + cfg.raw_context].T.reshape(-1)
        bits += [float(nn.loss(x.reshape(len(target), -1), target)) * len(target) for x in logits]
    return bits.tolist(), max(0, last) * len(text)


def validate(text: np.ndarray, w, stats, cfg: ModelConfig) -> tuple[float, int]:
    """validate_all of one model."""
    (bits,), n = validate_all(text, [(w, stats)], cfg)
    return bits, n


def _pack(w: dict, stats: dict) -> bytes:
    import pickle

    return pickle.dumps((w, stats), 5)


def fit(train: DataFrame, val: DataFrame, cfg: ModelConfig, epochs: int = 3, lanes: int = 64, steps: int | None = 100, rate: float = 1e-3, seed: int = 42, partitions: int = 4):
    """Epoch-synchronous training on (seq_id, bases) and, if there is one, corpus: (weights, stats, history rows); keeps the
    best validation epoch. Each task takes `steps` updates an epoch over `lanes` lanes of each corpus and goes on in the next
    epoch where it stopped, or with steps=None goes over all of its bases in every epoch; validation goes over all of its bases.
    Learning does not wait for validation, which comes last, for all epochs at once; where there are more cores than partitions,
    the lanes of each partition are shared by several tasks."""
    import pickle

    def listed(df):
        corpus = F.col("corpus") if "corpus" in df.columns else F.lit("")
        return df.select(corpus.alias("corpus"), F.col("seq_id").cast("long").alias("seq_id"), "bases")

    def grouped(batches):
        parts: dict[str, list[str]] = {}
        for b in batches:
            for name, s in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), strict=True):
                parts.setdefault(name, []).append(s)
        return parts

    spark = train.sparkSession
    w, stats = nn.init(cfg, seed), nn.running(cfg)
    dealt = listed(train).repartition(partitions, "seq_id").sortWithinPartitions("corpus", "seq_id")
    shares = max(1, min(lanes, spark.sparkContext.defaultParallelism // partitions))
    # Shares of a partition are tasks side by side: the same rows, of which each takes other lanes.
    first = F.pmod(F.hash("seq_id"), F.lit(partitions)) * shares
    check = listed(val).select("*", F.explode(F.sequence(first, first + (shares - 1))).alias("task")).repartitionById(partitions * shares, F.col("task"))
    check = check.sortWithinPartitions("corpus", "seq_id").select("corpus", "seq_id", "bases", "task")
    ends, losses = [], []
    for epoch in range(epochs):
        shared = spark.sparkContext.broadcast((w, stats))

        def learn(batches, shared=shared, epoch=epoch):
            w, stats = ({k: v.copy() for k, v in x.items()} for x in shared.value)
            parts = grouped(batches)
            if parts:
                text = side_by_side(parts, lanes, cfg.raw_context)
                w, value = walk(text, w, stats, cfg, steps, rate, epoch, epoch * (steps or 0))
                yield pa.RecordBatch.from_arrays([pa.array([_pack(w, stats)], pa.binary()), pa.array([value])], ["w", "loss"])

        rows = dealt.mapInArrow(learn, "w binary, loss double").collect()
        models = sorted(bytes(r["w"]) for r in rows)
        loaded = [pickle.loads(m) for m in models]
        w = {k: np.mean([m[0][k] for m in loaded], axis=0) for k in w}
        stats = {k: np.mean([m[1][k] for m in loaded], axis=0) for k in stats}
        ends.append((w, stats))
        losses.append(float(np.mean([r["loss"] for r in rows])))
        shared.unpersist()
    judged = spark.sparkContext.broadcast(ends)

    def judge(batches):
        from pyspark import TaskContext

        models, share = judged.value, TaskContext.get().partitionId() % shares
        bits, n = np.zeros(len(models)), 0
        for x in grouped(batches).values():
            found, k = validate_all(lane_text(x, lanes, cfg.raw_context)[share::shares], models, cfg)
            bits, n = bits + found, n + k
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(range(len(models)), pa.int32()), pa.array(bits), pa.array([n] * len(models), pa.int64())], ["epoch", "bits", "n"])

    v = check.mapInArrow(judge, "epoch int, bits double, n long").collect()
    judged.unpersist()
    history, best = [], None
    for epoch, (w, stats) in enumerate(ends):
        mine = [r for r in v if r["epoch"] == epoch]
        bpb = sum(r["bits"] for r in mine) / max(1, sum(r["n"] for r in mine))
        history.append((epoch, losses[epoch], bpb))
        if best is None or bpb < best[2]:
            best = w, stats, bpb
    return best[0], best[1], history


def fit_steps(train: DataFrame, cfg: ModelConfig, steps: int = 20, lanes: int = 64, rate: float = 1e-3, seed: int = 42, partitions: int = 2):
    """Step-synchronous training: every update is the mean gradient of all partitions. For small numbers of steps."""
    import pickle

    spark = train.sparkSession
    w, stats, opt, losses = nn.init(cfg, seed), nn.running(cfg), RMSProp(rate), []
    dealt = train.select("seq_id", "bases").repartition(partitions, "seq_id").sortWithinPartitions("seq_id").cache()
    for t in range(steps):
        shared = spark.sparkContext.broadcast((w, stats))

        def grads(batches, shared=shared, t=t):
            w, stats = shared.value
            seqs = [s for b in batches for s in b.column(1).to_pylist()]
            if seqs:
                text = lane_text(seqs, lanes, cfg.raw_context)
                at = t % max(1, text.shape[1] - cfg.raw_context)
                value, g, _ = gradients(w, stats, cfg, text[:, at : at + cfg.raw_context], text[:, at + cfg.raw_context], None, np.random.default_rng(t))
                yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(g, 5)], pa.binary()), pa.array([value])], ["g", "loss"])

        rows = dealt.mapInArrow(grads, "g binary, loss double").collect()
        gs = [pickle.loads(b) for b in sorted(bytes(r["g"]) for r in rows)]
        opt.step(w, {k: np.mean([g[k] for g in gs], axis=0) for k in gs[0]})
        losses.append(float(np.mean([r["loss"] for r in rows])))
        shared.unpersist()
    dealt.unpersist()
    return w, stats, losses


def fit_mixed(train: dict[str, DataFrame], val: dict[str, DataFrame], cfg: ModelConfig, **options):
    """One model for several corpora: 64 lanes of each stand side by side in every batch, at twice the rate."""
    options.setdefault("rate", 2e-3)

    def union(parts):
        every = None
        for name, df in sorted(parts.items()):
            one = df.select(F.lit(name).alias("corpus"), "seq_id", "bases")
            every = one if every is None else every.unionByName(one)
        return every

    return fit(union(train), union(val), cfg, **{"lanes": 64, **options})
