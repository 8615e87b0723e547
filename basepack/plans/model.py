"""Model configurations, their cost, weights as tables."""

from __future__ import annotations

import hashlib
from dataclasses import asdict, dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class ModelConfig:
    kind: str = "carry"  # carry, lstm, bilstm
    d_model: int = 16
    ffn: int = 32
    heads: int = 1
    hidden: int = 16
    context: int = 64
    kernel: int = 24
    pool: int = 3
    alphabet: int = 4
    input_coding: str = "one_hot"  # one_hot, embedding
    embed_width: int = 4
    ngram: int = 1
    byte_group: int = 1
    group_mode: str = "extend_context"
    memory: str = "latent"  # none, features, latent
    segments: int = 1
    position: str = "relative"  # none, absolute, relative
    block_order: str = "listed"  # listed, standard
    dropout: float = 0.1
    numeric_mode: str = "grid"  # lockstep, grid

    @property
    def raw_context(self) -> int:
        return self.context * (self.byte_group if self.group_mode == "extend_context" else 1)

    @property
    def width(self) -> int:
        """Input width of a word before byte grouping."""
        if self.input_coding == "embedding" or self.ngram > 1 or self.byte_group > 1:
            return self.embed_width
        return 4

    @property
    def rows(self) -> int:
        """N: rows of features of one window."""
        return (self.raw_context // self.ngram // self.byte_group - self.kernel + 1) // self.pool

    def digest(self) -> str:
        return hashlib.md5(repr(sorted(asdict(self).items())).encode()).hexdigest()[:16]


TINY = ModelConfig()
SMALL = replace(TINY, d_model=64, ffn=128, heads=2)
PAPER = ModelConfig(d_model=768, ffn=3072, hidden=512)
PRESETS = {"tiny": TINY, "small": SMALL, "paper": PAPER}
BYTE = replace(TINY, byte_group=2)
MULTI = replace(TINY, byte_group=2, ngram=2)
LSTM = replace(TINY, kind="lstm")
BILSTM = replace(TINY, kind="bilstm")


def memory_grid(base: ModelConfig = TINY) -> dict[str, ModelConfig]:
    """Latent carry by segment cut; without the cut the memory holds three windows."""
    return {
        "cut_only": replace(base, memory="features", segments=1),
        "latent_only": replace(base, memory="latent", segments=3),
        "both": replace(base, memory="latent", segments=1),
        "neither": replace(base, memory="features", segments=3),
    }


def model_cost(cfg: ModelConfig, batch: int = 64) -> list[tuple[str, int, int]]:
    """(layer, parameters, multiply-accumulates of a batch of windows)."""
    d, n = cfg.d_model, cfg.rows
    e = cfg.width * cfg.byte_group
    conv = cfg.raw_context // cfg.ngram // cfg.byte_group - cfg.kernel + 1
    out = []
    if cfg.width != 4 or cfg.input_coding == "embedding" or cfg.ngram > 1 or cfg.byte_group > 1:
        out.append(("embedding", 4**cfg.ngram * cfg.width, 0))
    out.append(("conv", cfg.kernel * e * d + d, conv * cfg.kernel * e * d))
    if cfg.kind == "carry":
        m = n * (1 + (cfg.segments if cfg.memory != "none" else 0))
        out.append(("batch_norm", 2 * d, 0))
        out.append(("attention", 3 * d * d + 2 * d, n * d * d + 2 * m * d * d + 2 * n * m * d))
        out.append(("layer_norm", 4 * d, 0))
        out.append(("feed_forward", 2 * d * cfg.ffn + cfg.ffn + d, n * 2 * d * cfg.ffn))
        out.append(("head", d * cfg.alphabet + cfg.alphabet, d * cfg.alphabet))
    else:
        h, sides = cfg.hidden, 2 if cfg.kind == "bilstm" else 1
        out.append(("lstm", sides * (4 * h * (d + h) + 4 * h), sides * n * 4 * h * (d + h)))
        if sides == 2:
            out.append(("attention", 2 * h, 2 * n * 2 * h))
        out.append(("head", sides * h * cfg.alphabet + cfg.alphabet, sides * h * cfg.alphabet))
    return [(layer, p, macs * batch) for layer, p, macs in out]


def cost_without_attention(cfg: ModelConfig) -> int:
    return sum(p for layer, p, _ in model_cost(cfg) if layer != "attention")


def save(spark: SparkSession, weights: dict[str, np.ndarray], path: str, weights_id: str) -> None:
    rows = [(weights_id, k, list(v.shape), v.astype("<f8").tobytes()) for k, v in weights.items()]
    spark.createDataFrame(rows, "weights_id string, name string, shape array<int>, data binary").write.mode("append").parquet(path)


def load(table: DataFrame, weights_id: str) -> dict[str, np.ndarray]:
    """A model has a few dozen tensors, so they are read on the driver and broadcast."""
    rows = table.where(table["weights_id"] == weights_id).collect()
    return {r["name"]: np.frombuffer(r["data"], "<f8").reshape(r["shape"]).copy() for r in rows}
