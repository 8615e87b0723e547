"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

A document is a sparse row: the share of each hashed word, and one-hot bins of statistics of its
structure (repetition, symbols, lines, word lengths) and of its metadata (length). The machine scores
w0 + sum w_i x_i + sum over pairs <v_i, v_j> x_i x_j; the pairs cost linear time, as half of
(sum v_i x_i)^2 - sum v_i^2 x_i^2 for each factor.

The model is fitted on the driver, by one core, from one text (least hash) of each of at most `max_train` labelled ids
(those of least id hash among the learning folds) and at most `max_features` features of them; every document is scored
in one pass over whole texts.

Defined results: null and empty texts are scored from the statistics alone; very long texts are read whole; repeated rows
are scored alike; two labels of one id count as the larger; ids without label are only scored; without any label every
score is 0.5; an empty table gives an empty result; a column `fm_score` of the input is replaced.
"""

from __future__ import annotations

from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BLOCK_BYTES, blocks, byte_column, fold, map_rows, materialise, packed, unpacked, words_of

WORDS = 1 << 16
BINS = 16
FACTORS = 8
THRESHOLD = 0.3
MAX_TRAIN = 8_000
#: Twelve bytes each on the driver.
MAX_FEATURES = 16_000_000

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#$%&*@^~|<>{}[]=+_\\/"]] = True
_PUNCT = np.zeros(256, bool)
_PUNCT[[ord(c) for c in ".,;:!?'\"()-"]] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
N_STATS = 12
SIZE = WORDS + N_STATS * BINS


def _bin(share: float) -> int:
    """Finer near 0: bin by the square root of a share in 0..1."""
    return min(BINS - 1, int(BINS * max(0.0, share) ** 0.5))


def row_of(data: bytes | None) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers (ascending) and values of one text."""
    data = data or b""
    words = words_of(data)
    n = len(words)
    ids = np.fromiter(map(crc32, words), np.int64, n) & (WORDS - 1)
    feats, counts = np.unique(ids, return_counts=True)
    raw = np.frombuffer(data, np.uint8)
    size = max(1, len(raw))
    lines = [x for x in data.split(b"\n") if x]
    stats = [
        min(BINS - 1, size.bit_length() // 2 * 2),
        _bin(len(feats) / max(1, n)),
        _bin(counts.max() / n if n else 0),
        _bin(float((ids[1:] == ids[:-1]).mean()) if n > 1 else 0),
        _bin(_SYMBOL[raw].sum() / size),
        _bin(_PUNCT[raw].sum() / size),
        _bin(_DIGIT[raw].sum() / size),
        _bin(_UPPER[raw].sum() / size),
        min(BINS - 1, int(size / max(1, n))),
        _bin(1 - len(set(lines)) / max(1, len(lines))),
        min(BINS - 1, len(lines).bit_length()),
        _bin(float((ids[2:] == ids[:-2]).mean()) if n > 2 else 0),
    ]
    numbers = WORDS + np.arange(N_STATS) * BINS + np.array(stats, np.int64)
    return np.concatenate((feats, numbers)), np.concatenate((np.sqrt(counts / max(1, n)), np.full(N_STATS, 0.5)))


def flatten(rows: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    starts = np.cumsum([0] + [len(i) for i, _ in rows[:-1]])
    return np.concatenate([i for i, _ in rows]), np.concatenate([v for _, v in rows]), starts


class Machine:
    """Factorisation machine with logistic loss, AdaGrad steps and L2 penalties."""

    def __init__(self, size: int = SIZE, factors: int = FACTORS, seed: int = 42) -> None:
        rng = np.random.default_rng(seed)
        self.bias = 0.0
        self.w = np.zeros(size)
        self.v = rng.normal(0, 0.05, (size, factors))

    def margins(self, feats, values, starts) -> np.ndarray:
        xv = self.v[feats] * values[:, None]
        total = np.add.reduceat(xv, starts)
        pairs = 0.5 * (total**2 - np.add.reduceat(xv**2, starts)).sum(axis=1)
        return self.bias + np.add.reduceat(self.w[feats] * values, starts) + pairs

    def scores(self, feats, values, starts) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margins(feats, values, starts), -35, 35)))

    def fit(self, rows, labels, epochs: int = 12, batch: int = 64, rate: float = 0.08, decay: float = 2e-5, seed: int = 7) -> Machine:
        labels = np.asarray(labels, float)
        rng = np.random.default_rng(seed)
        mean = min(max(labels.mean(), 0.01), 0.99)
        self.bias = float(np.log(mean / (1 - mean)))
        gw, gv, gb = np.full(len(self.w), 1e-4), np.full(self.v.shape, 1e-4), 1.0
        for _ in range(epochs):
            order = rng.permutation(len(rows))
            for a in range(0, len(order), batch):
                take = order[a : a + batch]
                feats, values, starts = flatten([rows[i] for i in take])
                owner = np.repeat(np.arange(len(take)), np.diff(np.append(starts, len(feats))))
                err = self.scores(feats, values, starts) - labels[take]
                xv = self.v[feats] * values[:, None]
                total = np.add.reduceat(xv, starts)
                used, at = np.unique(feats, return_inverse=True)
                dw = np.bincount(at, err[owner] * values) + decay * self.w[used]
                slope = (err[owner] * values)[:, None] * (total[owner] - xv)
                dv = np.stack([np.bincount(at, slope[:, f]) for f in range(slope.shape[1])], axis=1) + decay * self.v[used]
                gw[used] += dw**2
                gv[used] += dv**2
                gb += err.sum() ** 2
                self.w[used] -= rate * dw / np.sqrt(gw[used])
                self.v[used] -= rate * dv / np.sqrt(gv[used])
                self.bias -= rate * err.sum() / np.sqrt(gb)
        return self


def learning_texts(docs: DataFrame, labels: DataFrame, column: str, learn, limit: int) -> DataFrame:
    """(text, y, h): one text of each of at most `limit` labelled ids that `learn` admits; h is the hash of the text."""
    y = F.col(column).cast("int")
    labelled = labels.where(learn & F.col("doc_id").isNotNull() & y.isin(0, 1))
    picked = labelled.groupBy("doc_id").agg(F.max(y).alias("y")).orderBy(F.xxhash64(F.col("doc_id").cast("string")), "doc_id").limit(limit)
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(picked), "doc_id")
    one = texts.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text", "y")).alias("x"))
    return one.select("x.text", "x.y", "x.h")


def fit(docs: DataFrame, labels: DataFrame, column: str = "quality", mod: int = 5, keep_out: int = 0, max_train: int = MAX_TRAIN, max_features: int = MAX_FEATURES) -> Machine | None:
    texts = learning_texts(docs, labels, column, fold("doc_id", mod) != keep_out, max_train)

    def one(batch):
        found = [row_of(x) for x in byte_column(batch, "text")]
        cols = [pa.array([i.astype(np.int32) for i, _ in found], pa.list_(pa.int32())), pa.array([v for _, v in found], pa.list_(pa.float64())), *batch.columns[1:]]
        yield pa.RecordBatch.from_arrays(cols, ["feats", "vals", "y", "h"])

    found = materialise(map_rows(texts.repartition(max(8, docs.sparkSession.sparkContext.defaultParallelism)), "feats array<int>, vals array<double>, y int, h long", one), "quality-rows")
    before = Window.orderBy("h", "y").rowsBetween(Window.unboundedPreceding, 0)  # over the sizes of at most max_train rows
    sizes = found.select("h", "y", F.size("feats").alias("n")).withColumn("run", F.sum("n").over(before))
    last = sizes.where(F.col("run") <= max_features).agg(F.max("h")).first()[0]
    if last is None:
        return None
    rows = found.where(F.col("h") <= last).toArrow()
    data = [(f.values.to_numpy(), v.values.to_numpy()) for f, v in zip(rows["feats"], rows["vals"], strict=True)]
    order = sorted(range(len(data)), key=lambda i: (data[i][0].tobytes(), data[i][1].tobytes(), rows["y"][i].as_py()))
    return Machine().fit([data[i] for i in order], [rows["y"][i].as_py() for i in order])


def score(docs: DataFrame, model: Machine | None) -> DataFrame:
    """docs (any columns, one named text) plus fm_score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def one(batch):
        texts, out = byte_column(batch, "text"), []
        m = shared.value
        for a, b in blocks([len(x or b"") for x in texts], BLOCK_BYTES):
            out.append(m.scores(*flatten([row_of(x) for x in texts[a:b]])) if m else np.full(b - a, 0.5))
        values = np.concatenate(out) if out else np.zeros(0)
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(values)], [*batch.schema.names, "fm_score"])

    docs = docs.drop("fm_score")  # own name wins
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return map_rows(docs, f"{schema}, fm_score double", one)


def quality_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The contract's columns for every document."""
    model = fit(docs, labels)
    return score(docs.select("doc_id", "text"), model).select(
        "doc_id",
        (fold("doc_id", 5) == 0).alias("held_out"),
        F.col("fm_score").alias("score"),
        (F.col("fm_score") >= THRESHOLD).cast("int").alias("predicted"),
    )


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs that reach the threshold, with the columns they came with."""
    return unpacked(score(packed(docs), fit(docs, labels)).where(F.col("fm_score") >= THRESHOLD), docs.columns)
