"""SimHash near-duplicates by deletion-variant signatures.

A 64-bit fingerprint is cut into two halves. If two fingerprints differ in at most three bits, one
half differs in at most one. Every half is indexed 32 times with one bit deleted, so two halves that
differ in at most one bit share a variant; an equality join of variants finds every pair, and the
distance of the whole fingerprints verifies it.

Exact copies never reach the index: documents are first collapsed to distinct fingerprints with a
map-side combined aggregation. Variants are dealt by key and sorted, and each task walks its buckets
in vectorised steps. A task emits only the links that join two of its groups (a spanning forest), so
a bucket of n fingerprints yields fewer than n links while connectivity stays exact. A large bucket
is cut by the four bytes of its other half: those differ in at most three bits too, so two linked
members agree in one of the four bytes.

Classes are found with alternating star contractions over tables in the shared folder.

Defined results: null, empty and blank texts have fingerprint zero and are linked like any other;
repeated ids and rows are kept; very long texts are read whole; a null id never names a class unless all ids of it are null; an empty
table gives an empty result; other columns are not read by `cluster` and kept by `keep_one`, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_column, map_rows, materialise, packed, unpacked, words_of

MAX_BITS = 3
SEED = 42
SHINGLE = 3
#: Buckets over this many fingerprints are cut by the bytes of the other half.
LARGE_BUCKET = 2_048
CHUNK = 65_536
ROUNDS = 60


def fingerprint(data: bytes | None) -> int:
    words = words_of(data)
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) < SHINGLE:
        hashes = [digest(b" ".join(words), SEED)]
    else:
        line = b" ".join(words)
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = np.concatenate(([0], ends[: -SHINGLE]))
        hashes = [digest(line[a:b], SEED) for a, b in zip(starts.tolist(), (ends[SHINGLE - 1 :] - 1).tolist(), strict=True)]
    counts = np.zeros(64, np.int64)
    values = np.array(hashes, dtype="<u8")
    for i in range(0, len(values), CHUNK):
        part = values[i : i + CHUNK].view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * counts > len(values)).astype(np.uint8)
    return int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, digest: bool = False) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed 64-bit number. digest: a binary column that goes along."""
    more = ["digest"] if digest else []

    def one(batch):
        fps = np.array([fingerprint(x) for x in byte_column(batch, "text")], dtype=np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64()), *batch.columns[2:]], ["doc_id", "fp", *more])

    schema = "doc_id long, fp long" + (", digest binary" if digest else "")
    return map_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *more), schema, one)


def variants(nodes: DataFrame) -> DataFrame:
    """(key, fp): 64 one-deletion variants, the number of half and bit above the 31 bits that are left."""
    half = F.when(F.col("v") < 32, F.col("fp")).otherwise(F.shiftrightunsigned("fp", 32)).bitwiseAND(F.lit(0xFFFFFFFF))
    rest = F.expr("((half >> (bit + 1)) << bit) | (half & ((1L << bit) - 1))")
    return (
        nodes.select("fp", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("v"))
        .select("fp", "v", half.alias("half"), (F.col("v") % 32).alias("bit"))
        .select(F.shiftleft(F.col("v").cast("long"), 31).bitwiseOR(rest).alias("key"), "fp")
    )


class Forest:
    """Union-find over the linked fingerprints of one task."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        up = self.up
        while (y := up.setdefault(x, x)) != x:
            up[x] = x = up[y] if y in up else y
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def near(values: np.ndarray, to: np.uint64) -> np.ndarray:
    return np.bitwise_count(values ^ to) <= MAX_BITS


def walk_bucket(values: np.ndarray, low: bool, emit) -> None:
    """Links that span the near-duplicate graph of one bucket. low: the bucket is keyed by the lower half."""
    if len(values) > LARGE_BUCKET:
        for k in range(4):
            shift = np.uint64(8 * k + (32 if low else 0))
            piece = (values >> shift) & np.uint64(0xFF)
            order = np.argsort(piece, kind="stable")
            cuts = np.flatnonzero(np.diff(piece[order])) + 1
            for part in np.split(values[order], cuts):
                if len(part) > 1:
                    spread(part, emit)
    else:
        spread(values, emit)


def spread(values: np.ndarray, emit) -> None:
    """Breadth-first over values, each taken off the open list as soon as it is reached."""
    open_ = values
    while len(open_) > 1:
        todo, open_ = [open_[0]], open_[1:]
        while todo and len(open_):
            x = todo.pop()
            hit = near(open_, x)
            if hit.any():
                found = open_[hit]
                open_ = open_[~hit]
                for y in found:
                    emit(x, y)
                todo.extend(found)


def link_batches(batches):
    """Sorted (key, fp) batches of one task to links (a, b), a < b as signed numbers."""
    forest, out = Forest(), []

    def emit(x, y):
        a, b = (int(np.uint64(v).view(np.int64)) for v in (x, y))
        if forest.join(a, b):
            out.append((min(a, b), max(a, b)))

    def groups(keys, fps):
        """All buckets of keys are complete here."""
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(keys)) + 1, [len(keys)]))
        sizes = np.diff(cuts)
        for d in range(1, 4):  # buckets of two to four: all pairs at once
            same = (keys[d:] == keys[:-d]) & near(fps[d:], fps[:-d])
            at = np.flatnonzero(same)
            if len(at):
                small = sizes[np.searchsorted(cuts, at, side="right") - 1] <= 4
                for i in at[small].tolist():
                    emit(fps[i], fps[i + d])
        for g in np.flatnonzero(sizes > 4).tolist():
            walk_bucket(fps[cuts[g] : cuts[g + 1]], int(keys[cuts[g]]) >> 31 < 32, emit)

    rest_k, rest_f = [], []
    for b in batches:
        keys, fps = b.column(0).to_numpy(), b.column(1).to_numpy().view(np.uint64)
        if not len(keys):
            continue
        rest_k.append(keys)
        rest_f.append(fps)
        if rest_k[0][0] == keys[-1]:  # one bucket so far: wait for its end
            continue
        keys, fps = np.concatenate(rest_k), np.concatenate(rest_f)
        end = int(np.searchsorted(keys, keys[-1]))
        groups(keys[:end], fps[:end])
        rest_k, rest_f = [keys[end:]], [fps[end:]]
        if out:
            yield _links(out)
            out.clear()
    if rest_k:
        groups(np.concatenate(rest_k), np.concatenate(rest_f))
    if out:
        yield _links(out)


def _links(rows):
    a, b = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])


def links(nodes: DataFrame) -> DataFrame:
    """Links (a, b) between distinct fingerprints that keep every near-duplicate class together."""
    dealt = variants(nodes).repartition("key").sortWithinPartitions("key")
    return dealt.mapInArrow(link_batches, "a long, b long").distinct()


def _state(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first()
    return row[0], row[1]


def classes(edges: DataFrame) -> DataFrame:
    """(u, v): every linked node that is not the smallest of its class, with that smallest node.

    edges: (u, v) of longs. Alternates two star steps until the edges stay as they are: larger
    neighbours are hung on the smallest neighbour, then smaller ones are. Minima are aggregated with
    map-side combine and joined back, so that a node with very many neighbours is no single task.
    """
    now = materialise(edges.where("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc")
    seen = _state(now)
    for _ in range(ROUNDS):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = joined.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = materialise(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "cc")
        state = _state(now)
        if state == seen:
            return now
        seen = state
    raise RuntimeError(f"classes did not settle in {ROUNDS} rounds")


def rooted(nodes: DataFrame) -> DataFrame:
    """nodes (one row a fingerprint fp, and other columns) with the root of each one's class."""
    roots = classes(links(nodes.select("fp")).select(F.col("a").alias("u"), F.col("b").alias("v")))
    with_root = nodes.join(roots, nodes["fp"] == roots["u"], "left").select(*nodes.columns, F.coalesce("v", "fp").alias("root"))
    return materialise(with_root, "simhash-roots")


def cluster(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of docs (columns doc_id, text)."""
    fps = materialise(fingerprints(docs), "simhash-fp")
    nodes = rooted(materialise(fps.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "simhash-nodes"))
    named = nodes.groupBy("root").agg(F.min("first_id").alias("component_id"))
    table = nodes.join(named, "root").select("fp", "component_id")
    return fps.join(table, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def near_duplicates(docs: DataFrame) -> DataFrame:
    return cluster(docs.select("doc_id", "text"))


def keep_one(docs: DataFrame) -> DataFrame:
    """docs with one document of each class: the one whose id names it, by least text digest if the id repeats.

    A row is known by its id (which may be null) and the digest of its text. Equal texts are in one class, so such a
    key lies in one class, and of rows with one key any one stands for all."""
    digest = F.unhex(F.md5(F.coalesce("text", F.lit("")).cast("binary")))
    fps = fingerprints(docs.select("doc_id", "text", digest.alias("digest")), digest=True)
    key = F.struct(F.col("doc_id").isNull().alias("none"), F.coalesce("doc_id", F.lit(0)).alias("head"), F.col("digest").alias("head_digest"))
    nodes = rooted(materialise(fps.groupBy("fp").agg(F.min(key).alias("key")), "simhash-nodes"))
    heads = nodes.groupBy("root").agg(F.min("key").alias("key")).select("key.*")
    marked = packed(docs).withColumn("row_digest", digest)
    same_id = (F.coalesce(marked["doc_id"].cast("long"), F.lit(0)) == heads["head"]) & (marked["doc_id"].isNull() == heads["none"])
    kept = marked.join(heads, same_id & (marked["row_digest"] == heads["head_digest"]), "left_semi")
    # Rows of one id and text: the least of all, by its other columns as text, so that reruns agree.
    least = kept.groupBy("doc_id", "row_digest").agg(F.min_by(F.struct("text", "rest"), F.to_json("rest")).alias("x"))
    return unpacked(least.select("doc_id", "x.text", "x.rest"), docs.columns)
