"""Benchmark decontamination as a prefix-filtered join of word shingles.

Items are cut into windows of 13 words (a shorter item is one window). A window is the set of its
five-word shingles (a shorter one: its whole sequence). Since a window must be contained whole, one
shingle is a necessary prefix: the rarest over all documents, in one global order (count, then
shingle). Only prefix shingles are probed in documents; a hit says where the window would begin, is
dropped if that begins before the first word or ends after the last, and the words are then compared.

Two passes over the documents: one counts how often item shingles occur (map-side combined), one
probes. The item side is broadcast while it has at most `max_windows` windows. A larger item side stays distributed
(`mode='shuffle'`, tested equal): shingles meet by hash, frequent ones by broadcast of the fewer than 4096 that hold over a
4096th of all shingles, and what is found is verified word by word. A verdict depends on the text alone, so each
different text is judged once there.

Defined results: null, empty or wordless texts have n_words 0 and are clean; very long texts are read whole; items
without words take no part; repeated rows are judged alone; a null item id is skipped in the id list; empty tables work;
columns of the input named as the result's own are replaced, all others are kept whatever their names.
"""

from __future__ import annotations

import hashlib
from collections import Counter, defaultdict

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import alnum_words, byte_column, join_uneven, map_rows, materialise, packed, unpacked

WINDOW = 13
SHINGLE = 5
#: Proven size bound of what is broadcast: 200 000 windows are under 100 MB of words.
MAX_WINDOWS = 200_000
OUT = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def windows_of(words: list[bytes]) -> list[tuple[bytes, ...]]:
    if not words:
        return []
    return [tuple(words[i : i + WINDOW]) for i in range(max(1, len(words) - WINDOW + 1))]


def shingles_of(window: tuple[bytes, ...]) -> list[tuple[bytes, ...]]:
    q = min(SHINGLE, len(window))
    return [window[i : i + q] for i in range(len(window) - q + 1)]


def item_windows(items: DataFrame) -> DataFrame:
    """(item_id, win binary): distinct windows of each item, words joined by one space."""

    def one(batch):
        ids, wins = [], []
        for i, text in zip(batch.column(0).to_pylist(), byte_column(batch, "text"), strict=True):
            for w in dict.fromkeys(windows_of(alnum_words(text))):
                ids.append(i)
                wins.append(b" ".join(w))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(wins, pa.binary())], ["item_id", "win"])

    slim = items.where("item_id IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), "text")
    return map_rows(slim, "item_id long, win binary", one).distinct()


def _shingle_hash(words) -> int:
    return xxhash.xxh64_intdigest(b" ".join(words)) - (1 << 63)


def _lengths(shingles) -> list[int]:
    return sorted({len(s) for s in shingles})


def _runs(words: list[bytes], q: int):
    return words if q == 1 else zip(*(words[i:] for i in range(q)), strict=False)


def _found(words: list[bytes], wanted: dict, q: int) -> list[int]:
    """Positions where a wanted shingle of q words begins."""
    if q == 1:
        return [i for i, w in enumerate(words) if (w,) in wanted]
    return [i for i, s in enumerate(_runs(words, q)) if s in wanted]


def shingle_counts(docs: DataFrame, shingles: list[tuple[bytes, ...]]) -> dict[tuple[bytes, ...], int]:
    """How often each item shingle occurs in all documents. The answer is no longer than `shingles`."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast({s: k for k, s in enumerate(shingles)})
    sizes = _lengths(shingles)

    def count(batches):
        index, total = shared.value, Counter()
        for b in batches:
            for text in byte_column(b, "text"):
                words = alnum_words(text)
                for q in sizes:
                    if len(words) >= q:
                        runs = ((w,) for w in words) if q == 1 else _runs(words, q)
                        total.update(map(index.__getitem__, filter(index.__contains__, runs)))
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array(list(total.values()), pa.int64())], ["k", "n"])

    rows = docs.select("text").mapInArrow(count, "k int, n long").groupBy("k").agg(F.sum("n").alias("n")).collect()
    return {shingles[r["k"]]: r["n"] for r in rows}


def prefix_table(windows: dict, counts: dict) -> dict:
    """Rarest shingle -> [(offset in the window, window)]."""
    table = defaultdict(list)
    for w in windows:
        parts = shingles_of(w)
        best = min(range(len(parts)), key=lambda i: (counts.get(parts[i], 0), parts[i], i))
        if counts.get(parts[best], 0):  # else no document holds the window
            table[parts[best]].append((best, w))
    return dict(table)


def digest(items) -> str:
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()


def covered(spans: list[tuple[int, int]]) -> int:
    """Words inside any of the spans."""
    hit = end = 0
    for a, b in sorted(spans):
        hit += max(0, b - max(a, end))
        end = max(end, b)
    return hit


def verdict(n_words: int, spans: list[tuple[int, int]], items) -> tuple:
    hit = covered(spans)
    return n_words, hit, len(items), digest(items), hit > 0 and 20 * hit >= n_words


def judge(words: list[bytes], table: dict, owners: dict, sizes: list[int]) -> tuple:
    spans, items = [], set()
    for q in sizes:
        for at in _found(words, table, q):
            for offset, w in table[tuple(words[at : at + q])]:
                begin = at - offset
                if begin >= 0 and begin + len(w) <= len(words) and tuple(words[begin : begin + len(w)]) == w:
                    spans.append((begin, begin + len(w)))
                    items.update(owners[w])
    return verdict(len(words), spans, items)


def _columns(rows: list[tuple]) -> list[pa.Array]:
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_())
    return [pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]


def _broadcast_mode(docs: DataFrame, rows: list) -> DataFrame:
    spark = docs.sparkSession
    owners = defaultdict(list)
    for r in rows:
        owners[tuple(bytes(r["win"]).split(b" "))].append(r["item_id"])
    shingles = list(dict.fromkeys(s for w in owners for s in shingles_of(w)))
    counts = shingle_counts(docs, shingles) if shingles else {}
    shared = spark.sparkContext.broadcast((prefix_table(owners, counts), dict(owners)))
    names = ["n_words", "n_hit", "n_items", "items_sha256", "contaminated"]

    def probe(batch):
        table, own = shared.value
        sizes = _lengths(table)
        found = [judge(alnum_words(t), table, own, sizes) for t in byte_column(batch, "text")]
        yield pa.RecordBatch.from_arrays([*batch.columns, *_columns(found)], [*batch.schema.names, *names])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return map_rows(docs, f"{schema}, {OUT}", probe)


def _text_key() -> list[F.Column]:
    """96 bits that stand for a text."""
    return [F.xxhash64("text").alias("k1"), F.hash("text").alias("k2")]


def _shuffle_mode(docs: DataFrame, wins: DataFrame) -> DataFrame:
    """The item side stays distributed: document shingles are joined with prefix shingles by hash."""
    others = F.struct(F.lit(0).alias("_"), *[F.col(c) for c in docs.columns if c != "text"]).alias("rest")
    slim = docs.select("text", others)  # other columns travel in one struct, so that none clashes with the names used here
    texts = docs.select("text").distinct().select(*_text_key(), "text")
    windows = materialise(wins.select("win").distinct().withColumn("len", F.size(F.split(F.col("win").cast("string"), " "))), "decon-distinct")
    sizes = [r[0] for r in windows.select(F.least(F.lit(SHINGLE), "len")).distinct().collect()]  # at most SHINGLE

    def cut_texts(batch):
        k1, k2, h, at, n = [], [], [], [], []
        for a, b, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), byte_column(batch, "text"), strict=True):
            words = alnum_words(text)
            for q in sizes:
                h += [_shingle_hash(words[i : i + q]) for i in range(len(words) - q + 1)]
                at += range(len(words) - q + 1)
            more = len(h) - len(n)
            k1 += [a] * more
            k2 += [b] * more
            n += [len(words)] * more
        cols = [pa.array(k1, pa.int64()), pa.array(k2, pa.int32()), pa.array(h, pa.int64()), pa.array(at, pa.int32()), pa.array(n, pa.int32())]
        yield pa.RecordBatch.from_arrays(cols, ["k1", "k2", "sh", "at", "n"])

    def cut_windows(batch):
        w, size, h, off = [], [], [], []
        for win, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            for k, s in enumerate(shingles_of(tuple(win.split(b" ")))):
                w.append(win)
                size.append(n)
                h.append(_shingle_hash(s))
                off.append(k)
        cols = [pa.array(w, pa.binary()), pa.array(size, pa.int32()), pa.array(h, pa.int64()), pa.array(off, pa.int32())]
        yield pa.RecordBatch.from_arrays(cols, ["win", "len", "sh", "off"])

    runs = map_rows(texts, "k1 long, k2 int, sh long, at int, n int", cut_texts)
    parts = map_rows(windows, "win binary, len int, sh long, off int", cut_windows)
    # Counted before they meet the items, so that a frequent shingle is one row a task.
    seen = materialise(runs.groupBy("sh").agg(F.count("*").alias("seen")), "decon-seen")
    total = seen.agg(F.sum("seen")).first()[0] or 0
    first = F.min(F.struct("seen", "sh", "off")).alias("p")
    rarest = parts.join(seen, "sh", "left").withColumn("seen", F.coalesce("seen", F.lit(0))).groupBy("win", "len").agg(first).where("p.seen > 0")
    prefix = materialise(rarest.select("win", "len", "p.sh", "p.off", "p.seen"), "decon-prefix")
    cand = join_uneven(runs, prefix, ["sh"], "seen", total).withColumn("begin", F.col("at") - F.col("off")).where("begin >= 0 AND begin + len <= n")
    # At most as many candidates as a text has words times prefix windows of one shingle.
    listed = materialise(cand.groupBy("k1", "k2").agg(F.collect_set(F.struct("win", "begin")).alias("cands")), "decon-candidates")

    def verify(batch):
        hits, found = [], []
        for text, cands in zip(byte_column(batch, "text"), batch.column(3).to_pylist(), strict=True):
            words, spans, seen_ = alnum_words(text), [], set()
            for c in cands:
                w = c["win"].split(b" ")
                if words[c["begin"] : c["begin"] + len(w)] == w:
                    spans.append((c["begin"], c["begin"] + len(w)))
                    seen_.add(c["win"])
            hits.append(covered(spans))
            found.append(list(seen_))
        cols = [batch.column(0), batch.column(1), pa.array(hits, pa.int64()), pa.array(found, pa.list_(pa.binary()))]
        yield pa.RecordBatch.from_arrays(cols, ["k1", "k2", "hit", "wins"])

    judged = materialise(map_rows(texts.join(listed, ["k1", "k2"]), "k1 long, k2 int, hit long, wins array<binary>", verify).where("hit > 0"), "decon-hits")
    held = materialise(judged.select("k1", "k2", F.explode("wins").alias("win")), "decon-held")
    often = materialise(held.groupBy("win").agg(F.count("*").alias("k")).join(wins, "win"), "decon-owners")
    owned = join_uneven(held, often, ["win"], "k", held.count()).groupBy("k1", "k2").agg(F.collect_set("item_id").alias("items"))
    ids = F.array_join(F.sort_array(F.transform("items", lambda x: x.cast("string"))), ",")
    verdicts = judged.select("k1", "k2", "hit").join(owned, ["k1", "k2"], "left").select(
        "k1", "k2", "hit", F.size("items").cast("long").alias("n_items"), F.sha2(ids.cast("binary"), 256).alias("sha")
    )
    verdicts = materialise(verdicts, "decon-verdicts")  # written, so that a frequent text of docs can be split at the join

    def count_words(batch):
        n = pa.array([len(alnum_words(t)) for t in byte_column(batch, "text")], pa.int64())
        yield pa.RecordBatch.from_arrays([*batch.columns, n], [*batch.schema.names, "n_words"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in slim.schema)
    counted = map_rows(slim, f"{schema}, n_words long", count_words).withColumns({"k1": F.xxhash64("text"), "k2": F.hash("text")})
    hit = F.coalesce("hit", F.lit(0)).cast("long")
    kept = [F.col("text") if c == "text" else F.col("rest").getField(c).alias(c) for c in docs.columns]
    return counted.join(verdicts, ["k1", "k2"], "left").select(
        *kept, "n_words", hit.alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"),
        F.coalesce("sha", F.lit(digest(()))).alias("items_sha256"), ((hit > 0) & (20 * hit >= F.col("n_words"))).alias("contaminated"),
    )


def decontaminate(docs: DataFrame, items: DataFrame, mode: str = "auto", max_windows: int = MAX_WINDOWS) -> DataFrame:
    """docs (any columns, one named text) plus n_words, n_hit, n_items, items_sha256, contaminated."""
    docs = docs.drop("n_words", "n_hit", "n_items", "items_sha256", "contaminated")  # own names win
    wins = materialise(item_windows(items), "decon-windows")
    if mode == "shuffle" or mode == "auto" and wins.count() > max_windows:
        return _shuffle_mode(docs, wins)
    return _broadcast_mode(docs, wins.collect())


def keep_clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """docs that are not contaminated, with the columns they came with."""
    return unpacked(decontaminate(packed(docs), items).where("NOT contaminated"), docs.columns)


def contamination(spark: SparkSession, docs: DataFrame, items: DataFrame) -> DataFrame:
    return decontaminate(docs.select("doc_id", "text"), items).drop("text")
