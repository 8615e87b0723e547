"""Removal of repeated 200-byte strings with two-stage suffix sorting.

Which suffixes have to meet is decided by content: every 200-byte window has one minimiser (the
smallest hash of a 48-byte string inside it), and equal windows have the same one. Windows that share
a minimiser occurrence are consecutive and form a segment, so the starts of a text fall into segments
without overlap. Segments are grouped by their minimiser:

* a minimiser seen once has no repeats;
* equal segments (64-bit minimiser hash and 64-bit content hash) seen twice repeat in all their starts;
* different segments of one minimiser are laid side by side and their suffixes are sorted in two
  stages: only suffixes smaller than their successors are sorted directly, all others are induced by
  one scan over the buckets of first bytes. Adjacent common prefixes of 200 bytes or more are repeats;
* the segments of one minimiser are sorted in one task up to `GROUP_BYTES`. A larger group (one passage in very many
  contexts) is split: equal strings have equal hashes, so its strings are dealt to all tasks by 128 bits of hash and
  those alone in their part are no repeats. Both ways mark the same strings.

No shuffle puts all rows of a frequent minimiser or segment into one task: keys with over a 4096th of the rows are
broadcast instead, fewer than 4096 of them whatever the input (`common.join_uneven`).

Texts are read from the tables by each pass; what is shuffled is 28 bytes per segment, the bytes of
distinct segments that share a minimiser with others, and each text once for every join that needs something of it; a filter
of bits tells most of the others, which stay where they are (`common.with_marks`).
Copies of a segment are collapsed by map-side aggregation before they are sorted.

Defined results: null and empty texts have 0 bytes; texts under 200 bytes lose nothing; repeated rows
count as places of their own, so two equal texts of 200 bytes or more lose everything; overlapping
repeats inside one text count; very long texts are read in stretches; ids may be null or repeated; an empty table gives
an empty result; other columns are kept by `without_repeats` whatever their names.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import byte_column, join_uneven, map_rows, materialise, with_marks

LENGTH = 200
GRAM = 48
STRETCH = 1 << 18
POS_BITS = 20
#: Segments are gathered up to this many bytes before they are sorted.
SORT_BYTES = 1 << 19
#: A minimiser whose different segments have more bytes than this is split over tasks.
GROUP_BYTES = 1 << 20


def _mix(x: np.ndarray, k: int) -> np.ndarray:
    x = x * np.uint64(0x9E3779B97F4A7C15 + 2 * k)
    return x ^ (x >> np.uint64(29))


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the GRAM bytes that begin at each position, by joining hashes of 8, 16 and 32 bytes."""
    n = len(data) - 7
    h = np.zeros(n, np.uint64)
    for i in range(8):
        h |= data[i : i + n].astype(np.uint64) << np.uint64(8 * i)
    h = _mix(h, 1)
    h16 = _mix(h[:-8] + (h[8:] >> np.uint64(7)), 2)
    h32 = _mix(h16[:-16] + (h16[16:] >> np.uint64(7)), 3)
    h48 = _mix(h32[: len(h) - 40] + (h16[32:][: len(h) - 40] >> np.uint64(7)), 4)
    return h48 ^ (h48 >> np.uint64(32))


def minimisers(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For the window at each position: place and hash of its minimiser (the first, if hashes tie)."""
    width = LENGTH - GRAM + 1
    g = gram_hashes(data)
    best = (g & ~np.uint64((1 << POS_BITS) - 1)) | np.arange(len(g), dtype=np.uint64)
    span = 1
    while 2 * span <= width:
        best = np.minimum(best[:-span], best[span:])
        span *= 2
    if span < width:
        best = np.minimum(best[: len(best) - (width - span)], best[width - span :])
    place = (best & np.uint64((1 << POS_BITS) - 1)).astype(np.int64)
    return place, g[place]


def segments(data: bytes):
    """(hash of the minimiser, content hash, first start, number of starts) of each segment of a text."""
    whole, total = np.frombuffer(data, np.uint8), len(data) - LENGTH + 1
    places, hashes = [], []
    for a in range(0, max(0, total), STRETCH):
        place, h = minimisers(whole[a : min(len(data), a + STRETCH + LENGTH - 1)])
        places.append(place + a)
        hashes.append(h)
    if not places:
        return [], [], [], []
    place, h = np.concatenate(places), np.concatenate(hashes)
    first = np.concatenate(([0], np.flatnonzero(np.diff(place)) + 1))
    count = np.diff(np.concatenate((first, [total])))
    digest = xxhash.xxh64_intdigest
    content = [digest(data[a:b]) for a, b in zip(first.tolist(), (first + count + LENGTH - 1).tolist(), strict=True)]
    return h[first], content, first, count


def text_key(col="text"):
    return F.xxhash64(F.lit(1), F.col(col))


def scan(docs: DataFrame) -> DataFrame:
    """(h, c, doc_id, tk, lo, n): segments of every row; docs: doc_id, tk, text."""

    def one(batch):
        ids, keys = batch.column(0), batch.column(1)
        rows, h, c, lo, n = [], [], [], [], []
        for i, text in enumerate(byte_column(batch, "text")):
            if text and len(text) >= LENGTH:
                a, b, d, e = segments(text)
                rows.append(np.full(len(a), i))
                h.append(a)
                c.append(np.array(b, dtype=np.uint64))
                lo.append(d)
                n.append(e)
        if rows:
            take = pa.array(np.concatenate(rows))
            cols = [pa.array(np.concatenate(x).view(np.int64)) for x in (h, c)]
            cols += [ids.take(take), keys.take(take)] + [pa.array(np.concatenate(x).astype(np.int32)) for x in (lo, n)]
            yield pa.RecordBatch.from_arrays(cols, ["h", "c", "doc_id", "tk", "lo", "n"])

    return map_rows(docs.where("length(text) > 0"), "h long, c long, doc_id long, tk long, lo int, n int", one)


def _eight(padded: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on as one number that sorts as they do."""
    out = np.zeros(len(at), np.uint64)
    for i in range(8):
        out = (out << np.uint64(8)) | padded[at + i]
    return out


def direct_order(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Positions by the LENGTH bytes that follow: eight bytes a round, and only positions still equal go on."""
    padded = np.concatenate((data, np.zeros(LENGTH + 8, np.uint8))).astype(np.uint64)
    order = at[np.argsort(_eight(padded, at), kind="stable")]
    key = _eight(padded, order)
    group = np.cumsum(np.concatenate(([0], key[1:] != key[:-1])))  # numbers ascend along order
    open_ = np.arange(len(order))
    for depth in range(8, LENGTH, 8):
        g = group[open_]
        same = np.concatenate((g[1:] == g[:-1], [False]))
        open_ = open_[same | np.concatenate(([False], same[:-1]))]
        if not len(open_):
            break
        g, key = group[open_], _eight(padded, order[open_] + depth)
        by = np.lexsort((key, g))
        order[open_] = order[open_][by]
        g, key = g[by], key[by]
        new = np.concatenate(([True], (g[1:] != g[:-1]) | (key[1:] != key[:-1])))
        # Groups are told apart by the place of their first member.
        group[open_] = len(order) + open_[np.maximum.accumulate(np.where(new, np.arange(len(new)), 0))]
    return order


def two_stage_order(text: bytes, runs: list[tuple[int, int]]) -> np.ndarray:
    """Positions of `runs` (first, last) and some that follow them by their suffixes, right to LENGTH bytes at least.

    A position is sorted directly if its suffix is smaller than the next one; every run is drawn out to
    such a position, if need be into what stands behind its segment: suffixes of the whole text keep the order of
    their first bytes. The others are larger than their successor, so a scan over the buckets of first
    bytes meets the successor first and puts each at the next free place at the head of its bucket.
    """
    text += b"\x00\xff"  # a rise that the last run can be drawn out to
    data = np.frombuffer(text, np.uint8)
    size = len(text)
    step = np.zeros(size, np.int8)
    step[:-1] = np.sign(data[1:].astype(np.int16) - data[:-1].astype(np.int16))
    # The next unequal byte tells which of two neighbours is smaller.
    at = np.where(step != 0, np.arange(size), size - 1)
    ahead = np.minimum.accumulate(at[::-1])[::-1]
    smaller = step[ahead] > 0
    ends = np.flatnonzero(smaller)
    first, last = (np.array(x, np.int64) for x in zip(*runs, strict=True))
    drawn = ends[np.searchsorted(ends, last)]
    change = np.zeros(size + 1, np.int64)
    np.add.at(change, first, 1)
    np.add.at(change, drawn + 1, -1)
    inside = np.cumsum(change[:-1]) > 0
    direct = direct_order(data, np.flatnonzero(inside & smaller)).tolist()
    sizes = np.bincount(data[inside], minlength=256)
    tails = np.cumsum(sizes)
    heads = (tails - sizes).tolist()
    tails = tails.tolist()
    order = [-1] * int(sizes.sum())
    for i in reversed(direct):
        tails[text[i]] -= 1
        order[tails[text[i]]] = i
    waits = (inside & ~smaller).tolist()
    for j in range(len(order)):
        i = order[j] - 1
        if i >= 0 and waits[i]:
            b = text[i]
            order[heads[b]] = i
            heads[b] += 1
    return np.array(order, np.int64)


def repeated_starts(text: bytes, runs: list[tuple[int, int]], strings: np.ndarray) -> np.ndarray:
    """Marks of the positions in `strings` whose next LENGTH bytes also begin at another such position."""
    order = two_stage_order(text, runs)
    order = order[order < len(text)]
    order = order[strings[order]]
    marks = np.zeros(len(text), bool)
    if len(order) > 1:
        views = np.lib.stride_tricks.sliding_window_view(np.frombuffer(text, np.uint8), LENGTH)
        for a in range(0, len(order) - 1, 4096):
            part = order[a : a + 4097]
            rows = views[part]
            unequal = rows[1:] != rows[:-1]
            prefix = np.where(unequal.any(axis=1), unequal.argmax(axis=1), LENGTH)
            same = prefix >= LENGTH
            marks[part[1:][same]] = True
            marks[part[:-1][same]] = True
    return marks


def sort_groups(batches):
    """Batches of (h, c, seg) sorted by h and c to (h, c, a, len): runs of repeated starts inside segments."""
    kept: list[tuple[int, int, bytes]] = []
    size = 0

    def flush(rows):
        text, runs, strings = [], [], []
        at = 0
        for _, _, seg in rows:
            n = len(seg) - LENGTH + 1
            text.append(seg)
            runs.append((at, at + n - 1))
            at += len(seg)
        joined = b"".join(text)
        strings = np.zeros(len(joined), bool)
        for a, b in runs:
            strings[a : b + 1] = True
        marks = repeated_starts(joined, runs, strings)
        h, c, first, length = [], [], [], []
        for (gh, gc, _), (a, b) in zip(rows, runs, strict=True):
            m = np.concatenate(([0], marks[a : b + 1].view(np.int8), [0]))
            edge = np.diff(m)
            for x, y in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
                h.append(gh)
                c.append(gc)
                first.append(x)
                length.append(y - x)
        cols = [pa.array(h, pa.int64()), pa.array(c, pa.int64()), pa.array(first, pa.int32()), pa.array(length, pa.int32())]
        return pa.RecordBatch.from_arrays(cols, ["h", "c", "a", "len"])

    for b in batches:
        for h, c, seg in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
            if kept and kept[-1][:2] == (h, c):  # rows of equal id and text ask for the same segment
                continue
            if size > SORT_BYTES and kept[-1][0] != h:
                yield flush(kept)
                kept, size = [], 0
            kept.append((h, c, seg))
            size += len(seg)
    if kept:
        yield flush(kept)


def _wanted_texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(text, segs): one text looked up for all that is wanted of it; wanted: doc_id, tk, h, c, lo, n."""
    lists = materialise(wanted.groupBy("doc_id", "tk").agg(F.collect_list(F.struct("h", "c", "lo", "n")).alias("segs")), "substr-wanted", clean=True)
    asked = with_marks(docs, lists, ["tk", "doc_id"]).where("marked").drop("marked")
    return asked.join(lists.hint("shuffle_hash"), ["tk", "doc_id"]).select("text", "segs")


def split_runs(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(h, c, a, len): as sort_groups, for groups too large for a task: their strings are dealt by hash."""
    def one(batch):
        h, c, a, x, y = [], [], [], [], []
        for text, segs in zip(byte_column(batch, "text"), batch.column(1).to_pylist(), strict=True):
            for s in segs:
                for i in range(s["n"]):
                    w = text[s["lo"] + i : s["lo"] + i + LENGTH]
                    h.append(s["h"])
                    c.append(s["c"])
                    a.append(i)
                    x.append(xxhash.xxh64_intdigest(w, 1) - (1 << 63))
                    y.append(xxhash.xxh64_intdigest(w, 2) - (1 << 63))
        cols = [pa.array(v, pa.int64()) for v in (h, c)] + [pa.array(a, pa.int32())] + [pa.array(v, pa.int64()) for v in (x, y)]
        yield pa.RecordBatch.from_arrays(cols, ["h", "c", "a", "x", "y"])

    strings = materialise(map_rows(_wanted_texts(docs, wanted), "h long, c long, a int, x long, y long", one).distinct(), "substr-strings", clean=True)
    often = materialise(strings.groupBy("x", "y").agg(F.count("*").alias("k")).where("k > 1"), "substr-often", clean=True)
    found = join_uneven(strings, often, ["x", "y"], "k", strings.count(), "left_semi", "merge").select("h", "c", "a")
    # Starts side by side are one run, as sort_groups gives them; a segment has at most LENGTH - GRAM + 1 of them.
    run = F.col("a") - F.row_number().over(Window.partitionBy("h", "c").orderBy("a"))
    return found.withColumn("run", run).groupBy("h", "c", "run").agg(F.min("a").alias("a"), F.count("*").cast("int").alias("len")).drop("run")


def cut_segments(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(h, c, seg): the bytes of wanted segments."""
    def one(batch):
        h, c, seg = [], [], []
        for text, segs in zip(byte_column(batch, "text"), batch.column(1).to_pylist(), strict=True):
            for s in segs:
                h.append(s["h"])
                c.append(s["c"])
                seg.append(text[s["lo"] : s["lo"] + s["n"] + LENGTH - 1])
        yield pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(c, pa.int64()), pa.array(seg, pa.binary())], ["h", "c", "seg"])

    return map_rows(_wanted_texts(docs, wanted), "h long, c long, seg binary", one)


def keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(-1 << 62))).withColumn("tk", text_key())


def repeated_runs(docs: DataFrame, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """(tk, doc_id, spans): merged by the caller; docs: doc_id, tk, text as `keyed` gives them."""
    segs = materialise(scan(docs.select("doc_id", "tk", "text")), "substr-segments", clean=True)
    often = materialise(segs.groupBy("h").agg(F.count("*").alias("k")).where("k > 1"), "substr-often", clean=True)
    some = materialise(join_uneven(segs, often, ["h"], "k", segs.count(), "left_semi", "merge"), "substr-repeated", clean=True)
    # Any occurrence stands for equal segments; the four columns come from one row.
    at = [F.first(x).alias(x) for x in ("doc_id", "tk", "lo", "n")]
    kinds = materialise(some.groupBy("h", "c").agg(F.count("*").alias("k"), *at), "substr-kinds", clean=True)
    mixed = kinds.groupBy("h").agg(F.count("*").alias("m"), F.sum(F.col("n") + LENGTH - 1).alias("bytes")).where("m > 1")
    mixed = materialise(mixed, "substr-mixed", clean=True)
    texts, fields, n_kinds = docs.select("doc_id", "tk", "text"), ("h", "c", "doc_id", "tk", "lo", "n"), kinds.count()

    def members(groups: DataFrame) -> DataFrame:
        return join_uneven(kinds, groups.select("h", "m"), ["h"], "m", n_kinds, "left_semi", "merge").select(*fields)

    found = cut_segments(texts, members(mixed.where(F.col("bytes") <= group_bytes)))
    parts = found.repartition("h").sortWithinPartitions("h", "c").mapInArrow(sort_groups, "h long, c long, a int, len int")
    large = mixed.where(F.col("bytes") > group_bytes)
    if not large.isEmpty():
        parts = parts.unionByName(split_runs(texts, members(large)))
    parts = materialise(parts, "substr-runs", clean=True)  # few rows, but the shuffled texts behind them are the largest
    # Segments seen once have runs of their own; those seen twice or more repeat whole, wherever they are.
    lo = F.col("lo") + F.col("a")
    once = parts.join(kinds.where("k = 1").drop("k").hint("merge"), ["h", "c"]).select("tk", "doc_id", lo.alias("from"), (lo + F.col("len") + LENGTH - 1).alias("to"))
    full = kinds.where("k > 1").select("h", "c", "k")
    whole = join_uneven(some, full, ["h", "c"], "k", some.count(), "left_semi", "merge").select("tk", "doc_id", F.col("lo").alias("from"), (F.col("lo") + F.col("n") + LENGTH - 1).alias("to"))
    # Repeated rows give the same spans again.
    return whole.unionByName(once).groupBy("tk", "doc_id").agg(F.collect_set(F.struct("from", "to")).alias("spans"))


def split(text: bytes | None, spans) -> tuple[bytes, int, int]:
    """What is left of a text, bytes removed, maximal runs removed."""
    if not text or not spans:
        return text or b"", 0, 0
    kept, at, runs, removed, start = [], 0, 0, 0, None
    for a, b in sorted((s["from"], s["to"]) for s in spans):
        if start is None or a > at:
            kept.append(text[at:a])
            runs += 1
            start = a
        if b > at:
            removed += b - max(a, at)
            at = b
    kept.append(text[at:])
    return b"".join(kept), removed, runs


def _with_spans(docs: DataFrame) -> DataFrame:
    k = keyed(docs.withColumn("given_id", F.col("doc_id")))
    spans = materialise(repeated_runs(k), "substr-spans", clean=True)  # written, so that a frequent key of docs can be split at the join
    marked = with_marks(k, spans, ["tk", "doc_id"])
    found = marked.where("marked").drop("marked").join(spans.hint("shuffle_hash"), ["tk", "doc_id"], "left")
    alone = marked.where("NOT marked").drop("marked").withColumn("spans", F.lit(None).cast(spans.schema["spans"].dataType))
    return found.unionByName(alone)


def dedup_report(docs: DataFrame) -> DataFrame:
    """The contract's columns for every row of docs."""
    joined = _with_spans(docs.select("doc_id", "text")).select(F.col("given_id").cast("long").alias("doc_id"), "text", "spans")

    def one(batch):
        rows = []
        for text, spans in zip(byte_column(batch, "text"), batch.column(2).to_pylist(), strict=True):
            left, removed, runs = split(text, spans)
            rows.append((len(text or b""), removed, runs, hashlib.sha256(left).hexdigest()))
        cols = [batch.column(0)] + [pa.array([r[i] for r in rows], pa.string() if i == 3 else pa.int64()) for i in range(4)]
        yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return map_rows(joined, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string", one)


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs with repeated strings cut from text (a character cut in two goes) and n_chars set anew; rows cut to nothing go."""
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    # Other columns travel in one struct, so that none clashes with the names used here.
    rest = F.struct(F.lit(0).alias("_"), *[F.col(c) for c in others]).alias("rest")
    joined = _with_spans(docs.select("doc_id", "text", rest)).select(F.col("given_id").alias("doc_id"), "text", "rest", "spans")

    def one(batch):
        keep, texts = [], []
        for text, spans in zip(byte_column(batch, "text"), batch.column(batch.num_columns - 1).to_pylist(), strict=True):
            left, removed, _ = split(text, spans)
            keep.append(bool(left) or not removed)
            texts.append(None if text is None else left.decode("utf-8", "ignore"))
        cols, names = list(batch.columns[:-1]), batch.schema.names[:-1]
        cols[1] = pa.array(texts, pa.string())
        yield pa.RecordBatch.from_arrays(cols, names).filter(pa.array(keep, pa.bool_()))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in joined.drop("spans").schema)
    out = map_rows(joined, schema, one).select("doc_id", "text", *[F.col("rest").getField(c).alias(c) for c in others]).select(*docs.columns)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out
