"""Substitution baselines over k-mers: exact repeats, palindromes, two scans, approximate repeats, dictionaries, parses."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.alphabet import reverse_complement


def kmers(df: DataFrame, k: int) -> DataFrame:
    """(seq_id, pos, kmer) of every position."""
    return (
        df.where(F.length("bases") >= k)
        .select("seq_id", "bases", F.explode(F.sequence(F.lit(0), F.length("bases") - k)).alias("p"))
        .select("seq_id", F.col("p").cast("long").alias("pos"), F.substring("bases", F.col("p") + 1, F.lit(k)).alias("kmer"))
    )


def spectrum(df: DataFrame, k: int) -> DataFrame:
    return kmers(df, k).groupBy("kmer").agg(F.count("*").alias("n"))


def exact_repeats(df: DataFrame, k: int = 16) -> DataFrame:
    """(kmer, first_seq, first_pos, n) of those that occur twice or more."""
    g = kmers(df, k).groupBy("kmer").agg(F.min(F.struct("seq_id", "pos")).alias("f"), F.count("*").alias("n"))
    return g.where("n > 1").select("kmer", F.col("f.seq_id").alias("first_seq"), F.col("f.pos").alias("first_pos"), "n")


def palindromes(df: DataFrame, k: int = 16) -> DataFrame:
    """(kmer, n, m): k-mers whose reverse complement also occurs; a sort-merge join of two spectra."""
    s = spectrum(df, k)
    other = s.select(F.col("kmer").alias("rc"), F.col("n").alias("m"))
    return s.withColumn("rc", reverse_complement(F.col("kmer"))).join(other.hint("merge"), "rc").where("kmer <= rc").select("kmer", "rc", "n", "m")


def nearest_copy(df: DataFrame, k: int = 16) -> DataFrame:
    """(seq_id, pos, src): last earlier place of the same k-mer in the sequence (as-of)."""
    w = Window.partitionBy("seq_id", "kmer").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return kmers(df, k).withColumn("src", F.max("pos").over(w)).where("src IS NOT NULL").select("seq_id", "pos", "src")


def matches(df: DataFrame, k: int = 16) -> DataFrame:
    """(seq_id, pos, src, len): maximal runs on one diagonal of nearest copies (first of two scans)."""
    d = nearest_copy(df, k).withColumn("diag", F.col("pos") - F.col("src"))
    w = Window.partitionBy("seq_id", "diag").orderBy("pos")
    runs = d.withColumn("g", F.col("pos") - F.row_number().over(w))
    return runs.groupBy("seq_id", "diag", "g").agg(F.min("pos").alias("pos"), F.min("src").alias("src"), (F.count("*") + k - 1).alias("len")).drop("diag", "g")


def two_scan_gain(df: DataFrame, k: int = 16, pointer_bits: int = 24) -> DataFrame:
    """Second scan: bits saved by each match against two bits a base."""
    return matches(df, k).withColumn("gain", 2 * F.col("len") - pointer_bits)


def blocks(df: DataFrame, size: int) -> DataFrame:
    n = F.expr(f"length(bases) div {size}")
    return df.where(F.length("bases") >= size).select(
        "seq_id", "bases", F.explode(F.sequence(F.lit(0), n.cast("int") - 1)).alias("b")
    ).select("seq_id", F.col("b").cast("long").alias("b"), F.substring("bases", F.col("b") * size + 1, F.lit(size)).alias("block"))


def approx_repeats(df: DataFrame, size: int = 32, seed: int = 6, max_edits: int = 4) -> DataFrame:
    """Pairs of blocks that differ by at most max_edits edits, each once. max_edits + 1 seeds side by side: at least one is
    free of edits and stands at most max_edits places off in the other block, so every pair shares a shifted seed."""
    if (max_edits + 1) * seed > size:
        raise ValueError("the block has no room for max_edits + 1 seeds")
    b = blocks(df, size).withColumn("id", F.struct("seq_id", "b"))

    def cut(at):
        return b.select("id", "block", F.explode(at).alias("o", "p")).select("id", "block", "o", F.substring("block", F.col("p") + 1, F.lit(seed)).alias("s"))

    starts = [o * seed for o in range(max_edits + 1)]
    near = [(o, p) for o in starts for p in range(o - max_edits, o + max_edits + 1) if 0 <= p <= size - seed]
    left = cut(F.create_map(*[F.lit(x) for o in starts for x in (o, o)]))
    right = b.select("id", "block", F.explode(F.array(*[F.struct(F.lit(o).alias("o"), F.lit(p).alias("p")) for o, p in near])).alias("x"))
    right = right.select("id", "block", "x.o", F.substring("block", F.col("x.p") + 1, F.lit(seed)).alias("s"))
    left = left.select("o", "s", F.col("id").alias("a"), F.col("block").alias("x"))
    right = right.select("o", "s", F.col("id").alias("c"), F.col("block").alias("y"))
    pairs = left.join(right, ["o", "s"]).where("a < c").select("a", "c", "x", "y").distinct()
    e = F.levenshtein("x", "y")
    return pairs.where(e <= max_edits).select(
        F.col("a.seq_id").alias("seq_a"), F.col("a.b").alias("block_a"), F.col("c.seq_id").alias("seq_c"), F.col("c.b").alias("block_c"), e.alias("edits")
    )


def substituted(df: DataFrame, size: int = 32, seed: int = 6, max_diffs: int = 4) -> DataFrame:
    """(a, c, diffs): earlier and later block that differ in at most max_diffs places (max_diffs + 1 seeds, one of them equal)."""
    b = blocks(df, size).select(F.struct("seq_id", "b").alias("id"), "block")
    cut = b.select("id", "block", F.explode(F.sequence(F.lit(0), F.lit(max_diffs * seed), F.lit(seed))).alias("o"))
    cut = cut.withColumn("s", F.substring("block", F.col("o") + 1, F.lit(seed)))
    left = cut.select("o", "s", F.col("id").alias("a"), F.col("block").alias("x"))
    right = cut.select("o", "s", F.col("id").alias("c"), F.col("block").alias("y"))
    pairs = left.join(right, ["o", "s"]).where("a < c").select("a", "c", "x", "y").distinct()
    diffs = F.size(F.filter(F.zip_with(F.split("x", ""), F.split("y", ""), lambda p, q: p != q), lambda t: t))
    return pairs.withColumn("diffs", diffs).where(F.col("diffs") <= max_diffs)


def repeat_blocks(df: DataFrame, size: int = 32, pointer_bits: int = 24, diff_bits: int = 7) -> DataFrame:
    """(seq_id, b, block, src_seq, src_b, at, letters, bits): approximate repeats are found first over everything; a block
    without an earlier like one stands as it is, two bits a base, and another refers to the one of those that gains most
    (places and letters of the differences), if that is cheaper."""
    pairs = substituted(df, size)
    every = blocks(df, size).select(F.struct("seq_id", "b").alias("c"), "block")
    roots = every.join(pairs.select("c").distinct(), "c", "left_anti").select(F.col("c").alias("a"))
    cost = F.lit(pointer_bits) + diff_bits * F.col("diffs")
    best = pairs.join(roots, "a").where(cost < 2 * size).groupBy("c").agg(F.min(F.struct(cost.alias("bits"), "a", "x", "y")).alias("m"))
    places = F.filter(F.transform(F.split("m.x", ""), lambda p, i: F.when(p != F.substring("m.y", i + 1, F.lit(1)), i)), lambda i: i.isNotNull())
    refs = best.select("c", F.col("m.a").alias("a"), F.col("m.bits").alias("bits"), places.alias("at"), F.col("m.y").alias("y"))
    letters = F.array_join(F.transform("at", lambda i: F.substring("y", i + 1, F.lit(1))), "")
    refs = refs.select("c", "a", "bits", "at", letters.alias("letters"))
    j = every.join(refs, "c", "left")
    return j.select(
        "c.seq_id", "c.b", F.when(F.col("a").isNull(), F.col("block")).alias("block"), F.col("a.seq_id").alias("src_seq"), F.col("a.b").alias("src_b"), "at", "letters",
        F.coalesce("bits", F.lit(2 * size)).cast("long").alias("bits"),
    )


def repeat_blocks_back(coded: DataFrame) -> DataFrame:
    """(seq_id, b, block): references are looked up in the blocks that stand as they are, which are all they refer to."""
    roots = coded.where("block IS NOT NULL").select(F.col("seq_id").alias("src_seq"), F.col("b").alias("src_b"), F.col("block").alias("src"))
    j = coded.where("block IS NULL").join(roots, ["src_seq", "src_b"])
    mended = F.array_join(F.transform(F.split("src", ""), lambda x, i: F.coalesce(F.substring("letters", F.nullif(F.array_position("at", i), F.lit(0)).cast("int"), F.lit(1)), x)), "")
    return coded.where("block IS NOT NULL").select("seq_id", "b", "block").unionByName(j.select("seq_id", "b", mended.alias("block")))


def multi_pass(df: DataFrame, sizes=(32, 16)) -> DataFrame:
    """Dictionary from repeated passes: repeated k-mers of each size that lie in no larger one already found."""
    out, found = None, None
    for i, k in enumerate(sizes):
        s = exact_repeats(df, k).select("kmer", "n")
        if found is not None:
            inner = kmers(found.select(F.lit(0).alias("seq_id"), F.col("kmer").alias("bases")), k).select("kmer").distinct()
            s = s.join(inner, "kmer", "left_anti")
        found = s
        part = s.select(F.lit(i + 1).alias("pass"), "kmer", "n")
        out = part if out is None else out.unionByName(part)
    return out


def _tokens(s: str, k: int) -> list[tuple[str, int, int | None, int, str | None]]:
    """(op, pos, src, len, literal) from left to right: the first earlier place of the next k bases, drawn out."""
    out, seen, i, lit = [], {}, 0, 0
    while i < len(s):
        src = seen.get(s[i : i + k]) if i + k <= len(s) else None
        n = 1
        if src is not None:
            n = k
            while i + n < len(s) and s[src + n] == s[i + n]:
                n += 1
            if lit < i:
                out.append(("literal", lit, None, i - lit, s[lit:i]))
            out.append(("copy", i, src, n, None))
        for j in range(i, min(i + n, len(s) - k + 1)):
            seen.setdefault(s[j : j + k], j)
        i += n
        if src is not None:
            lit = i
    if lit < len(s) or not s:
        out.append(("literal", lit, None, len(s) - lit, s[lit:]))
    return out


def _expanded(tokens) -> str:
    """Inverse of _tokens; a copy may reach into itself."""
    out: list[str] = []
    for op, _, src, n, literal in tokens:
        if op == "literal":
            out.extend(literal)
        else:
            for j in range(n):
                out.append(out[src + j])
    return "".join(out)


def greedy_parse(df: DataFrame, k: int = 16) -> DataFrame:
    """(seq_id, op, pos, src, len, literal): literal and copy tokens from left to right; sequential, one sequence a row."""
    import pandas as pd

    def parse(batches):
        for b in batches:
            rows = [(seq, *t) for seq, s in zip(b["seq_id"], b["bases"], strict=True) for t in _tokens(s or "", k)]
            yield pd.DataFrame(rows, columns=["seq_id", "op", "pos", "src", "len", "literal"]).astype({"src": "Int64"})

    return df.select("seq_id", "bases").mapInPandas(parse, "seq_id long, op string, pos long, src long, len long, literal string")


def expand(tokens: DataFrame) -> DataFrame:
    """Inverse of greedy_parse from the tokens alone: (seq_id, bases)."""
    import pandas as pd

    def build(batches):
        for b in batches:
            rows = []
            for seq, toks in zip(b["seq_id"], b["toks"], strict=True):
                ordered = sorted(((t["op"], int(t["pos"]), t["src"], int(t["len"]), t["literal"]) for t in toks), key=lambda t: t[1])
                rows.append((seq, _expanded((op, p, None if src is None else int(src), n, lit) for op, p, src, n, lit in ordered)))
            yield pd.DataFrame(rows, columns=["seq_id", "bases"])

    listed = tokens.groupBy("seq_id").agg(F.collect_list(F.struct("op", "pos", "src", "len", "literal")).alias("toks"))
    return listed.mapInPandas(build, "seq_id long, bases string")


def repeat_encode(df: DataFrame, k: int = 16) -> DataFrame:
    """(seq_id, n, copies, lit, payload, n_bits): exact repeats, and literals by order-2 arithmetic coding; copies hold
    (literals before, source, length) as 32-bit numbers. One lane a sequence."""
    import numpy as np
    import pyarrow as pa

    from .codec import OrderStep, codes_of, encode_lanes

    def run(batches):
        for b in batches:
            copies, lits, n = [], [], []
            for s in b.column(1).to_pylist():
                plan, before, text = [], 0, []
                for op, _, src, size, literal in _tokens(s or "", k):
                    if op == "literal":
                        before += size
                        text.append(literal)
                    else:
                        plan += (before, src, size)
                        before = 0
                copies.append(np.array(plan, "<u4").tobytes())
                lits.append(codes_of("".join(text)))
                n.append(len(s or ""))
            sizes = np.array([len(x) for x in lits], np.int64)
            body = np.zeros((len(lits), sizes.max(initial=0)), np.int64)
            for i, x in enumerate(lits):
                body[i, : len(x)] = x
            data = encode_lanes(OrderStep((2,), len(lits), np.zeros((len(lits), 0), np.int64)), body, sizes) if lits else []
            bits = [8 * (len(c) + len(p)) for c, p in zip(copies, data, strict=True)]
            cols = [b.column(0), pa.array(n, pa.int64()), pa.array(copies, pa.binary()), pa.array(sizes), pa.array(data, pa.binary()), pa.array(bits, pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, ["seq_id", "n", "copies", "lit", "payload", "n_bits"])

    return df.select(F.col("seq_id").cast("long").alias("seq_id"), "bases").mapInArrow(run, "seq_id long, n long, copies binary, lit long, payload binary, n_bits long")


def repeat_decode(coded: DataFrame) -> DataFrame:
    """(seq_id, bases) of repeat_encode's rows. One order needs no mixing, so lanes may stand in other batches."""
    import numpy as np
    import pyarrow as pa

    from .codec import OrderStep, bases_of, decode_lanes

    def run(batches):
        for b in batches:
            sizes = np.array(b.column(2).to_pylist(), np.int64)
            body = decode_lanes(OrderStep((2,), len(sizes), np.zeros((len(sizes), 0), np.int64)), b.column(3).to_pylist(), sizes)
            out = []
            for i, c in enumerate(b.column(1).to_pylist()):
                text, at, tokens = bases_of(body[i, : sizes[i]]), 0, []
                for before, src, n in np.frombuffer(c, "<u4").reshape(-1, 3).tolist():
                    tokens += [("literal", 0, None, before, text[at : at + before]), ("copy", 0, src, n, None)]
                    at += before
                out.append(_expanded([*tokens, ("literal", 0, None, 0, text[at:])]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string())], ["seq_id", "bases"])

    return coded.select("seq_id", "copies", "lit", "payload").mapInArrow(run, "seq_id long, bases string")


def cheapest_parse(s: str, k: int = 16, pointer_bits: int = 24) -> int:
    """Bits of the cheapest split into literals (two bits each) and copies of at least k bases from any earlier place."""
    n, reach, seen = len(s), [0] * len(s), {}
    for i in range(n - k + 1):
        places = seen.setdefault(s[i : i + k], [])
        for src in places:
            m = k
            while i + m < n and s[src + m] == s[i + m]:
                m += 1
            reach[i] = max(reach[i], m)
        places.append(i)
    cost = [0] * (n + 1)
    for i in range(n - 1, -1, -1):
        # Every beginning of the longest copy is a copy too.
        cost[i] = min([cost[i + 1] + 2, *(pointer_bits + c for c in cost[i + k : i + reach[i] + 1])])
    return cost[0]


def dp_parse(df: DataFrame, k: int = 16, pointer_bits: int = 24) -> DataFrame:
    """(seq_id, bits): cheapest split of each sequence into literals and copies, by dynamic programming."""
    import pandas as pd

    def parse(batches):
        for b in batches:
            yield pd.DataFrame({"seq_id": b["seq_id"], "bits": [cheapest_parse(s or "", k, pointer_bits) for s in b["bases"]]})

    return df.select("seq_id", "bases").mapInPandas(parse, "seq_id long, bits long")
