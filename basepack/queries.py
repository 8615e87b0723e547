"""Queries of the library over the given tables, each with SQL for DuckDB where SQL can express it.

Every query runs over its whole table. Floats are rounded; codec sizes are asserted in tests instead of hashed.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .functions import alphabet as A
from .functions import coder as C
from .operators import attention as T
from .operators import codec, context, general, grouping, substitution
from .plans import experiments, measures, model, published
from .sources import tables as S
from .streaming import bits as B

Q, SQL = {}, {}


def query(name: str, sql: str | None = None):
    def put(fn):
        Q[name] = fn
        if sql is not None:
            SQL[name] = sql
        return fn

    return put


EVENT_CASE = "CASE event_type WHEN 'click' THEN 'A' WHEN 'view' THEN 'G' WHEN 'purchase' THEN 'C' WHEN 'signup' THEN 'T' ELSE 'N' END"
EV = f"""ev AS (SELECT user_id AS seq_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS pos,
  {EVENT_CASE} AS base, instr('AGCTN', {EVENT_CASE}) - 1 AS code FROM events)"""
EVSEQ = f"{EV}, es AS (SELECT seq_id, string_agg(base, '' ORDER BY pos) AS bases FROM ev GROUP BY seq_id)"
DQ = f"dq AS (SELECT doc_id AS seq_id, lang, source, {A.quad_sql('text')} AS bases FROM documents)"
DL = f"dl AS (SELECT doc_id AS seq_id, lang, source, {A.letter_sql('text')} AS bases FROM documents)"
PQ = f"pq AS (SELECT page_id AS seq_id, {A.quad_sql('html')} AS bases FROM pages)"
BQ = f"bq AS (SELECT item_id AS seq_id, {A.quad_sql('text')} AS bases FROM benchmark)"
EM = "em AS (SELECT vec_id // 13 AS seg, vec_id % 13 AS i, embedding::DOUBLE[] AS vec FROM embeddings)"


def kmer_sql(view: str, k: int) -> str:
    return f"km AS (SELECT seq_id, p AS pos, substr(bases, (p + 1)::INT, {k}) AS kmer FROM (SELECT seq_id, bases, unnest(range(0, length(bases) - {k - 1})) AS p FROM {view}))"


def digest_sql(cte: str, view: str) -> str:
    return f"WITH {cte} SELECT seq_id, length(bases)::BIGINT AS n_bases, md5(bases) AS digest FROM {view}"


# Maps and sequence views.
Q["quad_map"] = lambda s, d: general.digests(S.doc_quad(s, d))
SQL["quad_map"] = digest_sql(DQ, "dq")
Q["letter_map"] = lambda s, d: general.digests(S.doc_letter(s, d))
SQL["letter_map"] = digest_sql(DL, "dl")
Q["event_sequences"] = lambda s, d: S.event_seq(s, d).select("seq_id", "bases")
SQL["event_sequences"] = f"WITH {EVSEQ} SELECT seq_id, bases FROM es"
Q["order_sequences"] = lambda s, d: S.order_seq(s, d).select("seq_id", "bases")
SQL["order_sequences"] = """SELECT o_custkey AS seq_id, string_agg(translate(substr(o_orderpriority, 1, 1), '12345', 'AGCTN'), '' ORDER BY o_orderdate, o_orderkey,
  translate(substr(o_orderpriority, 1, 1), '12345', 'AGCTN')) AS bases FROM orders GROUP BY 1"""
Q["quad_inverse"] = lambda s, d: S.doc_quad(s, d).select("seq_id", F.md5(A.quad_bytes(F.col("bases"))).alias("digest"))
SQL["quad_inverse"] = "SELECT doc_id AS seq_id, md5(text) AS digest FROM documents"
Q["pack_codes"] = lambda s, d: general.raw2(S.event_seq(s, d)).select("seq_id", F.lower(F.hex("payload")).alias("packed"))
SQL["pack_codes"] = f"""WITH {EVSEQ}, k AS (SELECT seq_id, replace(bases, 'N', '') AS b FROM es),
  p AS (SELECT seq_id, translate(rpad(b, (ceil(length(b) / 4.0) * 4)::INT, 'A'), 'AGCT', '0123') AS g FROM k)
  SELECT seq_id, lower(array_to_string(list_transform(range(0, length(g) // 2), lambda i: substr('0123456789abcdef',
    (substr(g, (2 * i + 1)::INT, 1)::INT * 4 + substr(g, (2 * i + 2)::INT, 1)::INT + 1)::INT, 1)), '')) AS packed FROM p"""
Q["valid_sequences"] = lambda s, d: S.doc_letter(s, d).select("seq_id", F.col("bases").rlike("^[AGCT]+$").alias("valid"))
SQL["valid_sequences"] = f"WITH {DL} SELECT seq_id, regexp_full_match(bases, '[AGCT]+') AS valid FROM dl"
Q["reverse_complement"] = lambda s, d: S.doc_letter(s, d).select("seq_id", F.md5(A.reverse_complement(F.col("bases")).cast("binary")).alias("digest"))
SQL["reverse_complement"] = f"WITH {DL} SELECT seq_id, md5(reverse(translate(bases, 'AGCTN', 'TCGAN'))) AS digest FROM dl"


def _composition(s, d):
    letters = F.explode(F.array(*[F.lit(b) for b in "AGCT"]))
    q = S.load(s, d, "documents").select("lang", A.quad_map(F.col("text")).alias("bases")).select("lang", "bases", letters.alias("base"))
    return q.groupBy("lang", "base").agg(F.sum(F.length("bases") - F.length(F.replace("bases", F.col("base"), F.lit("")))).cast("long").alias("n"))


Q["base_composition"] = _composition
SQL["base_composition"] = f"WITH {DQ} SELECT lang, base, sum(length(bases) - length(replace(bases, base, '')))::BIGINT AS n FROM dq, (VALUES ('A'), ('G'), ('C'), ('T')) b(base) GROUP BY ALL"
Q["unknown_runs"] = lambda s, d: S.event_seq(s, d).select("seq_id", F.explode(A.unknown_runs(F.col("bases"))).alias("r")).select("seq_id", "r.pos", F.col("r.len").cast("long").alias("len"))
SQL["unknown_runs"] = f"WITH {EV}, g AS (SELECT seq_id, pos, pos - row_number() OVER (PARTITION BY seq_id ORDER BY pos) AS k FROM ev WHERE base = 'N') SELECT seq_id, min(pos)::BIGINT AS pos, count(*)::BIGINT AS len FROM g GROUP BY seq_id, k"
Q["unknown_rate"] = lambda s, d: S.load(s, d, "documents").select("lang", A.letter_map(F.col("text")).alias("b")).groupBy("lang").agg(
    F.sum(F.length("b") - F.length(F.replace("b", F.lit("N"), F.lit("")))).cast("long").alias("n_unknown"), F.sum(F.length("b")).cast("long").alias("n"))
SQL["unknown_rate"] = f"WITH {DL} SELECT lang, sum(length(bases) - length(replace(bases, 'N', '')))::BIGINT AS n_unknown, sum(length(bases))::BIGINT AS n FROM dl GROUP BY lang"
Q["unknown_round_trip"] = lambda s, d: general.digests(A.merge_unknown(A.split_unknown(S.event_seq(s, d))))
SQL["unknown_round_trip"] = digest_sql(EVSEQ, "es")

# Groups, fragments, words.
Q["fixed_groups"] = lambda s, d: grouping.fixed_groups(S.doc_quad(s, d), 4096).select("seq_id", F.col("group_id").cast("long").alias("group_id"), "start", F.col("n_bases").cast("long").alias("n_bases"))
SQL["fixed_groups"] = f"WITH {DQ} SELECT seq_id, (p // 4096)::BIGINT AS group_id, p AS start, least(4096, length(bases) - p)::BIGINT AS n_bases FROM (SELECT *, unnest(range(0, length(bases), 4096)) AS p FROM dq)"
Q["group_ntile"] = lambda s, d: grouping.fixed_count(S.event_rows(s, d), 8).groupBy("seq_id", "bucket").agg(F.count("*").alias("n"))
SQL["group_ntile"] = f"WITH {EV}, t AS (SELECT seq_id, ntile(8) OVER (PARTITION BY seq_id ORDER BY pos)::INT AS bucket FROM ev) SELECT seq_id, bucket, count(*) AS n FROM t GROUP BY ALL"


def _budget(s, d):
    """Shortest group of each document whose fragment costs no more than an order-0 model saves on it, in bits a base."""
    q = S.doc_quad(s, d).where("length(bases) > 0").select("seq_id", F.length("bases").alias("n"), A.base_counts(F.col("bases")).alias("counts"))
    share = F.transform(F.filter("counts", lambda c: c > 0), lambda c: c / F.col("n"))
    saved = F.aggregate(share, F.lit(2.0), lambda a, x: a + x * F.log2(x))
    b = q.select("seq_id", F.round(saved, 6).alias("budget")).where("budget > 0")
    return b.select("seq_id", "budget", grouping.budget_length(F.col("budget")).alias("length"))


Q["length_for_budget"] = _budget
SQL["length_for_budget"] = f"""WITH {DQ}, c AS (SELECT seq_id, length(bases) AS n, length(bases) - length(replace(bases, base, '')) AS c FROM dq, (VALUES ('A'), ('G'), ('C'), ('T')) b(base) WHERE length(bases) > 0),
  b AS (SELECT seq_id, round(2 + sum(CASE WHEN c > 0 THEN c::DOUBLE / n * log2(c::DOUBLE / n) ELSE 0 END), 6) AS budget FROM c GROUP BY seq_id)
  SELECT seq_id, budget, ceil(round(128 / budget, 6))::BIGINT AS length FROM b WHERE budget > 0"""
SIZES = (1000, 4000, 16000, 64000, 213000)


def _overhead(s, d):
    n = S.doc_quad(s, d).select(F.length("bases").cast("long").alias("n"), F.explode(F.array(*[F.lit(x) for x in SIZES])).alias("length"))
    g = F.sum(F.ceil(F.col("n") / F.col("length")))
    return n.groupBy("length").agg(g.cast("long").alias("groups"), F.round(g * 128 / F.sum("n"), 9).alias("overhead"))


Q["fragment_overhead_sweep"] = _overhead
SQL["fragment_overhead_sweep"] = f"WITH {DQ} SELECT l::INT AS length, sum(ceil(length(bases) / l::DOUBLE))::BIGINT AS groups, round(sum(ceil(length(bases) / l::DOUBLE)) * 128 / sum(length(bases)), 9) AS overhead FROM dq, (VALUES {', '.join(f'({x})' for x in SIZES)}) t(l) GROUP BY l"
Q["initial_fragments"] = lambda s, d: grouping.initial_fragment(S.doc_letter(s, d)).select("seq_id", "at", "fragment")
SQL["initial_fragments"] = f"WITH {DL}, f AS (SELECT seq_id, bases, regexp_extract(bases, '[AGCT]{{64}}') AS fr FROM dl) SELECT seq_id, CASE WHEN fr <> '' THEN (instr(bases, fr) - 1)::BIGINT END AS at, nullif(fr, '') AS fragment FROM f"
Q["fragment_pack"] = lambda s, d: grouping.initial_fragment(S.doc_quad(s, d)).where("fragment IS NOT NULL").select("seq_id", F.lower(F.hex(A.pack(F.col("fragment")))).alias("packed"))
SQL["fragment_pack"] = "SELECT doc_id AS seq_id, substr(lower(hex(encode(text))), 1, 32) AS packed FROM documents WHERE strlen(text) >= 16"
Q["concat_corpus"] = lambda s, d: grouping.concat_corpus(S.even(S.load(s, d, "documents").select("lang", F.col("doc_id").alias("seq_id"), "text"), "seq_id").select("lang", "seq_id", A.quad_map(F.col("text")).alias("bases")), "lang").select("lang", "seq_id", "offset")
SQL["concat_corpus"] = f"WITH {DQ} SELECT lang, seq_id, coalesce(sum(length(bases)) OVER (PARTITION BY lang ORDER BY seq_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS offset FROM dq"


def _position(s, d):
    g = grouping.fixed_groups(S.event_seq(s, d), 16).select("seq_id", "group_id", "start", (F.col("start") + F.col("n_bases")).alias("stop"))
    r = S.event_rows(s, d).select("seq_id", "pos")
    return r.join(g, (r["seq_id"] == g["seq_id"]) & (r["pos"] >= g["start"]) & (r["pos"] < g["stop"])).select(r["seq_id"], "pos", F.col("group_id").cast("long").alias("group_id"))


Q["position_to_group"] = _position
SQL["position_to_group"] = f"WITH {EV} SELECT seq_id, pos::BIGINT AS pos, (pos // 16)::BIGINT AS group_id FROM ev"
Q["ngram_words"] = lambda s, d: grouping.ngram_words(S.event_seq(s, d), 3)
SQL["ngram_words"] = f"WITH {EVSEQ} SELECT seq_id, i, substr(bases, (3 * i + 1)::INT, 3) AS word FROM (SELECT *, unnest(range(0, length(bases) // 3)) AS i FROM es)"


def _vocab(s, d):
    """All words of three bases with their codes, and how often each stands in the event sequences."""
    n = grouping.ngram_words(S.event_seq(s, d), 3).groupBy("word").agg(F.count("*").alias("n"))
    return grouping.ngram_vocab(s, 3).join(n, "word", "left").select("word", "code", F.coalesce("n", F.lit(0)).alias("n"))


Q["ngram_vocab"] = _vocab
SQL["ngram_vocab"] = f"""WITH {EVSEQ}, w AS (SELECT substr(bases, (3 * i + 1)::INT, 3) AS word, count(*) AS n FROM (SELECT *, unnest(range(0, length(bases) // 3)) AS i FROM es) GROUP BY 1), b AS (SELECT * FROM (VALUES ('A', 0), ('G', 1), ('C', 2), ('T', 3)) t(b, v)),
  v AS (SELECT x.b || y.b || z.b AS word, (x.v * 16 + y.v * 4 + z.v)::BIGINT AS code FROM b x, b y, b z) SELECT word, code, coalesce(n, 0) AS n FROM v LEFT JOIN w USING (word)"""
Q["ngram_top"] = lambda s, d: grouping.ngram_words(S.doc_quad(s, d), 3).groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(20)
SQL["ngram_top"] = f"WITH {DQ}, w AS (SELECT substr(bases, (3 * i + 1)::INT, 3) AS word FROM (SELECT *, unnest(range(0, length(bases) // 3)) AS i FROM dq)) SELECT word, count(*) AS n FROM w GROUP BY word ORDER BY n DESC, word LIMIT 20"


def _byte_group(s, d):
    out = None
    for g in (2, 4):
        x = grouping.byte_group_df(S.segments(s, d), g).select(F.lit(g).alias("g"), "seg", "r", F.size("vec").alias("width"), F.round(F.aggregate("vec", F.lit(0.0), lambda a, b: a + b), 6).alias("total"), F.round(F.element_at("vec", -1), 6).alias("last"))
        out = x if out is None else out.unionByName(x)
    return out


Q["byte_group_reshape"] = _byte_group
SQL["byte_group_reshape"] = f"WITH {EM}, g AS (SELECT * FROM (VALUES (2), (4)) t(g)), f AS (SELECT g, seg, i // g AS r, flatten(list(vec ORDER BY i)) AS v FROM em, g GROUP BY ALL) SELECT g, seg, r, len(v)::INT AS width, round(list_sum(v), 6) + 0.0::DOUBLE AS total, round(v[-1], 6) + 0.0::DOUBLE AS last FROM f"


def _shapes(s, d):
    rows = [(k, p.fg or 1 << 60, p.ng, p.bg, *p.shapes().values()) for k, p in grouping.ablation_grid().items()]
    g = s.createDataFrame(rows, "config string, fg long, ng int, bg int, raw int, words int, length int, conv int, n int")
    n = S.doc_quad(s, d).select(F.length("bases").cast("long").alias("b"))
    j = n.join(F.broadcast(g))  # four configurations
    return j.groupBy("config", "n").agg(F.sum(F.ceil(F.col("b") / F.col("fg"))).cast("long").alias("groups"), F.sum(F.expr("b div ng")).cast("long").alias("words"), F.sum(F.expr("b div ng div bg")).cast("long").alias("rows"))


Q["grouping_ablation_shapes"] = _shapes
SQL["grouping_ablation_shapes"] = f"""WITH {DQ}, g AS (SELECT * FROM (VALUES ('none', 1152921504606846976, 1, 1, 13), ('byte', 1152921504606846976, 1, 2, 13),
  ('byte_ngram', 1152921504606846976, 2, 2, 3), ('all', 213000, 2, 2, 3)) t(config, fg, ng, bg, n))
  SELECT config, n::INT AS n, sum(ceil(length(bases) / fg::DOUBLE))::BIGINT AS groups, sum(length(bases) // ng)::BIGINT AS words, sum(length(bases) // ng // bg)::BIGINT AS rows FROM dq, g GROUP BY config, n"""
Q["lane_batches"] = lambda s, d: grouping.lane_batches(grouping.fixed_groups(S.doc_quad(s, d), 4096), 64, 8).select("seq_id", F.col("group_id").cast("long").alias("group_id"), "shard", "batch", F.col("lane").cast("long").alias("lane"))
SQL["lane_batches"] = f"""WITH {DQ}, g AS (SELECT seq_id, p // 4096 AS group_id, least(4096, length(bases) - p) AS n FROM (SELECT *, unnest(range(0, length(bases), 4096)) AS p FROM dq)),
  k AS (SELECT *, ((seq_id * 31 + group_id) % 8)::INT AS shard FROM g), r AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY n, seq_id, group_id) - 1 AS k FROM k)
  SELECT seq_id, group_id::BIGINT AS group_id, shard, (k // 64)::BIGINT AS batch, (k % 64)::BIGINT AS lane FROM r"""
Q["dedupe_groups"] = lambda s, d: grouping.fixed_groups(S.doc_quad(s, d), 4096).groupBy(F.md5(F.col("bases").cast("binary")).alias("digest")).agg(F.count("*").alias("n"), F.min("seq_id").alias("kept"))
SQL["dedupe_groups"] = f"WITH {DQ} SELECT md5(substr(bases, (p + 1)::INT, 4096)) AS digest, count(*) AS n, min(seq_id) AS kept FROM (SELECT *, unnest(range(0, length(bases), 4096)) AS p FROM dq) GROUP BY 1"

# Inputs and layers.
Q["one_hot_windows"] = lambda s, d: S.event_rows(s, d).select("seq_id", "pos", F.concat_ws("", F.transform(F.sequence(F.lit(0), F.lit(4)), lambda j: F.when(F.col("code") == j, 1).otherwise(0).cast("string"))).alias("vec"))
SQL["one_hot_windows"] = f"WITH {EV} SELECT seq_id, pos::BIGINT AS pos, array_to_string(list_transform(range(0, 5), lambda j: CASE WHEN code = j THEN '1' ELSE '0' END), '') AS vec FROM ev"


def _embed(s, d):
    t = s.createDataFrame([(c, (17 * c + 31 * j) % 7 / 8.0) for c in range(5) for j in range(4)], "code int, x double").groupBy("code").agg(F.sum("x").alias("x"))
    r = S.event_rows(s, d).join(F.broadcast(t), "code")  # five codes
    w = Window.partitionBy("seq_id").orderBy("pos").rowsBetween(-3, 0)
    return r.select("seq_id", "pos", F.round(F.sum("x").over(w), 6).alias("total"))


Q["embed_windows"] = _embed
SQL["embed_windows"] = f"WITH {EV}, t AS (SELECT c, sum((17 * c + 31 * j) % 7 / 8.0::DOUBLE) AS x FROM range(0, 5) a(c), range(0, 4) b(j) GROUP BY c) SELECT seq_id, pos::BIGINT AS pos, round(sum(x) OVER (PARTITION BY seq_id ORDER BY pos ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS total FROM ev JOIN t ON code = c"
Q["contexts_64"] = lambda s, d: S.event_rows(s, d).select("seq_id", "pos", F.concat_ws("", F.collect_list("base").over(Window.partitionBy("seq_id").orderBy("pos").rowsBetween(-64, -1))).alias("ctx"))
SQL["contexts_64"] = f"WITH {EV} SELECT seq_id, pos::BIGINT AS pos, coalesce(string_agg(base, '') OVER (PARTITION BY seq_id ORDER BY pos ROWS BETWEEN 64 PRECEDING AND 1 PRECEDING), '') AS ctx FROM ev"
Q["context_lag"] = lambda s, d: S.event_rows(s, d).select("seq_id", "pos", *[F.lag("base", k).over(Window.partitionBy("seq_id").orderBy("pos")).alias(f"b{k}") for k in (1, 2)], F.lead("base", 1).over(Window.partitionBy("seq_id").orderBy("pos")).alias("next"))
SQL["context_lag"] = f"WITH {EV} SELECT seq_id, pos::BIGINT AS pos, lag(base, 1) OVER w AS b1, lag(base, 2) OVER w AS b2, lead(base, 1) OVER w AS next FROM ev WINDOW w AS (PARTITION BY seq_id ORDER BY pos)"


def _conv(s, d):
    w = Window.partitionBy("seq_id").orderBy("pos")
    near = F.collect_list("code").over(w.rowsBetween(0, 23))
    y = F.aggregate(F.transform(near, lambda c, k: c * ((17 * k) % 7 - 3) / 8.0), F.lit(0.0), lambda a, b: a + b)
    return S.event_rows(s, d).withColumn("full", F.size(near)).withColumn("y", y).where("full = 24").select("seq_id", "pos", "y")


CONV = f"cv AS (SELECT * FROM (SELECT seq_id, pos, list(code) OVER w AS near FROM ev WINDOW w AS (PARTITION BY seq_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND 23 FOLLOWING)) WHERE len(near) = 24), cy AS (SELECT seq_id, pos, list_sum(list_transform(range(0, 24), lambda k: near[k + 1] * ((17 * k) % 7 - 3) / 8.0::DOUBLE)) AS y FROM cv)"
Q["conv1d_windows"] = _conv
SQL["conv1d_windows"] = f"WITH {EV}, {CONV} SELECT seq_id, pos::BIGINT AS pos, y FROM cy"
Q["maxpool_3"] = lambda s, d: _conv(s, d).groupBy("seq_id", F.expr("pos div 3").alias("i")).agg(F.max(F.greatest("y", F.lit(0.0))).alias("y"))
SQL["maxpool_3"] = f"WITH {EV}, {CONV} SELECT seq_id, (pos // 3)::BIGINT AS i, max(greatest(y, 0.0::DOUBLE)) AS y FROM cy GROUP BY 1, 2"
Q["layer_norm"] = lambda s, d: T.layer_norm_df(S.segments(s, d)).select("seg", "i", "d", F.round("y", 6).alias("y"))
SQL["layer_norm"] = f"WITH {EM}, r AS (SELECT seg, i, unnest(range(0, 64)) AS d, unnest(vec) AS x FROM em) SELECT seg, i, d::INT AS d, round((x - avg(x) OVER w) / sqrt(var_pop(x) OVER w + 1e-5), 6) + 0.0::DOUBLE AS y FROM r WINDOW w AS (PARTITION BY seg, i)"
GELU = "0.5 * x * (1 + tanh(sqrt(2 / pi()) * (x + 0.044715 * x * x * x)))"
Q["gelu_table"] = lambda s, d: S.load(s, d, "embeddings").select("vec_id", F.posexplode(F.col("embedding").cast("array<double>")).alias("d", "x")).select("vec_id", "d", F.expr(f"round({GELU}, 6)").alias("y"))
SQL["gelu_table"] = f"SELECT vec_id, d::INT AS d, round({GELU}, 6) + 0.0::DOUBLE AS y FROM (SELECT vec_id, unnest(range(0, len(embedding))) AS d, unnest(embedding::DOUBLE[]) AS x FROM embeddings)"
Q["sinusoid_table"] = lambda s, d: T.sinusoid_df(s).select("i", "d", F.round("g", 9).alias("g"))
SIN = "CASE WHEN d % 2 = 0 THEN sin(i / pow(10000.0::DOUBLE, (d // 2) * 2 / 64.0::DOUBLE)) ELSE cos(i / pow(10000.0::DOUBLE, (d // 2) * 2 / 64.0::DOUBLE)) END"
SQL["sinusoid_table"] = f"SELECT i, d::INT AS d, round({SIN}, 9) + 0.0::DOUBLE AS g FROM range(0, 13) a(i), range(0, 64) b(d)"
Q["relative_offsets"] = lambda s, d: s.range(13).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(-13).cast("long"), F.lit(12).cast("long"))).alias("j")).withColumn("delta", F.col("i") - F.col("j"))
SQL["relative_offsets"] = "SELECT i, j, i - j AS delta FROM range(0, 13) a(i), range(-13, 13) b(j)"
Q["scores_absolute"] = lambda s, d: T.scores_absolute(S.segments(s, d)).select("seg", "i", "j", F.round("a", 6).alias("a"))
SQL["scores_absolute"] = f"WITH {EM}, g AS (SELECT i, list({SIN} ORDER BY d) AS g FROM range(0, 13) a(i), range(0, 64) b(d) GROUP BY i), c AS (SELECT seg, em.i, list_transform(list_zip(vec, g), lambda z: z[1] + z[2]) AS x FROM em JOIN g USING (i)) SELECT a.seg, a.i, b.i AS j, round(list_dot_product(a.x, b.x), 6) + 0.0::DOUBLE AS a FROM c a JOIN c b USING (seg)"
Q["scores_relative"] = lambda s, d: T.scores_relative(S.segments(s, d)).select("seg", "i", "j", F.round("a", 6).alias("a"))
SQL["scores_relative"] = f"WITH {EM}, g AS (SELECT i AS delta, list({SIN} ORDER BY d) AS g FROM range(-12, 13) a(i), range(0, 64) b(d) GROUP BY i) SELECT a.seg, a.i, b.i AS j, round(list_dot_product(list_transform(a.vec, lambda x: x + 0.125::DOUBLE), b.vec) + list_dot_product(list_transform(a.vec, lambda x: x - 0.25::DOUBLE), g.g), 6) + 0.0::DOUBLE AS a FROM em a JOIN em b USING (seg) JOIN g ON g.delta = a.i - b.i"


def attend_sql(keys: str, queries: str = "SELECT seg, i, vec AS q FROM em") -> str:
    return f"""q AS ({queries}), k AS ({keys}), s AS (SELECT q.seg, q.i, k.k, list_dot_product(q.q, k.k) / 8 AS s FROM q JOIN k USING (seg)),
  e AS (SELECT seg, i, k, exp(s - max(s) OVER w) AS e FROM s WINDOW w AS (PARTITION BY seg, i)), a AS (SELECT seg, i, k, e / sum(e) OVER (PARTITION BY seg, i) AS a FROM e)
  SELECT seg, i, d::INT AS d, round(sum(a * x), 6) + 0.0::DOUBLE AS o FROM (SELECT seg, i, a, unnest(range(0, 64)) AS d, unnest(k) AS x FROM a) GROUP BY seg, i, d"""


def _attend(m):
    return lambda s, d: T.attend_memory(S.segments(s, d), m).select("seg", "i", "d", F.round("o", 6).alias("o"))


for _name, _m in (("attend_none", 0), ("attend_features_cut", 1), ("attend_features_long", 3)):
    Q[_name] = _attend(_m)
    SQL[_name] = f"WITH {EM}, " + attend_sql(f"SELECT seg + t AS seg, vec AS k FROM em, range(0, {_m + 1}) r(t)")


Q["attend_latent_whole"] = lambda s, d: T.attend_latent_whole(S.segments(s, d)).select("seg", "i", "d", F.round("o", 6).alias("o"))
Q["softmax_rows"] = lambda s, d: T.scores(S.segments(s, d).select("seg", "i", F.col("vec").alias("q")), S.segments(s, d).select("seg", F.col("i").alias("j"), F.col("vec").alias("k"))).groupBy("seg", "i").agg(F.round(F.log(F.sum(F.exp("s"))), 6).alias("log_sum"))
SQL["softmax_rows"] = f"WITH {EM} SELECT a.seg, a.i, round(ln(sum(exp(list_dot_product(a.vec, b.vec) / 8))), 6) AS log_sum FROM em a JOIN em b USING (seg) GROUP BY 1, 2"
Q["dot_products"] = lambda s, d: S.load(s, d, "embeddings").select("vec_id", F.round(T.dot(F.col("embedding").cast("array<double>"), F.col("embedding").cast("array<double>")), 6).alias("norm2"))
SQL["dot_products"] = "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS norm2 FROM embeddings"

# Coding.
def _steps(s, d):
    """Blocks of 12 bases, the most that doubles hold; the model is that of the whole sequence."""
    rows = S.event_rows(s, d)
    near = rows.withColumn("block", F.expr("pos div 12")).join(C.order0(rows).select("seq_id", "code", "below", "share"), ["seq_id", "code"])
    parts = F.sort_array(F.collect_list(F.struct("pos", "below", "share")))
    return near.groupBy("seq_id", "block").agg(parts.alias("steps")).withColumn("iv", C.interval(F.col("steps")))


def _encoded(s, d):
    return _steps(s, d).select("seq_id", "block", F.round("iv.low", 12).alias("low"), F.round(F.log2("iv.width"), 6).alias("log_width"))




def _tags(s, d):
    bits, tag = C.shortest_tag(F.col("iv.low"), F.col("iv.width"))
    return _steps(s, d).withColumn("n_bits", bits.cast("long")).withColumn("tag", tag)


Q["shortest_tag_blocks"] = lambda s, d: _tags(s, d).select("seq_id", "block", "n_bits", F.round("tag", 12).alias("tag"))


def _unfold(s, d):
    """Decodes each block from its tags alone: one, or several where the interval gets too narrow for one."""
    model = F.sort_array(F.collect_list(F.struct("below", "share", "code")))
    m = C.order0(S.event_rows(s, d)).groupBy("seq_id").agg(model.alias("m"))

    def tagged(p):
        return F.struct(C.shortest_tag(p["low"], p["width"])[1].alias("tag"), p["n"].alias("n"))

    def unfold(part):
        start = F.struct(F.lit("").alias("out"), F.lit(0.0).alias("low"), F.lit(1.0).alias("width"))

        def step(acc, i):
            # Bounds by the encoder's own sums, so that a tag on a bound falls to the side it was made for.
            hit = F.element_at(F.filter("m", lambda x: acc["low"] + x["below"] * acc["width"] <= part["tag"]), -1)
            return F.struct(F.concat(acc["out"], F.substring(F.lit(A.ALPHABET), hit["code"].cast("int") + 1, F.lit(1))).alias("out"), (acc["low"] + hit["below"] * acc["width"]).alias("low"), (acc["width"] * hit["share"]).alias("width"))

        return F.aggregate(F.sequence(F.lit(1), part["n"]), start, step, lambda a: a["out"])

    t = _steps(s, d).select("seq_id", "block", F.transform(C.parts(F.col("steps")), tagged).alias("tags")).join(m, "seq_id")
    return t.select("seq_id", "block", F.array_join(F.transform("tags", unfold), "").alias("bases"))


IVB = f"""RECURSIVE {EV}, c AS (SELECT seq_id, code, count(*) AS n FROM ev GROUP BY ALL), p AS (SELECT seq_id, code, coalesce(sum(n) OVER (PARTITION BY seq_id ORDER BY code ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE / sum(n) OVER (PARTITION BY seq_id)::DOUBLE AS below, n::DOUBLE / sum(n) OVER (PARTITION BY seq_id)::DOUBLE AS share FROM c),
  st AS (SELECT seq_id, pos // 12 AS block, pos % 12 AS k, below, share FROM ev JOIN p USING (seq_id, code)),
  f AS (SELECT seq_id, block, -1::BIGINT AS k, 0.0::DOUBLE AS low, 1.0::DOUBLE AS width FROM (SELECT DISTINCT seq_id, block FROM st) UNION ALL SELECT f.seq_id, f.block, f.k + 1, f.low + st.below * f.width, f.width * st.share FROM f JOIN st ON st.seq_id = f.seq_id AND st.block = f.block AND st.k = f.k + 1),
  z AS (SELECT seq_id, block::BIGINT AS block, arg_max(low, k) AS low, arg_max(width, k) AS width FROM f GROUP BY seq_id, block)"""
Q["interval_blocks_encode"] = _encoded
SQL["interval_blocks_encode"] = f"WITH {IVB} SELECT seq_id, block, round(low, 12) AS low, round(log2(width), 6) AS log_width FROM z"
SQL["shortest_tag_blocks"] = f"WITH {IVB} SELECT seq_id, block, (ceil(-log2(width)) + 1)::BIGINT AS n_bits, round(ceil(low * pow(2, ceil(-log2(width)) + 1)) / pow(2, ceil(-log2(width)) + 1), 12) AS tag FROM z"
Q["interval_blocks_decode"] = _unfold
SQL["interval_blocks_decode"] = f"WITH {EVSEQ} SELECT seq_id, (p // 12)::BIGINT AS block, substr(bases, (p + 1)::INT, 12) AS bases FROM (SELECT *, unnest(range(0, length(bases), 12)) AS p FROM es)"
Q["quantise_cdf"] = lambda s, d: C.order0(S.event_rows(s, d)).select("seq_id", F.col("code").cast("long").alias("code"), (1 + F.floor(F.col("share") * (65536 - 5))).cast("long").alias("count"))
SQL["quantise_cdf"] = f"WITH {EV}, c AS (SELECT seq_id, code, count(*) AS n FROM ev GROUP BY ALL) SELECT seq_id, code::BIGINT AS code, (1 + floor(n::DOUBLE / sum(n) OVER (PARTITION BY seq_id)::DOUBLE * 65531))::BIGINT AS count FROM c"
Q["static_code_length"] = lambda s, d: C.order0(S.event_rows(s, d)).groupBy("seq_id").agg(F.round(F.sum(-F.col("n") * F.log2("share")), 4).alias("bits"))
SQL["static_code_length"] = f"WITH {EV}, c AS (SELECT seq_id, code, count(*) AS n FROM ev GROUP BY ALL), p AS (SELECT *, n / sum(n) OVER (PARTITION BY seq_id)::DOUBLE AS s FROM c) SELECT seq_id, round(sum(-n * log2(s)), 4) AS bits FROM p GROUP BY seq_id"

# Statistical baselines.
def adaptive_sql(k: int, tag: str = "") -> str:
    ctx = " + ".join(["0"] + [f"lag(code, {i}) OVER (PARTITION BY seq_id ORDER BY pos) * {5 ** (i - 1)}" for i in range(1, k + 1)])
    b = "ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING"
    return f"c{tag} AS (SELECT *, {ctx} AS ctx FROM ev), a{tag} AS (SELECT seq_id, pos, (count(*) OVER (PARTITION BY seq_id, ctx, code ORDER BY pos {b}) + 1.0::DOUBLE) / (count(*) OVER (PARTITION BY seq_id, ctx ORDER BY pos {b}) + 5) AS p FROM c{tag} WHERE ctx IS NOT NULL)"


for _k in range(4):
    Q[f"order_{_k}_adaptive"] = lambda s, d, k=_k: context.adaptive(S.event_rows(s, d), k).agg(F.count("*").alias("n"), F.round(F.avg("bits"), 6).alias("bits"))
    SQL[f"order_{_k}_adaptive"] = f"WITH {EV}, {adaptive_sql(_k)} SELECT count(*) AS n, round(avg(-log2(p)), 6) AS bits FROM a"
    Q[f"order_{_k}_entropy"] = lambda s, d, k=_k: context.entropy(S.event_rows(s, d), k).select("n", F.round("h", 6).alias("h"))
    _ctx = " + ".join(["0"] + [f"lag(code, {i}) OVER (PARTITION BY seq_id ORDER BY pos) * {5 ** (i - 1)}" for i in range(1, _k + 1)])
    SQL[f"order_{_k}_entropy"] = f"WITH {EV}, c AS (SELECT code, {_ctx} AS ctx FROM ev), n AS (SELECT ctx, code, count(*) AS n FROM c WHERE ctx IS NOT NULL GROUP BY ALL), t AS (SELECT *, sum(n) OVER (PARTITION BY ctx) AS t FROM n) SELECT sum(n)::BIGINT AS n, round(sum(-n * log2(n / t::DOUBLE)) / sum(n), 6) AS h FROM t"
def _document_order(s, d, k):
    """Empirical entropy of order k over the bases of all documents, from counts of words of k + 1 bases."""
    w = context.word_counts(S.doc_quad(s, d), k + 1).select(F.expr("word div 4").alias("ctx"), "n")
    t = w.withColumn("t", F.sum("n").over(Window.partitionBy("ctx")))
    return t.agg(F.sum("n").alias("n"), F.round(F.sum(-F.col("n") * F.log2(F.col("n") / F.col("t"))) / F.sum("n"), 6).alias("h"))


for _k in (4, 8):
    Q[f"documents_order_{_k}_entropy"] = lambda s, d, k=_k: _document_order(s, d, k)
    SQL[f"documents_order_{_k}_entropy"] = f"WITH {DQ}, w AS (SELECT substr(bases, (p + 1)::INT, {_k + 1}) AS kmer FROM (SELECT bases, unnest(range(0, greatest(0, length(bases) - {_k}))) AS p FROM dq)), c AS (SELECT substr(kmer, 1, {_k}) AS ctx, count(*) AS n FROM w GROUP BY kmer), t AS (SELECT *, sum(n) OVER (PARTITION BY ctx) AS t FROM c) SELECT sum(n)::BIGINT AS n, round(sum(-n * log2(n / t::DOUBLE)) / sum(n), 6) AS h FROM t"
Q["mixed_context_choice"] = lambda s, d: context.competing(S.event_rows(s, d)).select("seq_id", "k", F.round("bits", 6).alias("bits"))
SQL["mixed_context_choice"] = f"WITH {EV}, " + ", ".join(adaptive_sql(k, str(k)) for k in range(4)) + ", u AS (" + " UNION ALL ".join(f"SELECT seq_id, {k}::INT AS k, round(sum(-log2(p)) / count(*), 9) AS b, sum(-log2(p)) / count(*) AS bits FROM a{k} GROUP BY seq_id" for k in range(4)) + "), r AS (SELECT *, row_number() OVER (PARTITION BY seq_id ORDER BY b, k) AS r FROM u) SELECT seq_id, k, round(bits, 6) AS bits FROM r WHERE r = 1"
Q["blended_matches"] = lambda s, d: context.blended(S.event_rows(s, d)).groupBy("seq_id").agg(F.round(F.avg("bits"), 6).alias("bits"))
SQL["blended_matches"] = f"WITH {EV}, {adaptive_sql(1, '1')}, {adaptive_sql(2, '2')} SELECT seq_id, round(avg(-log2(a1.p * 0.5 + a2.p * 0.5)), 6) AS bits FROM a1 JOIN a2 USING (seq_id, pos) GROUP BY seq_id"
Q["em_mixture"] = lambda s, d: s.createDataFrame([(i, round(x, 6)) for i, x in enumerate(context.em_mixture(S.event_rows(s, d)))], "k int, weight double")
Q["pick_cheaper_orders"] = lambda s, d: context.competing(S.event_rows(s, d), (1, 2)).select("seq_id", "k")
SQL["pick_cheaper_orders"] = f"WITH {EV}, {adaptive_sql(1, '1')}, {adaptive_sql(2, '2')}, u AS (SELECT seq_id, 1 AS k, round(avg(-log2(p)), 9) AS b FROM a1 GROUP BY seq_id UNION ALL SELECT seq_id, 2, round(avg(-log2(p)), 9) FROM a2 GROUP BY seq_id), r AS (SELECT *, row_number() OVER (PARTITION BY seq_id ORDER BY b, k) AS r FROM u) SELECT seq_id, k::INT AS k FROM r WHERE r = 1"


def _field_split(s, d):
    e = S.load(s, d, "events")
    delta = F.col("event_id") - F.lag("event_id").over(Window.partitionBy("user_id").orderBy("event_id"))
    f = e.select(F.coalesce(delta, F.lit(0)).cast("string").alias("id"), F.col("event_type").alias("base"), F.floor(F.col("value") / 10).cast("long").cast("string").alias("quality"))
    long = f.select(F.explode(F.map_from_arrays(F.array(F.lit("id"), F.lit("base"), F.lit("quality")), F.array("id", "base", "quality"))).alias("field", "v"))
    n = long.groupBy("field", "v").agg(F.count("*").alias("n")).withColumn("t", F.sum("n").over(Window.partitionBy("field")))
    return n.groupBy("field").agg(F.round(F.sum(-F.col("n") * F.log2(F.col("n") / F.col("t"))) / F.max("t"), 6).alias("bits"))


Q["field_split_bits"] = _field_split
SQL["field_split_bits"] = """WITH f AS (SELECT coalesce(event_id - lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id), 0)::VARCHAR AS id, event_type AS base, floor(value / 10)::BIGINT::VARCHAR AS quality FROM events),
  l AS (SELECT 'id' AS field, id AS v FROM f UNION ALL SELECT 'base', base FROM f UNION ALL SELECT 'quality', quality FROM f), n AS (SELECT field, v, count(*) AS n FROM l GROUP BY ALL), t AS (SELECT *, sum(n) OVER (PARTITION BY field) AS t FROM n)
  SELECT field, round(sum(-n * log2(n / t::DOUBLE)) / max(t), 6) AS bits FROM t GROUP BY field"""

# Substitution baselines over the benchmark passages, whole.
BK = f"{BQ}, {kmer_sql('bq', 16)}"
Q["exact_repeats"] = lambda s, d: substitution.exact_repeats(S.bench_quad(s, d))
SQL["exact_repeats"] = f"WITH {BK}, f AS (SELECT kmer, min((seq_id, pos)) AS f, count(*) AS n FROM km GROUP BY kmer HAVING count(*) > 1) SELECT kmer, f[1] AS first_seq, f[2] AS first_pos, n FROM f"
Q["palindrome_repeats"] = lambda s, d: substitution.palindromes(S.bench_quad(s, d), 12)
SQL["palindrome_repeats"] = f"WITH {BQ}, {kmer_sql('bq', 12)}, s AS (SELECT kmer, count(*) AS n FROM km GROUP BY kmer), r AS (SELECT *, reverse(translate(kmer, 'AGCTN', 'TCGAN')) AS rc FROM s) SELECT r.kmer, r.rc, r.n, s.n AS m FROM r JOIN s ON r.rc = s.kmer WHERE r.kmer <= r.rc"
NEAR = "nc AS (SELECT seq_id, pos, src FROM (SELECT seq_id, pos, max(pos) OVER (PARTITION BY seq_id, kmer ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS src FROM km) WHERE src IS NOT NULL)"
Q["nearest_copy"] = lambda s, d: substitution.nearest_copy(S.bench_quad(s, d))
SQL["nearest_copy"] = f"WITH {BK}, {NEAR} SELECT seq_id, pos, src FROM nc"
Q["two_scan_gain"] = lambda s, d: substitution.two_scan_gain(S.bench_quad(s, d))
SQL["two_scan_gain"] = f"WITH {BK}, {NEAR}, g AS (SELECT *, pos - src AS diag, pos - row_number() OVER (PARTITION BY seq_id, pos - src ORDER BY pos) AS g FROM nc) SELECT seq_id, min(pos) AS pos, min(src) AS src, count(*) + 15 AS len, 2 * (count(*) + 15) - 24 AS gain FROM g GROUP BY seq_id, diag, g"
Q["approx_repeats"] = lambda s, d: substitution.approx_repeats(S.bench_quad(s, d))
SQL["approx_repeats"] = f"""WITH {BQ}, b AS (SELECT seq_id, b, substr(bases, (b * 32 + 1)::INT, 32) AS x FROM (SELECT *, unnest(range(0, length(bases) // 32)) AS b FROM bq)),
  p AS (SELECT l.seq_id AS seq_a, l.b AS block_a, r.seq_id AS seq_c, r.b AS block_c, levenshtein(l.x, r.x)::INT AS edits FROM b l JOIN b r ON (l.seq_id, l.b) < (r.seq_id, r.b))
  SELECT * FROM p WHERE edits <= 4"""
Q["repeat_blocks_roundtrip"] = lambda s, d: substitution.repeat_blocks_back(substitution.repeat_blocks(S.bench_quad(s, d)))
SQL["repeat_blocks_roundtrip"] = f"WITH {BQ} SELECT seq_id, b, substr(bases, (b * 32 + 1)::INT, 32) AS block FROM (SELECT *, unnest(range(0, length(bases) // 32)) AS b FROM bq)"
Q["repeat_blocks_bits"] = lambda s, d: substitution.repeat_blocks(S.bench_quad(s, d)).groupBy("seq_id").agg(F.sum("bits").alias("bits"))
SQL["repeat_blocks_bits"] = f"""WITH {BQ}, b AS (SELECT seq_id, b, substr(bases, (b * 32 + 1)::INT, 32) AS x FROM (SELECT *, unnest(range(0, length(bases) // 32)) AS b FROM bq)),
  p AS (SELECT l.seq_id AS sa, l.b AS ba, r.seq_id AS sc, r.b AS bc, hamming(l.x, r.x) AS h FROM b l JOIN b r ON (l.seq_id, l.b) < (r.seq_id, r.b)), q AS (SELECT * FROM p WHERE h <= 4),
  m AS (SELECT sc, bc, min(24 + 7 * h) AS bits FROM q WHERE 24 + 7 * h < 64 AND (sa, ba) NOT IN (SELECT (sc, bc) FROM q) GROUP BY ALL)
  SELECT seq_id, sum(coalesce(bits, 64))::BIGINT AS bits FROM b LEFT JOIN m ON sc = seq_id AND bc = b GROUP BY seq_id"""
Q["repeat_order2_roundtrip"] = lambda s, d: general.digests(substitution.repeat_decode(substitution.repeat_encode(S.bench_quad(s, d))))
SQL["repeat_order2_roundtrip"] = digest_sql(BQ, "bq")
Q["multi_pass_dictionary"] = lambda s, d: substitution.multi_pass(S.bench_quad(s, d))
SQL["multi_pass_dictionary"] = f"""WITH {BQ}, {kmer_sql('bq', 32).replace('km AS', 'k32 AS', 1)}, {kmer_sql('bq', 16).replace('km AS', 'k16 AS', 1)}, one AS (SELECT kmer, count(*) AS n FROM k32 GROUP BY kmer HAVING count(*) > 1),
  inn AS (SELECT DISTINCT substr(kmer, (o + 1)::INT, 16) AS kmer FROM one, range(0, 17) r(o)), two AS (SELECT kmer, count(*) AS n FROM k16 WHERE kmer NOT IN (SELECT kmer FROM inn) GROUP BY kmer HAVING count(*) > 1)
  SELECT 1::INT AS pass, kmer, n FROM one UNION ALL SELECT 2::INT, kmer, n FROM two"""
Q["dp_parse"] = lambda s, d: substitution.dp_parse(S.bench_quad(s, d))
Q["greedy_parse_roundtrip"] = lambda s, d: general.digests(substitution.expand(substitution.greedy_parse(S.bench_quad(s, d))))
SQL["greedy_parse_roundtrip"] = digest_sql(BQ, "bq")
Q["nml_blocks"] = lambda s, d: general.nml_blocks(S.bench_quad(s, d)).select("seq_id", F.round("bits", 4).alias("bits"))
Q["bwt_blocks"] = lambda s, d: general.bwt_blocks(S.bench_quad(s, d))
SQL["bwt_blocks"] = f"WITH {BQ}, s AS (SELECT seq_id, (p // 60)::BIGINT AS block, substr(bases, (p + 1)::INT, 60) || '$' AS s FROM (SELECT *, unnest(range(0, greatest(length(bases), 1), 60)) AS p FROM bq)), r AS (SELECT seq_id, block, substr(s, (i + 1)::INT) || substr(s, 1, i::INT) AS r FROM (SELECT *, unnest(range(0, length(s))) AS i FROM s)) SELECT seq_id, block, string_agg(right(r, 1), '' ORDER BY r) AS last FROM r GROUP BY seq_id, block"

# Codecs: what comes back is hashed against the source.
for _c in general.CODECS:
    Q[f"t1_human_{_c}_roundtrip"] = lambda s, d, c=_c: general.round_trip(S.doc_quad(s, d), c)
    SQL[f"t1_human_{_c}_roundtrip"] = digest_sql(DQ, "dq")
    Q[f"t1_fish_{_c}_roundtrip"] = lambda s, d, c=_c: general.round_trip(S.page_quad(s, d), c)
    SQL[f"t1_fish_{_c}_roundtrip"] = digest_sql(PQ, "pq")
Q["t1_human_raw2_roundtrip"] = lambda s, d: general.digests(general.raw2_back(general.raw2(S.doc_quad(s, d))))
SQL["t1_human_raw2_roundtrip"] = digest_sql(DQ, "dq")
Q["t1_human_context_roundtrip"] = lambda s, d: codec.round_trip(S.doc_quad(s, d), codec.order_coder())
SQL["t1_human_context_roundtrip"] = digest_sql(DQ, "dq")
Q["t1_fish_context_roundtrip"] = lambda s, d: codec.round_trip(S.page_quad(s, d), codec.order_coder())
SQL["t1_fish_context_roundtrip"] = digest_sql(PQ, "pq")
# All methods over two small corpora in common, the passages and the event sequences.
NEURAL = {"carry": model.TINY, "byte": model.BYTE, "multilevel": model.MULTI, "conv_lstm": model.LSTM, "conv_bilstm": model.BILSTM}
SMALL = {"benchmark": (S.bench_quad, digest_sql(BQ, "bq"), (1, 2, 4, 8)), "events": (S.event_seq, digest_sql(EVSEQ, "es"), (1, 2))}
for _t, (_src, _sql, _orders) in SMALL.items():
    for _c in general.CODECS:
        Q[f"t1_{_t}_{_c}_roundtrip"] = lambda s, d, c=_c, f=_src: general.round_trip(f(s, d), c)
    Q[f"t1_{_t}_context_roundtrip"] = lambda s, d, f=_src, o=_orders: codec.round_trip(f(s, d), codec.order_coder(o))
    for _c, _cfg in NEURAL.items():
        Q[f"t1_{_t}_{_c}_roundtrip"] = lambda s, d, c=_c, g=_cfg, f=_src: codec.round_trip(f(s, d), codec.model_coder(g, c), 512, 64)
    for _c in (*general.CODECS, "context", *NEURAL):
        SQL[f"t1_{_t}_{_c}_roundtrip"] = _sql
for _c, _cfg in model.memory_grid().items():
    Q[f"t3_{_c}_roundtrip"] = lambda s, d, c=_c, g=_cfg: codec.round_trip(S.event_seq(s, d), codec.model_coder(g, c), 512, 64)
    SQL[f"t3_{_c}_roundtrip"] = digest_sql(EVSEQ, "es")


def _records(s, d):
    e = S.load(s, d, "events").select("event_id", A.event_base(F.col("event_type")).alias("bases"), F.floor(F.col("value") / 10).cast("string").alias("qual"))
    return e.repartition(int(s.conf.get("spark.sql.shuffle.partitions")), "event_id").sortWithinPartitions("event_id")


Q["field_aware_roundtrip"] = lambda s, d: general.field_aware_back(general.field_aware(_records(s, d)))
SQL["field_aware_roundtrip"] = f"SELECT event_id AS id, {EVENT_CASE} AS bases, floor(value / 10)::BIGINT::VARCHAR AS qual FROM events"
Q["static_fragment_roundtrip"] = lambda s, d: codec.static_decode(codec.static_encode(grouping.initial_fragment(S.doc_letter(s, d)).where("fragment IS NOT NULL").select("seq_id", F.col("fragment").alias("bases"))))
SQL["static_fragment_roundtrip"] = f"WITH {DL}, f AS (SELECT seq_id, regexp_extract(bases, '[AGCT]{{64}}') AS bases FROM dl) SELECT seq_id, bases FROM f WHERE bases <> ''"
Q["pick_cheaper"] = lambda s, d: general.pick_cheaper(general.encode(S.doc_quad(s, d), "deflate"), general.encode(S.doc_quad(s, d), "bwt"), ("deflate", "bwt"))

# Measures, plans, published figures.


def _costs(s, d):
    """Parameters of each layer, and its multiply-accumulates over all documents: a window a base after the first 64."""
    rows = [(k, layer, p, m) for k, c in (("paper", model.PAPER), ("tiny", model.TINY)) for layer, p, m in model.model_cost(c, 1)]
    layers = s.createDataFrame(rows, "config string, layer string, params long, macs long")
    windows = S.doc_quad(s, d).agg(F.coalesce(F.sum(F.greatest(F.length("bases") - model.TINY.context, F.lit(0))), F.lit(0)).cast("long").alias("windows"))
    return layers.crossJoin(F.broadcast(windows)).select("config", "layer", "params", (F.col("macs") * F.col("windows")).alias("macs"))  # windows: one row


Q["model_cost_table"] = _costs
SQL["model_cost_table"] = f"""WITH {DQ}, w AS (SELECT coalesce(sum(greatest(length(bases) - 64, 0)), 0)::BIGINT AS windows FROM dq), c AS (SELECT * FROM (VALUES ('paper', 768, 3072), ('tiny', 16, 32)) t(config, d, f)), l AS (
  SELECT config, 'conv' AS layer, 24 * 4 * d + d AS params, 41 * 24 * 4 * d AS macs FROM c UNION ALL SELECT config, 'batch_norm', 2 * d, 0 FROM c
  UNION ALL SELECT config, 'attention', 3 * d * d + 2 * d, 13 * d * d + 52 * d * d + 676 * d FROM c UNION ALL SELECT config, 'layer_norm', 4 * d, 0 FROM c
  UNION ALL SELECT config, 'feed_forward', 2 * d * f + f + d, 26 * d * f FROM c UNION ALL SELECT config, 'head', 4 * d + 4, 4 * d FROM c)
  SELECT config, layer, params::BIGINT AS params, macs::BIGINT * windows AS macs FROM l, w"""
Q["paper_relative"] = lambda s, d: published.relative(s)
SQL["paper_relative"] = published.RELATIVE_SQL
Q["split_counts"] = lambda s, d: S.doc_quad(s, d).groupBy(measures.split_of(F.col("seq_id")).alias("split")).agg(F.count("*").alias("docs"), F.sum(F.length("bases")).cast("long").alias("bases"))
SQL["split_counts"] = f"WITH {DQ} SELECT CASE WHEN seq_id % 10 < 7 THEN 'train' WHEN seq_id % 10 < 9 THEN 'val' ELSE 'test' END AS split, count(*) AS docs, sum(length(bases))::BIGINT AS bases FROM dq GROUP BY 1"


def _hybrid(s, d):
    u = S.doc_quad(s, d).select("corpus", "seq_id").unionByName(S.page_quad(s, d).select("corpus", "seq_id"))
    k = F.row_number().over(Window.partitionBy("corpus").orderBy("seq_id")) - 1
    return u.withColumn("batch", F.floor(k / 64)).groupBy("batch", "corpus").agg(F.count("*").alias("n"))


Q["hybrid_batches"] = _hybrid
SQL["hybrid_batches"] = "WITH u AS (SELECT 'doc_quad' AS corpus, doc_id AS k FROM documents UNION ALL SELECT 'page_quad', page_id FROM pages), b AS (SELECT corpus, (row_number() OVER (PARTITION BY corpus ORDER BY k) - 1) // 64 AS batch FROM u) SELECT batch, corpus, count(*) AS n FROM b GROUP BY ALL"
Q["t1_scores"] = lambda s, d: experiments.scores(s, d)
Q["t3_scores"] = lambda s, d: experiments.memory_scores(s, d)
Q["t4_scores"] = lambda s, d: experiments.grouping_scores(s, d)
Q["hybrid_scores"] = lambda s, d: experiments.hybrid_scores(s, d)
Q["train_history"] = lambda s, d: experiments.train_history(s, d)
Q["container_roundtrip"] = lambda s, d: experiments.container_roundtrip(s, d)
SQL["container_roundtrip"] = digest_sql(EVSEQ, "es")

# Operators around the methods.
Q["scan_prune"] = lambda s, d: S.load(s, d, "documents").where("n_chars > 1000").groupBy("lang").agg(F.count("*").alias("n"))
SQL["scan_prune"] = "SELECT lang, count(*) AS n FROM documents WHERE n_chars > 1000 GROUP BY lang"
ENT = "-sum(c * log2(c / t)) / max(t)"


def _order0_by(s, d, frame, keys, how="groupBy"):
    letters = F.explode(F.array(*[F.lit(b) for b in "AGCT"]))
    x = frame.select(*keys, A.quad_map(F.col("text")).alias("b")).select(*keys, "b", letters.alias("base"))
    n = getattr(x, how)(*keys, "base") if how == "groupBy" else None
    return n.agg(F.sum(F.length("b") - F.length(F.replace("b", F.col("base"), F.lit("")))).cast("long").alias("c"))


def _entropy_of(n, keys):
    w = Window.partitionBy(*keys)
    t = n.where("c > 0").withColumn("t", F.sum("c").over(w))
    return t.groupBy(*keys).agg(F.max("t").alias("n"), F.round(-F.sum(F.col("c") * F.log2(F.col("c") / F.col("t"))) / F.max("t"), 6).alias("bpb"))


def _by_quality(s, d):
    f = S.load(s, d, "documents").join(S.load(s, d, "labels"), "doc_id")
    return _entropy_of(_order0_by(s, d, f, ["quality"]), ["quality"])


Q["bpb_by_quality"] = _by_quality
SQL["bpb_by_quality"] = f"WITH {DQ}, x AS (SELECT quality, base, sum(length(bases) - length(replace(bases, base, '')))::DOUBLE AS c FROM dq JOIN labels ON doc_id = seq_id, (VALUES ('A'), ('G'), ('C'), ('T')) b(base) GROUP BY ALL), t AS (SELECT *, sum(c) OVER (PARTITION BY quality) AS t FROM x WHERE c > 0) SELECT quality, max(t)::BIGINT AS n, round({ENT}, 6) AS bpb FROM t GROUP BY quality"


def _sets(kind):
    def run(s, d):
        c = _order0_by(s, d, S.load(s, d, "documents"), ["lang", "source"])
        c.createOrReplaceTempView("base_counts")
        by = {"cube": "CUBE (lang, source)", "rollup": "ROLLUP (lang, source)", "sets": "GROUPING SETS ((lang), (source), ())"}[kind]
        g = s.sql(f"SELECT lang, source, grouping_id() AS gid, sum(CASE WHEN base IN ('G', 'C') THEN c ELSE 0 END) AS gc, sum(c) AS n FROM base_counts GROUP BY {by}")
        return g.select("lang", "source", F.col("gid").cast("long").alias("gid"), F.col("gc").cast("long").alias("gc"), F.col("n").cast("long").alias("n"))

    return run


for _k, _by in (("cube", "CUBE (lang, source)"), ("rollup", "ROLLUP (lang, source)"), ("sets", "GROUPING SETS ((lang), (source), ())")):
    Q[f"bpb_{_k}"] = _sets(_k)
    SQL[f"bpb_{_k}"] = f"WITH {DQ}, x AS (SELECT lang, source, base, sum(length(bases) - length(replace(bases, base, ''))) AS c FROM dq, (VALUES ('A'), ('G'), ('C'), ('T')) b(base) GROUP BY ALL) SELECT lang, source, (grouping(lang) * 2 + grouping(source))::BIGINT AS gid, sum(CASE WHEN base IN ('G', 'C') THEN c ELSE 0 END)::BIGINT AS gc, sum(c)::BIGINT AS n FROM x GROUP BY {_by}"
Q["kmer_spectrum"] = lambda s, d: substitution.spectrum(S.bench_quad(s, d), 8)
SQL["kmer_spectrum"] = f"WITH {BQ}, {kmer_sql('bq', 8)} SELECT kmer, count(*) AS n FROM km GROUP BY kmer"
Q["distinct_kmers"] = lambda s, d: substitution.kmers(S.bench_quad(s, d), 12).groupBy("seq_id").agg(F.countDistinct("kmer").alias("n"))
SQL["distinct_kmers"] = f"WITH {BQ}, {kmer_sql('bq', 12)} SELECT seq_id, count(DISTINCT kmer) AS n FROM km GROUP BY seq_id"
Q["approx_kmers"] = lambda s, d: substitution.kmers(S.bench_quad(s, d), 12).agg(F.approx_count_distinct("kmer", 0.02).alias("estimate"))
Q["top_kmers_per_item"] = lambda s, d: substitution.kmers(S.bench_quad(s, d), 4).groupBy("seq_id", "kmer").agg(F.count("*").alias("n")).withColumn("r", F.row_number().over(Window.partitionBy("seq_id").orderBy(F.desc("n"), "kmer"))).where("r <= 3").select("seq_id", "kmer", "n", F.col("r").cast("long").alias("r"))
SQL["top_kmers_per_item"] = f"WITH {BQ}, {kmer_sql('bq', 4)}, c AS (SELECT seq_id, kmer, count(*) AS n FROM km GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY seq_id ORDER BY n DESC, kmer) AS r FROM c) SELECT seq_id, kmer, n, r FROM r WHERE r <= 3"
Q["rolling_gc"] = lambda s, d: S.load(s, d, "events").select("user_id", "event_id", F.expr("sum(CASE WHEN event_type IN ('view', 'purchase') THEN 1L ELSE 0L END) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW)").alias("gc"))
SQL["rolling_gc"] = "SELECT user_id, event_id, sum((event_type IN ('view', 'purchase'))::BIGINT) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW)::BIGINT AS gc FROM events"
Q["longest_sequences"] = lambda s, d: S.doc_quad(s, d).select("seq_id", F.length("bases").cast("long").alias("n")).orderBy(F.desc("n"), "seq_id").limit(10)
SQL["longest_sequences"] = "SELECT doc_id AS seq_id, strlen(text) * 4 AS n FROM documents ORDER BY n DESC, seq_id LIMIT 10"
Q["events_by_day"] = lambda s, d: S.load(s, d, "events").groupBy(F.date_trunc("day", "ts").alias("day"), A.event_base(F.col("event_type")).alias("base")).agg(F.count("*").alias("n"))
SQL["events_by_day"] = f"SELECT date_trunc('day', ts)::TIMESTAMP AS day, {EVENT_CASE} AS base, count(*) AS n FROM events GROUP BY 1, 2"
Q["props_bucket"] = lambda s, d: S.load(s, d, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))
SQL["props_bucket"] = "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1"
EK = f"{EVSEQ}, {kmer_sql('es', 3)}"
Q["kmers_shared"] = lambda s, d: substitution.kmers(S.event_seq(s, d), 3).select("kmer").intersect(substitution.kmers(S.order_seq(s, d), 3).select("kmer"))
Q["kmers_only_events"] = lambda s, d: substitution.kmers(S.event_seq(s, d), 6).select("kmer").subtract(substitution.kmers(S.order_seq(s, d), 6).select("kmer"))
_OS = "os AS (" + SQL["order_sequences"] + ")"
for _n, _k, _op in (("kmers_shared", 3, "INTERSECT"), ("kmers_only_events", 6, "EXCEPT")):
    SQL[_n] = f"WITH {EVSEQ}, {_OS}, {kmer_sql('es', _k).replace('km AS', 'ka AS', 1)}, {kmer_sql('os', _k).replace('km AS', 'kb AS', 1)} SELECT kmer FROM ka {_op} SELECT kmer FROM kb"
Q["contaminated_kmers"] = lambda s, d: substitution.kmers(S.event_seq(s, d), 8).join(substitution.kmers(S.order_seq(s, d), 8).select("kmer").distinct(), "kmer", "left_semi").groupBy("seq_id").agg(F.count("*").alias("n"))
SQL["contaminated_kmers"] = f"WITH {EVSEQ}, {_OS}, {kmer_sql('es', 8).replace('km AS', 'ka AS', 1)}, {kmer_sql('os', 8).replace('km AS', 'kb AS', 1)} SELECT seq_id, count(*) AS n FROM ka WHERE kmer IN (SELECT kmer FROM kb) GROUP BY seq_id"
Q["repeat_free"] = lambda s, d: S.bench_quad(s, d).select("seq_id").join(substitution.nearest_copy(S.bench_quad(s, d)), "seq_id", "left_anti")
SQL["repeat_free"] = f"WITH {BK}, {NEAR} SELECT seq_id FROM bq WHERE seq_id NOT IN (SELECT seq_id FROM nc)"
Q["kmer_profile_map"] = lambda s, d: substitution.kmers(S.event_seq(s, d), 1).groupBy("seq_id", "kmer").agg(F.count("*").alias("n")).groupBy("seq_id").agg(F.map_from_entries(F.collect_list(F.struct("kmer", "n"))).alias("m")).select("seq_id", F.explode(F.map_filter("m", lambda k, v: v > 5)).alias("base", "n"))
SQL["kmer_profile_map"] = f"WITH {EV} SELECT seq_id, base, count(*) AS n FROM ev GROUP BY ALL HAVING count(*) > 5"
Q["udtf_kmers"] = lambda s, d: measures.udtf_kmers(S.event_seq(s, d), 3)
SQL["udtf_kmers"] = f"WITH {EK} SELECT seq_id, pos, kmer FROM km"
Q["udaf_bits"] = lambda s, d: measures.udaf_bits(S.event_rows(s, d))
SQL["udaf_bits"] = f"WITH {EV}, c AS (SELECT seq_id, code, count(*) AS n FROM ev GROUP BY ALL), p AS (SELECT *, n / sum(n) OVER (PARTITION BY seq_id)::DOUBLE AS s FROM c) SELECT seq_id, round(sum(-n * log2(s)) / sum(n), 6) AS bits FROM p GROUP BY seq_id"
Q["sql_bpb"] = lambda s, d: measures.sql_bpb(s, S.event_seq(s, d))
SQL["sql_bpb"] = f"WITH {EVSEQ} SELECT seq_id, length(bases)::BIGINT AS n_bases, round(2.0::DOUBLE * length(replace(bases, 'N', '')) / length(bases), 6) AS raw_bpb, reverse(translate(bases, 'AGCTN', 'TCGAN')) AS rc FROM es"

# Streams, each to its end and against the batch form.
Q["stream_bits_by_day"] = B.bits_by_day
SQL["stream_bits_by_day"] = f"WITH {EV}, t AS (SELECT seq_id, pos, ts FROM (SELECT user_id AS seq_id, ts, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS pos FROM events)), {adaptive_sql(1)} SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS n, round(sum(-log2(p)), 4) AS bits FROM a JOIN t USING (seq_id, pos) GROUP BY 1"
Q["stream_sliding"] = B.sliding
SQL["stream_sliding"] = "SELECT (date_trunc('day', ts) - to_days(k::INT))::TIMESTAMP AS start, event_type, count(*) AS n FROM events, range(0, 2) r(k) GROUP BY 1, 2"
Q["stream_sessions"] = B.sessions
SQL["stream_sessions"] = "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n FROM s GROUP BY user_id, s"
Q["stream_dedupe"] = B.dedupe
SQL["stream_dedupe"] = "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1"


def queries():
    return dict(Q)


def oracle_sql():
    return dict(SQL)


def entry(spark, sf_dir):
    """Compress and decompress the benchmark passages with the multi-level carry coder: sizes, and whether all came back."""
    src = S.bench_quad(spark, sf_dir)
    c = codec.model_coder(model.MULTI, "multilevel")
    box = codec.compress(src, c, 512, 64)
    back = codec.decompress(box, c, 64).select("seq_id", F.md5(F.col("bases").cast("binary")).alias("after"))
    sizes = box.groupBy("seq_id").agg(F.sum("n_bases").alias("n_bases"), F.sum("n_bits").alias("n_bits"))
    before = src.select("seq_id", F.md5(F.col("bases").cast("binary")).alias("before"))
    j = sizes.join(back, "seq_id").join(before, "seq_id")
    return j.select("seq_id", "n_bases", "n_bits", F.round(F.col("n_bits") / F.col("n_bases"), 6).alias("bpb"), (F.col("before") == F.col("after")).alias("lossless"))
