"""Measures (E) and the smaller workloads (W)."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.functions import edit as D
from clipflow.functions import phonemes as G
from clipflow.operators import evaluate as E
from clipflow.operators import lm as M
from clipflow.sources import lattices as L
from clipflow.sources import standin as S
from clipflow.sources.tables import load, written
from clipflow.workloads import decode as W
from clipflow.workloads import lexicon as A
from clipflow.workloads.registry import query

UT = S.UTTERANCES_SQL
LEVELS = {1: 40, 2: 20, 3: 10}

_PAIRS = f"WITH {UT}, lv AS (SELECT * FROM (VALUES (1, 40), (2, 20), (3, 10)) AS x(level, m)), " + """k AS (SELECT level, doc_id, s, bucket, words, i, ('0x' || substr(md5('corrupt|' || level || '|' || doc_id || '|' || s || '|' || (i - 1)), 1, 8))::BIGINT % m AS h
      FROM ut, lv, LATERAL (SELECT unnest(range(1, len(words) + 1)) AS i) WHERE bucket = 9),
    o AS (SELECT level, doc_id, s, bucket, any_value(words) AS ref, flatten(list(CASE WHEN h = 0 THEN [] WHEN h = 1 THEN [coalesce(words[i + 1], words[1])] WHEN h = 2 THEN [words[i], words[i]] ELSE [words[i]] END ORDER BY i)) AS hyp,
      count(*) FILTER (WHERE h <= 2) AS n_ops FROM k GROUP BY 1, 2, 3, 4)"""
_PH = "array_to_string(list_transform($0, lambda w: " + G.g2p_sql("w") + "), '')"
_CODE = "array_to_string(list_transform($0, lambda w: substr('" + D.WORD_CODES[:92] + "', list_position(list_sort(list_distinct(list_concat(ref, hyp))), w)::INT, 1)), '')"
_EDITS = _PAIRS + f""", x AS (SELECT level, doc_id, s, bucket, ref, hyp, {_PH.replace('$0', 'ref')} AS rp, {_PH.replace('$0', 'hyp')} AS hp, array_to_string(ref, ' ') AS rc, array_to_string(hyp, ' ') AS hc, {_CODE.replace('$0', 'ref')} AS rw, {_CODE.replace('$0', 'hyp')} AS hw FROM o),
    ed AS (SELECT level, doc_id, s, bucket, 'phone' AS unit, levenshtein(rp, hp) AS edits, length(rp) AS ref_len FROM x UNION ALL SELECT level, doc_id, s, bucket, 'char', levenshtein(rc, hc), length(rc) FROM x
      UNION ALL SELECT level, doc_id, s, bucket, 'word', levenshtein(rw, hw), len(ref) FROM x)"""


def pairs(spark, d):
    """level, doc_id, s, bucket, ref, hyp: test utterances, each word dropped, replaced by the next, doubled or kept by a hash."""
    u = S.utterances(spark, d).where("bucket = 9")
    u = u.select(F.explode(F.create_map(*[F.lit(x) for kv in LEVELS.items() for x in kv])).alias("level", "m"), "*")
    h = "cast(conv(substring(md5(concat_ws('|', 'corrupt', cast(level AS string), cast(doc_id AS string), cast(s AS string), cast(i AS string))), 1, 8), 16, 10) AS long) % m"
    hyp = f"flatten(transform(words, (w, i) -> transform(array({h}), h -> CASE WHEN h = 0 THEN array() WHEN h = 1 THEN array(coalesce(get(words, i + 1), words[0])) WHEN h = 2 THEN array(w, w) ELSE array(w) END)[0]))"
    return u.select("level", "doc_id", "s", "bucket", F.col("words").alias("ref"), F.expr(hyp).alias("hyp"))


def edits(spark, d):
    """level, doc_id, s, bucket, unit, edits, ref_len in three units."""
    p = pairs(spark, d)
    phones = lambda c: F.array_join(F.transform(c, lambda w: G.g2p(w)), "")
    chars = lambda c: F.array_join(c, " ")
    rows = F.array(
        F.struct(F.lit("phone").alias("unit"), D.edit_text(phones("ref"), phones("hyp")).alias("edits"), F.length(phones("ref")).cast("long").alias("ref_len")),
        F.struct(F.lit("char").alias("unit"), D.edit_text(chars("ref"), chars("hyp")).alias("edits"), F.length(chars("ref")).cast("long").alias("ref_len")),
        F.struct(F.lit("word").alias("unit"), D.edit_words("ref", "hyp").alias("edits"), F.size("ref").cast("long").alias("ref_len")),
    )
    return p.select("level", "doc_id", "s", "bucket", F.inline(rows))


def _unit(unit):
    @query(f"e_edit_{unit}", _EDITS + f" SELECT level::INT AS level, doc_id, s, edits, ref_len FROM ed WHERE unit = '{unit}'")
    def f(spark, d):
        return edits(spark, d).where(F.col("unit") == unit).select("level", "doc_id", "s", "edits", "ref_len")


for _u in ("phone", "char", "word"):
    _unit(_u)


@query("e_error_rates", _EDITS + " SELECT level::INT AS level, unit, round(sum(edits) / sum(ref_len)::DOUBLE, 6) AS rate FROM ed GROUP BY 1, 2")
def e_error_rates(spark, d):
    return E.error_rate(edits(spark, d), ["level", "unit"]).select("level", "unit", F.round("rate", 6).alias("rate"))


@query("e_rates_rollup", _EDITS + " SELECT level::INT AS level, unit, round(sum(edits) / sum(ref_len)::DOUBLE, 6) AS rate, count(*) AS n FROM ed GROUP BY ROLLUP (level, unit)")
def e_rates_rollup(spark, d):
    return edits(spark, d).rollup("level", "unit").agg(F.round(F.sum("edits") / F.sum("ref_len"), 6).alias("rate"), F.count(F.lit(1)).alias("n"))


def _poisson_sql() -> str:
    total, whens = 0.0, []
    for k in range(8):
        total += math.exp(-1) / math.factorial(k)
        whens.append(f"WHEN u < {total!r} THEN {k}")
    return "CASE " + " ".join(whens) + " ELSE 8 END"


@query("e_bootstrap", _EDITS + f""", w0 AS (SELECT level, block, edits, ref_len, md5('boot|' || block || '|' || doc_id || '|' || s) AS h FROM ed, (SELECT unnest(range(0, 13)) AS block) WHERE unit = 'word'),
    w AS (SELECT level, block * 8 + j AS rep, edits, ref_len, ('0x' || substr(h, 4 * j::INT + 1, 4))::BIGINT / 65536.0::DOUBLE AS u FROM w0, (SELECT unnest(range(0, 8)) AS j) WHERE block * 8 + j < 100),
    r AS (SELECT level, rep, sum(edits * ({_poisson_sql()})) / sum(ref_len * ({_poisson_sql()}))::DOUBLE AS x FROM w GROUP BY 1, 2), t AS (SELECT level, sum(edits) / sum(ref_len)::DOUBLE AS wer FROM ed WHERE unit = 'word' GROUP BY 1)
    SELECT level::INT AS level, round(any_value(wer), 6) AS wer, round(stddev_samp(x), 6) AS se FROM r JOIN t USING (level) GROUP BY 1""")
def e_bootstrap(spark, d):
    e = edits(spark, d).where("unit = 'word'")
    return E.bootstrap_se(e, ["level"], ["doc_id", "s"]).select("level", F.round("rate", 6).alias("wer"), F.round("se", 6).alias("se"))


# operations that are known because they were made: one phoneme a frame of the simulator
_OPS = f"""WITH {W._WORDS_SQL}, p AS (SELECT word, CAST(unnest(range(1, length(phones) + 1)) AS INT) AS i, phones FROM types), o AS (SELECT substr(phones, i, 1) AS ref_tok, ('0x' || substr(md5('ops|' || word || '|' || i), 1, 8))::BIGINT % 10 AS h FROM p),
    ops AS (SELECT CASE h WHEN 0 THEN 'del' WHEN 1 THEN 'ins' WHEN 2 THEN 'sub' WHEN 3 THEN 'sub' ELSE 'match' END AS op, CASE WHEN h = 1 THEN NULL ELSE ref_tok END AS ref_tok,
      CASE h WHEN 0 THEN NULL WHEN 2 THEN translate(ref_tok, '{L._KEYS}', '{L.NEAR1}') WHEN 3 THEN translate(ref_tok, '{L._KEYS}', '{L.NEAR2}') ELSE ref_tok END AS hyp_tok FROM o)"""


def _ops(spark, d):
    p = W._bench_words(spark, d).where("length(phones) > 0").select("word", "phones", F.explode(F.expr("sequence(1, length(phones))")).alias("i"))
    h = S.hash8(F.lit("ops"), F.col("word"), F.col("i").cast("string")) % 10
    o = p.select(F.expr("substring(phones, i, 1)").alias("r"), h.alias("h"))
    op = F.when(F.col("h") == 0, "del").when(F.col("h") == 1, "ins").when(F.col("h").isin(2, 3), "sub").otherwise("match")
    hyp = F.when(F.col("h") == 2, F.translate("r", L._KEYS, L.NEAR1)).when(F.col("h") == 3, F.translate("r", L._KEYS, L.NEAR2)).when(F.col("h") != 0, F.col("r"))
    return o.select(op.alias("op"), F.when(F.col("h") != 1, F.col("r")).alias("ref_tok"), hyp.alias("hyp_tok"))


@query("e_insdel", _OPS + ", g AS (SELECT CASE WHEN op = 'del' THEN ref_tok ELSE hyp_tok END AS phone, count(*) FILTER (WHERE op = 'ins') AS i, count(*) FILTER (WHERE op = 'del') AS d FROM ops WHERE op IN ('ins', 'del') GROUP BY 1) SELECT phone, round(i / sum(i) OVER (), 6) AS ins_share, round(d / sum(d) OVER (), 6) AS del_share FROM g")
def e_insdel(spark, d):
    return E.insdel_heatmap(_ops(spark, d)).select("phone", F.round("ins_share", 6).alias("ins_share"), F.round("del_share", 6).alias("del_share"))


@query("e_confusion", _OPS + ", g AS (SELECT ref_tok AS ref, hyp_tok AS hyp, count(*) AS n FROM ops WHERE op = 'sub' GROUP BY 1, 2) SELECT ref, hyp, n, round(n / sum(n) OVER (PARTITION BY ref), 6) AS share FROM g")
def e_confusion(spark, d):
    return E.confusion(_ops(spark, d)).select("ref", "hyp", "n", F.round("share", 6).alias("share"))


_LAT = f"WITH {W._WORDS_SQL}, {L.lattice_sql('types', ['word'], 0.25)}, sums AS (SELECT word, t, sym, sum(p) AS p FROM lattice GROUP BY 1, 2, 3)"


@query("e_entropy", _LAT + " SELECT word AS utt, t, round(-sum(p * ln(p)), 6) AS h FROM sums GROUP BY 1, 2")
def e_entropy(spark, d):
    return E.frame_entropy(L.lattice(W._bench_words(spark, d), ["word"]), ["word"]).select(F.col("word").alias("utt"), "t", F.round("h", 6).alias("h"))


@query("e_top3", _LAT + ", r AS (SELECT *, row_number() OVER (PARTITION BY word, t ORDER BY round(p, 9) DESC, sym) AS rank FROM sums) SELECT word AS utt, t, rank::INT AS rank, sym, round(p, 6) AS p FROM r WHERE rank <= 3")
def e_top3(spark, d):
    return E.frame_topk(L.lattice(W._bench_words(spark, d), ["word"]), ["word"], 3).select(F.col("word").alias("utt"), "t", "rank", "sym", F.round("p", 6).alias("p"))


@query("e_compare", _EDITS + """, t AS (SELECT unit || '-' || level AS method, sum(edits) / sum(ref_len)::DOUBLE AS wer FROM ed GROUP BY 1)
    SELECT method, round(wer, 6) AS wer, round(wer - min(wer) OVER (), 4) AS to_best, round(1 - min(wer) OVER () / wer, 4) AS best_reduction, round(lag(wer) OVER q - wer, 4) AS to_previous, round(1 - wer / lag(wer) OVER q, 4) AS reduction FROM t WINDOW q AS (ORDER BY wer DESC, method)""")
def e_compare(spark, d):
    """The rates of the corrupted test utterances, a method for each unit and level."""
    rates = E.error_rate(edits(spark, d).withColumn("method", F.concat_ws("-", "unit", "level")), ["method"]).withColumnRenamed("rate", "wer")
    return E.compare(rates).select("method", F.round("wer", 6).alias("wer"), *[F.round(c, 4).alias(c) for c in ("to_best", "best_reduction", "to_previous", "reduction")])


# ---- workloads


@query("w_human_context", f"WITH {UT} SELECT doc_id, s, array_to_string(words[1:6], ' ') AS shown, array_to_string(words[7:], ' ') AS target, len(words) - 6 AS n_target FROM ut WHERE bucket = 9 AND len(words) >= 12")
def w_human_context(spark, d):
    u = S.utterances(spark, d).where("bucket = 9 AND size(words) >= 12")
    return u.select("doc_id", "s", F.array_join(F.slice("words", 1, 6), " ").alias("shown"), F.array_join(F.expr("slice(words, 7, size(words))"), " ").alias("target"), (F.size("words") - 6).cast("long").alias("n_target"))


_NOLM = W._COUNTS3 + f""", tk AS (SELECT doc_id, s, i, words[i] AS w, CASE WHEN i = 1 THEN '<s>' ELSE words[i - 1] END AS prev FROM ut, LATERAL (SELECT unnest(range(1, len(words) + 1)) AS i) WHERE bucket = 9),
    vo AS (SELECT w, c FROM counts WHERE "order" = 1 AND w <> '</s>'), lx AS (SELECT w, c, {G.g2p_sql('w')} AS ph FROM vo), hg AS (SELECT ph FROM lx GROUP BY 1 HAVING count(*) > 1),
    ca AS (SELECT doc_id, s, i, lx.w AS cand, lx.c AS cu, coalesce(b.c, 0) AS cb FROM (SELECT *, {G.g2p_sql('w')} AS ph FROM tk) t JOIN hg USING (ph) JOIN lx USING (ph) LEFT JOIN counts b ON b."order" = 2 AND b.ctx = t.prev AND b.w = lx.w)"""


@query("w_no_lm", _NOLM + " SELECT doc_id, s, i::INT AS pos, arg_max(cand, (cu, cand)) AS pick_uni, arg_max(cand, (cb, cu, cand)) AS pick_bi FROM ca GROUP BY 1, 2, 3")
def w_no_lm(spark, d):
    """Choice among homophones by unigram counts, and by bigram counts first."""
    counts = M.ngram_counts(W._lines(spark, d), 2)
    lex = counts.where("order = 1 AND w <> '</s>'").select("w", F.col("c").alias("cu")).withColumn("ph", G.g2p(F.col("w")))
    many = lex.groupBy("ph").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("ph")
    u = S.utterances(spark, d).where("bucket = 9").select("doc_id", "s", "words", F.posexplode("words").alias("i", "w"))
    t = u.select("doc_id", "s", (F.col("i") + 1).alias("pos"), F.when(F.col("i") == 0, "<s>").otherwise(F.expr("get(words, i - 1)")).alias("prev"), G.g2p(F.col("w")).alias("ph"))
    c = t.join(many, "ph").join(lex.withColumnRenamed("w", "cand"), "ph")
    bi = counts.where("order = 2").select(F.col("ctx").alias("prev"), F.col("w").alias("cand"), F.col("c").alias("b"))
    c = c.join(bi, ["prev", "cand"], "left").withColumn("cb", F.coalesce("b", F.lit(0)))
    return c.groupBy("doc_id", "s", "pos").agg(F.max_by("cand", F.struct("cu", "cand")).alias("pick_uni"), F.max_by("cand", F.struct("cb", "cu", "cand")).alias("pick_bi"))


_EXT = f"WITH {S.CLIPS_SQL}, " + """cv AS (SELECT conv_id, turn, regexp_extract_all(lower(text), '[a-z]+') AS words, ('0x' || substr(md5('clip|' || conv_id || '|' || turn), 1, 8))::BIGINT AS h FROM conversations),
    b AS (SELECT cv.*, dur, max_yaw, max_pitch FROM cv JOIN ev1 ON ev1.event_id = h % (SELECT max(event_id) + 1 FROM events) JOIN clips USING (user_id, w) WHERE len(words) > 0),
    e AS (SELECT conv_id, turn, coalesce(dur >= 1 AND max_yaw <= 30 AND max_pitch <= 30, FALSE) AS kept, len(words) AS n, len(list_filter(range(1, len(words) + 1), lambda i: ('0x' || substr(md5('ext|' || conv_id || '|' || turn || '|' || i), 1, 8))::BIGINT % 10 < CASE WHEN max_yaw <= 30 AND max_pitch <= 30 THEN 4 ELSE 5 END)) AS edits FROM b)"""


def external(spark, d):
    """conv_id, turn, words, dur, max_yaw, max_pitch, kept: each turn shown by the clip that an event, drawn by a hash, is of."""
    ev = S.frames(spark, d).select("event_id", "user_id", "w")
    total = load(spark, d, "events", "event_id").agg(F.max("event_id") + 1).scalar()
    cv = load(spark, d, "conversations", "conv_id", "turn", "text").select("conv_id", "turn", F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)")).alias("words"))
    cv = cv.where("size(words) > 0").withColumn("event_id", S.hash8(F.lit("clip"), F.col("conv_id").cast("string"), F.col("turn").cast("string")) % total)
    b = cv.join(ev, "event_id").join(S.clips(spark, d).select("user_id", "w", "dur", "max_yaw", "max_pitch"), ["user_id", "w"])
    return b.withColumn("kept", F.coalesce(F.expr("dur >= 1 AND max_yaw <= 30 AND max_pitch <= 30"), F.lit(False)))


@query("w_external", _EXT + " SELECT 'full' AS subset, count(*) AS n, round(sum(edits) / sum(n)::DOUBLE, 6) AS wer FROM e UNION ALL SELECT 'filtered', count(*), round(sum(edits) / sum(n)::DOUBLE, 6) FROM e WHERE kept")
def w_external(spark, d):
    """The external set, all and as the mining rules filter it; words fail by a hash, more often at wide angles."""
    b = external(spark, d)
    h = "cast(conv(substring(md5(concat_ws('|', 'ext', cast(conv_id AS string), cast(turn AS string), cast(i AS string))), 1, 8), 16, 10) AS long) % 10"
    e = b.select("kept", F.size("words").alias("n"), F.expr(f"size(filter(sequence(1, size(words)), i -> {h} < CASE WHEN max_yaw <= 30 AND max_pitch <= 30 THEN 4 ELSE 5 END))").alias("edits"))
    both = e.select(F.explode(F.when(F.col("kept"), F.array(F.lit("full"), F.lit("filtered"))).otherwise(F.array(F.lit("full")))).alias("subset"), "n", "edits")
    return both.groupBy("subset").agg(F.count(F.lit(1)).alias("c"), F.round(F.sum("edits") / F.sum("n"), 6).alias("wer")).select("subset", F.col("c").alias("n"), "wer")


# ---- from decodes


#: Fixed value: the word error rate, in percent, that the paper prints for another group's model trained on that set.
EXTERNAL_PUBLISHED = 57.9


@query("w_external_decoded")
def w_external_decoded(spark, d):
    """The external set decoded, whole and filtered, with the published row beside it: lattices are noisier at wide angles."""
    from clipflow.operators import baselines as B

    b = external(spark, d).withColumn("wide", F.expr("max_yaw > 30 OR max_pitch > 30")).withColumn("utt", F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string"), F.col("event_id").cast("string")))
    b = written(b.select("utt", "words", "wide", "kept"), "external")
    full = next(m for m in B.METHODS if m.name == "full_ph")
    from dataclasses import replace

    graph = B.graph(W._lines(spark, d), full)
    hyps = B.hypotheses(b.where("NOT wide"), full, graph).unionByName(B.hypotheses(b.where("wide"), replace(full, swap=0.4), graph))
    e = B.edits(hyps).where("unit = 'word'").join(b.select("utt", "kept"), "utt")
    both = e.select(F.explode(F.when(F.col("kept"), F.array(F.lit("full"), F.lit("filtered"))).otherwise(F.array(F.lit("full")))).alias("subset"), "utt", "edits", "ref_len")
    rates = E.bootstrap_se(both, ["subset"], ["utt"], 48).join(both.groupBy("subset").agg(F.count(F.lit(1)).alias("n")), "subset")
    ours = rates.select("subset", F.lit("full_ph").alias("method"), "n", F.round(100 * F.col("rate"), 1).alias("wer"), F.round(100 * F.col("se"), 1).alias("se"))
    printed = spark.createDataFrame([("full", "ext_attn", None, EXTERNAL_PUBLISHED, None)], "subset string, method string, n long, wer double, se double")
    return ours.unionByName(printed)


def _operations(spark, d):
    """op, ref_tok, hyp_tok: the phonemes of all test sentences aligned with those of the full method's decoded words."""
    from clipflow.operators import baselines as B
    from clipflow.workloads import tables_main as TM

    full = next(m for m in B.METHODS if m.name == "full_ph")
    hyps = B.hypotheses(written(TM.utterances(spark, d), "utterances"), full, B.graph(W._lines(spark, d), full))
    phones = lambda c: F.split(F.array_join(F.transform(c, lambda w: G.g2p(w)), ""), "")
    return written(E.align_ops(hyps.select("utt", phones("ref").alias("ref"), phones("hyp").alias("hyp")), ["utt"]), "operations")


@query("w_heatmap_decoded")
def w_heatmap_decoded(spark, d):
    """Shares of insertions and deletions by phoneme from alignments of decoded to true phonemes."""
    return E.insdel_heatmap(_operations(spark, d)).select("phone", F.round("ins_share", 6).alias("ins_share"), F.round("del_share", 6).alias("del_share"))


@query("w_confusion_decoded")
def w_confusion_decoded(spark, d):
    """Which phoneme was taken for which, from the same alignments."""
    return E.confusion(_operations(spark, d)).select("ref", "hyp", "n", F.round("share", 6).alias("share"))


@query("w_rerank")
def w_rerank(spark, d):
    """The benchmark's sentences: five strings of the unigram decoder each, and the one that a trigram model picks."""
    from clipflow.operators import baselines as B
    from clipflow.operators import fst as T
    from dataclasses import replace

    uni = replace(next(m for m in B.METHODS if m.name == "unigram_ph"), swap=0.1)
    b = load(spark, d, "benchmark", "item_id", "text").select(F.col("item_id").cast("string").alias("utt"), F.slice(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)")), 1, 12).alias("words")).where("size(words) > 0")
    lattice = L.lattice(b.withColumn("phones", F.array_join(F.transform("words", lambda w: G.g2p(w)), "")), ["utt"], "phones", uni.swap, "rerank")
    nbest = written(T.fst_decode(lattice, B.decoder(W._lines(spark, d), uni), ["utt"], 5), "nbest")
    model, weights = M.katz_model(W._lines(spark, d), 3)
    picked = M.rerank(nbest, ["utt"], model, weights, 3, 0.6)
    first = nbest.where("rank = 0").select("utt", F.col("words").alias("first"))
    both = b.withColumnRenamed("words", "ref").join(first, "utt").join(picked.select("utt", F.col("words").alias("picked")), "utt")
    return both.select("utt", F.size("ref").alias("n"), D.edit_words("ref", "first").alias("edits_first"), D.edit_words("ref", "picked").alias("edits_picked"))


_TITLE = "regexp_extract(html, '<title>(.*?)</title>', 1)"


@query("w_human_protocol", f"""WITH {UT}, np AS (SELECT max(page_id) + 1 AS n FROM pages), t AS (SELECT ut.*, source AS category, {_TITLE} AS title FROM ut JOIN documents USING (doc_id) CROSS JOIN np LEFT JOIN pages ON page_id = doc_id % np.n WHERE bucket = 9)
    SELECT doc_id, s, 'plain' AS condition, '' AS shown, NULL AS title, NULL AS category, 10 AS views, array_to_string(words, ' ') AS target FROM t UNION ALL
    SELECT doc_id, s, 'context', array_to_string(words[1:6], ' '), title, category, 10, array_to_string(words[7:], ' ') FROM t WHERE len(words) >= 12""")
def w_human_protocol(spark, d):
    """What a lipreader is given for each test sentence: nothing, or six words, title and category; ten views, each at half or whole speed."""
    pages = load(spark, d, "pages", "page_id", "html").select("page_id", F.regexp_extract("html", "<title>(.*?)</title>", 1).alias("title"))
    docs = load(spark, d, "documents", "doc_id", F.col("source").alias("category"))
    u = S.utterances(spark, d).where("bucket = 9").join(docs, "doc_id").withColumn("page_id", F.col("doc_id") % pages.agg(F.max("page_id") + 1).scalar()).join(pages, "page_id", "left")
    none = F.lit(None).cast("string")
    plain = u.select("doc_id", "s", F.lit("plain").alias("condition"), F.lit("").alias("shown"), none.alias("title"), none.alias("category"), F.lit(10).alias("views"), F.array_join("words", " ").alias("target"))
    more = u.where("size(words) >= 12").select("doc_id", "s", F.lit("context").alias("condition"), F.array_join(F.slice("words", 1, 6), " ").alias("shown"), "title", "category", F.lit(10).alias("views"), F.array_join(F.expr("slice(words, 7, size(words))"), " ").alias("target"))
    return plain.unionByName(more)


@query("w_speech_faces", """WITH f AS (SELECT l_orderkey, count(*) AS n, count(*) FILTER (WHERE p_size >= 20) AS wide FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1)
    SELECT o_orderstatus AS kind, count(*) AS n_segments, count(n) AS n_with_faces, count(*) - count(n) AS n_without, coalesce(sum(n), 0)::BIGINT AS n_faces, coalesce(sum(wide), 0)::BIGINT AS n_wide FROM orders LEFT JOIN f ON l_orderkey = o_orderkey GROUP BY 1""")
def w_speech_faces(spark, d):
    """Segments joined with the faces seen in them, as orders with their lines: left, semi and anti forms, faces by the size of their part."""
    seg = load(spark, d, "orders", "o_orderkey", F.col("o_orderstatus").alias("kind"))
    face = load(spark, d, "lineitem", "l_orderkey", "l_partkey").join(load(spark, d, "part", "p_partkey", "p_size"), F.expr("p_partkey = l_partkey"))
    seen = face.groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("p_size") >= 20).alias("wide"))
    left = seg.join(seen, seg["o_orderkey"] == seen["l_orderkey"], "left").groupBy("kind").agg(F.count(F.lit(1)).alias("n_segments"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_faces"), F.coalesce(F.sum("wide"), F.lit(0)).alias("n_wide"))
    semi = seg.join(seen, seg["o_orderkey"] == seen["l_orderkey"], "left_semi").groupBy("kind").agg(F.count(F.lit(1)).alias("n_with_faces"))
    anti = seg.join(seen, seg["o_orderkey"] == seen["l_orderkey"], "left_anti").groupBy("kind").agg(F.count(F.lit(1)).alias("n_without"))
    return left.join(semi, "kind", "left").join(anti, "kind", "left").na.fill(0, ["n_with_faces", "n_without"])


@query("w_human_conversation", """SELECT u.conv_id, u.turn, array_to_string(regexp_extract_all(lower(u.text), '[a-z]+'), ' ') AS shown, array_to_string(regexp_extract_all(lower(a.text), '[a-z]+'), ' ') AS target
    FROM conversations u JOIN conversations a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 WHERE u.role = 'user' AND a.role = 'assistant' AND len(regexp_extract_all(lower(a.text), '[a-z]+')) >= 6""")
def w_human_conversation(spark, d):
    """The with-context test in its second form: a user's turn is the context, the answer is what is to be read."""
    words = lambda c: F.regexp_extract_all(F.lower(c), F.lit("([a-z]+)"))
    c = load(spark, d, "conversations", "conv_id", "turn", "role", "text")
    user = c.where("role = 'user'").select("conv_id", "turn", F.array_join(words("text"), " ").alias("shown"))
    answer = c.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), words("text").alias("w")).where("size(w) >= 6")
    return user.join(answer, ["conv_id", "turn"]).select("conv_id", "turn", "shown", F.array_join("w", " ").alias("target"))


@query("e_scale", f"""WITH {UT}, x AS (SELECT bucket = 9 AS test, doc_id, s, unnest(words) AS w FROM ut), g AS (SELECT test, count(DISTINCT (doc_id, s)) AS n_utts, count(*) AS n_words, count(DISTINCT w) AS n_types FROM x GROUP BY 1)
    SELECT test, n_utts, n_words, n_types, round(n_words / 7100.0::DOUBLE * 37 / 60, 6) AS hours, round(log10(n_words / min(n_words) OVER ()::DOUBLE), 6) AS magnitude FROM g""")
def e_scale(spark, d):
    """Hours, vocabulary and sequences of training and test, and how many orders of magnitude the larger is above."""
    x = S.utterances(spark, d).select((F.col("bucket") == 9).alias("test"), "doc_id", "s", F.posexplode("words").alias("i", "w"))
    g = x.groupBy("test").agg(F.count_if(F.col("i") == 0).alias("n_utts"), F.count(F.lit(1)).alias("n_words"), F.count_distinct("w").alias("n_types"))
    least = F.min("n_words").over(Window.partitionBy())  # two rows
    return g.select("test", "n_utts", "n_words", "n_types", F.round(F.col("n_words") / 7100.0 * 37 / 60, 6).alias("hours"), F.round(F.log10(F.col("n_words") / least), 6).alias("magnitude"))
