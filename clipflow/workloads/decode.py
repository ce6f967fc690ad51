"""CTC (C), transducer (F) and language-model (M) queries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.functions import ctc as X
from clipflow.functions import phonemes as G
from clipflow.operators import ctc as K
from clipflow.operators import fst as T
from clipflow.operators import lm as M
from clipflow.operators.pipeline import min_words_filter  # noqa: F401
from clipflow.sources import lattices as L
from clipflow.sources import standin as S
from clipflow.sources.tables import load
from clipflow.workloads import lexicon as A
from clipflow.workloads.registry import query

UT = S.UTTERANCES_SQL

# ---- C

#: Labels over three symbols (0 is blank) and numbers of frames, one for each label of an embedding; the first is the paper's example.
TOYS = (("122", 5), ("122", 3), ("122", 4), ("12", 4), ("1", 3), ("11", 4), ("121", 4), ("2", 1), ("22", 2), ("12", 2))


def _toys(spark, d):
    """vec_id, label, T, l, frames: the first numbers of each embedding, by their size, as probabilities of three symbols a frame."""
    known = spark.createDataFrame([(i, label, t, [int(c) for c in label]) for i, (label, t) in enumerate(TOYS)], "toy int, label string, T int, l array<int>")
    e = load(spark, d, "embeddings", "vec_id", "embedding", "label").withColumnRenamed("label", "toy").join(F.broadcast(known), "toy")  # ten rows
    x = "1D + abs(cast(embedding[{}] AS double))"
    frame = f"transform(array(array({', '.join(x.format(f'3 * t + {k}') for k in range(3))})), w -> transform(w, y -> y / (w[0] + w[1] + w[2])))[0]"
    return e.select("vec_id", "label", "T", "l", F.expr(f"transform(sequence(0, T - 1), t -> {frame})").alias("frames"))


_W = "(1 + abs(embedding[3 * {t} - {k}]::DOUBLE))"
_TOYS_SQL = "known AS (SELECT * FROM (VALUES " + ", ".join(f"({i}, '{label}', {t})" for i, (label, t) in enumerate(TOYS)) + ") AS x(toy, label, T)), toys AS (SELECT vec_id, known.label, T, embedding FROM embeddings JOIN known ON toy = embeddings.label)"
# every string over 0, 1, 2 of T frames, collapsed
_ALL = f"""WITH RECURSIVE {_TOYS_SQL}, u(n, s, c, last) AS (SELECT 0, '', '', '0' UNION ALL SELECT n + 1, s || k, c || CASE WHEN k = '0' OR k = last THEN '' ELSE k END, k FROM u, (VALUES ('0'), ('1'), ('2')) AS v(k) WHERE n < 5),
    m AS (SELECT vec_id, label, T, count(u.s) AS n FROM toys LEFT JOIN u ON u.n = T AND u.c = label GROUP BY 1, 2, 3),
    w AS (SELECT vec_id, label, T, u.s, list_product(list_transform(range(1, T + 1), lambda t: embedding_at(t))) AS p FROM toys LEFT JOIN u ON u.n = T AND u.c = label),
    pr AS (SELECT vec_id, label, T, sum(CASE WHEN s IS NULL THEN 0 ELSE p END) AS p FROM w GROUP BY 1, 2, 3)""".replace("embedding_at(t)", f"(1 + abs(embedding[3 * t - 2 + substr(u.s, t, 1)::INT]::DOUBLE)) / ({_W.format(t='t', k=2)} + {_W.format(t='t', k=1)} + {_W.format(t='t', k=0)})")


@query("c_brute", _ALL + " SELECT vec_id, label, T, round(p, 9) AS p FROM pr")
def c_brute(spark, d):
    """By enumeration in tables: each frame multiplies the strings by the symbols."""
    steps = spark.createDataFrame(sorted(set(TOYS)), "label string, T int").select("label", "T", F.explode(F.expr("transform(sequence(0, cast(pow(3, T) AS int) - 1), i -> lpad(conv(cast(i AS string), 10, 3), T, '0'))")).alias("u"))
    cut = steps.withColumn("c", F.array_join(X.ctc_collapse("split(u, '')", "0"), "")).where("c = label").select("label", "T", "u")
    rows = _toys(spark, d).join(F.broadcast(cut), ["label", "T"], "left")  # at most 243 strings a toy
    p = F.expr("aggregate(transform(frames, (f, i) -> f[cast(substring(u, i + 1, 1) AS int)]), 1D, (a, x) -> a * x)")
    return rows.groupBy("vec_id", "label", "T").agg(F.round(F.sum(F.when(F.col("u").isNotNull(), p).otherwise(0.0)), 9).alias("p"))


@query("c_forward", _ALL + " SELECT vec_id, label, T, round(p, 9) AS p FROM pr")
def c_forward(spark, d):
    return _toys(spark, d).select("vec_id", "label", "T", F.round(X.ctc_probability("frames", "l"), 9).alias("p"))


@query("c_alignments", _ALL + " SELECT vec_id, label, T, n FROM m")
def c_alignments(spark, d):
    return _toys(spark, d).select("vec_id", "label", "T", X.ctc_alignments(F.col("T"), F.size("l"), X.adjacent_repeats("l")).alias("n"))


@query("c_infeasible", _ALL + " SELECT vec_id, label, T, n = 0 AS infeasible FROM m")
def c_infeasible(spark, d):
    return _toys(spark, d).select("vec_id", "label", "T", (F.col("T") < F.size("l") + X.adjacent_repeats("l")).alias("infeasible"))


_COLLAPSED = """c0 AS (SELECT {k}, t, s, lag(s) OVER (PARTITION BY {k} ORDER BY t) AS b FROM peaks),
    c1 AS (SELECT {k}, coalesce(string_agg(CASE WHEN s <> '_' AND (b IS NULL OR s <> b) THEN s END, '' ORDER BY t), '') AS labels FROM c0 GROUP BY {k})"""
_WORDS_SQL = f"types AS (SELECT word, {G.g2p_sql('word')} AS phones FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS word FROM benchmark))"


def _bench_words(spark, d):
    w = load(spark, d, "benchmark", "text").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("word")).distinct()
    return w.select("word", G.g2p(F.col("word")).alias("phones"))


@query("c_collapse", f"WITH {_WORDS_SQL}, {L.lattice_sql('types', ['word'], 0.25)}, {_COLLAPSED.format(k='word')} SELECT word AS utt, labels FROM c1")
def c_collapse(spark, d):
    """Of simulated peaks."""
    p = _bench_words(spark, d).withColumn("u", L.peaks("phones", ["word"], 0.25))
    return p.where("size(u) > 0").select(F.col("word").alias("utt"), F.array_join(X.ctc_collapse("u"), "").alias("labels"))


@query("c_greedy", f"WITH {_WORDS_SQL}, {L.lattice_sql('types', ['word'], 0.25)}, {_COLLAPSED.format(k='word')} SELECT word AS utt, labels FROM c1")
def c_greedy(spark, d):
    """From the lattices: the peak is the likeliest symbol."""
    return K.ctc_greedy(L.lattice(_bench_words(spark, d), ["word"]), ["word"]).withColumnRenamed("word", "utt")


@query("c_homophone_toy", f"""WITH RECURSIVE {A._TYPES}, ph AS (SELECT word, {G.g2p_sql('word')} AS phones FROM types), pr AS (SELECT x.word AS a, y.word AS b FROM ph x JOIN ph y ON x.phones = y.phones AND length(x.word) = length(y.word) AND x.word < y.word),
    r(a, b, i, string, p) AS (SELECT a, b, 1, '', 1.0::DOUBLE FROM pr UNION ALL SELECT a, b, i + 1, string || CASE k WHEN 0 THEN substr(a, i, 1) ELSE substr(b, i, 1) END, CASE WHEN substr(a, i, 1) = substr(b, i, 1) THEN p ELSE p / 2 END
      FROM r, (VALUES (0), (1)) AS v(k) WHERE i <= length(a) AND (k = 0 OR substr(a, i, 1) <> substr(b, i, 1)))
    SELECT a, b, string, p, string IN (a, b) AS is_word FROM r WHERE i = length(a) + 1""")
def c_homophone_toy(spark, d):
    """Independent positions fit to two homophones give weight to strings that are neither: all pairs of one length among the documents' words."""
    ph = A.types(spark, d).select("word", G.g2p(F.col("word")).alias("phones"), F.length("word").alias("n"))
    pairs = ph.withColumnRenamed("word", "a").join(ph.withColumnRenamed("word", "b"), ["phones", "n"]).where("a < b")
    step = "flatten(transform(out, s -> transform(array_distinct(array(substring(a, i, 1), substring(b, i, 1))), c -> concat(s, c))))"
    strings = pairs.select("a", "b", F.expr(f"aggregate(sequence(1, n), array(''), (out, i) -> {step})").alias("strings"))
    return strings.select("a", "b", F.explode("strings").alias("string"), (F.lit(1.0) / F.size("strings")).alias("p")).withColumn("is_word", (F.col("string") == F.col("a")) | (F.col("string") == F.col("b")))


@query("c_wordpost", f"WITH {A._LEX}, s AS (SELECT word, -0.5 * length(phones) - 0.1 * pron_id AS lp FROM lex) SELECT word, round(max(lp) + ln(sum(exp(lp - m))), 6) AS s_sum, round(max(lp), 6) AS s_max FROM (SELECT word, lp, max(lp) OVER (PARTITION BY word) AS m FROM s) GROUP BY 1")
def c_wordpost(spark, d):
    """Word score by all pronunciations and by the dominant one; a pronunciation's sound score is a stand-in by length."""
    s = A.lexicon(spark, d).select("word", (-0.5 * F.length("phones") - 0.1 * F.col("pron_id")).cast("double").alias("lp"))
    g = s.groupBy("word").agg(F.collect_list("lp").alias("x"))  # three at most
    return g.select("word", F.round(X.logsumexp("x"), 6).alias("s_sum"), F.round(F.array_max("x"), 6).alias("s_max"))


# ---- M

_UNITS = f"WITH {UT}, tr AS (SELECT DISTINCT array_to_string(words, ' ') AS line FROM ut WHERE bucket <> 9), pd AS (SELECT list_concat(['<s>'], string_split(line, ' '), ['</s>']) AS p FROM tr)"
_COUNTS = _UNITS + """, g AS (SELECT n AS ord, array_to_string(p[i:i + n - 2], ' ') AS ctx, p[i + n - 1] AS w FROM pd, (SELECT unnest(range(1, {order} + 1)) AS n), LATERAL (SELECT unnest(range(1, greatest(len(p) - n + 2, 1))) AS i)),
    counts AS (SELECT ord AS "order", CASE WHEN ord = 1 THEN '' ELSE ctx END AS ctx, w, count(*) AS c FROM g WHERE NOT (ord = 1 AND w = '<s>') GROUP BY 1, 2, 3),
    cc AS (SELECT "order", """ + ", ".join(f"count(*) FILTER (WHERE c = {r}) AS n{r}" for r in range(1, 7)) + """ FROM counts GROUP BY 1)"""
_COUNTS3, _COUNTS5 = _COUNTS.replace("{order}", "3"), _COUNTS.replace("{order}", "5")


def _lines(spark, d):
    """Training sentences, equal ones once: copies would bend the counts of counts."""
    return S.utterances(spark, d).where("bucket <> 9").select(F.array_join("words", " ").alias("line")).distinct().select(F.split("line", " ").alias("words"))


@query("m_ngrams", _COUNTS5 + ' SELECT c."order"::INT AS "order", count(*) AS types, sum(c)::BIGINT AS tokens, ' + ", ".join(f"any_value(n{r}) AS n{r}" for r in range(1, 7)) + ' FROM counts c JOIN cc USING ("order") GROUP BY 1')
def m_ngrams(spark, d):
    c = M.ngram_counts(_lines(spark, d), 5)
    return c.groupBy("order").agg(F.count(F.lit(1)).alias("types"), F.sum("c").alias("tokens"), *[F.count_if(F.col("c") == r).alias(f"n{r}") for r in range(1, 7)])


def _disc_sql(r: int) -> str:
    top = "(6.0::DOUBLE * n6 / nullif(n1, 0))"
    turing = f"(({r + 1}.0::DOUBLE * n{r + 1} / nullif(n{r}, 0)) / {r} - {top}) / nullif(1 - {top}, 0)"
    return f"SELECT \"order\", {r} AS r, CASE WHEN {turing} > 0 AND {turing} <= 1 THEN {turing} ELSE ({r} - n1 / (n1 + 2 * n2)::DOUBLE) / {r} END AS d, NOT coalesce({turing} > 0 AND {turing} <= 1, FALSE) AS guarded FROM cc"


_DISC = ", disc AS (" + " UNION ALL ".join(map(_disc_sql, range(1, 6))) + ")"


@query("m_katz_discounts", _COUNTS5 + _DISC + ' SELECT "order"::INT AS "order", r, round(d, 6) AS d, guarded FROM disc')
def m_katz_discounts(spark, d):
    return M.katz_discounts(M.ngram_counts(_lines(spark, d), 5)).select("order", "r", F.round("d", 6).alias("d"), "guarded")


_MODEL = _COUNTS3 + _DISC + """, tot AS (SELECT "order", ctx, sum(c) AS total FROM counts GROUP BY 1, 2),
    model AS (SELECT c."order", c.ctx, c.w, CASE WHEN c."order" = 1 THEN 1.0::DOUBLE ELSE coalesce(d, 1.0) END * c.c / total AS p, c.c FROM counts c JOIN tot t ON t."order" = c."order" AND t.ctx = c.ctx LEFT JOIN disc ON disc."order" = c."order" AND r = c.c),
    bw AS (SELECT h."order", h.ctx, sum(h.p) AS used, sum(l.p) AS lower, sum(h.c) AS n FROM model h LEFT JOIN model l ON l."order" = h."order" - 1 AND l.w = h.w AND l.ctx = CASE WHEN h."order" = 2 THEN '' ELSE regexp_replace(h.ctx, '^[^ ]* ', '') END WHERE h."order" > 1 GROUP BY 1, 2),
    bow AS (SELECT "order", ctx, n, CASE WHEN round(1 - lower, 12) > 0 THEN greatest((1 - used) / (1 - lower), 0) ELSE 0 END AS bow FROM bw)"""


@query("m_katz_bow", _MODEL + ' SELECT ctx, round(bow, 6) AS bow FROM bow WHERE "order" = 2 AND n >= 50')
def m_katz_bow(spark, d):
    counts = M.ngram_counts(_lines(spark, d), 3)
    often = counts.where("order = 2").groupBy("ctx").agg(F.sum("c").alias("n")).where("n >= 50")
    return M.back_off_weights(M.katz_train(counts, 2), 2).join(often, "ctx", "left_semi").select("ctx", F.round("bow", 6).alias("bow"))


_SCORE = _MODEL + """, te AS (SELECT doc_id, s, list_concat(['<s>'], words, ['</s>']) AS p FROM ut WHERE bucket = 9), tg AS (SELECT doc_id, s, i, p[i] AS w, CASE WHEN i > 2 THEN p[i - 2] || ' ' || p[i - 1] END AS c3, p[i - 1] AS c2 FROM te, LATERAL (SELECT unnest(range(2, len(p) + 1)) AS i)),
    sc AS (SELECT tg.doc_id, tg.s, ln(greatest(1e-9, CASE WHEN c3 IS NULL THEN q2 ELSE coalesce(m3.p, coalesce(b3.bow, 1) * q2) END)) AS logp FROM
      (SELECT tg.*, coalesce(m2.p, coalesce(b2.bow, 1) * coalesce(m1.p, 1e-9)) AS q2 FROM tg LEFT JOIN model m1 ON m1."order" = 1 AND m1.w = tg.w LEFT JOIN model m2 ON m2."order" = 2 AND m2.ctx = c2 AND m2.w = tg.w LEFT JOIN bow b2 ON b2."order" = 2 AND b2.ctx = c2) tg
      LEFT JOIN model m3 ON m3."order" = 3 AND m3.ctx = c3 AND m3.w = tg.w LEFT JOIN bow b3 ON b3."order" = 3 AND b3.ctx = c3)"""


def _test_scores(spark, d):
    model, weights = M.katz_model(_lines(spark, d), 3)
    return M.katz_logprob(M.word_grams(S.utterances(spark, d).where("bucket = 9"), ["doc_id", "s"], 3), model, 3, weights=weights)


@query("m_katz_score", _SCORE + " SELECT doc_id, s, round(sum(logp), 4) AS logp FROM sc GROUP BY 1, 2")
def m_katz_score(spark, d):
    return _test_scores(spark, d).groupBy("doc_id", "s").agg(F.round(F.sum("logp"), 4).alias("logp"))


@query("m_perplexity", _SCORE + " SELECT round(exp(-avg(logp)), 3) AS perplexity, count(*) AS n_words FROM sc")
def m_perplexity(spark, d):
    return M.perplexity(_test_scores(spark, d)).select(F.round("perplexity", 3).alias("perplexity"), "n_words")


@query("m_prune", _COUNTS3 + ', t AS (SELECT c FROM counts WHERE "order" = 2 ORDER BY c DESC, ctx, w LIMIT 5000) SELECT count(*) AS n, min(c) AS min_count FROM t')
def m_prune(spark, d):
    return M.prune(M.ngram_counts(_lines(spark, d), 3), 2, 5000).agg(F.count(F.lit(1)).alias("n"), F.min("c").alias("min_count"))


# ---- F


@query("f_ctc_arcs", f"WITH a AS (SELECT unnest(string_split('{G.ALPHABET}', '')) AS x) SELECT CASE WHEN b.x = '_' OR a.x = b.x THEN 'silent' ELSE 'emits' END AS kind, count(*) AS n FROM a, a b GROUP BY 1")
def f_ctc_arcs(spark, d):
    arcs = spark.createDataFrame(T.ctc_arcs(G.ALPHABET), "src int, dst int, ilab string, olab string, w double")
    return arcs.groupBy(F.when(F.col("olab") == "", "silent").otherwise("emits").alias("kind")).agg(F.count(F.lit(1)).alias("n"))


@query("f_lexicon_arcs", f"""WITH {A._LEX}, st AS (SELECT DISTINCT substr(phones, 1, i) AS dst FROM lex, LATERAL (SELECT unnest(range(1, length(phones) + 1)) AS i)), le AS (SELECT DISTINCT phones, word FROM lex WHERE phones <> ''),
    arcs AS (SELECT right(dst, 1) AS ilab, '' AS olab FROM st UNION ALL SELECT '', word FROM le) SELECT ilab, count(*) AS n, sum(length(olab))::BIGINT AS letters FROM arcs GROUP BY 1""")
def f_lexicon_arcs(spark, d):
    return T.lexicon_arcs(A.lexicon(spark, d)).groupBy("ilab").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("olab")).alias("letters"))


@query("f_lm_arcs", _MODEL + """, arcs AS (SELECT 'word' AS kind, -ln(p) AS cost FROM model WHERE "order" <= 2 UNION ALL SELECT 'back-off', CASE WHEN bow > 0 THEN -ln(bow) END FROM bow WHERE "order" = 2)
    SELECT kind, count(*) AS n, round(sum(cost), 2) AS cost FROM arcs GROUP BY 1""")
def f_lm_arcs(spark, d):
    model = M.katz_train(M.ngram_counts(_lines(spark, d), 3), 2)
    arcs = T.lm_arcs(model, M.back_off_weights(model, 2), 2)
    return arcs.groupBy(F.when(F.col("olab") == "", "back-off").otherwise("word").alias("kind")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("cost"), 2).alias("cost"))


#: Three words of two homophones, a bigram model, four frames.
TOY_LEX = (("ab", "xy"), ("abb", "xy"), ("c", "z"))
TOY_LM = {("<s>", "ab"): 0.6, ("<s>", "abb"): 0.3, ("<s>", "c"): 0.1, ("ab", "c"): 0.7, ("abb", "c"): 0.2, ("c", "ab"): 0.5, ("c", "c"): 0.5}
TOY_FRAMES = ({"x": 0.8, "z": 0.2}, {"y": 0.6, "_": 0.4}, {"_": 0.7, "y": 0.3}, {"z": 0.9, "x": 0.1})


def _toy_machines():
    lex, lm = T.Fst(), T.Fst()
    lex.finals[0] = 0.0
    state = 1
    for word, phones in TOY_LEX:
        at = 0
        for i, p in enumerate(phones):
            to = 0 if i == len(phones) - 1 else state
            state += i < len(phones) - 1
            lex.add(at, p, word if to == 0 else "", 0.0, to)
            at = to
    names = {w: i for i, w in enumerate(["<s>", *[w for w, _ in TOY_LEX]])}
    import math

    for (a, b), p in TOY_LM.items():
        lm.add(names[a], b, b, -math.log(p), names[b])
    lm.finals = {i: 0.0 for w, i in names.items() if w != "<s>"}
    return lex, lm


# reachable arcs of the composed machine: lexicon state x language-model state
_LEXA = "(VALUES (0,'x','',1),(1,'y','ab',0),(0,'x','',2),(2,'y','abb',0),(0,'z','c',0)) AS x(s,i,o,t)"
_LMA = "(VALUES " + ", ".join(f"('{a}','{b}',{p})" for (a, b), p in TOY_LM.items()) + ") AS y(s,w,p)"


@query("f_compose_toy", f"""WITH RECURSIVE la AS (SELECT * FROM {_LEXA}), lm AS (SELECT * FROM {_LMA}), r(l, m) AS (SELECT 0, '<s>' UNION SELECT la.t, coalesce(lm.w, r.m) FROM r JOIN la ON la.s = r.l LEFT JOIN lm ON la.o <> '' AND lm.s = r.m AND lm.w = la.o WHERE la.o = '' OR lm.w IS NOT NULL),
    arcs AS (SELECT r.l, r.m, la.i, la.o, la.t, coalesce(lm.w, r.m) AS m2, coalesce(-ln(lm.p), 0) AS cost FROM r JOIN la ON la.s = r.l LEFT JOIN lm ON la.o <> '' AND lm.s = r.m AND lm.w = la.o WHERE la.o = '' OR lm.w IS NOT NULL),
    good(l, m) AS (SELECT l, m FROM r WHERE l = 0 AND m <> '<s>' UNION SELECT a.l, a.m FROM arcs a JOIN good g ON a.t = g.l AND a.m2 = g.m)
    SELECT i AS ilab, o AS olab, count(*) AS n, round(sum(cost), 6) AS cost FROM arcs a WHERE EXISTS (SELECT 1 FROM good g WHERE g.l = a.l AND g.m = a.m) AND EXISTS (SELECT 1 FROM good g WHERE g.l = a.t AND g.m = a.m2) GROUP BY 1, 2""")
def f_compose_toy(spark, d):
    m = T.compose(*_toy_machines())
    rows = [(i, o, w) for arcs in m.arcs.values() for i, o, w, _ in arcs]
    return spark.createDataFrame(rows, "ilab string, olab string, w double").groupBy("ilab", "olab").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("w"), 6).alias("cost"))


_FR = "(VALUES " + ", ".join(f"({t},'{s}',{p})" for t, f in enumerate(TOY_FRAMES) for s, p in f.items()) + ") AS f(t,s,p)"


@query("f_decode_toy", f"""WITH RECURSIVE la AS (SELECT * FROM {_LEXA}), lm AS (SELECT * FROM {_LMA}), f AS (SELECT * FROM {_FR}),
    u(t, last, ph, lp) AS (SELECT -1, '_', '', 0::DOUBLE UNION ALL SELECT u.t + 1, f.s, ph || CASE WHEN f.s = '_' OR f.s = last THEN '' ELSE f.s END, lp + ln(f.p) FROM u JOIN f ON f.t = u.t + 1),
    a AS (SELECT ph, max(lp) AS lp FROM u WHERE t = 3 GROUP BY 1),
    w(ph, words, last, lp) AS (SELECT ph, '', '<s>', lp FROM a UNION ALL SELECT substr(ph, length(phones) + 1), trim(words || ' ' || word), word, lp + ln(lm.p) FROM w, (VALUES ('ab','xy'),('abb','xy'),('c','z')) AS x(word, phones), lm WHERE starts_with(ph, phones) AND lm.s = last AND lm.w = word)
    SELECT words, round(-lp, 6) AS cost FROM w WHERE ph = '' AND words <> '' ORDER BY cost, words LIMIT 1""")
def f_decode_toy(spark, d):
    import math

    lm = {((a,) if a != "<s>" else ()) + (b,): math.log(p) for (a, b), p in TOY_LM.items()}
    decoder = T.Decoder(list(TOY_LEX), {**lm, **{(w, "</s>"): 0.0 for w, _ in TOY_LEX}}, {(w,): -math.inf for w, _ in TOY_LEX}, order=2, beam=1e9)
    rows = [("toy", t, s, p) for t, f in enumerate(TOY_FRAMES) for s, p in f.items()]
    found = T.fst_decode(spark.createDataFrame(rows, "utt string, t int, sym string, p double"), decoder, ["utt"])
    return found.select(F.array_join("words", " ").alias("words"), F.round(-F.col("score"), 6).alias("cost"))


def _candidates(u):
    """Three corrupted copies of each utterance: the k-th drops the word at position k + 1 and doubles the one after."""
    k = u.select("doc_id", "s", "words", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))).alias("k"))
    return k.select("doc_id", "s", "k", F.expr("concat(slice(words, 1, k), array(words[k + 1]), slice(words, k + 2, 40))").alias("words"))


@query("f_rerank", _MODEL + """, ca AS (SELECT doc_id, s, k, list_concat(['<s>'], words[1:k], [words[k + 2]], words[k + 2:k + 41], ['</s>']) AS p FROM ut, (SELECT unnest(range(0, 3)) AS k) WHERE bucket = 9),
    cg AS (SELECT doc_id, s, k, p[i] AS w, p[i - 1] AS c2 FROM ca, LATERAL (SELECT unnest(range(2, len(p) + 1)) AS i)),
    cs AS (SELECT cg.doc_id, cg.s, k, round(sum(ln(greatest(1e-9, coalesce(m2.p, coalesce(b2.bow, 1) * coalesce(m1.p, 1e-9))))), 4) AS score FROM cg LEFT JOIN model m1 ON m1."order" = 1 AND m1.w = cg.w LEFT JOIN model m2 ON m2."order" = 2 AND m2.ctx = c2 AND m2.w = cg.w LEFT JOIN bow b2 ON b2."order" = 2 AND b2.ctx = c2 GROUP BY 1, 2, 3)
    SELECT doc_id, s, pick, score FROM (SELECT doc_id, s, k AS pick, score, row_number() OVER (PARTITION BY doc_id, s ORDER BY score DESC, k) AS r FROM cs) WHERE r = 1""")
def f_rerank(spark, d):
    model = M.katz_train(M.ngram_counts(_lines(spark, d), 3), 2)
    grams = M.word_grams(_candidates(S.utterances(spark, d).where("bucket = 9")), ["doc_id", "s", "k"], 2)
    scored = M.katz_logprob(grams, model, 2).groupBy("doc_id", "s", "k").agg(F.round(F.sum("logp"), 4).alias("score"))
    w = Window.partitionBy("doc_id", "s").orderBy(F.desc("score"), "k")
    return scored.withColumn("r", F.row_number().over(w)).where("r = 1").select("doc_id", "s", F.col("k").cast("long").alias("pick"), "score")
