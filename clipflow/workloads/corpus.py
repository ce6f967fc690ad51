"""Corpus pipeline queries (P)."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.operators import pipeline as P
from clipflow.sources import standin as S
from clipflow.sources.tables import load
from clipflow.workloads.registry import query

CL, FR, PX, PT, UT = S.CLIPS_SQL, S.FRAMES_SQL, S.PIXELS_SQL, S.POINTS_SQL, S.UTTERANCES_SQL
CLIPS, FRAMES = f"WITH {CL}", f"WITH {FR}"


@query("p_funnel", CLIPS + """, f AS (SELECT sum(1) AS c0, count(*) FILTER (WHERE r1) AS c1, count(*) FILTER (WHERE r1 AND r2) AS c2, count(*) FILTER (WHERE r1 AND r2 AND r3) AS c3,
    count(*) FILTER (WHERE r1 AND r2 AND r3 AND r4) AS c4, count(*) FILTER (WHERE r1 AND r2 AND r3 AND r4 AND r5) AS c5
    FROM (SELECT dur BETWEEN 1 AND 12 AS r1, min_eye >= 80 AS r2, fps >= 23 AS r3, max_yaw <= 30 AND max_pitch <= 30 AS r4, round(sp, 9) >= 0.25 AS r5 FROM clips))
    SELECT 0::BIGINT AS rule_no, 'all' AS rule, c0::BIGINT AS n_clips FROM f UNION ALL SELECT 1, 'duration', c1 FROM f UNION ALL SELECT 2, 'eye width', c2 FROM f
    UNION ALL SELECT 3, 'frame rate', c3 FROM f UNION ALL SELECT 4, 'pose', c4 FROM f UNION ALL SELECT 5, 'speaking', c5 FROM f""")
def p_funnel(spark, d):
    return P.funnel(S.clips(spark, d))


@query("p_duration", CLIPS + " SELECT user_id, w, round(dur, 6) AS dur FROM clips WHERE dur BETWEEN 1 AND 12")
def p_duration(spark, d):
    return P.duration_filter(S.clips(spark, d)).select("user_id", "w", F.round("dur", 6).alias("dur"))


#: Frequent words of four languages.
STOP = {
    "en": "the of and to in that is was he for it with as his on be".split(), "es": "de la que el en y los se del las un por con no una su".split(),
    "fr": "de la le et les des en un du une que est pour qui dans sur".split(), "de": "der die und in den von zu das mit sich des auf ist im dem nicht".split(),
}
_SPLIT = "string_split(regexp_replace(lower(text), '[^a-zäöüßéèêçñáíóú]+', ' ', 'g'), ' ')"


def _votes(spark, d):
    words = F.split(F.regexp_replace(F.lower("text"), "[^a-zäöüßéèêçñáíóú]+", " "), " ")
    df = load(spark, d, "documents", "doc_id", "lang", "text").withColumn("ws", words)
    for g, stop in STOP.items():
        df = df.withColumn(g, F.expr(f"size(filter(ws, x -> x IN ({', '.join(map(repr, stop))})))"))
    best = F.greatest(*STOP)
    guess = F.when(best == 0, "none")
    for g in STOP:
        guess = guess.when(F.col(g) == best, g)
    return df.withColumn("guess", guess)


_VOTES = "WITH v0 AS (SELECT doc_id, lang, " + _SPLIT + " AS ws FROM documents), v AS (SELECT doc_id, lang, " + ", ".join(
    f"len(list_filter(ws, lambda x: x IN ({', '.join(repr(w) for w in s)}))) AS {g}" for g, s in STOP.items()
) + " FROM v0), g AS (SELECT doc_id, lang, CASE WHEN greatest(en, es, fr, de) = 0 THEN 'none' " + " ".join(f"WHEN {g} = greatest(en, es, fr, de) THEN '{g}'" for g in STOP) + " END AS guess FROM v)"


@query("p_language", _VOTES + " SELECT doc_id, guess FROM g")
def p_language(spark, d):
    return _votes(spark, d).select("doc_id", "guess")


@query("p_lang_confusion", _VOTES + " SELECT lang, guess, count(*) AS n FROM g GROUP BY 1, 2")
def p_lang_confusion(spark, d):
    return _votes(spark, d).groupBy("lang", "guess").agg(F.count(F.lit(1)).alias("n"))


@query("p_minwords", "SELECT doc_id, n::BIGINT AS n_words, n >= 6 AS ge6, n >= 12 AS ge12 FROM (SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]+')) AS n FROM documents)")
def p_minwords(spark, d):
    n = F.size(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).cast("long")
    return load(spark, d, "documents", "doc_id", "text").select("doc_id", n.alias("n_words")).select("*", (F.col("n_words") >= 6).alias("ge6"), (F.col("n_words") >= 12).alias("ge12"))


_TOY = "(VALUES (0,.7,.2,.1),(1,.6,.3,.1),(2,.2,.7,.1),(3,.1,.6,.3),(4,.1,.3,.6),(5,.1,.2,.7)) AS l(t,a,b,c)"


@query("p_align_toy", f"""WITH l AS (SELECT * FROM {_TOY}), k AS (SELECT x.t AS c1, y.t AS c2 FROM l x JOIN l y ON x.t >= 1 AND y.t > x.t),
    s AS (SELECT c1, c2, sum(ln(CASE WHEN t < c1 THEN a WHEN t < c2 THEN b ELSE c END)) AS logp FROM k CROSS JOIN l GROUP BY 1, 2)
    SELECT c1::INT AS c1, c2::INT AS c2, round(logp, 6) AS logp FROM s ORDER BY logp DESC, c1, c2 LIMIT 1""")
def p_align_toy(spark, d):
    from clipflow.operators.align import best_cuts

    lattice = spark.sql(f"SELECT t, CAST(a AS DOUBLE) AS a, CAST(b AS DOUBLE) AS b, CAST(c AS DOUBLE) AS c FROM {_TOY}")
    return best_cuts(lattice, ["a", "b", "c"]).select(F.col("cuts")[0].alias("c1"), F.col("cuts")[1].alias("c2"), F.round("logp", 6).alias("logp"))


@query("p_trim", f"""WITH {PX}, g AS (SELECT vec_id, unnest(range(0, 144)) AS i FROM embeddings), pad AS (SELECT g.vec_id, i // 12 AS r, i % 12 AS c, coalesce(v, 0) AS v
    FROM g LEFT JOIN px ON px.vec_id = g.vec_id AND px.r = i // 12 - 2 AND px.c = i % 12 - 2),
    rr AS (SELECT vec_id, min(r) AS r0, max(r) AS r1 FROM (SELECT vec_id, r FROM pad GROUP BY 1, 2 HAVING min(v) <> max(v)) GROUP BY 1),
    cc AS (SELECT vec_id, min(c) AS c0, max(c) AS c1 FROM (SELECT vec_id, c FROM pad GROUP BY 1, 2 HAVING min(v) <> max(v)) GROUP BY 1)
    SELECT vec_id, r0::INT AS r0, r1::INT AS r1, c0::INT AS c0, c1::INT AS c1 FROM rr JOIN cc USING (vec_id)""")
def p_trim(spark, d):
    from clipflow.functions.frames import trim_bounds

    pad = "transform(sequence(0, 143), i -> CASE WHEN i DIV 12 BETWEEN 2 AND 9 AND i % 12 BETWEEN 2 AND 9 THEN cast(embedding[(i DIV 12 - 2) * 8 + i % 12 - 2] AS double) ELSE 0D END)"
    e = load(spark, d, "embeddings", "vec_id", "embedding").withColumn("px", F.expr(pad))
    return e.select("vec_id", trim_bounds("px", 12, 12).alias("b")).select("vec_id", "b.*")


_DAYS = FRAMES + """, h0 AS (SELECT user_id, CAST(floor(e / 86400) AS BIGINT) AS day, event_type, count(*) AS n FROM frames GROUP BY 1, 2, 3),
    h1 AS (SELECT user_id, day, event_type, n / sum(n) OVER (PARTITION BY user_id, day) AS share FROM h0),
    days AS (SELECT DISTINCT user_id, day FROM h0), o AS (SELECT user_id, day, lag(day) OVER (PARTITION BY user_id ORDER BY day) AS prev FROM days),
    kinds AS (SELECT DISTINCT event_type FROM events),
    dd AS (SELECT o.user_id, o.day, sum(abs(coalesce(a.share, 0) - coalesce(b.share, 0))) AS dist FROM o CROSS JOIN kinds
      LEFT JOIN h1 a ON a.user_id = o.user_id AND a.day = o.day AND a.event_type = kinds.event_type
      LEFT JOIN h1 b ON b.user_id = o.user_id AND b.day = o.prev AND b.event_type = kinds.event_type WHERE prev IS NOT NULL GROUP BY 1, 2)"""


@query("p_shots", _DAYS + " SELECT user_id, day, round(dist, 6) AS dist, round(dist, 6) > 0.6 AS is_cut FROM dd")
def p_shots(spark, d):
    f = S.frames(spark, d).withColumn("day", F.floor(F.col("e") / 86400).cast("long"))
    # shares as maps: whatever types the days have, none is left out
    n = f.groupBy("user_id", "day", "event_type").agg(F.count(F.lit(1)).alias("n"))
    h = n.groupBy("user_id", "day").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("h"), F.sum("n").alias("total"))
    h = h.select("user_id", "day", F.transform_values("h", lambda _, v: v / F.col("total")).alias("h"))
    cut = P.shot_boundaries_of_maps(h, ["user_id"], "day").where("prev IS NOT NULL")
    return cut.select("user_id", "day", F.round("dist", 6).alias("dist"), (F.round("dist", 6) > 0.6).alias("is_cut"))


@query("p_track_links", FRAMES + """, b AS (SELECT user_id, value AS x, CAST(k AS DOUBLE) AS y, CAST(100 + k AS DOUBLE) AS s, lead(value) OVER q AS x2, CAST(lead(k) OVER q AS DOUBLE) AS y2
      FROM frames WINDOW q AS (PARTITION BY user_id, w ORDER BY t)),
    c AS (SELECT user_id, s, 100 + y2 AS s2, greatest(0, least(x + s, x2 + 100 + y2) - greatest(x, x2)) * greatest(0, least(y + s, y2 + 100 + y2) - greatest(y, y2)) AS inter FROM b WHERE x2 IS NOT NULL)
    SELECT user_id, count(*) FILTER (WHERE inter / (s * s + s2 * s2 - inter) >= 0.3) AS n_links FROM c GROUP BY 1""")
def p_track_links(spark, d):
    from clipflow.operators.tracks import link_next

    boxes = S.frames(spark, d).select("user_id", "w", "t", F.col("value").alias("x"), F.col("k").cast("double").alias("y"), (100.0 + F.col("k")).alias("s"))
    return link_next(boxes, ["user_id", "w"], 0.3).where("x2 IS NOT NULL").groupBy("user_id").agg(F.count_if("linked").alias("n_links"))


@query("p_join_speech_faces", FRAMES + """, s AS (SELECT user_id, w, min(e) AS t0, max(e) AS t1 FROM frames GROUP BY 1, 2), f AS (SELECT user_id, CAST(floor(e / 172800) AS BIGINT) AS f, min(e) AS u0, max(e) AS u1 FROM frames GROUP BY 1, 2)
    SELECT s.user_id, w, f, round(least(t1, u1) - greatest(t0, u0), 3) AS overlap FROM s JOIN f ON s.user_id = f.user_id AND t0 <= u1 AND u0 <= t1""")
def p_join_speech_faces(spark, d):
    f = S.frames(spark, d)
    seg = f.groupBy("user_id", "w").agg(F.min("e").alias("t0"), F.max("e").alias("t1"))
    face = f.groupBy("user_id", F.floor(F.col("e") / 172800).cast("long").alias("f")).agg(F.min("e").alias("u0"), F.max("e").alias("u1"))
    return P.interval_join(seg, face, "user_id", 172800.0).select("user_id", "w", "f", F.round(F.least("t1", "u1") - F.greatest("t0", "u0"), 3).alias("overlap"))


_LAP = f"""WITH {PX}, lap AS (SELECT a.vec_id, a.label, max(CASE WHEN b.r = a.r AND b.c = a.c THEN -4 * b.v END) + sum(CASE WHEN b.r = a.r AND b.c = a.c THEN 0 ELSE b.v END) AS l
      FROM px a JOIN px b ON a.vec_id = b.vec_id AND abs(a.r - b.r) + abs(a.c - b.c) <= 1 WHERE a.r BETWEEN 1 AND 6 AND a.c BETWEEN 1 AND 6 GROUP BY a.vec_id, a.label, a.r, a.c),
    lv AS (SELECT vec_id, label, var_pop(l) AS lap_var FROM lap GROUP BY 1, 2)"""


def _sharpness(spark, d):
    from clipflow.functions.frames import laplacian_variance

    e = load(spark, d, "embeddings")
    return e.select("vec_id", "label", laplacian_variance("embedding", 8, 8).alias("lap_var"))


@query("p_laplacian", _LAP + " SELECT vec_id, round(lap_var, 6) AS lap_var FROM lv")
def p_laplacian(spark, d):
    return _sharpness(spark, d).select("vec_id", F.round("lap_var", 6).alias("lap_var"))


@query("p_quality", _LAP + " SELECT label, count(*) FILTER (WHERE round(lap_var, 9) >= 0.22) AS n_sharp, count(*) FILTER (WHERE round(lap_var, 9) < 0.22) AS n_blurry FROM lv GROUP BY 1")
def p_quality(spark, d):
    v = F.round("lap_var", 9)
    return _sharpness(spark, d).groupBy("label").agg(F.count_if(v >= 0.22).alias("n_sharp"), F.count_if(v < 0.22).alias("n_blurry"))


def _flag(name, column, predicate, stat):
    @query(name, CLIPS + f" SELECT user_id, w, round({column}, 6) AS stat, coalesce({predicate}, FALSE) AS keep FROM clips")
    def f(spark, d):
        return S.clips(spark, d).select("user_id", "w", F.round(F.expr(stat), 6).alias("stat"), F.coalesce(F.expr(predicate), F.lit(False)).alias("keep"))

    return f


p_eye = _flag("p_eye", "min_eye", "min_eye >= 80", "min_eye")
p_fps = _flag("p_fps", "fps", "fps >= 23", "fps")
p_pose = _flag("p_pose", "greatest(max_yaw, max_pitch)", "max_yaw <= 30 AND max_pitch <= 30", "greatest(max_yaw, max_pitch)")
p_speaking = _flag("p_speaking", "sp", "n >= 2 AND round(sp, 9) >= 0.25", "sp")


@query("p_downsample", FRAMES + """, g AS (SELECT user_id, w, t, floor((e - min(e) OVER (PARTITION BY user_id, w)) / 36000 * 30) AS slot FROM frames),
    k AS (SELECT user_id, w, slot, lag(slot) OVER (PARTITION BY user_id, w ORDER BY t) AS before FROM g)
    SELECT user_id, w, count(*) AS n_before, count(*) FILTER (WHERE before IS NULL OR slot <> before) AS n_after FROM k GROUP BY 1, 2""")
def p_downsample(spark, d):
    f = S.frames(spark, d)
    f = f.withColumn("sec", (F.col("e") - F.min("e").over(Window.partitionBy("user_id", "w"))) / 36000)
    n = f.groupBy("user_id", "w").agg(F.count(F.lit(1)).alias("n_before"))
    return n.join(P.downsample_fps(f).groupBy("user_id", "w").agg(F.count(F.lit(1)).alias("n_after")), ["user_id", "w"])


_G = {o: math.exp(-0.5 * o * o) for o in range(-3, 4)}


@query("p_smooth", FRAMES + ", s AS (SELECT event_id, " + ", ".join(f"{'lag' if o < 0 else 'lead'}(value, {abs(o)}) OVER q AS v{o + 3}" for o in _G) + " FROM frames WINDOW q AS (PARTITION BY user_id, w ORDER BY t)) SELECT event_id, round(("
       + " + ".join(f"coalesce(v{o + 3} * {g!r}, 0)" for o, g in _G.items()) + ") / (" + " + ".join(f"CASE WHEN v{o + 3} IS NULL THEN 0 ELSE {g!r} END" for o, g in _G.items()) + "), 6) AS smoothed FROM s")
def p_smooth(spark, d):
    f = S.frames(spark, d)
    return f.select("event_id", F.round(P.gaussian_smooth(f, "value", ["user_id", "w"], ["t"]), 6).alias("smoothed"))


@query("p_smooth_time", FRAMES + """ SELECT a.event_id, round(sum(b.value * exp(-0.5 * pow((a.e - b.e) / 28800, 2))) / sum(exp(-0.5 * pow((a.e - b.e) / 28800, 2))), 5) AS smoothed
    FROM frames a JOIN frames b ON a.user_id = b.user_id AND a.w = b.w AND b.e BETWEEN a.e - 86400 AND a.e + 86400 GROUP BY 1""")
def p_smooth_time(spark, d):
    f = S.frames(spark, d)
    return P.gaussian_smooth_time(f, "value", ["user_id", "w"], "e", 28800, 86400).select("event_id", F.round("smoothed", 5).alias("smoothed"))


@query("p_reference_face", f"WITH {PT} SELECT point_no, round(avg(x), 6) AS x, round(avg(y), 6) AS y FROM pts GROUP BY 1")
def p_reference_face(spark, d):
    return S.points(spark, d).groupBy("point_no").agg(F.round(F.avg("x"), 6).alias("x"), F.round(F.avg("y"), 6).alias("y"))


@query("p_affine", f"""WITH {PT}, ref AS (SELECT point_no, avg(x) AS u, avg(y) AS v FROM pts GROUP BY 1), j AS (SELECT vec_id, x, y, u, v FROM pts JOIN ref USING (point_no)),
    s AS (SELECT vec_id, count(*)::DOUBLE AS n, sum(x) AS sx, sum(y) AS sy, sum(x*x) AS sxx, sum(x*y) AS sxy, sum(y*y) AS syy, sum(u) AS su, sum(v) AS sv, sum(x*u) AS sxu, sum(y*u) AS syu, sum(x*v) AS sxv, sum(y*v) AS syv, sum(u*u) AS suu, sum(v*v) AS svv FROM j GROUP BY 1),
    t AS (SELECT *, sxx - sx*sx/n AS cxx, sxy - sx*sy/n AS cxy, syy - sy*sy/n AS cyy, sxu - sx*su/n AS cxu, syu - sy*su/n AS cyu, sxv - sx*sv/n AS cxv, syv - sy*sv/n AS cyv, suu - su*su/n AS cuu, svv - sv*sv/n AS cvv FROM s),
    o AS (SELECT *, (cxu*cyy - cyu*cxy) / (cxx*cyy - cxy*cxy) AS a, (cyu*cxx - cxu*cxy) / (cxx*cyy - cxy*cxy) AS b, (cxv*cyy - cyv*cxy) / (cxx*cyy - cxy*cxy) AS d, (cyv*cxx - cxv*cxy) / (cxx*cyy - cxy*cxy) AS e FROM t)
    SELECT vec_id, round(a, 6) AS a, round(b, 6) AS b, round((su - a*sx - b*sy) / n, 6) AS c, round(d, 6) AS d, round(e, 6) AS e, round((sv - d*sx - e*sy) / n, 6) AS f,
      round(cuu + cvv - a*cxu - b*cyu - d*cxv - e*cyv, 6) AS residual FROM o""")
def p_affine(spark, d):
    p = S.points(spark, d)
    ref = p.groupBy("point_no").agg(F.avg("x").alias("u"), F.avg("y").alias("v"))  # 32 rows
    fit = P.fit_affine(p.join(F.broadcast(ref), "point_no"), "vec_id")
    return fit.select("vec_id", *[F.round(c, 6).alias(c) for c in [*"abcdef", "residual"]])


@query("p_crop", f"WITH {PX} SELECT vec_id, round(sum(v), 6) AS s FROM px WHERE r BETWEEN 2 AND 5 AND c BETWEEN 2 AND 5 GROUP BY 1")
def p_crop(spark, d):
    from clipflow.functions.frames import crop_nearest

    e = load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", crop_nearest("embedding", 8, 2, 2, 4, 4).alias("px"))
    return e.select("vec_id", F.round(F.expr("aggregate(px, 0D, (s, v) -> s + v)"), 6).alias("s"))


@query("p_split", "SELECT CAST(('0x' || substr(md5('split|' || doc_id), 1, 8))::BIGINT % 10 AS INT) AS bucket, count(*) AS n_docs, sum(n_chars)::BIGINT AS n_chars FROM documents GROUP BY 1")
def p_split(spark, d):
    return P.split_by_hash(load(spark, d, "documents", "doc_id", "n_chars"), "doc_id").groupBy("bucket").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("n_chars").alias("n_chars"))


@query("p_decontam", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))")
def p_decontam(spark, d):
    from clipflow.operators.holdout import without_passages

    return without_passages(load(spark, d, "documents", "doc_id", "text"), load(spark, d, "benchmark")).select("doc_id")


@query("p_stats", f"WITH {UT}, x AS (SELECT unnest(words) AS w FROM ut WHERE bucket = 9) SELECT (SELECT count(*) FROM ut WHERE bucket = 9) AS n_utts, count(*) AS n_words, count(DISTINCT w) AS n_types, round(count(*) / 7100.0 * 37 / 60, 6) AS hours_proxy FROM x")
def p_stats(spark, d):
    u = S.utterances(spark, d).where("bucket = 9")
    w = u.select(F.posexplode("words").alias("i", "w"))
    return w.agg(F.count_if(F.col("i") == 0).alias("n_utts"), F.count(F.lit(1)).alias("n_words"), F.count_distinct("w").alias("n_types"), F.round(F.count(F.lit(1)) / 7100.0 * 37 / 60, 6).alias("hours_proxy"))


# ---- the language rule by character trigrams

_LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèêçñáíóú"
_PLAIN = "' ' || trim(regexp_replace(lower({}), '[^" + _LETTERS + "]+', ' ', 'g')) || ' '"
_TRIGRAMS = f"""WITH t0 AS (SELECT doc_id, lang, {_PLAIN.format("text")} AS x FROM documents), t1 AS (SELECT doc_id, lang, unnest(list_transform(range(1, length(x) - 1), lambda i: substr(x, i, 3))) AS g FROM t0),
    dg AS (SELECT doc_id, lang, g, count(*) AS n FROM t1 GROUP BY 1, 2, 3), lg AS (SELECT lang, g, sum(n) AS n FROM dg WHERE ('0x' || substr(md5('split|' || doc_id), 1, 8))::BIGINT % 10 <> 9 GROUP BY 1, 2),
    ls AS (SELECT lang, sum(n) AS total FROM lg GROUP BY 1), vs AS (SELECT count(DISTINCT g) AS v FROM lg), kg AS (SELECT DISTINCT g FROM lg),
    sc AS (SELECT doc_id, ls.lang, sum(dg.n * ln((coalesce(lg.n, 0) + 1) / (total + v)::DOUBLE)) AS score FROM dg JOIN kg USING (g) CROSS JOIN ls CROSS JOIN vs LEFT JOIN lg ON lg.lang = ls.lang AND lg.g = dg.g GROUP BY 1, 2),
    pk AS (SELECT doc_id, lang AS guess, row_number() OVER (PARTITION BY doc_id ORDER BY round(score, 4) DESC, lang) AS r FROM sc)"""


def trigram_guesses(spark, d):
    """doc_id, lang, guess by naive Bayes over character trigrams, learnt from the documents that aren't held out."""
    text = load(spark, d, "documents", "doc_id", "lang", "text")
    x = F.concat(F.lit(" "), F.trim(F.regexp_replace(F.lower("text"), f"[^{_LETTERS}]+", " ")), F.lit(" "))
    return P.trigram_bayes(text.select("doc_id", "lang", x.alias("x")), "doc_id", "lang", "x", _LETTERS + " ", S.hash8(F.lit("split"), F.col("doc_id").cast("string")) % 10 != 9)


@query("p_language_trigram", _TRIGRAMS + " SELECT doc_id, guess FROM pk WHERE r = 1")
def p_language_trigram(spark, d):
    return trigram_guesses(spark, d)


# ---- several faces a frame

@query("p_tracks_multi", FRAMES + """, b AS (SELECT user_id, w, t, value AS x, CAST(k AS DOUBLE) AS y, CAST(100 + k AS DOUBLE) AS s FROM frames),
    l AS (SELECT *, lag(x) OVER q AS x0, lag(y) OVER q AS y0, lag(s) OVER q AS s0 FROM b WINDOW q AS (PARTITION BY user_id, w ORDER BY t)),
    i AS (SELECT *, greatest(0, least(x + s, x0 + s0) - greatest(x, x0)) * greatest(0, least(y + s, y0 + s0) - greatest(y, y0)) AS inter FROM l)
    SELECT user_id, w, 2 * count(*) FILTER (WHERE x0 IS NULL OR inter / (s * s + s0 * s0 - inter) < 0.3) AS n_tracks, 2 * count(*) AS n_boxes FROM i GROUP BY 1, 2""")
def p_tracks_multi(spark, d):
    """Two faces a frame, the second far to the right of the first: twice as many tracks as of one."""
    from clipflow.operators.tracks import multi_face_tracks

    f = S.frames(spark, d).select("user_id", "w", F.col("t").cast("int").alias("t"), "value", F.col("k").cast("double").alias("y"), (100.0 + F.col("k")).alias("s"))
    boxes = f.select("user_id", "w", "t", F.explode(F.array(F.lit(0), F.lit(1))).alias("face"), "value", "y", "s").withColumn("x", F.col("value") + 1000.0 * F.col("face"))
    t = multi_face_tracks(boxes.select("user_id", "w", "t", "face", "x", "y", "s"), ["user_id", "w"], 0.3)
    return t.groupBy("user_id", "w").agg((F.max("track") + 1).cast("long").alias("n_tracks"), F.count(F.lit(1)).alias("n_boxes"))


# ---- the lips' thumbnail

#: A turned and scaled canonical view, x = a j + b i + c and y = d j + e i + f.
VIEW = {"a": 0.35, "b": 0.1, "c": 0.8, "d": -0.1, "e": 0.4, "f": 1.2}


@query("p_crop_bilinear", f"""WITH {PX}, o AS (SELECT vec_id, unnest(range(0, 256)) AS k FROM embeddings), p AS (SELECT vec_id, k, least(greatest({VIEW['a']} * (k % 16) + {VIEW['b']} * (k // 16) + {VIEW['c']}, 0), 7)::DOUBLE AS x,
      least(greatest({VIEW['d']} * (k % 16) + {VIEW['e']} * (k // 16) + {VIEW['f']}, 0), 7)::DOUBLE AS y FROM o),
    q AS (SELECT p.*, floor(x)::INT AS c0, floor(y)::INT AS r0, x - floor(x) AS wx, y - floor(y) AS wy FROM p),
    z AS (SELECT q.vec_id, k, (1 - wy) * ((1 - wx) * a.v + wx * b.v) + wy * ((1 - wx) * c.v + wx * e.v) AS v FROM q JOIN px a ON a.vec_id = q.vec_id AND a.r = r0 AND a.c = c0 JOIN px b ON b.vec_id = q.vec_id AND b.r = r0 AND b.c = least(c0 + 1, 7)
      JOIN px c ON c.vec_id = q.vec_id AND c.r = least(r0 + 1, 7) AND c.c = c0 JOIN px e ON e.vec_id = q.vec_id AND e.r = least(r0 + 1, 7) AND e.c = least(c0 + 1, 7))
    SELECT vec_id, round(sum(v), 6) AS s, round(sum(v * (k + 1)), 4) AS checksum FROM z GROUP BY 1""")
def p_crop_bilinear(spark, d):
    from clipflow.functions.frames import sample_bilinear

    view = {k: f"{v}D" for k, v in VIEW.items()}
    e = load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", sample_bilinear("embedding", 8, 8, 16, 16, **view).alias("px"))
    checksum = F.expr("aggregate(zip_with(px, sequence(1, 256), (v, k) -> v * k), 0D, (s, v) -> s + v)")
    return e.select("vec_id", F.round(F.expr("aggregate(px, 0D, (s, v) -> s + v)"), 6).alias("s"), F.round(checksum, 4).alias("checksum"))


# ---- the whole cascade

_EVIDENCE = _DAYS + f""", {PX},
    clips0 AS (SELECT user_id, w, count(*) AS n, (max(e) - min(e)) / 36000 AS dur, min(78 + 0.5 * k) AS min_eye, max(abs((value - 50) / 5)) AS max_yaw, max(abs((k - 50) * 0.7)) AS max_pitch, stddev_pop(value / (100 + k)) AS sp FROM ev1 GROUP BY 1, 2),
    clips AS (SELECT *, CASE WHEN dur > 0 THEN 25.0::DOUBLE * (n - 1) / dur END AS fps, ('0x' || substr(md5('bind|' || user_id || '|' || w), 1, 8))::BIGINT AS h FROM clips0),
    cuts AS (SELECT user_id, CAST(floor(day / 6) AS BIGINT) AS w, count(*) FILTER (WHERE round(dist, 6) > 0.6 AND floor(day / 6) = floor((day - 1) / 6)) AS n_cuts FROM dd GROUP BY 1, 2),
    """ + _VOTES.removeprefix("WITH ") + """, sp0 AS (SELECT doc_id, text FROM documents), nw AS (SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]+')) AS n_words FROM sp0),
    """ + _LAP.removeprefix(f"WITH {PX}, ") + """, sy AS (SELECT a.vec_id, sqrt(sum(pow(a.v - b.v, 2))) AS sync_d FROM px a JOIN px b ON b.vec_id = a.vec_id + 1 AND b.r = a.r AND b.c = a.c GROUP BY 1),
    nd AS (SELECT max(doc_id) + 1 AS d, (SELECT max(vec_id) + 1 FROM embeddings) AS v FROM documents),
    ev AS (SELECT clips.*, guess AS lang_guess, n_words, coalesce(n_cuts, 0) AS n_cuts, 8 AS trimmed_side, lap_var, sync_d FROM clips CROSS JOIN nd LEFT JOIN g ON g.doc_id = h % nd.d LEFT JOIN nw ON nw.doc_id = h % nd.d LEFT JOIN cuts ON cuts.user_id = clips.user_id AND cuts.w = clips.w
      LEFT JOIN lv ON lv.vec_id = (h // 7) % nd.v LEFT JOIN sy ON sy.vec_id = (h // 7) % nd.v)"""


def evidence(spark, d):
    """Clips with all that the rules look at: landmarks, a transcript, shots, pixels and sound, bound by a hash of the clip."""
    from clipflow.functions.frames import laplacian_variance, trim_bounds
    from clipflow.operators.sync import sync_distance

    c = S.clips(spark, d).withColumn("h", S.hash8(F.lit("bind"), F.col("user_id").cast("string"), F.col("w").cast("string")))
    docs, vecs = load(spark, d, "documents", "doc_id", "text"), load(spark, d, "embeddings", "vec_id", "embedding")
    c = c.withColumn("doc_id", F.col("h") % docs.agg(F.max("doc_id") + 1).scalar()).withColumn("vec_id", F.expr("h DIV 7") % vecs.agg(F.max("vec_id") + 1).scalar())
    said = _votes(spark, d).select("doc_id", F.col("guess").alias("lang_guess"), F.size(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("n_words"))
    cuts = p_shots(spark, d).where("is_cut AND floor(day / 6) = floor((day - 1) / 6)").groupBy("user_id", F.floor(F.col("day") / 6).cast("long").alias("w")).agg(F.count(F.lit(1)).alias("n_cuts"))
    pad = "transform(sequence(0, 143), i -> CASE WHEN i DIV 12 BETWEEN 2 AND 9 AND i % 12 BETWEEN 2 AND 9 THEN cast(embedding[(i DIV 12 - 2) * 8 + i % 12 - 2] AS double) ELSE 0D END)"
    seen = vecs.withColumn("px", F.expr(pad)).withColumn("b", trim_bounds("px", 12, 12))
    seen = seen.select("vec_id", "embedding", F.least(F.col("b.r1") - F.col("b.r0"), F.col("b.c1") - F.col("b.c0")).alias("side"), laplacian_variance("embedding", 8, 8).alias("lap_var"))
    heard = vecs.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("sound"))
    seen = seen.join(heard, "vec_id", "left").select("vec_id", (F.col("side") + 1).alias("trimmed_side"), "lap_var", sync_distance("sound", "embedding").alias("sync_d"))
    out = c.join(said, "doc_id", "left").join(cuts, ["user_id", "w"], "left").join(seen, "vec_id", "left")
    return out.withColumn("n_cuts", F.coalesce("n_cuts", F.lit(0)))


def _full_sql(mode: str) -> str:
    rules, shown, passed = P.rules_of(mode, P.FULL), [], []
    for i, (name, predicate, _) in enumerate(rules):
        passed.append(f"coalesce({predicate}, FALSE)")
        shown.append(f"SELECT {i}::BIGINT AS rule_no, '{name}' AS rule, count(*) FILTER (WHERE {' AND '.join(passed)}) AS n_clips FROM ev")
    return " UNION ALL ".join(shown)


for _mode in ("train", "infer", "eval"):

    @query(f"p_cascade_{_mode}", _EVIDENCE + " " + _full_sql(_mode))
    def _cascade(spark, d, mode=_mode):
        """Clips that survive each rule of the whole cascade in one of its modes."""
        return P.funnel(evidence(spark, d), P.rules_of(mode, P.FULL))
