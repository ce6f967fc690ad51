"""Synchrony queries (S)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.operators import sync as S
from clipflow.sources.tables import load
from clipflow.workloads.registry import query

THRESHOLD, MARGIN = 1.30, 1.5

_DIST = "sqrt(list_sum(list_transform(range(1, 65), lambda i: pow(CAST(a[i] AS DOUBLE) - CAST(v[i] AS DOUBLE), 2))))"
PAIRS = f"""WITH n AS (SELECT count(*) AS n FROM embeddings), e AS (SELECT vec_id, label, embedding AS v FROM embeddings),
    r AS (SELECT x.vec_id, x.label, x.v, list_transform(range(1, 65), lambda i: CAST(x.v[i] AS DOUBLE) + 4 * CAST(y.v[i] AS DOUBLE)) AS r FROM e x CROSS JOIN n JOIN e y ON y.vec_id = (7 * x.vec_id + 3) % n.n),
    p AS (SELECT vec_id, label, v, list_transform(r, lambda z: z / sqrt(list_sum(list_transform(r, lambda q: q * q)))) AS a FROM r),
    s AS (SELECT vec_id, 1 AS y, a, v FROM p UNION ALL SELECT vec_id, 0, a, nv FROM (SELECT vec_id, a, lead(v, 5) OVER (PARTITION BY label ORDER BY vec_id) AS nv FROM p) WHERE nv IS NOT NULL),
    d AS (SELECT vec_id, y, {_DIST} AS d FROM s)"""


def _aligned(spark, d):
    e = load(spark, d, "embeddings").withColumnRenamed("embedding", "v")
    n = e.agg(F.count(F.lit(1)).alias("n"))
    partner = e.select(F.col("vec_id").alias("p"), F.col("v").alias("pv"))
    keyed = e.withColumn("p", (7 * F.col("vec_id") + 3) % n.select("n").scalar())
    raw = keyed.join(partner, "p").withColumn("r", F.expr("zip_with(v, pv, (x, y) -> cast(x AS double) + 4D * cast(y AS double))"))
    unit = "transform(array(sqrt(aggregate(r, 0D, (s, x) -> s + x * x))), n -> transform(r, x -> x / n))[0]"
    return raw.select("vec_id", "label", F.expr(unit).alias("a"), "v")


def _scored(spark, d):
    return S.sync_classify(S.make_pairs(_aligned(spark, d), "label", "vec_id", 5), THRESHOLD)


@query("s_windows9", """WITH x AS (SELECT label, vec_id, count(*) OVER q AS n, avg(CAST(embedding[1] AS DOUBLE)) OVER q AS m FROM embeddings WINDOW q AS (PARTITION BY label ORDER BY vec_id ROWS BETWEEN 4 PRECEDING AND 4 FOLLOWING))
    SELECT label, vec_id, round(m, 6) AS mean FROM x WHERE n = 9""")
def s_windows9(spark, d):
    w = Window.partitionBy("label").orderBy("vec_id").rowsBetween(-4, 4)
    e = load(spark, d, "embeddings").select("label", "vec_id", F.col("embedding")[0].cast("double").alias("x"))
    e = e.select("label", "vec_id", F.count(F.lit(1)).over(w).alias("n"), F.avg("x").over(w).alias("m")).where("n = 9")
    return e.select("label", "vec_id", F.round("m", 6).alias("mean"))


@query("s_distance", PAIRS + " SELECT vec_id, y, round(d, 6) AS d FROM d")
def s_distance(spark, d):
    return _scored(spark, d).select("vec_id", "y", F.round("d", 6).alias("d"))


@query("s_pairs", PAIRS + " SELECT y, count(*) AS n FROM d GROUP BY 1")
def s_pairs(spark, d):
    return S.make_pairs(_aligned(spark, d), "label", "vec_id", 5).groupBy("y").agg(F.count(F.lit(1)).alias("n"))


@query("s_contrastive", PAIRS + f" SELECT y, round(avg(CASE WHEN y = 1 THEN d * d ELSE pow(greatest(0, {MARGIN} - d), 2) END), 6) AS loss FROM d GROUP BY 1")
def s_contrastive(spark, d):
    return _scored(spark, d).groupBy("y").agg(F.round(F.avg(S.contrastive_loss(F.col("d"), F.col("y"), MARGIN)), 6).alias("loss"))


@query("s_slide100", PAIRS + """, o AS (SELECT e.label, d.d, row_number() OVER (PARTITION BY e.label ORDER BY vec_id) - 1 AS t, count(*) OVER (PARTITION BY e.label) AS n FROM d JOIN e USING (vec_id) WHERE y = 1),
    k AS (SELECT label, i, CAST(floor(i * (n - 9) / 99.0::DOUBLE) AS INT) AS f FROM (SELECT DISTINCT label, n FROM o WHERE n >= 9), (SELECT unnest(range(0, 100)) AS i)),
    m AS (SELECT k.label, i, avg(d) AS m FROM k JOIN o ON o.label = k.label AND t BETWEEN f AND f + 8 GROUP BY 1, 2)
    SELECT label, round(avg(m), 6) AS score FROM m GROUP BY 1""")
def s_slide100(spark, d):
    x = S.sync_classify(_aligned(spark, d), THRESHOLD)
    x = x.groupBy("label").agg(F.array_sort(F.collect_list(F.struct("vec_id", "d"))).alias("rows")).select("label", F.expr("transform(rows, r -> r.d)").alias("ds"))
    return S.window_scores(x, "ds").where("score IS NOT NULL").select("label", F.round("score", 6).alias("score"))


_MEASURES = "round(avg(CASE WHEN (rd < {t}) = (y = 1) THEN 1.0::DOUBLE ELSE 0 END), 6) AS accuracy, round(count(*) FILTER (WHERE rd < {t} AND y = 1) / nullif(count(*) FILTER (WHERE rd < {t}), 0)::DOUBLE, 6) AS \"precision\", round(count(*) FILTER (WHERE rd < {t} AND y = 1) / count(*) FILTER (WHERE y = 1)::DOUBLE, 6) AS recall"


@query("s_accuracy", PAIRS + ", q AS (SELECT y, round(d, 9) AS rd FROM d) SELECT " + _MEASURES.format(t=THRESHOLD) + " FROM q")
def s_accuracy(spark, d):
    s = _scored(spark, d).withColumn("pred", (F.round("d", 9) < THRESHOLD).cast("int"))
    return S.accuracy(s).select(*[F.round(c, 6).alias(c) for c in ("accuracy", "precision", "recall")])


@query("s_threshold_sweep", PAIRS + ", q AS (SELECT y, round(d, 9) AS rd FROM d), t AS (SELECT CAST(unnest(range(20, 33)) * 5 AS DOUBLE) / 100 AS threshold) SELECT threshold, " + _MEASURES.format(t="threshold") + " FROM q CROSS JOIN t GROUP BY 1")
def s_threshold_sweep(spark, d):
    # distances fall into 13 cells: counts of a pass are summed upwards, the pairs are not copied
    cells = [i * 5 / 100 for i in range(20, 33)]
    cell = F.lit(len(cells))
    for i in reversed(range(len(cells))):
        cell = F.when(F.col("rd") < cells[i], i).otherwise(cell)
    counts = _scored(spark, d).withColumn("rd", F.round("d", 9)).groupBy(cell.alias("cell")).agg(F.count_if(F.col("y") == 1).alias("p"), F.count_if(F.col("y") == 0).alias("n"))
    both = spark.createDataFrame([(i, c) for i, c in enumerate(cells)] + [(len(cells), None)], "cell int, threshold double").join(counts, "cell", "left").fillna(0, ["p", "n"])
    w = Window.orderBy("cell")  # 14 rows
    s = both.select("threshold", F.sum("p").over(w).alias("tp"), F.sum("n").over(w).alias("fp"), F.sum("p").over(Window.partitionBy()).alias("pos"), F.sum("n").over(Window.partitionBy()).alias("neg"))
    return s.where("threshold IS NOT NULL").select("threshold", F.round((F.col("tp") + F.col("neg") - F.col("fp")) / (F.col("pos") + F.col("neg")), 6).alias("accuracy"),
        F.round(F.try_divide("tp", F.col("tp") + F.col("fp")), 6).alias("precision"), F.round(F.col("tp") / F.col("pos"), 6).alias("recall"))


@query("s_random_pairs", PAIRS + """, k AS (SELECT p.*, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS i, count(*) OVER (PARTITION BY label) AS n FROM p),
    q AS (SELECT *, (i + 1 + ('0x' || substr(md5('shift|' || vec_id), 1, 8))::BIGINT % (n - 1)) % n AS j FROM k WHERE n > 1),
    m AS (SELECT vec_id, 1 AS y, a, v FROM p UNION ALL SELECT q.vec_id, 0, q.a, k.v FROM q JOIN k ON k.label = q.label AND k.i = q.j)
    SELECT vec_id, y, round(""" + _DIST + """, 6) AS d FROM m""")
def s_random_pairs(spark, d):
    """Negatives by random shifts of the video within its group."""
    s = S.sync_classify(S.random_shifts(_aligned(spark, d), "label", "vec_id"), THRESHOLD)
    return s.select("vec_id", "y", F.round("d", 6).alias("d"))


FRAMES_OF, BANDS, SIDE = 9, 6, 6


def windows(spark, d):
    """clip, i, x, truth, key, v: each embedding (x) a clip of 24 frames, cut into windows that begin at frame i. ``v`` names
    the window whose video it has: pairs are dealt out before ``rendered`` makes them ten times as large."""
    e = load(spark, d, "embeddings", "vec_id", "embedding").select(F.col("vec_id").cast("long").alias("clip"), F.col("embedding").alias("x"))
    starts = F.array(*[F.lit(i) for i in range(0, 24 - FRAMES_OF + 1, 5)])
    w = e.select("clip", F.explode(starts).alias("i"), "x", (F.pmod("clip", F.lit(5)) > 0).cast("int").alias("truth"))
    return w.withColumn("key", F.col("clip") * 100 + F.col("i")).withColumn("v", F.struct("clip", "i", "x"))


def rendered(pairs):
    """pairs with a (9 x 6 spectrogram) of their own window and v (9 x 36 pixels) of the window that ``v`` names.

    A clip's sound is a mix of its pixels; every fifth clip's sound is another's.
    """
    from functools import lru_cache

    import numpy as np
    import pyarrow as pa

    mix = np.random.default_rng(11).normal(0, 1, (SIDE * SIDE, BANDS)) / SIDE

    def make(batches):
        @lru_cache(256)
        def clip(vec, x):
            rng = np.random.default_rng(vec)
            base = np.frombuffer(x)[: SIDE * SIDE] * 8
            video = base * np.cumsum(rng.normal(0, 0.8, (24, 1)), axis=0) + 0.5 * rng.normal(size=(24, SIDE * SIDE))
            heard = video if vec % 5 else base * np.cumsum(rng.normal(0, 0.8, (24, 1)), axis=0)
            sound = heard @ mix + 0.1 * rng.normal(size=(24, BANDS))
            return sound / max(sound.std(), 1e-9), video / max(video.std(), 1e-9)

        def cut(ids, starts, xs, which):
            return np.stack([clip(vec, np.asarray(x, float).tobytes())[which][i : i + FRAMES_OF].ravel() for vec, i, x in zip(ids.to_pylist(), starts.to_pylist(), xs.to_numpy(zero_copy_only=False))])

        for whole in batches:
            for at in range(0, whole.num_rows, 512):  # a pair takes over 3 kB
                b = whole.slice(at, 512)
                a, v = cut(*b.columns[:3], 0), cut(*b.column(3).flatten(), 1)
                lists = [pa.FixedSizeListArray.from_arrays(m.ravel(), m.shape[1]).cast(pa.list_(pa.float64())) for m in (a, v)]
                yield pa.RecordBatch.from_arrays([b.column(0), *lists, *b.columns[4:]], names=["clip", "a", "v", "truth", "y"])

    return pairs.select("clip", "i", "x", "v", "truth", "y").mapInArrow(make, "clip long, a array<double>, v array<double>, truth int, y int")


@query("s_towers")
def s_towers(spark, d):
    """Spatiotemporal against spatial towers: two rounds of training and self-filtering on windows with randomly shifted negatives.

    Accuracy of single windows and of the mean over a clip's windows, and the share of pairs in step before and after filtering.
    """
    from clipflow.sources.tables import written

    clips = windows(spark, d)
    moved = S.random_shifts(clips.withColumn("g", F.lit(0) + F.col("clip") % 64), "g", "key").drop("g")
    pairs = written(rendered(moved).withColumn("held_out", F.col("clip") % 3 == 0), "sync-pairs")
    out = []
    for name, k_t in (("spatiotemporal", 3), ("spatial", 1)):
        start = S.ConvTowers.start(BANDS, FRAMES_OF, SIDE, dim=6, filters=(3,), k_t=k_t)
        towers, kept, losses = S.self_filter(pairs.where("NOT held_out").drop("held_out"), start, FRAMES_OF, rounds=2, epochs=6, rate=0.3, longest=1.0)
        scored = written(S.distances(pairs.where("held_out").drop("held_out"), towers, FRAMES_OF), "sync-scored")
        cut = scored.agg(F.percentile_approx("d", 0.5)).first()[0]
        single = scored.agg(F.avg(((F.col("d") < cut) == (F.col("y") == 1)).cast("double"))).first()[0]
        mean = scored.groupBy("clip", "y").agg(F.avg("d").alias("d")).agg(F.avg(((F.col("d") < cut) == (F.col("y") == 1)).cast("double"))).first()[0]
        share = lambda rows: rows.where("y = 1").agg(F.avg("truth")).first()[0]
        out.append((name, float(losses[0]), float(losses[-1]), float(single), float(mean), float(share(pairs.where("NOT held_out"))), float(share(kept))))
    return spark.createDataFrame(out, "towers string, loss_first double, loss_last double, accuracy_window double, accuracy_clip double, in_step_before double, in_step_after double")
