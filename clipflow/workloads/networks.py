"""Network queries (N)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.functions import ctc as X
from clipflow.operators import nn as N
from clipflow.operators import trained as R
from clipflow.sources import standin as S
from clipflow.sources.tables import load
from clipflow.workloads.registry import query

CONFIGS = {"full": N.config_full(), "small": N.config_small(), "fullconv": N.config_fullconv()}
_ROWS = [(name, *r) for name, rows in CONFIGS.items() for r in rows]
_VALUES = "cfg AS (SELECT * FROM (VALUES " + ", ".join(str(r) for r in _ROWS) + ") AS x(model, layer, kind, k_t, k_s, c_in, c_out, stride, dilation))"


def _configs(spark):
    return spark.createDataFrame(_ROWS, "model string, " + N.CONFIG)


def _running(column="value"):
    return F.sum(column).over(Window.partitionBy("model").orderBy("layer"))


@query("n_receptive", f"WITH {_VALUES} SELECT model, layer::INT AS layer, (k_t - 1) * dilation AS value, 1 + sum((k_t - 1) * dilation) OVER (PARTITION BY model ORDER BY layer)::BIGINT AS running FROM cfg WHERE kind IN ('conv3d', 'dilated')")
def n_receptive(spark, d):
    """Frames that an output sees; 11 for the five layers of the vision module."""
    c = _configs(spark).where("kind IN ('conv3d', 'dilated')").withColumn("value", F.expr("(k_t - 1) * dilation"))
    return c.select("model", "layer", "value", (1 + _running()).alias("running"))


@query("n_params", f"WITH {_VALUES}, p AS (SELECT model, layer, kind, CAST({N.PARAMS} AS BIGINT) AS value FROM cfg) SELECT model, layer::INT AS layer, kind, value, sum(value) OVER (PARTITION BY model ORDER BY layer)::BIGINT AS running FROM p")
def n_params(spark, d):
    return _configs(spark).withColumn("value", F.expr(N.PARAMS).cast("long")).select("model", "layer", "kind", "value", _running().alias("running"))


@query("n_activations", f"WITH {_VALUES}, s AS (SELECT *, 128 - 2 * row_number() OVER (PARTITION BY model ORDER BY layer) AS side FROM cfg WHERE kind = 'conv3d'), v AS (SELECT model, layer, 75::BIGINT * side * side * c_out AS value FROM s) SELECT model, layer::INT AS layer, value, sum(value) OVER (PARTITION BY model ORDER BY layer)::BIGINT AS running FROM v")
def n_activations(spark, d):
    """Activations of 75 frames of 128 x 128 without spatial padding: the first two layers have most of them a filter."""
    c = _configs(spark).where("kind = 'conv3d'").withColumn("side", 128 - 2 * F.row_number().over(Window.partitionBy("model").orderBy("layer")))
    c = c.withColumn("value", F.expr("75L * side * side * c_out"))
    return c.select("model", "layer", "value", _running().alias("running"))


_CH = f"WITH {S.PIXELS_SQL}"


@query("n_groupnorm", _CH + ", g AS (SELECT vec_id, r // 2 AS grp, avg(v) AS mean, var_pop(v) AS var FROM px GROUP BY 1, 2) SELECT g.vec_id, g.grp::INT AS grp, round(any_value(mean), 6) AS mean, round(any_value(var), 6) AS var, round(sum((v - mean) / sqrt(var + 1e-5) * (c + 1)), 4) AS checksum FROM px JOIN g ON g.vec_id = px.vec_id AND g.grp = px.r // 2 GROUP BY 1, 2")
def n_groupnorm(spark, d):
    """Rows are channels, two to a group, statistics by example."""
    w = Window.partitionBy("vec_id", "grp")
    p = S.pixels(spark, d).withColumn("grp", F.expr("r DIV 2").cast("int"))
    p = p.withColumn("mean", F.avg("v").over(w)).withColumn("var", F.var_pop("v").over(w))
    hat = (F.col("v") - F.col("mean")) / F.sqrt(F.col("var") + 1e-5)
    return p.groupBy("vec_id", "grp").agg(F.round(F.first("mean"), 6).alias("mean"), F.round(F.first("var"), 6).alias("var"), F.round(F.sum(hat * (F.col("c") + 1)), 4).alias("checksum"))


@query("n_batchnorm", _CH + " SELECT r AS channel, round(avg(v), 6) AS mean, round(var_pop(v), 6) AS var FROM px GROUP BY 1")
def n_batchnorm(spark, d):
    s = N.batch_norm_statistics(S.pixels(spark, d), "r", "v")
    return s.select(F.col("r").alias("channel"), F.round("mean", 6).alias("mean"), F.round("var", 6).alias("var"))


def _dil(v: str, n: int, q: str) -> str:
    return f"0.25 * coalesce(lag({v}, {n}) OVER {q}, 0) + 0.5 * {v} + 0.25 * coalesce(lead({v}, {n}) OVER {q}, 0)"


@query("n_dilated", "WITH a AS (SELECT event_id, user_id, ts, " + _dil("value", 1, "(PARTITION BY user_id ORDER BY ts, event_id)") + " AS y1 FROM events), b AS (SELECT *, " + _dil("y1", 2, "(PARTITION BY user_id ORDER BY ts, event_id)") + " AS y2 FROM a) SELECT event_id, round(" + _dil("y2", 4, "(PARTITION BY user_id ORDER BY ts, event_id)") + ", 9) AS y FROM b")
def n_dilated(spark, d):
    """Three layers of one channel and kernel (1/4, 1/2, 1/4), dilations 1, 2, 4: one shuffle and one sort for all."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    x = load(spark, d, "events", "event_id", "user_id", "ts", "value").withColumn("y", F.col("value"))
    for n in (1, 2, 4):
        x = x.withColumn("y", 0.25 * F.coalesce(F.lag("y", n).over(w), F.lit(0.0)) + 0.5 * F.col("y") + 0.25 * F.coalesce(F.lead("y", n).over(w), F.lit(0.0)))
    return x.select("event_id", F.round("y", 9).alias("y"))


@query("n_softmax", "WITH e AS (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS x, unnest(range(0, 64)) AS i FROM embeddings), z AS (SELECT vec_id, max(x) AS m, sum(exp(x)) AS z FROM e GROUP BY 1) SELECT e.vec_id, round(exp(m) / z, 6) AS max_p, min(i)::INT AS arg FROM e JOIN z USING (vec_id) WHERE x = m GROUP BY 1, 2")
def n_softmax(spark, d):
    e = load(spark, d, "embeddings", "vec_id", "embedding").withColumn("p", X.softmax("embedding"))
    m = F.array_max("p")
    return e.select("vec_id", F.round(m, 6).alias("max_p"), (F.array_position("p", m) - 1).cast("int").alias("arg"))


def rendered(spark, d):
    """clip_id, px, label of every embedding's clip."""
    return R.rendered(spark, d).select("clip_id", "px", F.col("phones").alias("label"))


@query("n_train")
def n_train(spark, d):
    """Loss by step of the small network over all rendered clips, 64 of them a step."""
    clips = rendered(spark, d)
    net = N.Net.start(R.SIDE, 1, [2, 2], 8, 1, R.PHONES + 1)
    n = clips.count()
    _, losses = N.train(clips, net, R.SIDE, steps=max(12, -(-n // 64)), rate=0.05, workers=8, per_worker=8)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(losses)], "step int, loss double")


@query("e_table_trained")
def e_table_trained(spark, d):
    """The methods' own networks, trained on rendered clips: error rates on held-out ones."""
    return R.rates(spark, d)


@query("n_audio")
def n_audio(spark, d):
    """The audio network alone: convolutions over the spectrogram, recurrent layers, phonemes."""
    return R.rates(spark, d, R.METHODS[:1])


@query("w_ablations")
def w_ablations(spark, d):
    """The full network without one of its choices: motion in the convolutions, normalisation, gates, smooth crops, frontal faces."""
    out = R.rates(spark, d, R.ABLATIONS)
    out = out.unionByName(R.rates(spark, d, (R.Variant("no_smoothing"),), smooth=False))
    return out.unionByName(R.rates(spark, d, (R.Variant("wide_angle"),), angle=60.0))


@query("n_saliency")
def n_saliency(spark, d):
    """Strength of the guided gradient, entropy and top three symbols of every frame of every clip, by a trained network."""
    clips = R.rendered(spark, d)
    some = clips.where("NOT held_out").orderBy(S.hash8(F.lit("pick"), F.col("clip_id").cast("string")), "clip_id").limit(128)
    v = R.Variant("full_ph", steps=60)
    net, _, _ = R.fit(v, [(R.clip_of(v, r.px, r.mel), [int(i) for i in r.phones]) for r in some.toLocalIterator()])
    return N.saliency(clips.select("clip_id", "px", F.col("phones").alias("label")), net, R.SIDE).select("clip_id", "t", "strength", "entropy", "top")
