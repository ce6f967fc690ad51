"""Surfaces beside the DataFrame API: SQL functions, Arrow functions, aggregates, table functions, sources, observation."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipflow.functions import phonemes as G
from clipflow.functions import session
from clipflow.operators import pipeline as P
from clipflow.sources import clock
from clipflow.sources import standin as S
from clipflow.sources.tables import load
from clipflow.workloads.registry import query


@query("x_lateral", "SELECT n_name, s.n, round(s.total, 2) AS total FROM nation, LATERAL (SELECT count(*) AS n, sum(c_acctbal) AS total FROM customer WHERE c_nationkey = n_nationkey AND c_acctbal > 0) s")
def x_lateral(spark, d):
    """A subquery for each row, by a lateral join that the optimiser turns into an aggregate and a join."""
    inner = "SELECT count(*) AS n, sum(c_acctbal) AS total FROM {c} WHERE c_nationkey = n_nationkey AND c_acctbal > 0"
    c, n = load(spark, d, "customer", "c_nationkey", "c_acctbal"), load(spark, d, "nation", "n_nationkey", "n_name")
    return spark.sql("SELECT n_name, s.n, round(s.total, 2) AS total FROM {n}, LATERAL (" + inner + ") s", c=c, n=n)


_VIS = "translate(" + G.g2p_sql("w") + ", '" + "".join(G.VISEMES.values()) + "', '" + "".join(k * len(v) for k, v in G.VISEMES.items()) + "')"


@query("x_udf_twins", f"WITH w AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM benchmark) SELECT w AS word, levenshtein(w, {G.g2p_sql('w')}) AS native, levenshtein(w, {G.g2p_sql('w')}) AS arrow, {_VIS} AS looks, TRUE AS same FROM w")
def x_udf_twins(spark, d):
    """The same distance and visemes by expressions and by Arrow functions."""
    w = load(spark, d, "benchmark", "text").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("word")).distinct()
    w = w.withColumn("ph", G.g2p(F.col("word"))).withColumns({"native": F.levenshtein("word", "ph").cast("long"), "arrow": session.edit_arrow("word", "ph"), "looks": G.viseme(F.col("ph")), "looks2": session.viseme_arrow("ph")})
    return w.select("word", "native", "arrow", "looks", ((F.col("native") == F.col("arrow")) & (F.col("looks") == F.col("looks2"))).alias("same"))


@query("x_udaf", "SELECT c_mktsegment AS segment, round(sum(length(c_name)) / sum(c_nationkey + 1)::DOUBLE, 9) AS rate FROM customer GROUP BY 1")
def x_udaf(spark, d):
    """The pooled rate as an Arrow aggregate over five groups."""
    c = load(spark, d, "customer", "c_mktsegment", "c_name", "c_nationkey")
    return c.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.round(session.pooled_rate(F.length("c_name"), F.col("c_nationkey") + 1), 9).alias("rate"))


@query("x_udtf", f"WITH w AS (SELECT DISTINCT n_name AS word, {G.g2p_sql('lower(n_name)')} AS ph FROM nation), p AS (SELECT word, ph, unnest(range(1, length(ph) + 1)) AS i FROM w) SELECT word, (i - 1)::INT AS pos, substr(ph, i::INT, 1) AS phone, CASE WHEN contains('{G.VOWELS}', substr(ph, i::INT, 1)) THEN 2 ELSE 2 END AS frames FROM p")
def x_udtf(spark, d):
    """Phonemes of each name with their frames at 25 a second, by a table function in a lateral join."""
    session.register(spark)
    words = load(spark, d, "nation", "n_name").select(F.col("n_name").alias("word"), G.g2p(F.lower("n_name")).alias("ph")).distinct()
    return spark.sql("SELECT word, pos, phone, frames FROM {w}, LATERAL clip_phone_frames(ph, 25D)", w=words)


@query("x_sql_functions", f"WITH w AS (SELECT DISTINCT n_name AS word, {G.g2p_sql('lower(n_name)')} AS w0 FROM nation) SELECT word, translate(w0, '{''.join(G.VISEMES.values())}', '{''.join(k * len(v) for k, v in G.VISEMES.items())}') AS looks, levenshtein(word, w0) AS edits, regexp_replace(word, '_', '', 'g') AS plain FROM w")
def x_sql_functions(spark, d):
    """The registered functions from SQL; each letter twice collapses to the name where no letter repeats."""
    session.register(spark)
    words = load(spark, d, "nation", "n_name").select(F.col("n_name").alias("word"), G.g2p(F.lower("n_name")).alias("ph")).distinct()
    path = "flatten(transform(split(word, ''), x -> array(x, x, '_')))"
    return spark.sql(f"SELECT word, clip_viseme(ph) AS looks, clip_edits(word, ph) AS edits, clip_collapse({path}) AS plain FROM {{w}}", w=words)


@query("x_observe", f"WITH {S.CLIPS_SQL} SELECT count(*) AS n_in, count(*) FILTER (WHERE coalesce(dur BETWEEN 1 AND 12, FALSE)) AS n_duration, count(*) FILTER (WHERE dur BETWEEN 1 AND 12 AND min_eye >= 80 AND fps >= 23 AND max_yaw <= 30 AND max_pitch <= 30 AND round(sp, 9) >= 0.25) AS n_out FROM clips")
def x_observe(spark, d):
    """Counts that are observed while the cascade's rows flow by, without a pass of their own."""
    kept, seen = P.observed_cascade(S.clips(spark, d), every=("duration",))
    kept.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen["in"].get["n"], seen["duration"].get["n"], seen["out"].get["n"])], "n_in long, n_duration long, n_out long")


@query("x_datasource", "SELECT clip, t::INT AS t, round(t / 25.0::DOUBLE, 9) AS sec FROM (SELECT unnest(range(0, 40)) AS clip), (SELECT unnest(range(0, 75)) AS t)")
def x_datasource(spark, d):
    """Frame times from the engine's own source: forty clips of three seconds, ten a task."""
    clock.register(spark)
    c = spark.read.format("frame_clock").options(clips=40, seconds=3, fps=25, clips_per_task=10).load()
    return c.select("clip", "t", F.round("sec", 9).alias("sec"))
