"""Stand-ins for video, audio and transcripts: views of the given tables that carry the methods' inputs.

Nothing here claims to be real footage. A clip is a user's events in a six-day bucket, a frame one event; 36,000 seconds
of event time count as one second at 25 frames.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from clipflow.sources.tables import load

BUCKET, SECOND = 518_400, 36_000


def epoch(ts: str) -> Column:
    """Seconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.expr(f"CAST(datediff({ts}, DATE'1970-01-01') AS DOUBLE) * 86400 + hour({ts}) * 3600 + minute({ts}) * 60 + CAST(extract(SECOND FROM {ts}) AS DOUBLE)")


def frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, user_id, w, t (order in the clip), e (seconds), value, k, event_type."""
    ev = load(spark, sf_dir, "events", "event_id", "user_id", "ts", "value", "props", "event_type")
    ev = ev.select("event_id", "user_id", epoch("ts").alias("e"), "value", F.get_json_object("props", "$.k").cast("int").alias("k"), "event_type")
    ev = ev.withColumn("w", F.floor(F.col("e") / BUCKET).cast("long"))
    return ev.withColumn("t", F.row_number().over(Window.partitionBy("user_id", "w").orderBy("e", "event_id")).cast("long"))


def clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, w, n, dur, fps, min_eye, max_yaw, max_pitch, sp. One partial aggregation; no window."""
    ev = load(spark, sf_dir, "events", "user_id", "ts", "value", "props")
    ev = ev.select("user_id", epoch("ts").alias("e"), "value", F.get_json_object("props", "$.k").cast("int").alias("k"))
    ev = ev.withColumn("w", F.floor(F.col("e") / BUCKET).cast("long"))
    c = ev.groupBy("user_id", "w").agg(
        F.count(F.lit(1)).alias("n"),
        ((F.max("e") - F.min("e")) / SECOND).alias("dur"),
        F.min(78 + 0.5 * F.col("k")).alias("min_eye"),
        F.max(F.abs((F.col("value") - 50) / 5)).alias("max_yaw"),
        F.max(F.abs((F.col("k") - 50) * 0.7)).alias("max_pitch"),
        F.stddev_pop(F.col("value") / (100 + F.col("k"))).alias("sp"),
    )
    return c.withColumn("fps", F.when(F.col("dur") > 0, 25.0 * (F.col("n") - 1) / F.col("dur")))


FRAMES_SQL = """ev0 AS (SELECT event_id, user_id, epoch(ts) AS e, value, CAST(regexp_extract(props, '"k": ?(-?[0-9]+)', 1) AS INT) AS k, event_type FROM events),
    ev1 AS (SELECT *, CAST(floor(e / 518400) AS BIGINT) AS w FROM ev0),
    frames AS (SELECT *, row_number() OVER (PARTITION BY user_id, w ORDER BY e, event_id) AS t FROM ev1)"""
CLIPS_SQL = FRAMES_SQL + """,
    clips0 AS (SELECT user_id, w, count(*) AS n, (max(e) - min(e)) / 36000 AS dur, min(78 + 0.5 * k) AS min_eye, max(abs((value - 50) / 5)) AS max_yaw,
        max(abs((k - 50) * 0.7)) AS max_pitch, stddev_pop(value / (100 + k)) AS sp FROM ev1 GROUP BY 1, 2),
    clips AS (SELECT *, CASE WHEN dur > 0 THEN 25.0::DOUBLE * (n - 1) / dur END AS fps FROM clips0)"""


def pixels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, label, r, c, v: embeddings as 8 x 8 frames."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("i", "v"))
    return e.select("vec_id", "label", F.floor(F.col("i") / 8).cast("int").alias("r"), (F.col("i") % 8).alias("c"), F.col("v").cast("double").alias("v"))


PIXELS_SQL = """px0 AS (SELECT vec_id, label, unnest(range(0, 64)) AS i, unnest(embedding) AS v FROM embeddings),
    px AS (SELECT vec_id, label, CAST(i // 8 AS INT) AS r, CAST(i % 8 AS INT) AS c, CAST(v AS DOUBLE) AS v FROM px0)"""


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, point_no, x, y: embeddings as 32 landmarks."""
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.select("vec_id", F.posexplode(F.expr("transform(sequence(0, 31), i -> struct(cast(embedding[2 * i] AS double) AS x, cast(embedding[2 * i + 1] AS double) AS y))")).alias("point_no", "p")).select("vec_id", "point_no", "p.x", "p.y")


POINTS_SQL = """pt0 AS (SELECT vec_id, embedding, unnest(range(0, 32)) AS point_no FROM embeddings),
    pts AS (SELECT vec_id, CAST(point_no AS INT) AS point_no, CAST(embedding[2 * point_no + 1] AS DOUBLE) AS x, CAST(embedding[2 * point_no + 2] AS DOUBLE) AS y FROM pt0)"""


def hash8(*parts: Column) -> Column:
    """First 8 hex digits of md5 as a number: the same in every engine."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long")


PIECE = 40  # words that 12 seconds of speech hold


def utterances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, s, words, bucket (0 to 9): English sentences of ASCII-letter words, in pieces of 40, of 6 words at least.

    ``s`` is 100,000 times the sentence's number plus the piece's.
    """
    d = load(spark, sf_dir, "documents", "doc_id", "text", "lang").where("lang = 'en'")
    d = d.withColumn("bucket", (hash8(F.lit("split"), F.col("doc_id").cast("string")) % 10).cast("int"))
    s = d.select("doc_id", "bucket", F.posexplode(F.split(F.lower("text"), "[.]")).alias("n", "line"))
    s = s.select("doc_id", "bucket", "n", F.regexp_extract_all("line", F.lit("([a-z]+)")).alias("w")).where("size(w) > 0")
    s = s.select("doc_id", "bucket", "n", F.posexplode(F.expr(f"transform(sequence(0, (size(w) - 1) DIV {PIECE}), k -> slice(w, cast(k * {PIECE} + 1 AS int), {PIECE}))")).alias("k", "words"))
    return s.select("doc_id", "bucket", (F.col("n").cast("long") * 100000 + F.col("k")).alias("s"), "words").where(F.size("words") >= 6)


UTTERANCES_SQL = f"""ut0 AS (SELECT doc_id, CAST(('0x' || substr(md5('split|' || doc_id), 1, 8))::BIGINT % 10 AS INT) AS bucket, string_split(lower(text), '.') AS ls FROM documents WHERE lang = 'en'),
    ut1 AS (SELECT doc_id, bucket, CAST(unnest(range(0, len(ls))) AS BIGINT) AS n, unnest(ls) AS line FROM ut0),
    ut2 AS (SELECT doc_id, bucket, n, regexp_extract_all(line, '[a-z]+') AS w FROM ut1),
    ut3 AS (SELECT doc_id, bucket, n, w, unnest(range(0, (len(w) - 1) // {PIECE} + 1)) AS k FROM ut2 WHERE len(w) > 0),
    ut AS (SELECT doc_id, bucket, n * 100000 + k AS s, w[k * {PIECE} + 1 : k * {PIECE} + {PIECE}] AS words FROM ut3 WHERE len(w[k * {PIECE} + 1 : k * {PIECE} + {PIECE}]) >= 6)"""
