"""The subpackage's queries and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.llm import decontam, exact, licences, packing, shards, simhash, substring, suffix, toxicity, urls
from clipflow.llm.common import for_now, scratch, table

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def index_for(spark: SparkSession) -> exact.DigestIndex:
    name = for_now(spark, f"digest_index_{uuid.uuid4().hex}", is_table=True)
    return exact.DigestIndex(spark, name, buckets=max(16, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def op1_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_groups(table(spark, sf_dir, "documents"))


def op3_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    stored = shards.reshard(table(spark, sf_dir, "documents"), scratch(spark, "shards"))
    return stored.select("doc_id", "lang", "source", "n_chars", F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def arrivals(docs: DataFrame) -> list[DataFrame]:
    """The table as two batches, all of the first's ids being smaller; null ids are in the second."""
    middle = docs.approxQuantile("doc_id", [0.5], 0.05)
    if not middle:
        return [docs]
    first = F.col("doc_id") <= int(middle[0])
    return [docs.where(first), docs.where(~F.coalesce(first, F.lit(False)))]


def op5_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = substring.WindowIndex(spark, scratch(spark, "window-index"))
    done = [index.add(batch, with_kept=False) for batch in arrivals(table(spark, sf_dir, "documents"))]
    return reduce(DataFrame.unionByName, done)


def op6_suffix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.dedup_bytes(table(spark, sf_dir, "documents"), with_kept=False)


def op7_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.in_arrivals(arrivals(table(spark, sf_dir, "documents")), index_for(spark))


def op8_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontam.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, model).select("doc_id", (toxicity.remainder("doc_id") == 1).alias("held_out"), "score", "predicted", "worst")


def op10_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"), urls.labelled_table(spark))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_licences": op1_licences,
    "op2_simhash": op2_simhash,
    "op3_shards": op3_shards,
    "op4_packing": op4_packing,
    "op5_substring": op5_substring,
    "op6_suffix": op6_suffix,
    "op7_exact": op7_exact,
    "op8_decontam": op8_decontam,
    "op9_toxicity": op9_toxicity,
    "op10_urls": op10_urls,
}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

ORACLE: dict[str, str] = {
    "op3_shards": "SELECT doc_id, lang, source, n_chars, sha256(text) AS text_sha256 FROM documents",
    "op5_substring": r"""
        WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
        win AS (SELECT r, doc_id, i, array_to_string(w[i:i + 12], ' ') AS p FROM (SELECT *, unnest(range(1, len(w) - 11)) AS i FROM d)),
        earliest AS (SELECT p, min(doc_id) AS m FROM win GROUP BY p),
        gone AS (SELECT DISTINCT r, unnest(range(i, i + 13)) AS k FROM win JOIN earliest USING (p) WHERE m < doc_id),
        word AS (SELECT r, k, w[k] AS x FROM (SELECT r, w, unnest(range(1, len(w) + 1)) AS k FROM d)),
        kept AS (SELECT r, count(*) AS n, string_agg(x, ' ' ORDER BY k) AS t FROM word ANTI JOIN gone USING (r, k) GROUP BY r)
        SELECT doc_id, len(w) AS n_words, len(w) - coalesce(n, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
        FROM d LEFT JOIN kept USING (r)""",
    "op7_exact": r"""
        WITH d AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
        SELECT doc_id, min(doc_id) OVER (PARTITION BY text_sha256) AS keep_id, count(*) OVER (PARTITION BY text_sha256) AS group_size,
               doc_id = min(doc_id) OVER (PARTITION BY text_sha256) AS kept, text_sha256
        FROM d""",
    "op8_decontam": rf"""
        WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w FROM documents),
        b AS (SELECT item_id, {_WORDS} AS w FROM benchmark),
        cut AS (SELECT item_id, w, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS i FROM b WHERE len(w) > 0),
        pat AS (SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i:i + 9], ' ') AS p FROM cut),
        lengths AS (SELECT DISTINCT n FROM pat),
        spots AS (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, lengths WHERE len(w) >= n),
        hit AS (SELECT r, i, n, item_id FROM (SELECT r, i, n, array_to_string(w[i:i + n - 1], ' ') AS p FROM spots) JOIN pat USING (p, n)),
        words AS (SELECT r, count(DISTINCT k) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS k FROM hit) GROUP BY r),
        items AS (SELECT r, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS t FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY r)
        SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(t, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
        FROM d LEFT JOIN words USING (r) LEFT JOIN items USING (r)""",
}
