"""Phoneme and lexicon queries (A)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from clipflow.functions import phonemes as G
from clipflow.sources.tables import load
from clipflow.workloads.registry import query

_TOK = "tok AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS word FROM documents WHERE lang = 'en')"
_TYPES = f"{_TOK}, types AS (SELECT DISTINCT word FROM tok UNION SELECT unnest([{', '.join(repr(w) for w in G.OVERRIDES)}]))"
_LEX = f"""{_TYPES}, l0 AS (SELECT word, {G.g2p_sql('word')} AS p FROM types),
    l1 AS (SELECT word, p, translate(p, 'T', 'D') AS p2, CASE WHEN regexp_extract(p, '^[^iIeE{{AOoUuV@3YWX]*[iIeE{{AOoUuV@3YWX]') = '' THEN p
      ELSE regexp_extract(p, '^[^iIeE{{AOoUuV@3YWX]*[iIeE{{AOoUuV@3YWX]') || translate(substr(p, length(regexp_extract(p, '^[^iIeE{{AOoUuV@3YWX]*[iIeE{{AOoUuV@3YWX]')) + 1), 'E', '@') END AS p3 FROM l0),
    lex AS (SELECT word, 0 AS pron_id, p AS phones FROM l1 UNION ALL SELECT word, 1, p2 FROM l1 WHERE p2 <> p UNION ALL SELECT word, CASE WHEN p2 <> p THEN 2 ELSE 1 END, p3 FROM l1 WHERE p3 <> p AND p3 <> p2)"""


def tokens(spark, d):
    docs = load(spark, d, "documents", "doc_id", "text", "lang").where("lang = 'en'")
    return docs.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("word"))


def types(spark, d):
    given = spark.createDataFrame([(w,) for w in G.OVERRIDES], "word string")
    return tokens(spark, d).select("word").unionByName(given).distinct()


def lexicon(spark, d):
    """word, pron_id, phones: one row a pronunciation."""
    return types(spark, d).select("word", F.posexplode(G.pronunciations(F.col("word"))).alias("pron_id", "phones"))


@query("a_alphabet", f"""WITH {_TYPES}, u AS (SELECT unnest(string_split({G.g2p_sql('word')}, '')) AS symbol FROM types), c AS (SELECT symbol, count(*) AS n FROM u GROUP BY 1)
    SELECT i::INT AS i, substr('{G.ALPHABET}', i + 1, 1) AS symbol, CASE WHEN i < 24 THEN 'consonant' WHEN i < 40 THEN 'vowel' WHEN i = 40 THEN 'silence' ELSE 'blank' END AS kind, coalesce(n, 0) AS n
    FROM (SELECT unnest(range(0, {len(G.ALPHABET)})) AS i) LEFT JOIN c ON c.symbol = substr('{G.ALPHABET}', i + 1, 1)""")
def a_alphabet(spark, d):
    """The symbols, and how often the words of the documents have each."""
    kind = lambda c: "consonant" if c in G.CONSONANTS else "vowel" if c in G.VOWELS else "silence" if c == G.SILENCE else "blank"
    symbols = spark.createDataFrame([(i, c, kind(c)) for i, c in enumerate(G.ALPHABET)], "i int, symbol string, kind string")
    used = types(spark, d).select(F.explode(F.split(G.g2p(F.col("word")), "")).alias("symbol")).groupBy("symbol").agg(F.count(F.lit(1)).alias("n"))
    return symbols.join(used, "symbol", "left").select("i", "symbol", "kind", F.coalesce("n", F.lit(0)).alias("n"))


@query("a_g2p", f"WITH {_TYPES} SELECT word, {G.g2p_sql('word')} AS phones FROM types")
def a_g2p(spark, d):
    return types(spark, d).select("word", G.g2p(F.col("word")).alias("phones"))


@query("a_lexicon", f"WITH {_LEX} SELECT word, pron_id, phones FROM lex")
def a_lexicon(spark, d):
    return lexicon(spark, d)


@query("a_homophones", f"WITH {_LEX} SELECT phones, count(*) AS n_words, string_agg(word, ' ' ORDER BY word) AS words FROM lex WHERE pron_id = 0 GROUP BY 1 HAVING count(*) > 1")
def a_homophones(spark, d):
    g = lexicon(spark, d).where("pron_id = 0").groupBy("phones").agg(F.collect_list("word").alias("ws"))
    return g.where(F.size("ws") > 1).select("phones", F.size("ws").cast("long").alias("n_words"), F.array_join(F.array_sort("ws"), " ").alias("words"))


@query("a_char_lexicon", f"WITH {_TYPES} SELECT word, array_to_string(string_split(word, ''), ' ') AS spelled FROM types")
def a_char_lexicon(spark, d):
    return types(spark, d).select("word", F.array_join(F.split("word", ""), " ").alias("spelled"))


def unigram_dictionary(toks, size: int):
    """word, c, logp: the ``size`` most frequent words (ties by word) with add-one smoothing over the dictionary and one unknown."""
    top = toks.groupBy("word").agg(F.count(F.lit(1)).alias("c")).orderBy(F.desc("c"), "word").limit(size)
    total = Window.partitionBy()  # of at most ``size`` rows
    return top.select("word", "c", F.log((F.col("c") + 1.0) / (F.sum("c").over(total) + F.count(F.lit(1)).over(total) + 1)).alias("logp"))


@query("a_unigram", f"WITH {_TOK}, c AS (SELECT word, count(*) AS c FROM tok GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 1000) SELECT word, c, round(ln((c + 1.0::DOUBLE) / ((SELECT sum(c) FROM c) + (SELECT count(*) FROM c) + 1)), 6) AS logp FROM c")
def a_unigram(spark, d):
    return unigram_dictionary(tokens(spark, d), 1000).select("word", "c", F.round("logp", 6).alias("logp"))


_VIS = "translate(phones, '{}', '{}')".format("".join(G.VISEMES.values()), "".join(k * len(v) for k, v in G.VISEMES.items()))


@query("a_viseme", f"WITH {_LEX}, v AS (SELECT unnest(string_split({_VIS}, '')) AS viseme FROM lex WHERE pron_id = 0) SELECT viseme, count(*) AS n FROM v WHERE viseme <> '' GROUP BY 1")
def a_viseme(spark, d):
    v = lexicon(spark, d).where("pron_id = 0").select(F.explode(F.split(G.viseme(F.col("phones")), "")).alias("viseme"))
    return v.where("viseme <> ''").groupBy("viseme").agg(F.count(F.lit(1)).alias("n"))


@query("a_oov", f"""WITH {_TOK}, v AS (SELECT DISTINCT word FROM tok), b AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS word FROM benchmark)
    SELECT 'before' AS vocabulary, count(*) AS n_tokens, count(*) FILTER (WHERE word NOT IN (SELECT word FROM v)) AS n_oov FROM b UNION ALL SELECT 'after', count(*), 0 FROM b""")
def a_oov(spark, d):
    b = load(spark, d, "benchmark", "text").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("word"))
    known = tokens(spark, d).select("word").distinct()

    def rate(name, vocabulary):
        joined = b.join(vocabulary.withColumn("hit", F.lit(1)), "word", "left")
        return joined.agg(F.count(F.lit(1)).alias("n_tokens"), F.count_if(F.col("hit").isNull()).alias("n_oov")).select(F.lit(name).alias("vocabulary"), "n_tokens", "n_oov")

    return rate("before", known).unionByName(rate("after", known.unionByName(b).distinct()))
