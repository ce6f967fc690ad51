"""URL filter: rules by host and path, and a logistic regression on hashed character n-grams for the rest.

DataFrame functions only. The regression is trained from a small labelled table: at most a few hundred URLs, which is
what bounds its one-row training table. Its weights are linear in the examples' features, so gradient descent on
them is carried out on one number an example, through the table of inner products.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
SIZES = (3, 4, 5)
BUCKETS = 1 << 14


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules of the query.
RULES = (Rule("net", "/", "block"), Rule("example.net", "/en/", "allow"), Rule("example.com", "/de/", "block"), Rule("org", "/fr/", "allow"))

#: The labelled table: 1 is unwanted.
LABELLED = (
    ("http://free-casino-slots.example.biz/bonus/win-cash", 1), ("https://bet-poker-online.example.info/jackpot/4411", 1), ("http://casino-royal-bets.test/roulette/spin", 1),
    ("https://lucky-slots-777.test/jackpot/free-spins", 1), ("http://xxx-porn-tube.test/videos/9912", 1), ("https://hot-porn-cams.example.biz/live/sex", 1),
    ("http://adult-sex-dating.test/join/now", 1), ("https://nude-cams-xxx.example.info/free/room7", 1), ("http://cheap-viagra-pills.test/buy/online", 1),
    ("https://pharmacy-no-prescription.test/cialis/order", 1), ("http://buy-pills-cheap.example.biz/viagra/discount", 1), ("https://warez-crack-keygen.test/download/full", 1),
    ("http://torrent-crack-serials.test/keygen/2231", 1), ("https://free-movies-torrent.example.biz/download/hd", 1), ("http://payday-loan-fast.test/apply/cash", 1),
    ("https://quick-loans-cash.example.info/credit/instant", 1), ("http://secure-login-paypa1.test/verify/account", 1), ("https://account-verify-bank.test/login/confirm", 1),
    ("http://win-free-iphone.test/prize/claim", 1), ("https://click-track-ads.example.biz/banner/redirect", 1), ("http://adserver-popunder.test/click/banner?id=4", 1),
    ("https://replica-watches-cheap.test/rolex/sale", 1), ("http://forex-crypto-profit.test/signal/win", 1), ("https://bitcoin-doubler.example.biz/invest/profit", 1),
    ("http://betting-odds-free.test/casino/poker", 1), ("https://sexcams.test/xxx/porn/live", 1), ("http://spam-seo-links.test/buy/backlinks", 1),
    ("https://essay-writing-cheap.test/order/now", 1), ("http://weight-loss-pills.test/buy/miracle", 1), ("https://malware-download.test/free/crack.exe", 1),
    ("https://news.example.com/en/world/10231", 0), ("https://blog.example.org/en/20114.html", 0), ("http://www.example.org/fr/articles/1822", 0),
    ("https://m.example.net/de/2291", 0), ("https://docs.example.com/guide/install.html", 0), ("https://wiki.example.org/es/historia", 0),
    ("http://library.example.edu/catalog/8821", 0), ("https://www.example.com/de/18822", 0), ("https://forum.example.net/en/thread/2011?page=2", 0),
    ("https://recipes.example.com/en/bread", 0), ("http://museum.example.org/fr/exposition/112", 0), ("https://university.example.edu/physics/course/101", 0),
    ("https://weather.example.com/en/today", 0), ("https://blog.example.net/en/5512?utm_source=feed", 0), ("http://www.example.net/es/noticias/331", 0),
    ("https://m.example.com/fr/9021#top", 0), ("https://travel.example.org/en/mountains/22", 0), ("http://city.example.org/en/council/minutes", 0),
    ("https://journal.example.edu/volume/12/article/7", 0), ("https://music.example.com/de/konzert/771", 0), ("https://theory.example.org/en/4001/", 0),
    ("http://history.example.com/fr/8812.html", 0), ("https://garden.example.net/en/roses/16", 0), ("https://science.example.org/es/30412", 0),
    ("http://school.example.edu/de/klasse/4", 0), ("https://m.example.org/en/45348#top", 0), ("http://blog.example.com/fr/20768", 0),
    ("https://sport.example.com/en/football/119", 0), ("https://health.example.org/en/advice/sleep", 0), ("http://code.example.net/en/project/readme", 0),
)


def host(url: Column) -> Column:
    """Between the first ``://`` and ``/``, ``?``, ``#`` or the end, A-Z lowered; empty for null or no ``://``."""
    return F.translate(F.coalesce(F.regexp_extract(url, "(?s)^.*?://([^/?#]*)", 1), F.lit("")), _UPPER, _LOWER)


def path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, "(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host_col: Column, path_col: Column, rules: tuple[Rule, ...]) -> Column:
    """(rule, verdict) of the longest rule that fits host or a domain above it, and the path's start; else null."""
    chosen = F.lit(None).cast("struct<rule:string,verdict:string>")
    for r in sorted(rules, key=lambda r: (len(r.name), r.name)):
        fits = ((host_col == r.host) | host_col.endswith("." + r.host)) & path_col.startswith(r.path)
        chosen = F.when(fits, F.struct(F.lit(r.name).alias("rule"), F.lit(r.verdict).alias("verdict"))).otherwise(chosen)
    return chosen


def _grams(text: Column, mark: str) -> list[Column]:
    """Bucket numbers of all n-grams of one part."""
    return [
        F.when(F.length(text) >= n, F.transform(F.sequence(F.lit(1), F.length(text) - n + 1), lambda i, n=n: F.pmod(F.xxhash64(F.lit(mark), F.substring(text, i, n)), F.lit(BUCKETS))))
        .otherwise(F.array().cast("array<bigint>"))
        for n in SIZES
    ]


def grams(host_col: Column, path_col: Column) -> Column:
    """The distinct buckets of a URL's n-grams; host and path ends are marked and kept apart."""
    parts = [*_grams(F.concat(F.lit("^"), host_col, F.lit("$")), "host"), *_grams(F.concat(path_col, F.lit("$")), "path")]
    return F.array_distinct(F.concat(*parts))


def train(labelled: DataFrame, max_rows: int = 500, rounds: int = 200, rate: float = 0.5, decay: float = 1e-3) -> DataFrame:
    """labelled (url, label) -> one row: bias, weights (array of ``BUCKETS`` doubles). Null urls or labels teach nothing.

    At most ``max_rows`` examples are used, those with the smallest hash: they are one row, with their products.
    """
    some = labelled.where("url IS NOT NULL AND label IN (0, 1)").orderBy(F.xxhash64("url"), "url", "label").limit(max_rows)
    seen = some.select(grams(host(F.col("url")), path(F.col("url"))).alias("b"), F.col("label").cast("double").alias("y"))
    one = seen.agg(F.array_sort(F.collect_list(F.struct("b", "y"))).alias("x"))
    # transform(array(v), v -> ...)[0] names a value, so that it is worked out once
    product = "transform(x, p -> transform(x, q -> 1D + size(array_intersect(p.b, q.b)) / sqrt(cast(size(p.b) * size(q.b) AS double))))"
    slope = "x[i].y - 1D / (1D + exp(-aggregate(zip_with(k[i], a, (u, v) -> u * v), 0D, (s, t) -> s + t)))"
    steps = f"""aggregate(sequence(1, {int(rounds)}), transform(x, p -> 0D), (a, step) ->
        transform(a, (own, i) -> own * {1 - rate * decay}D + {rate}D * ({slope})))"""
    fitted = f"transform(array(x), x -> transform(array({product}), k -> zip_with(x, {steps}, (p, w) -> struct(p.b AS b, w)))[0])[0]"
    shares = one.select(F.explode(F.expr(fitted)).alias("f")).select("f.b", "f.w")
    spread = "concat(array(struct(-1L AS bucket, w AS w)), transform(b, g -> struct(g AS bucket, w / sqrt(cast(size(b) AS double)) AS w)))"
    weights = shares.select(F.inline(F.expr(spread))).groupBy("bucket").agg(F.sum("w").alias("w"))
    model = weights.agg(F.map_from_entries(F.collect_list(F.struct("bucket", "w"))).alias("m"))  # one entry a bucket at most
    dense = f"transform(array(m), m -> transform(sequence(0L, {BUCKETS - 1}L), i -> coalesce(m[i], 0D)))[0]"
    return model.select(F.expr("coalesce(m[-1L], 0D)").alias("bias"), F.expr(dense).alias("weights"))


def judge(pages: DataFrame, labelled: DataFrame, rules: tuple[Rule, ...] = RULES, threshold: float = 0.5, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row per page: page_id, host, path, rule (null if none fits), verdict, score (of the regression, 0 to 1).

    Null urls and those without ``://`` have an empty host and path, which the regression judges like any other. Rows that
    repeat are judged each; an empty table gives no rows; other columns are not read. The model's row, whose size the
    number of buckets fixes, reaches the tasks as a constant; there is no join and no shuffle.
    """
    parts = pages.select(F.col(id_col).alias("page_id"), host(F.col(url_col)).alias("host"), path(F.col(url_col)).alias("path"))
    model = train(labelled).select(F.struct("bias", "weights").alias("model")).scalar()
    rows = parts.withColumn("model", model).withColumn("b", grams(F.col("host"), F.col("path")))
    z = "transform(array(b), b -> aggregate(b, 0D, (s, g) -> s + model.weights[cast(g AS int)]) / sqrt(cast(greatest(size(b), 1) AS double)))[0]"
    rows = rows.withColumn("score", F.expr(f"1D / (1D + exp(-(model.bias + {z})))")).withColumn("chosen", rule_of(F.col("host"), F.col("path"), rules))
    verdict = F.coalesce("chosen.verdict", F.when(F.col("score") >= threshold, "block").otherwise("allow"))
    return rows.select("page_id", "host", "path", F.col("chosen.rule").alias("rule"), verdict.alias("verdict"), "score")


def labelled_table(spark: SparkSession) -> DataFrame:
    values = ", ".join(f"('{u}', {y})" for u, y in LABELLED)
    return spark.sql(f"SELECT * FROM VALUES {values} AS t(url, label)")
