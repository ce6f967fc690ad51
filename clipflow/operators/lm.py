"""n-gram counts and Katz back-off models as DataFrames: nothing of a model's size reaches the driver."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipflow.sources.tables import written


def ngram_counts(sentences: DataFrame, order: int = 5, words: str = "words") -> DataFrame:
    """sentences (array of words) -> order, ctx (words joined by spaces), w, c, with <s> and </s> marks.

    All orders come out of one pass; counts are summed before the one shuffle.
    """
    padded = F.concat(F.array(F.lit("<s>")), F.col(words), F.array(F.lit("</s>")))
    grams = "flatten(transform(sequence(1, {0}), n -> transform(filter(sequence(1, greatest(size(p), 1)), i -> i + n - 1 <= size(p)), i -> struct(n AS order, array_join(slice(p, i, n - 1), ' ') AS ctx, p[i + n - 2] AS w))))".format(order)
    g = sentences.select(padded.alias("p")).select(F.explode(F.expr(grams)).alias("g")).select("g.*").where("NOT (order = 1 AND w = '<s>')")
    return g.groupBy("order", "ctx", "w").agg(F.count(F.lit(1)).alias("c"))


def count_of_counts(counts: DataFrame, most: int = 6) -> DataFrame:
    """order, n1 .. n<most>: one row an order."""
    return counts.groupBy("order").agg(*[F.count_if(F.col("c") == r).alias(f"n{r}") for r in range(1, most + 1)])


def _ratio(r: int) -> str:
    """Good-Turing discount of count r, or absolute discounting where that leaves (0, 1]."""
    top = "try_divide(6D * n6, n1)"
    turing = f"try_divide(try_divide({r + 1}D * n{r + 1}, n{r}) / {r}D - {top}, 1D - {top})"
    absolute = f"({r}D - try_divide(cast(n1 AS double), n1 + 2 * n2)) / {r}D"
    ok = f"coalesce({turing} > 0 AND {turing} <= 1, FALSE)"
    return f"struct({r} AS r, CASE WHEN {ok} THEN {turing} ELSE coalesce({absolute}, 1D) END AS d, NOT ({ok}) AS guarded)"


def katz_discounts(counts: DataFrame, k: int = 5) -> DataFrame:
    """order, r, d, guarded for counts 1 to k; larger counts keep all their mass."""
    return discounts_of(count_of_counts(counts, k + 1), k)


def discounts_of(often: DataFrame, k: int = 5) -> DataFrame:
    """The same from counts of counts: order, n1 .. n<k + 1>."""
    return often.select("order", F.inline(F.expr(f"array({', '.join(_ratio(r) for r in range(1, k + 1))})")))


def suffix_of(ctx: Column) -> Column:
    """A context without its first word."""
    return F.when(F.instr(ctx, " ") > 0, F.regexp_replace(ctx, "^[^ ]* ", "")).otherwise("")


def katz_train(counts: DataFrame, order: int = 3, k: int = 5) -> DataFrame:
    """order, ctx, w, p (discounted), bow (of the context ctx + w as seen by the next order; null where it is none).

    Order 1 is the plain maximum likelihood. A context's back-off weight is what its discounts free, over the lower
    order's mass of the words it was not seen with. Each order takes two shuffles by context; hot contexts are summed
    before them.
    """
    discounts = F.broadcast(katz_discounts(counts, k))  # k rows an order
    model = None
    for n in range(1, order + 1):
        here = counts.where(F.col("order") == n)
        total = here.groupBy("ctx").agg(F.sum("c").alias("total"))
        p = here.join(total, "ctx")
        if n == 1:
            p = p.select("order", "ctx", "w", (F.col("c") / F.col("total")).alias("p"))
        else:
            p = p.join(discounts, (discounts.order == p.order) & (discounts.r == p.c), "left").select(p.order, "ctx", "w", (F.coalesce("d", F.lit(1.0)) * F.col("c") / F.col("total")).alias("p"))
        model = p if model is None else model.unionByName(p)
    return model


def back_off_weights(model: DataFrame, order: int) -> DataFrame:
    """ctx, bow of one order's contexts (order > 1).

    A context whose words take all of the lower order's mass has weight zero: what its discounts free is lost, so its
    probabilities sum to less than one. All others sum to one.
    """
    high, low = model.where(F.col("order") == order), model.where(F.col("order") == order - 1)
    low = low.select(F.col("ctx").alias("lctx"), F.col("w"), F.col("p").alias("lp"))
    if order > 2:  # a lower probability may itself be backed off; seen words of a longer context are seen in the shorter
        joined = high.withColumn("lctx", suffix_of(F.col("ctx"))).join(low, ["lctx", "w"], "left")
    else:
        joined = high.withColumn("lctx", F.lit("")).join(low, ["lctx", "w"], "left")
    left = joined.groupBy("ctx").agg(F.sum("p").alias("used"), F.sum("lp").alias("lower"))
    return left.select("ctx", F.when(F.round(1 - F.col("lower"), 12) > 0, F.greatest((1 - F.col("used")) / (1 - F.col("lower")), F.lit(0.0))).otherwise(0.0).alias("bow"))


def katz_model(sentences: DataFrame, order: int, k: int = 5, most: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(model, weights: order, ctx, bow), each written once, as scoring and decoding read them again and again.

    All n-grams are kept; a caller that asks for a pruned model names ``most``: an order with more n-grams than that is cut to
    its ``most`` frequent ones before training.
    """
    counts = written(ngram_counts(sentences, order), "ngrams")
    if most is not None:
        sizes = {r["order"]: r["n"] for r in counts.groupBy("order").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row an order
        if any(n > most for n in sizes.values()):
            parts = [prune(counts, n, most) if sizes[n] > most else counts.where(F.col("order") == n) for n in sorted(sizes)]
            counts = written(reduce(DataFrame.unionByName, parts), "pruned")
    model = written(katz_train(counts, order, k), "katz")
    weights = None
    for n in range(2, order + 1):
        w = back_off_weights(model, n).select(F.lit(n).alias("order"), "ctx", "bow")
        weights = w if weights is None else weights.unionByName(w)
    if weights is None:
        weights = model.where("false").select("order", "ctx", F.col("p").alias("bow"))
    return model, written(weights, "back-off")


def katz_logprob(grams: DataFrame, model: DataFrame, order: int, floor: float = 1e-9, weights: DataFrame | None = None) -> DataFrame:
    """grams (.., w, h: array of up to order - 1 words before) -> with logp of w after h.

    One join an order for the probability and one for the weight, all sort-merge; a small model is broadcast by its size.
    ``weights`` are those of ``katz_model``; without them they are worked out in the plan.
    """
    out = grams
    for n in range(1, order + 1):
        ctx = F.array_join(F.slice("h", F.greatest(F.size("h") - (n - 2), F.lit(1)), n - 1), " ") if n > 1 else F.lit("")
        out = out.withColumn(f"c{n}", F.when(F.size("h") >= n - 1, ctx))
        m = model.where(F.col("order") == n).select(F.col("ctx").alias(f"c{n}"), "w", F.col("p").alias(f"p{n}"))
        out = out.join(m, [f"c{n}", "w"], "left")
        if n > 1:
            bows = back_off_weights(model, n) if weights is None else weights.where(F.col("order") == n)
            out = out.join(bows.select(F.col("ctx").alias(f"c{n}"), F.col("bow").alias(f"b{n}")), f"c{n}", "left")
    p = F.coalesce("p1", F.lit(floor))
    for n in range(2, order + 1):
        p = F.when(F.col(f"c{n}").isNull(), p).otherwise(F.coalesce(F.col(f"p{n}"), F.coalesce(F.col(f"b{n}"), F.lit(1.0)) * p))
    names = grams.columns
    return out.select(*names, F.log(F.greatest(p, F.lit(floor))).alias("logp"))


def word_grams(sentences: DataFrame, keys: list[str], order: int) -> DataFrame:
    """keys, i, w, h: each word of each sentence (and its end) with the words before it."""
    padded = F.concat(F.array(F.lit("<s>")), F.col("words"), F.array(F.lit("</s>")))
    s = sentences.select(*keys, padded.alias("p")).select(*keys, "p", F.explode(F.expr("sequence(1, size(p) - 1)")).alias("i"))
    return s.select(*keys, "i", F.expr("p[i]").alias("w"), F.expr(f"slice(p, greatest(i - {order - 2}, 1), least(i, {order - 1}))").alias("h"))


def perplexity(scored: DataFrame) -> DataFrame:
    return scored.agg(F.exp(-F.avg("logp")).alias("perplexity"), F.count(F.lit(1)).alias("n_words"))


def prune(counts: DataFrame, order: int, most: int) -> DataFrame:
    """The ``most`` most frequent n-grams of an order, ties by text: a distributed top-k."""
    return counts.where(F.col("order") == order).orderBy(F.desc("c"), "ctx", "w").limit(most)


def rerank(nbest: DataFrame, keys: list[str], model: DataFrame, weights: DataFrame, order: int, weight: float = 1.0) -> DataFrame:
    """nbest (keys, rank, words, score) -> keys, words, score: the string with the best score plus weighed log probability.

    Ties go to the better rank. A clip has a few strings, so its choice is one small group.
    """
    logp = katz_logprob(word_grams(nbest, [*keys, "rank"], order), model, order, weights=weights).groupBy(*keys, "rank").agg(F.sum("logp").alias("logp"))
    both = nbest.join(logp, [*keys, "rank"]).withColumn("total", F.col("score") + weight * F.col("logp"))
    best = both.groupBy(*keys).agg(F.max_by(F.struct("words", "total"), F.struct(F.round("total", 9), -F.col("rank"))).alias("b"))
    return best.select(*keys, F.col("b.words").alias("words"), F.col("b.total").alias("score"))
