"""The mining cascade: one function for each rule, cheap ones first."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F


def duration_filter(df: DataFrame, lo: float = 1, hi: float = 12) -> DataFrame:
    return df.where(F.col("dur").between(lo, hi))


def min_words_filter(df: DataFrame, n: int = 6, col: str = "words") -> DataFrame:
    return df.where(F.size(col) >= n)


def eye_width_filter(df: DataFrame, least: float = 80) -> DataFrame:
    return df.where(F.col("min_eye") >= least)


def min_fps_filter(df: DataFrame, least: float = 23) -> DataFrame:
    return df.where(F.col("fps") >= least)


def pose_filter(df: DataFrame, most: float = 30, axes: tuple[str, ...] = ("max_yaw", "max_pitch")) -> DataFrame:
    for a in axes:
        df = df.where(F.col(a) <= most)
    return df


def speaking_filter(df: DataFrame, least: float = 0.25, min_frames: int = 2) -> DataFrame:
    """Low cost, high recall; voice-overs pass it."""
    return df.where((F.col("n") >= min_frames) & (F.round("sp", 9) >= least))


#: (rule, predicate, modes that apply it): train, infer and eval. Inference leaves out what only makes training pairs;
#: blurry clips and short transcripts go for evaluation only.
RULES: tuple[tuple[str, str, str], ...] = (
    ("all", "TRUE", "train infer eval"),
    ("duration", "dur BETWEEN 1 AND 12", "train eval"),
    ("eye width", "min_eye >= 80", "train infer eval"),
    ("frame rate", "fps >= 23", "train infer eval"),
    ("pose", "max_yaw <= 30 AND max_pitch <= 30", "train infer eval"),
    ("speaking", "round(sp, 9) >= 0.25", "train eval"),
)
#: With the rules that need more than landmarks: transcript, shots, pixels and sound.
FULL: tuple[tuple[str, str, str], ...] = (
    *RULES[:2],
    ("language", "lang_guess = 'en'", "train eval"),
    ("words", "n_words >= 6", "eval"),
    ("shots", "n_cuts = 0", "train infer eval"),
    ("padding", "trimmed_side >= 6", "train infer eval"),
    ("blur", "round(lap_var, 9) >= 0.22", "eval"),
    *RULES[2:],
    ("synchrony", "round(sync_d, 9) < 1.4", "train eval"),
)


def rules_of(mode: str, rules: tuple[tuple[str, str, str], ...] = RULES) -> tuple[tuple[str, str, str], ...]:
    return tuple(r for r in rules if mode in r[2].split())


def run_cascade(df: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, mode: str = "train") -> DataFrame:
    """The rows that all rules of the mode keep: train, infer or eval."""
    for _, predicate, _ in rules_of(mode, rules):
        df = df.where(predicate)
    return df


def observed_cascade(df: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, mode: str = "train", every: tuple[str, ...] = ()) -> tuple[DataFrame, dict[str, Observation]]:
    """run_cascade and the numbers of rows before it, after the rules named in ``every`` and after all.

    They are counted while the result is computed, once it is; each observed place keeps filters from being joined.
    """
    seen: dict[str, Observation] = {}

    def watched(name: str, rows: DataFrame) -> DataFrame:
        seen[name] = Observation(name)
        return rows.observe(seen[name], F.count(F.lit(1)).alias("n"))

    df = watched("in", df)
    for name, predicate, _ in rules_of(mode, rules):
        df = df.where(predicate)
        df = watched(name, df) if name in every else df
    return watched("out", df), seen


def funnel(df: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES) -> DataFrame:
    """rule_no, rule, n_clips: survivors after each rule, in one pass and one row a task."""
    flags, sums = F.lit(True), []
    for i, (name, predicate, _) in enumerate(rules):
        flags = flags & F.coalesce(F.expr(predicate), F.lit(False))
        sums.append(F.struct(F.lit(i).cast("long").alias("rule_no"), F.lit(name).alias("rule"), F.coalesce(F.sum(flags.cast("long")), F.lit(0)).alias("n_clips")))
    return df.agg(F.array(*sums).alias("a")).select(F.inline("a"))


def reorder_rules(sample: DataFrame, rules: tuple[tuple[str, str, str], ...], costs: dict[str, float]) -> list[tuple[str, str, str]]:
    """Rules by cost / (share dropped), which is the cheapest order of independent filters. One pass over a sample."""
    row = sample.agg(*[F.avg(F.coalesce(F.expr(p), F.lit(False)).cast("double")).alias(n) for n, p, _ in rules]).first()
    return sorted(rules, key=lambda r: costs.get(r[0], 1.0) / max(1e-9, 1 - (row[r[0]] or 0.0)))


def histogram_distance(a: str, b: str, metric: str = "l1") -> Column:
    """Between two equally long arrays of shares."""
    terms = {
        "l1": "abs(x - y)",
        "chi2": "CASE WHEN x + y > 0 THEN (x - y) * (x - y) / (x + y) ELSE 0D END",
        "intersection": "-least(x, y)",
    }[metric]
    total = F.expr(f"aggregate(zip_with({a}, {b}, (x, y) -> {terms}), 0D, (s, v) -> s + v)")
    return 1 + total if metric == "intersection" else total


def shot_boundaries(hist: DataFrame, keys: list[str], order: str, threshold: float = 0.6, metric: str = "l1") -> DataFrame:
    """hist (keys, order, h: array of shares) -> the same with dist to the one before and is_cut."""
    w = Window.partitionBy(*keys).orderBy(order)
    out = hist.withColumn("prev", F.lag("h").over(w))
    return out.withColumn("dist", histogram_distance("h", "prev", metric)).withColumn("is_cut", F.coalesce(F.col("dist") > threshold, F.lit(False)))


def shot_boundaries_of_maps(hist: DataFrame, keys: list[str], order: str, threshold: float = 0.6) -> DataFrame:
    """The same for histograms as maps from a bin to its share, absolute differences summed over the bins of either."""
    w = Window.partitionBy(*keys).orderBy(order)
    out = hist.withColumn("prev", F.lag("h").over(w))
    total = "aggregate(array_union(map_keys(h), map_keys(prev)), 0D, (s, k) -> s + abs(coalesce(h[k], 0D) - coalesce(prev[k], 0D)))"
    out = out.withColumn("dist", F.expr(total))
    return out.withColumn("is_cut", F.coalesce(F.col("dist") > threshold, F.lit(False)))


def naive_bayes(counts: DataFrame, key: str, label: str, feature: str, learn: Column) -> DataFrame:
    """counts (key, label, feature, n) -> key, guess: the label of the largest likelihood, add-one smoothed, ties by name.

    Rows where ``learn`` holds teach; features that none of them has say nothing. The model has a row a feature, which the
    feature's alphabet bounds (three of some 40 letters: below 64,000), with all labels' logarithms in one array.
    """
    seen = counts.where(learn & F.col(label).isNotNull()).groupBy(label, feature).agg(F.sum("n").alias("n"))
    labels = [r[0] for r in seen.select(label).distinct().orderBy(label).collect()]  # languages: a handful
    if not labels:
        return counts.select(key).distinct().withColumn("guess", F.lit(None).cast("string"))
    wide = seen.groupBy(feature).agg(*[F.coalesce(F.sum(F.when(F.col(label) == x, F.col("n"))), F.lit(0)).alias(f"n{i}") for i, x in enumerate(labels)])
    size = wide.agg(F.count(F.lit(1)).alias("v"), *[F.sum(f"n{i}").alias(f"t{i}") for i in range(len(labels))])
    model = wide.crossJoin(F.broadcast(size)).select(feature, *[F.log((F.col(f"n{i}") + 1) / (F.col(f"t{i}") + F.col("v"))).alias(f"l{i}") for i in range(len(labels))])  # one row
    scored = counts.join(model, feature).groupBy(key).agg(*[F.sum(F.col("n") * F.col(f"l{i}")).alias(f"l{i}") for i in range(len(labels))])
    best = F.greatest(*[F.round(f"l{i}", 4) for i in range(len(labels))]) if len(labels) > 1 else F.round("l0", 4)
    guess = F.coalesce(*[F.when(F.round(f"l{i}", 4) == best, x) for i, x in enumerate(labels)])
    return scored.select(key, guess.alias("guess"))


def trigram_bayes(texts: DataFrame, key: str, label: str, text: str, alphabet: str, learn: Column) -> DataFrame:
    """``naive_bayes`` over the character trigrams of texts that have only letters of ``alphabet``: the same guesses.

    A trigram is a number below the alphabet's cube. Tasks add up counts by label and rows' likelihoods in arrays of that
    size, so a text's trigrams are never rows of a table; the texts are read twice, once to learn and once to guess.
    """
    v = len(alphabet)
    lut = np.full(max(map(ord, alphabet)) + 1, v, np.int64)
    lut[[ord(c) for c in alphabet]] = np.arange(v)

    def pieces(b: pa.RecordBatch) -> list[pa.RecordBatch]:
        """Rows of about ``LETTERS_AT_ONCE`` letters, or one longer text."""
        part = np.cumsum(pc.utf8_length(b.column(1)).to_numpy(zero_copy_only=False)) // LETTERS_AT_ONCE
        at = np.nonzero(np.diff(part, prepend=-1))[0]
        return [b.slice(i, j - i) for i, j in zip(at, [*at[1:], b.num_rows])]

    def coded(x: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Row and number of each trigram of a batch."""
        size = pc.utf8_length(x).to_numpy(zero_copy_only=False).astype(np.int64)
        letters = lut[np.frombuffer("".join(x.to_pylist()).encode("utf-32-le"), np.uint32)]
        row = np.repeat(np.arange(len(size)), size)
        if len(row) < 3:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        whole = row[2:] == row[:-2]
        return row[2:][whole], (letters[:-2] * v * v + letters[1:-1] * v + letters[2:])[whole]

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for whole in batches:
            for b in pieces(whole):
                row, g = coded(b.column(1))
                names = b.column(0).dictionary_encode()
                of = names.indices.to_numpy()[row]
                for j, name in enumerate(names.dictionary.to_pylist()):
                    total[name] = total.get(name, 0) + np.bincount(g[of == j], minlength=v**3)
        for name, n in total.items():
            at = np.nonzero(n)[0]
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at, pa.int64()), pa.array(n[at], pa.int64())], names=["label", "g", "n"])

    known = texts.where(F.col(text).isNotNull())
    seen = known.where(learn & F.col(label).isNotNull()).select(F.col(label).alias("label"), F.col(text).alias("x")).mapInArrow(add, "label string, g long, n long")
    rows = seen.groupBy("label", "g").agg(F.sum("n").alias("n")).toArrow()  # at most v cubed a label
    labels = sorted(set(rows["label"].to_pylist()))  # languages: a handful
    if not labels:
        return known.where(F.length(text) > 2).select(key).distinct().withColumn("guess", F.lit(None).cast("string"))
    counts = np.zeros((len(labels), v**3), np.int64)
    counts[[labels.index(x) for x in rows["label"].to_pylist()], rows["g"].to_numpy()] = rows["n"].to_numpy()
    taught = counts.sum(axis=0) > 0
    logs = np.where(taught, np.log((counts + 1) / (counts.sum(axis=1, keepdims=True) + taught.sum())), 0.0)
    sent = texts.sparkSession.sparkContext.broadcast((taught, logs))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        taught, logs = sent.value
        for whole in batches:
            for b in pieces(whole):
                row, g = coded(b.column(1))
                has = np.bincount(row, weights=taught[g], minlength=b.num_rows) > 0
                found = [np.bincount(row, weights=x[g], minlength=b.num_rows)[has] for x in logs]
                yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(has)), *map(pa.array, found)], names=[key, *[f"l{j}" for j in range(len(labels))]])

    scored = known.select(key, text).mapInArrow(score, f"{key} {dict(texts.dtypes)[key]}, " + ", ".join(f"l{j} double" for j in range(len(labels))))
    scored = scored.groupBy(key).agg(*[F.round(F.sum(f"l{j}"), 4).alias(f"l{j}") for j in range(len(labels))])
    best = F.greatest(*[F.col(f"l{j}") for j in range(len(labels))]) if len(labels) > 1 else F.col("l0")
    return scored.select(key, F.coalesce(*[F.when(F.col(f"l{j}") == best, x) for j, x in enumerate(labels)]).alias("guess"))


#: Letters whose trigrams a task holds at once.
LETTERS_AT_ONCE = 1_000_000


def downsample_fps(frames: DataFrame, cap: float = 30, keys: tuple[str, ...] = ("user_id", "w"), time: str = "sec") -> DataFrame:
    """Frames kept when floor(time * cap) moves on: never more than ``cap`` a second; slower clips stay as they are."""
    w = Window.partitionBy(*keys).orderBy(time, "t")
    slot = F.floor(F.col(time) * cap)
    return frames.withColumn("slot", slot).withColumn("before", F.lag("slot").over(w)).where("before IS NULL OR slot <> before").drop("slot", "before")


def gaussian_smooth(df: DataFrame, col: str, keys: list[str], order: list[str], sigma: float = 1.0, radius: int = 3) -> Column:
    """Index kernel over 2 * radius + 1 rows, renormalised at the ends; one window for all terms."""
    import math

    w = Window.partitionBy(*keys).orderBy(*order)
    num, den = F.lit(0.0), F.lit(0.0)
    for o in range(-radius, radius + 1):
        g = math.exp(-0.5 * (o / sigma) ** 2)
        v = F.col(col) if o == 0 else (F.lag(col, -o) if o < 0 else F.lead(col, o)).over(w)
        num = num + F.coalesce(v * g, F.lit(0.0))
        den = den + F.when(v.isNotNull(), g).otherwise(0.0)
    return num / den


def gaussian_smooth_time(df: DataFrame, col: str, keys: list[str], time: str, sigma: float, reach: float) -> DataFrame:
    """df with ``smoothed``: the kernel in time over all rows within ``reach`` of each, for uneven frame times.

    A row's neighbours are gathered; a clip's length and frame rate bound them.
    """
    near = Window.partitionBy(*keys).orderBy(time).rangeBetween(-reach, reach)
    out = df.withColumn("_near", F.collect_list(F.struct(F.col(time).alias("e"), F.col(col).cast("double").alias("v"))).over(near))
    g = f"exp(-0.5D * pow(({time} - x.e) / {float(sigma)}D, 2))"
    return out.withColumn("smoothed", F.expr(f"aggregate(_near, struct(0D AS n, 0D AS d), (s, x) -> struct(s.n + x.v * {g} AS n, s.d + {g} AS d), s -> s.n / s.d)")).drop("_near")


def iou_1d_box(x1: Column, y1: Column, s1: Column, x2: Column, y2: Column, s2: Column) -> Column:
    """Overlap share of two squares given by corner and side."""
    wx = F.greatest(F.lit(0.0), F.least(x1 + s1, x2 + s2) - F.greatest(x1, x2))
    wy = F.greatest(F.lit(0.0), F.least(y1 + s1, y2 + s2) - F.greatest(y1, y2))
    inter = wx * wy
    return inter / (s1 * s1 + s2 * s2 - inter)


def interval_join(a: DataFrame, b: DataFrame, key: str, width: float) -> DataFrame:
    """Rows of a (key, t0, t1, ...) and b (key, u0, u1, ...) that overlap, each pair once.

    Both sides are dealt to time buckets of ``width``, so the join is an equi-join on (key, bucket); a pair is kept in the
    bucket where the later of the two begins. A long video is many buckets, and adaptive execution splits what stays hot.
    """
    cut = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width)))
    left, right = a.withColumn("bucket", cut("t0", "t1")), b.withColumn("bucket", cut("u0", "u1"))
    both = left.join(right, [key, "bucket"]).where("t0 <= u1 AND u0 <= t1")
    return both.where(F.col("bucket") == F.floor(F.greatest("t0", "u0") / width)).drop("bucket")


def fit_affine(pairs: DataFrame, key: str) -> DataFrame:
    """pairs (key, x, y, u, v) -> a..f with u = a x + b y + c and v = d x + e y + f by least squares, and the residual.

    Normal equations from sums of one pass, solved by Cramer's rule: no Python, one row a key in the shuffle.
    """
    s = pairs.groupBy(key).agg(
        F.count(F.lit(1)).cast("double").alias("n"), *[F.sum(F.expr(e)).alias(n) for n, e in dict(sx="x", sy="y", sxx="x*x", sxy="x*y", syy="y*y", su="u", sv="v", sxu="x*u", syu="y*u", sxv="x*v", syv="y*v", suu="u*u", svv="v*v").items()]
    )
    det = "(sxx * (syy * n - sy * sy) - sxy * (sxy * n - sy * sx) + sx * (sxy * sy - syy * sx))"

    def solve(p: str, q: str, r: str, names: str) -> dict[str, str]:
        return {
            names[0]: f"({p} * (syy * n - sy * sy) - sxy * ({q} * n - sy * {r}) + sx * ({q} * sy - syy * {r})) / {det}",
            names[1]: f"(sxx * ({q} * n - sy * {r}) - {p} * (sxy * n - sy * sx) + sx * (sxy * {r} - {q} * sx)) / {det}",
            names[2]: f"(sxx * (syy * {r} - {q} * sy) - sxy * (sxy * {r} - {q} * sx) + {p} * (sxy * sy - syy * sx)) / {det}",
        }

    for n, e in {**solve("sxu", "syu", "su", "abc"), **solve("sxv", "syv", "sv", "def")}.items():
        s = s.withColumn(n, F.expr(e))
    residual = "suu + svv - (a * sxu + b * syu + c * su) - (d * sxv + e * syv + f * sv)"
    return s.select(key, *"abcdef", F.expr(residual).alias("residual"))


def split_by_hash(df: DataFrame, key: str, seed: str = "split", buckets: int = 10) -> DataFrame:
    from clipflow.sources.standin import hash8

    return df.withColumn("bucket", (hash8(F.lit(seed), F.col(key).cast("string")) % buckets).cast("int"))
