"""The lattice simulator: a labelled stand-in for a network's output. It tests decoding, language models and scores; its
error rates say nothing of real video."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipflow.functions.phonemes import CONSONANTS, VOWELS

#: Looks of each phoneme: its neighbours in the order of its class, two on.
_NEXT = {c: kind[(i + 1) % len(kind)] + kind[(i + 2) % len(kind)] for kind in (CONSONANTS, VOWELS) for i, c in enumerate(kind)}
_KEYS = "".join(_NEXT)
NEAR1, NEAR2 = "".join(v[0] for v in _NEXT.values()), "".join(v[1] for v in _NEXT.values())
PEAK = 0.8


def peaks(phones: str, keys: list[str], swap: float, seed: str = "sim") -> Column:
    """Array of one symbol a frame: each phoneme for one to three frames, swapped for a like one with probability
    ``swap``, with a blank between equal neighbours and after a quarter of all others."""
    k = ", ".join(f"cast({c} AS string)" for c in keys)
    h = f"cast(conv(substring(md5(concat_ws('|', '{seed}', {k}, cast(i AS string))), 1, 8), 16, 10) AS long)"
    sym = f"CASE WHEN ({h} DIV 16) % 1000 < {int(round(swap * 1000))} THEN translate(substring({phones}, i, 1), '{_KEYS}', '{NEAR1}') ELSE substring({phones}, i, 1) END"
    first = f"transform(filter(sequence(1, greatest(length({phones}), 1)), i -> i <= length({phones})), i -> struct({h} AS h, {sym} AS s))"
    frames = "transform(p, (x, i) -> concat(array_repeat(x.s, cast(1 + x.h % 3 AS int)), CASE WHEN i + 1 < size(p) AND (x.s = p[i + 1].s OR x.h % 4 = 0) THEN array('_') ELSE array() END))"
    return F.expr(f"transform(array({first}), p -> flatten({frames}))[0]")


def lattice(df: DataFrame, keys: list[str], phones: str = "phones", swap: float = 0.25, seed: str = "sim") -> DataFrame:
    """keys, t, sym, p in long form: the peak with 0.8, two like symbols 0.1 and 0.05, the blank the rest; after a blank
    peak, the vowel @ and s."""
    f = df.select(*keys, F.posexplode(peaks(phones, keys, swap, seed)).alias("t", "s"))
    n1, n2 = (F.when(F.col("s") == "_", c).otherwise(F.translate("s", _KEYS, near)) for c, near in (("@", NEAR1), ("s", NEAR2)))
    rest = F.when(F.col("s") == "_", "-").otherwise("_")
    return f.select(*keys, "t", F.inline(F.array(*[F.struct(s.alias("sym"), F.lit(p).alias("p")) for s, p in ((F.col("s"), 0.8), (n1, 0.1), (n2, 0.05), (rest, 0.05))])))


def lattice_frames(peak: Column) -> Column:
    """The rows of ``lattice`` from a clip's peaks, as an array of (t, sym, p) a frame: a clip stays a row."""
    near = lambda s, blank, to: F.when(s == "_", blank).otherwise(F.translate(s, _KEYS, to))

    def frame(s: Column, t: Column) -> Column:
        symbols = ((s, 0.8), (near(s, "@", NEAR1), 0.1), (near(s, "s", NEAR2), 0.05), (F.when(s == "_", "-").otherwise("_"), 0.05))
        return F.array(*[F.struct(t.alias("t"), x.alias("sym"), F.lit(p).alias("p")) for x, p in symbols])

    return F.transform(peak, frame)


LATTICE_SQL = """la0 AS (SELECT *, CAST(unnest(range(1, length(phones) + 1)) AS INT) AS i FROM {src}),
    la1 AS (SELECT *, ('0x' || substr(md5('{seed}|' || {keys} || '|' || i), 1, 8))::BIGINT AS h FROM la0),
    la2 AS (SELECT *, CASE WHEN (h // 16) % 1000 < {swap} THEN translate(substr(phones, i, 1), '{k}', '{n1}') ELSE substr(phones, i, 1) END AS s FROM la1),
    la3 AS (SELECT *, lead(s) OVER (PARTITION BY {part} ORDER BY i) AS nx FROM la2),
    la4 AS (SELECT {part}, i, unnest(list_concat(list_transform(range(0, 1 + h % 3), lambda q: s), CASE WHEN nx IS NOT NULL AND (s = nx OR h % 4 = 0) THEN ['_'] ELSE [] END)) AS s,
      unnest(range(0, 1 + h % 3 + CASE WHEN nx IS NOT NULL AND (s = nx OR h % 4 = 0) THEN 1 ELSE 0 END)) AS j FROM la3),
    peaks AS (SELECT {part}, CAST(row_number() OVER (PARTITION BY {part} ORDER BY i, j) - 1 AS INT) AS t, s FROM la4),
    lattice AS (SELECT {part}, t, s AS sym, 0.8::DOUBLE AS p FROM peaks UNION ALL SELECT {part}, t, CASE WHEN s = '_' THEN '@' ELSE translate(s, '{k}', '{n1}') END, 0.1::DOUBLE FROM peaks
      UNION ALL SELECT {part}, t, CASE WHEN s = '_' THEN 's' ELSE translate(s, '{k}', '{n2}') END, 0.05::DOUBLE FROM peaks UNION ALL SELECT {part}, t, CASE WHEN s = '_' THEN '-' ELSE '_' END, 0.05::DOUBLE FROM peaks)"""


def lattice_sql(source: str, keys: list[str], swap: float, seed: str = "sim") -> str:
    return LATTICE_SQL.format(src=source, seed=seed, keys=" || '|' || ".join(keys), part=", ".join(keys), swap=int(round(swap * 1000)), k=_KEYS, n1=NEAR1, n2=NEAR2)
