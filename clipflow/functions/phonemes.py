"""Alphabet, grapheme to phoneme rules, pronunciations and visemes, as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: One ASCII character for each phoneme, silence and blank.
CONSONANTS = "pbtdkgfvTDszSZhmnNlrwjCG"
VOWELS = "iIeE{AOoUuV@3YWX"
SILENCE, BLANK = "-", "_"
ALPHABET = CONSONANTS + VOWELS + SILENCE + BLANK
#: Rewriting steps, digits standing for phonemes that a later step must not touch.
STEPS = (
    ("tion", "04n"), ("igh", "7"), ("sch", "0"), ("sh", "0"), ("ch", "1"), ("th", "2"), ("ng", "3"), ("ph", "f"), ("ck", "k"), ("qu", "kw"), ("ee", "5"), ("ea", "5"), ("oo", "6"), ("ou", "8"), ("ow", "8"),
    ("oi", "9"), ("oy", "9"), ("ll", "l"), ("rr", "r"), ("tt", "t"), ("nn", "n"), ("ss", "s"), ("mm", "m"), ("pp", "p"), ("cc", "c"), ("ff", "f"), ("er", "4r"),
)
FROM, TO = "abcdefghijklmnopqrstuvwxyz0123456789", "{bkdEfghIGklmnApkrstVvwzjzSCTN@iuYWX"
#: Words whose pronunciation is given.
OVERRIDES = {"fare": "fEr", "fair": "fEr", "kind": "kYnd", "of": "Vv"}
#: Classes of sounds that look alike on the lips.
VISEMES = {"P": "pbm", "F": "fv", "T": "TD", "S": "sz", "H": "SZCG", "K": "kgNh", "D": "tdnl", "R": "rw", "J": "ji", "E": "IeE{", "A": "A@V3YX", "O": "OoUuW"}


def g2p(word: Column) -> Column:
    w = F.when((F.length(word) > 3) & word.endswith("e"), F.substring(word, 1, F.length(word) - 1)).otherwise(word)
    for a, b in STEPS:
        w = F.replace(w, F.lit(a), F.lit(b))
    w = F.translate(w, FROM, TO)
    for known, phones in OVERRIDES.items():
        w = F.when(word == known, phones).otherwise(w)
    return w


def g2p_sql(word: str) -> str:
    w = f"CASE WHEN length({word}) > 3 AND {word} LIKE '%e' THEN substr({word}, 1, length({word}) - 1) ELSE {word} END"
    for a, b in STEPS:
        w = f"replace({w}, '{a}', '{b}')"
    return "CASE " + " ".join(f"WHEN {word} = '{k}' THEN '{p}'" for k, p in OVERRIDES.items()) + f" ELSE translate({w}, '{FROM}', '{TO}') END"


def reduced(phones: Column) -> Column:
    """Every E after the first vowel becomes a schwa."""
    at = F.regexp_instr(phones, F.lit("[iIeE{AOoUuV@3YWX]"))
    return F.when(at > 0, F.concat(F.substring(phones, F.lit(1), at), F.translate(F.substring(phones, at + 1, F.length(phones)), "E", "@"))).otherwise(phones)


def pronunciations(word: Column) -> Column:
    """Distinct pronunciations, the dominant one first: as spelled, with voiced T, reduced."""
    p = g2p(word)
    return F.array_distinct(F.array(p, F.translate(p, "T", "D"), reduced(p)))


def viseme(phones: Column) -> Column:
    return F.translate(phones, "".join(VISEMES.values()), "".join(k * len(v) for k, v in VISEMES.items()))
