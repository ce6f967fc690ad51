"""The methods' networks, trained on rendered clips and judged on held-out ones: phoneme and word error rates that come
from learning, not from a simulator. The clips are toys (six phones, words of two), so only the order means anything.

A clip is made from a row of embeddings: the row's own vector is its noise, its label's neighbours its phones. Training
sets are bounded samples (``max_clips``), one network a task; held-out clips are all other rows, in one pass.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from clipflow.operators import ctc
from clipflow.operators import fst as T
from clipflow.operators import nn as N
from clipflow.operators.evaluate import align
from clipflow.sources.standin import hash8
from clipflow.sources.tables import load

PHONES, WORDS, SIDE, MEL, PER_PHONE = 6, 12, 8, 12, 4
MAX_CLIPS = 384  # training rows that one task may hold
SPELLINGS = "abcdefghijkl"  # two letters for each phone: which one is up to the word


def lexicon() -> list[tuple[str, tuple[int, int], str]]:
    """(word, its two phones, spelling); words with one spelling sound alike only if they are one word."""
    out = []
    for i in range(WORDS):
        a, b = 1 + i % PHONES, 1 + (5 * i + i // PHONES + 1) % PHONES
        out.append((f"w{i}", (a, b), SPELLINGS[a - 1 + PHONES * (i % 2)] + SPELLINGS[b - 1 + PHONES * ((i // 2) % 2)]))
    return out


def rendered(spark: SparkSession, sf_dir: str, smooth: bool = True, angle: float = 0.0) -> DataFrame:
    """clip_id, held_out, words, phones, letters (symbols from 1), px (T x 8 x 8 float32), mel (T x 12 float32), for every embedding.

    Each phone is four frames of its label's mean frame, growing or fading by phone, with the row's vector as noise. Without
    ``smooth`` the crop jumps by a pixel from frame to frame; ``angle`` (degrees) squeezes faces that look aside.
    """
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    mean = e.select("label", F.posexplode("embedding").alias("i", "v")).groupBy("label", "i").agg(F.avg("v").alias("v"))
    templates = np.zeros((10, SIDE * SIDE))
    for r in mean.where("label BETWEEN 0 AND 9").toLocalIterator():  # ten frames of 64 pixels
        templates[r.label, r.i] = r.v
    templates /= np.maximum(np.linalg.norm(templates, axis=1, keepdims=True), 1e-9)
    words = lexicon()
    tones = np.random.default_rng(5).normal(0, 1, (PHONES + 1, MEL))
    squeeze = math.cos(math.radians(angle))

    def render(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for vec, noise, h in zip(b["vec_id"], b["embedding"], b["h"]):
                rng = np.random.default_rng(int(vec))
                picked = [words[h % WORDS], words[(h // WORDS) % WORDS]]
                phones = [p for _, ps, _ in picked for p in ps]
                frames, sound = [], []
                for p in phones:
                    for k in range(PER_PHONE):
                        gain = (k + 1) / PER_PHONE if p % 2 else 1 - k / PER_PHONE
                        px = (8 * gain * templates[p] + 1.5 * np.asarray(noise) + 0.25 * rng.normal(size=SIDE * SIDE)).reshape(SIDE, SIDE)
                        if squeeze < 1:
                            px = px[:, np.clip(((np.arange(SIDE) - 3.5) / squeeze + 3.5).round().astype(int), 0, SIDE - 1)]
                        frames.append(px if smooth else np.roll(px, rng.integers(-1, 2, 2), (0, 1)))
                        sound.append(tones[p] * (0.6 + 0.4 * gain) + 0.4 * rng.normal(size=MEL))
                letters = [SPELLINGS.index(c) + 1 for _, _, s in picked for c in s]
                rows.append((vec, [w for w, _, _ in picked], phones, letters, np.array(frames, np.float32).tobytes(), np.array(sound, np.float32).tobytes()))
            yield pd.DataFrame(rows, columns=["clip_id", "words", "phones", "letters", "px", "mel"])

    keyed = e.select("vec_id", "embedding", hash8(F.lit("clip"), F.col("vec_id").cast("string")).alias("h"))
    clips = keyed.mapInPandas(render, "clip_id long, words array<string>, phones array<int>, letters array<int>, px binary, mel binary")
    return clips.withColumn("held_out", hash8(F.lit("split"), F.col("clip_id").cast("string")) % 3 == 0)


@dataclass(frozen=True)
class Variant:
    """One network: temporal module, unit, input, and whether it attends instead of aligning."""

    name: str
    temporal: str = "lstm"
    norm: bool = True
    drop: float = 0.0
    filters: tuple[int, ...] = (4, 6)
    hidden: int = 14
    k_t: int = 3
    unit: str = "phones"
    source: str = "px"
    attends: bool = False
    steps: int = 160


METHODS = (
    Variant("audio_ph", "gru", source="mel", filters=(), hidden=16),
    Variant("small_ch", "gru", norm=False, drop=0.3, filters=(2,), hidden=4, unit="letters"),
    Variant("small_ph", "gru", norm=False, drop=0.3, filters=(2,), hidden=4),
    Variant("attn_ch", filters=(4, 6), hidden=16, unit="letters", attends=True),
    Variant("large_gru_ph", "gru", norm=False, drop=0.3),
    Variant("fullconv_ph", "dilated", hidden=24),
    Variant("full_ph"),
)
#: What the design alternatives leave out, one at a time.
ABLATIONS = (Variant("full_ph"), Variant("spatial_only", k_t=1), Variant("dropout_no_norm", norm=False, drop=0.3), Variant("gru", "gru"))


def symbols(v: Variant) -> int:
    return 1 + (PHONES if v.unit == "phones" else len(SPELLINGS))


def start(v: Variant, seed: int = 0) -> N.Net:
    more = dict(temporal=v.temporal, norm=v.norm, drop=v.drop, seed=seed, dilations=(1, 2, 4))
    if v.source == "mel":
        return N.Net.start(1, MEL, [], v.hidden, 1, symbols(v), front=(16, 16), **more)
    return N.Net.start(SIDE, 1, list(v.filters), v.hidden, 1, symbols(v), k_t=v.k_t, **more)


def clip_of(v: Variant, px: bytes, mel: bytes) -> np.ndarray:
    x = np.frombuffer(mel, np.float32).reshape(-1, 1, 1, MEL) if v.source == "mel" else np.frombuffer(px, np.float32).reshape(-1, SIDE, SIDE, 1)
    return x.astype(float)


def fit(v: Variant, clips: list[tuple[np.ndarray, list[int]]], batch: int = 12, rate: float = 0.02, seed: int = 0) -> tuple[N.Net, N.AttnDecoder | None, list[float]]:
    """Adaptive steps over batches in turn; the loss is CTC's, or for attention the letters' given those before."""
    net, rng = start(v, seed), np.random.default_rng(seed)
    attn = None
    if v.attends:
        shape = net.forward(clips[0][0], encode=True)[0].shape[1]
        attn = N.AttnDecoder.start(shape, v.hidden, symbols(v), seed)
    params = {**net.params, **({f"attn.{k}": p for k, p in attn.params.items()} if attn else {})}
    first, second = ({k: np.zeros_like(p) for k, p in params.items()} for _ in range(2))
    losses = []
    for step in range(1, v.steps + 1):
        total, loss = {}, 0.0
        for i in rng.choice(len(clips), min(batch, len(clips)), replace=False):
            x, label = clips[i]
            if attn:
                frames, back = net.forward(x, rng, encode=True)
                value, grads, of_frames = attn.loss(frames, label)
                grads = {f"attn.{k}": g for k, g in grads.items()} | back(of_frames)[1]
            else:
                value, grads = net.loss(x, label, rng)
            loss += value
            for k, g in grads.items():
                total[k] = total.get(k, 0) + g
        for k, g in total.items():
            g = g / batch
            first[k] = 0.9 * first[k] + 0.1 * g
            second[k] = 0.99 * second[k] + 0.01 * g * g
            params[k] -= rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-8)
        losses.append(loss / batch)
    return net, attn, losses


def words_of(v: Variant, out: np.ndarray | list[int], decoder: T.Decoder) -> list[str]:
    """A lattice's words by the decoder; a letter string's by the spellings that it is made of."""
    if isinstance(out, list):
        text = "".join(SPELLINGS[k - 1] for k in out)
        spelled = {s: w for w, _, s in lexicon()}
        return [spelled[text[i : i + 2]] for i in range(0, len(text) - 1, 2) if text[i : i + 2] in spelled]
    frames = [{"_" if k == 0 else chr(96 + k): float(p) for k, p in enumerate(row) if p > -12} for row in out]
    return list(decoder.decode(frames)[0][0])


def decoder_of(v: Variant, train: list[list[str]]) -> T.Decoder:
    """Lexicon of the words by phones or spelling, and a bigram of training's word pairs with one added to each count."""
    sound = {w: "".join(chr(96 + p) for p in (ps if v.unit == "phones" else [SPELLINGS.index(c) + 1 for c in s])) for w, ps, s in lexicon()}
    lm: dict[tuple[str, ...], float] = {}
    for w in sound:
        lm[(w,)] = math.log((1 + sum(t[0] == w for t in train)) / (len(train) + len(sound)))
        n = sum(t[0] == w for t in train)
        for z in sound:
            lm[w, z] = math.log((1 + sum(t[0] == w and t[1] == z for t in train)) / (n + len(sound)))
    return T.Decoder(sorted(sound.items()), lm, {}, order=2, beam=14.0, max_active=60, weight=0.5)


def rates(spark: SparkSession, sf_dir: str, variants: tuple[Variant, ...] = METHODS, max_clips: int = MAX_CLIPS, smooth: bool = True, angle: float = 0.0) -> DataFrame:
    """method, params, loss_first, loss_last, n, unit_rate, word_rate of each variant on all held-out clips.

    Training: the ``max_clips`` rows that aren't held out with the smallest hash, one variant a task. Judging: every
    held-out clip by every network, in one pass over the clips.
    """
    clips = rendered(spark, sf_dir, smooth, angle)
    sample = clips.where("NOT held_out").orderBy(hash8(F.lit("pick"), F.col("clip_id").cast("string")), "clip_id").limit(max_clips)
    rows = [(list(r.words), list(r.phones), list(r.letters), bytes(r.px), bytes(r.mel)) for r in sample.toLocalIterator()]
    if not rows:
        raise ValueError("no clips to learn from")
    sent = spark.sparkContext.broadcast(rows)  # max_clips clips of a fixed size
    known = {v.name: v for v in variants}

    def learn(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import pickle

        for b in batches:
            for name in b["method"]:
                v = known[name]
                net, attn, losses = fit(v, [(clip_of(v, px, mel), phones if v.unit == "phones" else letters) for _, phones, letters, px, mel in sent.value])
                size = sum(p.size for p in net.params.values()) + (sum(p.size for p in attn.params.values()) if attn else 0)
                yield pd.DataFrame({"method": [name], "params": [size], "loss_first": [float(np.mean(losses[:8]))], "loss_last": [float(np.mean(losses[-8:]))], "model": [pickle.dumps((net.params, attn.params if attn else None))]})

    jobs = spark.createDataFrame([(n,) for n in known], "method string").repartition(len(known), "method")
    fitted = jobs.mapInPandas(learn, "method string, params long, loss_first double, loss_last double, model binary").collect()  # a row a method
    import pickle

    models = spark.sparkContext.broadcast({r.method: pickle.loads(r.model) for r in fitted})
    decoders = {n: decoder_of(v, [r[0] for r in rows]) for n, v in known.items()}

    def judge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        nets = {}
        for n, (params, attn) in models.value.items():
            net = start(known[n])
            net.params = params
            nets[n] = (net, N.AttnDecoder(attn) if attn else None)
        for b in batches:
            out = []
            for words, phones, letters, px, mel in zip(b["words"], b["phones"], b["letters"], b["px"], b["mel"]):
                for n, (net, attn) in nets.items():
                    v = known[n]
                    truth = [int(i) for i in (phones if v.unit == "phones" else letters)]
                    if attn:
                        heard = attn.beam(net.forward(clip_of(v, px, mel), encode=True)[0], most=len(truth) + 3)[0][0]
                        said = words_of(v, heard, decoders[n])
                    else:
                        logits = net.forward(clip_of(v, px, mel))[0]
                        logp = logits - np.logaddexp.reduce(logits, axis=1, keepdims=True)
                        heard = list(ctc.collapse([int(i) for i in logp.argmax(axis=1)]))
                        said = words_of(v, logp, decoders[n])
                    miss = lambda a, c: sum(o != "match" for o, _, _ in align(a, c))
                    out.append((n, miss(truth, heard), len(truth), miss(list(words), said), len(words)))
            yield pd.DataFrame(out, columns=["method", "u_edits", "u_len", "w_edits", "w_len"])

    judged = clips.where("held_out").select("words", "phones", "letters", "px", "mel").mapInPandas(judge, "method string, u_edits long, u_len long, w_edits long, w_len long")
    found = judged.groupBy("method").agg(F.count(F.lit(1)).alias("n"), (F.sum("u_edits") / F.sum("u_len")).alias("unit_rate"), (F.sum("w_edits") / F.sum("w_len")).alias("word_rate"))
    about = spark.createDataFrame([(r.method, r.params, r.loss_first, r.loss_last) for r in fitted], "method string, params long, loss_first double, loss_last double")
    return about.join(found, "method").select("method", "params", F.round("loss_first", 3).alias("loss_first"), F.round("loss_last", 3).alias("loss_last"), "n", F.round("unit_rate", 4).alias("unit_rate"), F.round("word_rate", 4).alias("word_rate"))
