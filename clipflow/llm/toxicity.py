"""Toxicity by multiple-instance learning.

A document is a bag of sentences. A sentence's probability is logistic in the weights of its words and word beginnings;
the document's is the noisy-or of its sentences, so labels of whole documents train the sentence model, and the
sentence scores say where the offence is.

Training reads a bounded sample: at most ``max_toxic`` and ``max_clean`` labelled rows, those with the smallest hash
of their id. Scores read every word of every text; nothing but the text enters them.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipflow.llm.common import ship, utf8

#: Sentence ends become line feeds, A-Z become a-z, other ASCII but digits becomes a space.
_SENTENCES = bytes(
    10 if chr(b) in ".!?\n" else b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256)
)
#: Bytes of a word's beginnings that are features beside the word.
HEADS = (4, 5, 6)
MAX_TOXIC, MAX_CLEAN = 2500, 5000
THRESHOLD = 0.7
MEMO = 300_000  # words whose weights a worker remembers


def sentences(text: bytes) -> list[list[bytes]]:
    """Words by sentence; sentences without words are left out."""
    return [w for s in text.translate(_SENTENCES).split(b"\n") if (w := s.split())]


def features(word: bytes) -> list[bytes]:
    return [word, *(b"^" + word[:n] for n in HEADS if len(word) > n)]


@dataclass
class Model:
    bias: float
    weights: dict[bytes, float]
    memo: dict[bytes, float] = field(default_factory=dict, repr=False)

    def word(self, word: bytes) -> float:
        if (known := self.memo.get(word)) is None:
            if len(self.memo) >= MEMO:
                self.memo.clear()
            known = self.memo[word] = sum(self.weights.get(f, 0.0) for f in features(word))
        return known

    def sentence_scores(self, bag: list[list[bytes]]) -> np.ndarray:
        z = np.array([sum(map(self.word, s)) for s in bag]) + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))

    def score(self, text: bytes) -> float:
        """1 - product of (1 - sentence score); an empty text has the score of one empty sentence."""
        p = self.sentence_scores(sentences(text) or [[]])
        return float(-np.expm1(np.log1p(-np.minimum(p, 1 - 1e-12)).sum()))


def fit(rows: Iterator[tuple[bytes, int]], epochs: int = 60, rate: float = 0.5, sparsity: float = 3e-4, min_docs: int = 4, toxic_share: float = 0.25) -> Model:
    """Full-batch adaptive gradient steps on the noisy-or likelihood; label 1 weighs ``toxic_share`` in all.

    ``sparsity`` is the price of a weight: words that a few toxic documents share by chance stay at zero.
    """
    types: dict[bytes, int] = {}
    tokens, lengths, bags, labels, seen_in = [], [], [], [], []
    for text, label in rows:
        bag = sentences(text) or [[]]
        own = [np.fromiter((types.setdefault(w, len(types)) for w in s), np.int32, len(s)) for s in bag]
        tokens += own
        lengths += [len(s) for s in bag]
        bags.append(len(bag))
        labels.append(label)
        seen_in.append(np.unique(np.concatenate(own)))
    if not labels or len(set(labels)) < 2:  # nothing to tell apart: the share of label 1
        share = min(max(np.mean(labels), 1e-6), 1 - 1e-6) if labels else 1e-6
        return Model(float(np.log(share / (1 - share))), {})
    names: dict[bytes, int] = {}
    often = np.bincount(np.concatenate(seen_in), minlength=len(types)) >= min_docs  # rarer words are no feature themselves
    of_type = [[names.setdefault(f, len(names)) for f in features(w)[0 if o else 1 :]] for w, o in zip(types, often)]
    feature = np.concatenate([np.array(x, np.int32) for x in of_type])
    owner = np.repeat(np.arange(len(of_type), dtype=np.int32), [len(x) for x in of_type])
    documents = np.bincount(feature, weights=np.bincount(np.concatenate(seen_in), minlength=len(types))[owner], minlength=len(names))
    usable = documents >= min_docs
    keep = usable[feature]
    feature, owner, of_type = feature[keep], owner[keep], None

    token, lengths, bags, y = np.concatenate(tokens), np.array(lengths), np.array(bags), np.array(labels, float)
    sentence_of = np.repeat(np.arange(len(lengths), dtype=np.int32), lengths)
    bag_of = np.repeat(np.arange(len(bags)), bags)
    share = np.where(y == 1, toxic_share / max(y.sum(), 1), (1 - toxic_share) / max((1 - y).sum(), 1))
    w, b = np.zeros(len(names)), -8.0
    gw, gb = np.full(len(names), 1e-8), 1e-8
    for _ in range(epochs):
        of_word = np.bincount(owner, weights=w[feature], minlength=len(types))
        z = np.bincount(sentence_of, weights=of_word[token], minlength=len(lengths)) + b
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        miss = np.bincount(bag_of, weights=np.log1p(-np.minimum(p, 1 - 1e-9)), minlength=len(bags))  # log of 1 - score
        score = np.clip(-np.expm1(miss), 1e-9, 1)
        slope = (share * (y - score) / score)[bag_of] * p
        d_word = np.bincount(token, weights=slope[sentence_of], minlength=len(types))
        d = np.bincount(feature, weights=d_word[owner], minlength=len(names))
        d_b = slope.sum()
        gw += d * d
        gb += d_b * d_b
        step = rate / np.sqrt(gw)
        w += step * d
        w = np.sign(w) * np.maximum(np.abs(w) - step * sparsity, 0)
        b += rate * d_b / np.sqrt(gb)
    return Model(float(b), {n: float(w[i]) for n, i in names.items() if abs(w[i]) > 1e-3 and usable[i]})


def remainder(id_col: str) -> Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 3


def learn(docs: DataFrame, labels: DataFrame, max_toxic: int = MAX_TOXIC, max_clean: int = MAX_CLEAN) -> Model:
    """A model from labelled rows that aren't held out. Null labels, ids and rows without a document teach nothing.

    At most ``max_toxic`` and ``max_clean`` rows reach the driver: of rows that repeat a labelled id, one text, that with
    the smallest hash; of labels that repeat an id, one. Empty tables give a model that finds nothing toxic.
    """
    ship(docs.sparkSession)
    usable = labels.where(remainder("doc_id") != 1).where("toxic IN (0, 1)").select("doc_id", "toxic").dropDuplicates(["doc_id"])
    picked = None
    for label, most in ((1, max_toxic), (0, max_clean)):
        some = usable.where(F.col("toxic") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
        picked = some if picked is None else picked.unionByName(some)
    # at most max_toxic + max_clean ids of 8 bytes: that bound allows the broadcast
    sample = docs.select("doc_id", utf8("text").alias("text")).join(F.broadcast(picked), "doc_id")
    sample = sample.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text", "toxic")).alias("r"))
    return fit((bytes(r.text), r.toxic) for r in sample.orderBy("doc_id").select("r.text", "r.toxic").toLocalIterator())


def score(docs: DataFrame, model: Model, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, score, predicted, worst (its highest sentence's number, null if it has none).

    Null and empty texts get the score of one empty sentence. Rows that repeat an id are scored each. An empty table
    gives no rows. Columns beside id and text are not read.
    """
    ship(docs.sparkSession)
    cast = docs.sparkSession.sparkContext.broadcast(model)  # at most the vocabulary of the bounded sample

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = cast.value
        for batch in batches:
            out: tuple[list, ...] = ([], [], [])
            for text in batch.column(1):
                bag = sentences(text.as_py())
                p = m.sentence_scores(bag or [[]])
                s = float(-np.expm1(np.log1p(-np.minimum(p, 1 - 1e-12)).sum()))
                out[0].append(s)
                out[1].append(int(s >= threshold))
                out[2].append(int(p.argmax()) if bag else None)
            kinds = (pa.float64(), pa.int32(), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(o, k) for o, k in zip(out, kinds))], names=["doc_id", "score", "predicted", "worst"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text")).mapInArrow(run, "doc_id long, score double, predicted int, worst int")


def reject(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score below the threshold, with all their columns, judged where they stand.

    Null and empty texts score as one empty sentence. Rows that repeat are judged each; an empty table stays empty; other
    columns may have any names.
    """
    ship(docs.sparkSession)
    cast = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = cast.value
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text"))
            yield batch.filter(pa.array([m.score((t.as_py() or "").encode()) < threshold for t in texts], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
