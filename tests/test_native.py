"""The search in Spark's own processes against the search by arrays."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from clipflow.operators import fst, native
from tests.test_more import toy_decoder


def random_decoder(rng, order):
    words = sorted({"".join(rng.choice(list("xyzuv"), rng.integers(1, 5))) for _ in range(60)})
    lexicon = [(f"{w}{i}", w) for w in words for i in range(1 + (len(w) == 2))]
    names = [w for w, _ in lexicon]
    lm = {(w,): -5 * rng.random() for w in [*names, "</s>"]}
    for n in range(2, order + 1):
        lm |= {(*(str(x) for x in rng.choice(names, n - 1)), str(rng.choice([*names, "</s>"]))): -4 * rng.random() for _ in range(400)}
    lm |= {("<s>", str(w)): -rng.random() for w in rng.choice(names, 20)} if order > 1 else {}
    back = {k[:-1]: 0.5 - rng.random() for k in lm if len(k) > 1}
    return fst.Decoder(lexicon, lm, back, order=order, beam=7.0, max_active=40, weight=0.7)


def shared(spark, decoder):
    send = lambda x: fst.Pieces(spark.sparkContext.broadcast((type(x), x.__dict__)), {})
    model = fst.WordModel.of(decoder)
    return fst.Shared(send(fst.Tree(decoder.tree, decoder.words, model.vocabulary)), send(model), decoder.beam, decoder.max_active, decoder.weight)


def both(spark, decoder, clips):
    df = spark.createDataFrame(list(enumerate(clips)), "utt long, rows array<struct<t int, sym string, p double>>").repartition(3)
    graph = shared(spark, decoder)
    fast = native.decode(df, graph)
    assert "Python" not in fast._jdf.queryExecution().executedPlan().toString()
    return [{r.utt: (r.words, r.score) for r in x.collect()} for x in (fst.clip_decode(df, graph), fast)]


@pytest.mark.parametrize("order", (1, 2, 4))
def test_the_native_search_equals_the_search_by_arrays(spark, order):
    rng = np.random.default_rng(order)
    for decoder in (toy_decoder(rng, order), random_decoder(rng, order)):
        clips = [[(t + 3, str(s), float(p)) for t in range(int(rng.integers(0, 40))) for s, p in zip(rng.choice(list("xyzuv_-"), 5), rng.dirichlet(np.ones(5)))] for _ in range(120)]
        clips[:2] = [(0, "-", 1.0)], []  # nothing that goes on; no frames
        want, got = both(spark, decoder, clips)
        assert want.keys() == got.keys() and all(want[u][0] == got[u][0] for u in want)
        assert [got[u][1] for u in want] == pytest.approx([x for _, x in want.values()])
        assert got[0] == ([], -math.inf) and got[1] == ([], 0.0)


def test_candidates_beyond_the_room_and_more_active_ones_than_allowed(spark):
    rng = np.random.default_rng(9)
    lexicon = [(f"w{i}", "".join(rng.choice(list("abcdefgh"), 3))) for i in range(9000)]
    decoder = fst.Decoder(lexicon, {(w,): -rng.random() for w, _ in lexicon} | {(a, b): -rng.random() for (a, _), (b, _) in zip(lexicon, lexicon[1:])}, {}, order=2, beam=1e9, max_active=20_000)
    clips = [[(t, s, 0.1 + 0.01 * t * i) for t in range(9) for i, s in enumerate("abcdefgh")]]
    for most in (20_000, 300):
        decoder.max_active = most
        want, got = both(spark, decoder, clips)
        assert got[0][1] == pytest.approx(want[0][1]) and (most == 300 or got[0][0] == want[0][0])
