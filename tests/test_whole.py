"""Word models that keep every n-gram and every word."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from clipflow.operators import baselines as B
from clipflow.operators import fst, grams


@pytest.mark.parametrize("order", (2, 3, 5))
def test_the_whole_model_scores_as_the_dictionaries(spark, monkeypatch, order):
    monkeypatch.setattr(grams, "RANGE", 40)
    monkeypatch.setattr(grams, "TOKENS", 50)
    rng = np.random.default_rng(order)
    lines = [x.split() for x in sorted({" ".join(rng.choice(list("abcdefgh"), rng.integers(1, 9), p=[0.3, 0.2, 0.1, 0.1, 0.1, 0.1, 0.05, 0.05])) for _ in range(200)})]
    train = spark.createDataFrame([(x,) for x in lines], "words array<string>").repartition(3)
    vocabulary = spark.createDataFrame([(c, c) for c in "abcdefgh"], "w string, phones string")
    lm, back = B.language_model(train, vocabulary, order)
    strings = fst.Decoder([(c, c) for c in "abcdefgh"], lm, back, order=order)
    want, model = fst.WordModel.of(strings), B.word_model(train, vocabulary, order)
    assert (model.n_states, len(model.lm_key), model.start) == (want.n_states, len(want.lm_key), want.start)
    for name in ("lm_key", "lm_to", "back_to"):
        assert (getattr(model, name) == getattr(want, name)).all()
    assert np.allclose(model.lm_p, want.lm_p) and np.allclose(model.back, np.maximum(want.back, np.log(1e-12)))  # what rounding leaves is none
    assert (model.first == np.searchsorted(model.lm_key, np.arange(model.n_states + 1) * model.v)).all()


def test_no_ngram_and_no_word_is_cut(spark, monkeypatch):
    """A model was cut to its frequent n-grams, a vocabulary to its frequent words."""
    assert not hasattr(B, "MAX_GRAMS") and not hasattr(B, "MAX_WORDS")
    monkeypatch.setattr(B.M, "prune", lambda *_: pytest.fail("pruned"))
    train = spark.range(3000).select(F.expr("array('w' || id, 'w' || (id * 7 % 3000), 'w' || (id + 1))").alias("words"))
    found = B.vocabulary_of(train)
    assert found.count() == 3001
    (graph,) = B.graphs(train, found, (B.Method("x", 0.0, order=3),))
    model = graph.value.word_scores.__self__
    assert len(model.lm_key) == 3002 + train.selectExpr("explode(array('<s> ' || words[0], words[0] || ' ' || words[1], words[1] || ' ' || words[2], words[2] || ' </s>')) AS g").distinct().count() + \
        train.selectExpr("explode(array('<s> ' || words[0] || ' ' || words[1], words[0] || ' ' || words[1] || ' ' || words[2], words[1] || ' ' || words[2] || ' </s>')) AS g").distinct().count()


def test_a_tree_made_of_arrays_is_the_tree_of_dictionaries():
    rng = np.random.default_rng(1)
    lexicon = [(f"w{i:03}", "".join(rng.choice(list("abc_"[:3]), rng.integers(0, 6)))) for i in range(300)]
    names = [w for w, _ in lexicon]
    want, got = fst.Tree(*fst.prefix_tree(lexicon), names), fst.Tree.of(np.arange(300), [s for _, s in lexicon])
    assert (got.n_nodes, got.symbols) == (want.n_nodes, want.symbols)

    def words(tree, node, said):
        out = {said: sorted(tree.word[tree.word_first[node] : tree.word_first[node + 1]].tolist())}
        for c, s in tree.symbols.items():
            to, hit = tree.step(np.array([node]), np.array([s]))
            if hit[0]:
                out |= words(tree, int(to[0]), said + c)
        return out

    assert words(got, 0, "") == words(want, 0, "")
    assert fst.Tree.of(np.zeros(0, int), []).n_nodes == 1


def test_streamed_broadcasts_are_pickles_and_mapped(spark):
    rows = spark.createDataFrame([("a", 8, bytearray(np.array([2, 3]).tobytes())), ("a", 0, bytearray(np.array([1]).tobytes())), ("b", 0, bytearray(8))], "name string, at long, data binary")
    array = fst.Mapped.of(rows, "a", "<i8", 4, [("a", 3, np.array([9]))])
    assert array.value.tolist() == [1, 2, 3, 9] and np.frombuffer(array.cast.value, "<i8").tolist() == [1, 2, 3, 9]
    assert [r[0] for r in spark.range(1).rdd.map(lambda _: (array.value.tolist(), array.value.flags.aligned)).collect()] == [[1, 2, 3, 9]]
