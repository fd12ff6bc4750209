"""Misspelled and quoted hits move the score, and the layout of the rows does not."""

import random

import numpy as np

from kgtrail.llm import op10_toxicity
from kgtrail.llm.kernels.lexicon import Lexicon, fit


def corpus(spark, parts):
    rng = random.Random(11)
    plain = [f"calm{i}" for i in range(300)] + ["ideot"]
    rows, labels = [], []
    for i in range(900):
        words = [rng.choice(plain) for _ in range(30)]
        toxic = i % 3 == 0
        if toxic:
            words[rng.randrange(30)] = rng.choice(["vermin", "idiot", "wretch"])
        elif i % 50 == 1:
            words[3] = "ideot"
        rows.append((i, " ".join(words)))
        labels.append((i, 0, int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(parts)
    return docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int").repartition(parts)


def test_misspelled_and_quoted_hits_count_less_but_count(spark):
    model = op10_toxicity.learn(*corpus(spark, 3))
    assert {"vermin", "idiot", "wretch"} <= set(model.terms) and "ideot" in model.innocent
    calm = "calm1 calm2 calm3 calm4 calm5 calm6"
    texts = [f"{calm} you vermin {calm}", f"{calm} you vermln {calm}", f'{calm} he said "you vermin" again {calm}', f"{calm} you calm7 {calm}", f"{calm} you ideot {calm}"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    plain, wrong, told, none, innocent = (r["score"] for r in sorted(op10_toxicity.score(docs, model).collect()))
    assert plain > wrong > told > none and abs(innocent - none) < 1e-9
    assert plain > 0.5 > told


def test_model_does_not_depend_on_the_layout(spark):
    one, other = op10_toxicity.learn(*corpus(spark, 2)), op10_toxicity.learn(*corpus(spark, 7))
    assert one.terms == other.terms and one.innocent == other.innocent
    assert np.allclose(one.weights, other.weights, atol=1e-9)


def test_parts_of_a_plain_hit_keep_their_order():
    rng = np.random.default_rng(1)
    y = np.repeat([0.0, 1.0], 200)
    x = np.column_stack([y * rng.random(400), (1 - y) * rng.random(400), np.zeros(400), rng.random(400)])
    w = fit(x, y)  # here misspelled hits speak against: the parts stay as they were before
    assert 0 < w[3] < w[2] < w[1] and np.isclose(w[2], 0.6 * w[1])


def test_innocent_words_are_no_misspellings():
    assert Lexicon({"idiot": 1.0}, ["ideot"]).match("ideot") is None
    assert Lexicon({"idiot": 1.0}, ["idiot"]).match("idiot") == ("idiot", 0)
