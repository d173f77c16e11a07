"""Disguised words of few letters, stretched ones and long tokens."""

import random

import numpy as np
from pyspark import cloudpickle

import factlake
from factlake.llm import language, toxicity


def letters(words):
    rnd = random.Random(0)
    clean = " ".join(rnd.choice(words.split()) for _ in range(3000))
    codes = np.bincount(language.grams(clean)[0], minlength=language.GRAMS).astype(float).reshape(64, 64, 64)
    return -np.log((codes + 1e-3) / (codes.sum(2, keepdims=True) + 0.064))


def test_decoding_of_heavy_disguise():
    log3 = letters("pathetic worthless idiot loser stupid riding into town under the moon and studio patio tools")
    for token, word in {"p47h371c": "pathetic", "w0r7h1355": "worthless", "1d107": "idiot", "1053r": "loser", "st" + "u" * 90 + "p1d": "stupid"}.items():
        assert word in toxicity.readings(token, log3), token
    assert toxicity.readings("3.14", log3) == [] and toxicity.decode("x" * 200_000, log3)
    long = toxicity.readings("un" + "d3rthemoonandstudio" * 5, log3)
    assert long and all(len(x) > 60 for x in long)


def test_words_are_cut_in_the_lattice():
    log3 = letters("you are a such an idiot moron scum loser stupid riding into town under the moon and studio patio tools what he said about it")
    runs = {"a m o r o n": "a moron", "y o u i d i o t": "you idiot", "i  d  i  o  t": "idiot", "y o u   a r e   a   l o s e r": "you are a loser", "$ c u m": "scum", "i.d.1.o.t": "idiot"}
    for run, text in runs.items():
        assert text in toxicity.decode(run, log3), (run, toxicity.decode(run, log3))
        held = [m for m in toxicity.tokens(f"they said {run} there") if m == run]
        assert held, run


def test_the_decoder_decides(spark, monkeypatch):
    """Disguised toxic words are caught by what the decoder restores, and only by that; clean texts stay clean."""
    rnd = random.Random(21)
    clean = "riding into town under the moon and studio patio tools what he said about it when they came home late to cook some rice for all who were there".split()
    toxic = "idiot moron loser stupid pathetic worthless".split()
    line = lambda n: [rnd.choice(clean) for _ in range(n)]
    texts, marks = [], []
    for i in range(400):
        w = line(30)
        if i % 4 == 0:
            w.insert(rnd.randrange(30), rnd.choice(toxic))
        texts.append(" ".join(w)), marks.append(int(i % 4 == 0))
    leet = str.maketrans("oiesat", "013547")
    hide = [lambda w: w.translate(leet), lambda w: " ".join(w), lambda w: "-".join(w), lambda w: "  ".join(w), lambda w: w[:2] + w[2] * 4 + w[3:], lambda w: w[:3] + " " + w[3:], lambda w: ".".join(w.translate(leet))]
    hidden = [" ".join(line(10)) + f" {h(w)} " + " ".join(line(10)) for w in toxic for h in hide]
    plain = [" ".join(line(30)) for _ in range(100)]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    model = toxicity.fit(d, d, spark.createDataFrame(list(enumerate(marks)), "doc_id long, toxic int"))
    new = spark.createDataFrame(list(enumerate(hidden + plain)), "doc_id long, text string").repartition(4)

    def caught():
        got = {r["doc_id"]: r["predicted"] for r in toxicity.score(new, model).collect()}
        return sum(got[i] for i in range(len(hidden))) / len(hidden), sum(got[len(hidden) + i] for i in range(100))

    share, wrong = caught()
    assert share >= 0.9 and wrong == 0, share
    monkeypatch.setattr(toxicity, "decode", lambda *a, **k: [])
    cloudpickle.register_pickle_by_value(factlake)  # so that workers see the decoder switched off
    try:
        assert caught()[0] <= 0.1
    finally:
        cloudpickle.unregister_pickle_by_value(factlake)
