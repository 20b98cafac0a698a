import random

import numpy as np
from pyspark.sql import functions as F

from levelsort.llm import toxicity as tx

LEXICON, GRAMMAR = tx.Lexicon({}, {}), tx.Grammar()


def score(text, model=None):
    model = model or tx.Model({}, {}, list(tx.PRIOR), tx.PRIOR_BIAS)
    return float(model.scores([tx.channels(text, LEXICON, GRAMMAR)])[0])


def by_hand(clause):
    """The five machines run side by side, each with its own state, without the product."""
    own, out = [0] * len(GRAMMAR.parts), [0.0] * len(tx.CHANNELS)
    found = False
    for cls, weight in clause:
        marks = set()
        for i, m in enumerate(GRAMMAR.parts):
            own[i], more = m.step(own[i], cls)
            marks |= more
        if marks & {"insult", "threat"}:
            found = True
            channel = tx.NEGATED if "negated" in marks else tx.REPORTED if "reported" in marks else tx.PLAIN if "insult" in marks else tx.THREATENED
            factor = tx.BARE if channel == tx.THREATENED and "sure" not in marks else 1.0
            out[channel] += factor * (weight or tx.THREAT_WEIGHT)
    if not found:
        return None
    if own[2]:
        out[tx.TARGETED] = out[tx.PLAIN]
    return out


def test_composition_equals_its_parts():
    rnd = random.Random(2)
    for _ in range(3000):
        clause = [(c, 4.0 if c == tx.INSULT else 0.0) for c in (rnd.randrange(tx.CLASSES) for _ in range(rnd.randint(0, 12)))]
        assert GRAMMAR.run(clause) == by_hand(clause)


def test_clauses_not_words():
    order = [score(t) for t in ("you are not an idiot.", "he said: you are an idiot.", "what an idiot.", "you are an idiot.")]
    assert order[0] <= order[1] < order[2] < order[3]
    assert score("I will kill you.") > 0.5 > score("")
    assert score("the weather will kill the harvest") == score("") == score(None)
    assert score("they will not attack you") < score("they will attack you")
    assert score("they attack you") < score("they will attack you")
    assert score("you idiot") < score("you idiot. you moron.")


def test_fitted_weights_keep_their_order():
    rnd = random.Random(1)
    rows, y = [], []
    for _ in range(400):  # no label shows a threat, and negated insults are all clean
        toxic = rnd.random() < 0.5
        rows.append([4.0 * toxic, 0.0, 0.0 if toxic else 4.0, 0.0, 0.0, 1.0])
        y.append(int(toxic))
    w, bias = tx.fit_channels(rows, y)
    assert min(w) >= 0 and w[tx.NEGATED] <= w[tx.REPORTED] <= w[tx.PLAIN] <= w[tx.THREATENED] and bias < 0
    p = tx.Model({}, {}, w, bias).scores(rows)
    assert ((p >= 0.5) == np.array(y, bool)).all()


def labelled(spark, n=240):
    rnd = random.Random(7)
    plain = [f"word{i}" for i in range(300)]
    docs, labels = [], []
    for i in range(n):
        words = [rnd.choice(plain) for _ in range(30)]
        if i % 3 == 0:
            words[rnd.randrange(30)] = rnd.choice(["blarg", "snorf"])
        docs.append((i, " ".join(words), "x"))
        labels.append((i, int(i % 3 == 0)))
    docs += [(n, None, "x"), (n + 1, "", "x"), (None, "blarg", "x"), (0, docs[0][1], "x")]
    labels += [(None, 1), (5, None), (0, 0), (n, 0)]
    return spark.createDataFrame(docs, "doc_id bigint, text string, score string"), spark.createDataFrame(labels, "doc_id bigint, toxic int")


def test_train_and_score_tables(spark):
    docs, labels = labelled(spark)
    model = tx.train(docs, labels)
    assert {"blarg", "snorf"} <= set(model.words)
    out = tx.score(docs, model).collect()
    assert len(out) == docs.count()
    truth = {i: int(i % 3 == 0) for i in range(240)}
    held = [r for r in out if r["held_out"] and r["doc_id"] is not None and r["doc_id"] < 240]
    assert held and all(r["predicted"] == truth[r["doc_id"]] for r in held)
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in out)
    empty = {r["score"] for r in out if r["doc_id"] in (240, 241)}
    assert len(empty) == 1
    kept = tx.drop_toxic(docs, model)
    assert kept.columns == docs.columns and kept.where("doc_id = 0").count() == 0 and kept.where("doc_id = 240").count() == 1
    assert tx.score(docs.limit(0), model).count() == 0


def test_held_out_labels_are_not_read(spark):
    docs, labels = labelled(spark)
    flipped = labels.withColumn("toxic", F.when(tx.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    one, two = tx.train(docs, labels), tx.train(docs, flipped)
    assert one.words == two.words and np.allclose(one.weights, two.weights)


def test_without_labels(spark):
    docs, labels = labelled(spark)
    model = tx.train(docs, labels.limit(0))
    assert model.words == {} and model.weights == list(tx.PRIOR)
    assert tx.train(docs.limit(0), labels).words == {}
