import random

import numpy as np
from mfaccel.llm import toxicity

MARKERS = ["foul", "trash", "stupid", "pathetic"]


def test_grades_count_marker_words_of_any_length(spark, monkeypatch):
    dice, rows, counts = random.Random(5), [], []
    for k in range(800):
        words = [f"w{dice.randrange(80)}" for _ in range(dice.randrange(20, 60))]
        counts.append(dice.randrange(1, 7) if k % 4 == 0 else 0)
        for _ in range(counts[-1]):
            words.insert(dice.randrange(len(words)), dice.choice(MARKERS))
        rows.append((k, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(n > 0)) for k, n in enumerate(counts)], "doc_id long, toxic int")
    given, fit = [], toxicity.Ordinal._fit
    monkeypatch.setattr(toxicity.Ordinal, "_fit", lambda self, x, grades: (given.append(grades), fit(self, x, grades))[1])
    model = toxicity.fit(docs, labels)
    want = [0 if not n else 1 if n < 2 else 2 if n < 4 else 3 for n in counts]
    assert np.bincount(given[0]).tolist() == np.bincount(want).tolist()
    have = {r.doc_id: r for r in toxicity.score(docs, model).collect()}
    for grade in (0, 1, 2, 3):
        assert np.mean([have[k].grade == grade for k in range(800) if want[k] == grade]) > 0.7
