"""The licence scan against a plain numpy version, wrapped notices, unseen licences, and ids that are null or repeated."""

import random

import numpy as np
from mfaccel.llm import license_scan
from mfaccel.llm.common import table
from mfaccel.llm.license_texts import OTHERS, TEMPLATES


def judged(text):
    """(family, probability, likeness, confirmed) of a unit by the definition."""
    weights, bias, heat = license_scan.model()
    grams = license_scan.grams_of(license_scan.words_of(text))
    z = (np.array(bias) + sum((np.array(weights[g]) for g in grams if g in weights), np.zeros(len(bias)))) / heat
    p = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
    k, likeness = int(p.argmax()), 0.0
    for t in {t for _, family, t, _ in license_scan.template_grams() if family == k}:
        rows = [(g, own) for g, family, turn, own in license_scan.template_grams() if (family, turn) == (k, t)]
        own = sum(o and g in grams for g, o in rows)
        if own:
            likeness = max(likeness, own / sum(o for _, o in rows), sum(g in grams for g, _ in rows) / len(grams))
    confirmed = k < len(TEMPLATES) and p[k] >= license_scan.SURE and likeness >= license_scan.ALIKE
    return (license_scan.FAMILIES[k] if confirmed else "unknown"), p[k], likeness, confirmed


def test_units_are_judged_as_by_the_definition(spark, data):
    dice = random.Random(2)
    known = [t for texts in TEMPLATES.values() for t in texts]
    texts = [*known, *OTHERS, *(" ".join(dice.sample(license_scan.words_of(dice.choice(known)), 2) + license_scan.words_of(dice.choice(known + OTHERS))) for _ in range(60))]
    lines = [x for r in table(spark, data, "documents").collect() for x in r.text.split("\n") if "icen" in x][:200]
    texts = [f"the license: {t}" for t in [*texts, *lines]]
    held = license_scan.candidates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    ids = {r.row: r.id for r in held.collect()}
    have = {ids[r.row]: r for r in license_scan.judge(held).collect()}
    assert len(have) == len(texts)
    for k, text in enumerate(texts):
        family, p, likeness, confirmed = judged(text)
        assert (have[k].family, have[k].confirmed) == (family, confirmed)
        assert abs(have[k].probability - p) < 1e-9 and abs(have[k].likeness - likeness) < 1e-12


def test_the_temperature_is_inside_its_grid_and_marks_cover_templates_without_cues():
    assert 0.5 < license_scan.model()[2] < 10 and len(license_scan.marks()) < 10
    assert all(any(c in " ".join(t.lower().split()) for c in [*license_scan.CUES, *license_scan.marks()]) for texts in TEMPLATES.values() for t in texts)


def test_every_sentence_passes_and_wrapped_notices_are_whole(spark):
    known = [(t, name) for name, texts in TEMPLATES.items() for t in texts]
    docs = spark.createDataFrame([(k, f"Some prose.\n{t}.\nMore prose of the day.") for k, (t, _) in enumerate(known)], "doc_id long, text string")
    have = {r.doc_id: r for r in license_scan.scan(docs).collect()}
    assert [have[k].license for k in range(len(known))] == [name for _, name in known]
    cases = [
        ("All rights reserved.", "unknown"), ("Distributed under GPLv3", "gpl-3.0"), ("CC BY 4.0", "cc-by-4.0"), ("CC0 1.0 Universal", "cc0"),
        ("Wir fahren mit dem Zug.", "none"), ("It is version 2 of the plan.", "none"), ("the weather is nice in the city", "none"),
        ("Intro.\n\nThis Source Code Form is subject\nto the terms of the Mozilla\nPublic License, v. 2.0\n\nOutro.", "mpl-2.0"),
        ("Permission is hereby granted, free\nof charge, to any person obtaining\na copy of this software and associated\ndocumentation files", "mit"),
        ("Released under the MIT License.\nReleased under the BSD 3-Clause License", "bsd,mit"),
        ("prose of the day\nRedistributions of source code must retain the\nabove copyright notice, this list of conditions\r\nand the following disclaimer\nand more prose", "bsd"),
        ("Licensed under the Sleepycat Public License 2.0", "unknown"), ("Sun Public License Version 1.0", "unknown"), ("Licensed under the Business Source License 1.1", "unknown"),
        ("SPDX-License-Identifier: SSPL-1.0", "unknown"), ("European Space Agency Public License v2.4", "unknown"), ("the MIT students asked for a license", "unknown"),
        ("Licensed under the Eclipse Public License 2.0", "epl-2.0"), ("Licensed under the EUPL, version 1.2", "eupl-1.2"),
        (f"Released under the {'x' * 64}a License", "unknown"), ("license " + "word " * 20000, "unknown"),
    ]
    rows = sorted(license_scan.scan(spark.createDataFrame([(k, t) for k, (t, _) in enumerate(cases)], "doc_id long, text string")).collect())
    assert [r.licenses or r.license for r in rows] == [w for _, w in cases]
    assert rows[9].n_confirmed == 2


def test_rows_without_id_and_rows_of_one_id_are_judged_one_by_one(spark):
    rows = [(None, "Released under the MIT License."), (None, "nothing"), (None, None), (3, "Released under the ISC License"), (3, "plain"), (3, "Released under the ISC License")]
    docs = spark.createDataFrame([(*r, "x", "y") for r in rows], "doc_id long, text string, row string, units string")
    have = sorted((str(r.doc_id), r.license) for r in license_scan.scan(docs).collect())
    assert have == [("3", "isc"), ("3", "isc"), ("3", "none"), ("None", "mit"), ("None", "none"), ("None", "none")]
    assert license_scan.scan(docs.limit(0)).count() == 0
