"""Licence scans by a trained paragraph classifier, with template comparison.

DataFrame functions only on the path of the documents. Units are paragraphs (between blank lines) and, as a notice often stands in one line of
other text, single lines. A line is a candidate if it holds a cue, a lower-case part of a word or phrase that speaks of rights, or a mark,
an n-gram by which the classifier knows a template that has no cue; a paragraph of several lines is one if a line of it is, or if a cue or
mark is wrapped over its lines. A unit's distinct n-grams of one to three words meet the weights of a multinomial logistic regression
(a small table, fixed by the templates); sums of weights give each family's probability, and two checks follow: the probability, after
calibration by a temperature, must reach SURE, and the likeness to a template of that family must reach ALIKE: the share of the
template's own n-grams of one and two words (those of at most one other family and of no text of the class "unknown") that the unit has, or, if
it has any of them, the share of the unit that is the template's. Other candidate lines are "unknown". Paragraphs count only if
they are confirmed as a family that no line of the document is.

The classifier is trained on the templates, on cut and padded versions of them, and, for the class "unknown", on sentences that speak of rights
without any known licence and on notices of made-up licences. Its temperature is calibrated on models that have not seen a third
of the families: there the versions of the unseen families, and made-up licences by other names, are "unknown".

Edge cases: null and empty texts have no candidate; a document without candidates has licence "none"; repeated rows, rows that share an id and rows
without id are judged one by one; a line repeated in a document counts once; words of any length are whole; empty tables work;
other columns are ignored.
"""

from __future__ import annotations

import random
from collections import defaultdict
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import cut
from mfaccel.llm.license_texts import OTHERS, TEMPLATES, UNKNOWN_FORMS, UNKNOWN_NAMES

#: Lower-case parts of a line that speak of rights: such a line is judged, and is "unknown" if no licence is confirmed.
CUES = ("rights reserved", "released under", "distributed under", "licen", "copyright", "permission", "warrant", "redistribut", "public domain", "gnu ", "spdx")
FAMILIES = [*TEMPLATES, "unknown"]
SURE, ALIKE, MOST = 0.6, 0.5, 3
_NOT_WORD = r"[^a-z0-9.+-]+"


def words_of(text: str) -> list[str]:
    """Words as the DataFrame path makes them: lower case, split where no letter, digit, dot, plus or hyphen is."""
    kept = "".join(c if c.isascii() and (c.isalnum() or c in ".+-") else " " for c in text.lower())
    return [w for w in (x.strip(".-") for x in kept.split(" ")) if w]


def grams_of(words: list[str], most: int = MOST) -> set[str]:
    return {" ".join(words[k : k + n]) for n in range(1, most + 1) for k in range(len(words) - n + 1)}


def _versions(text: str, dice: random.Random, count: int):
    """The text, and versions of it that lose words or stand among others."""
    words = words_of(text)
    yield words
    for _ in range(count):
        own = list(words)
        if len(own) > 6 and dice.random() < 0.5:
            first = dice.randrange(0, len(own) // 3)
            own = own[first : len(own) - dice.randrange(0, len(own) // 3)]
        if dice.random() < 0.4:
            own = [dice.choice(["the", "file", "see", "copyright", "2019", "author"]) for _ in range(dice.randrange(1, 4))] + own
        if dice.random() < 0.4:
            own = own + [dice.choice(["see", "license", "for", "details", "file", "terms"]) for _ in range(dice.randrange(1, 4))]
        yield own


def _made_up(names: list[str], dice: random.Random) -> list[str]:
    return [form.format(name.replace(" ", "-") if "SPDX" in form else name, dice.choice(["1.0", "2.0", "3", "4.0"])) for name in names for form in UNKNOWN_FORMS]


class Classifier:
    """Multinomial logistic regression over the families, by stochastic steps on distinct n-grams."""

    def __init__(self, data: list[tuple[set[str], int]], seed: int, epochs: int = 15):
        self.at = {g: k for k, g in enumerate(sorted({g for grams, _ in data for g in grams}))}
        self.weights, self.bias = np.zeros((len(self.at), len(FAMILIES))), np.zeros(len(FAMILIES))
        rows, dice = [(self.codes(grams), y) for grams, y in data], random.Random(seed)
        for epoch in range(epochs):
            rate = 0.3 / (1 + epoch / 3)
            dice.shuffle(rows)
            for codes, y in rows:
                step = -self.probabilities(codes)
                step[y] += 1
                step *= rate / np.sqrt(max(1, len(codes)))
                self.bias += 0.2 * step
                self.weights[codes] += step
            self.weights *= 0.995

    def codes(self, grams: set[str]) -> np.ndarray:
        return np.array(sorted(self.at[g] for g in grams if g in self.at), np.int64)

    def probabilities(self, codes: np.ndarray, heat: float = 1.0) -> np.ndarray:
        z = (self.bias + self.weights[codes].sum(axis=0)) / heat
        e = np.exp(z - z.max())
        return e / e.sum()


def _examples(dice: random.Random, names: list[str], without: set[str] = frozenset(), count: int = 12) -> list[tuple[set[str], int]]:
    """(n-grams, family) of versions of all texts; those of the families `without` are unknown."""
    unknown = len(FAMILIES) - 1
    of = [(t, unknown if name in without else k) for k, name in enumerate(TEMPLATES) for t in TEMPLATES[name]]
    of += [(t, unknown) for t in [*OTHERS, *_made_up(names, dice)]]
    return [(grams_of(v), y) for t, y in of for v in _versions(t, dice, count)]


@lru_cache(maxsize=1)
def model() -> tuple[dict[str, list[float]], list[float], float]:
    """(weights of the families by n-gram, biases, temperature); some thousand n-grams, the same on every run."""
    dice = random.Random(11)
    whole = Classifier(_examples(dice, UNKNOWN_NAMES), 1)
    heats, costs = [h / 4 for h in range(2, 41)], np.zeros(39)
    for fold in range(3):
        unseen = set(list(TEMPLATES)[fold::3])
        seen_names, other_names = UNKNOWN_NAMES[:6], UNKNOWN_NAMES[6:]
        train = [(g, y) for g, y in _examples(dice, seen_names) if y == len(FAMILIES) - 1 or FAMILIES[y] not in unseen]
        part = Classifier(train, 2 + fold, epochs=8)
        held = [(part.codes(g), y) for g, y in _examples(dice, other_names, unseen, count=3)]
        costs += [-sum(np.log(max(1e-12, part.probabilities(c, h)[y])) for c, y in held) for h in heats]
    heat = heats[int(np.argmin(costs))]
    return {g: [round(float(x), 6) for x in whole.weights[k]] for g, k in whole.at.items()}, [round(float(b), 6) for b in whole.bias], heat


def template_grams() -> list[tuple[str, int, int, bool]]:
    """(n-gram, family, template, whether it is an own one: of one or two words, in at most one other family and in no text without a licence)."""
    families_of: dict[str, set[int]] = defaultdict(set)
    found = [(k, t, words_of(text)) for k, name in enumerate(TEMPLATES) for t, text in enumerate(TEMPLATES[name])]
    for k, _, words in found:
        for g in grams_of(words):
            families_of[g].add(k)
    for text in [*OTHERS, *_made_up(UNKNOWN_NAMES, random.Random(0))]:
        for g in grams_of(words_of(text)):
            families_of[g].add(-1)
    return [(g, k, t, len(families_of[g]) <= 2 and -1 not in families_of[g] and g.count(" ") < 2) for k, t, words in found for g in sorted(grams_of(words))]


@lru_cache(maxsize=1)
def marks() -> list[str]:
    """The heaviest own n-gram of no other family, against the class "unknown", of each template without a cue; one with a digit or a mark within, if there is any."""
    known = [x for x in template_grams() if x[3] and len(x[0]) > 4]
    weights, found, own = model()[0], [], {(g, k, t) for g, k, t, _ in known if all(g != h or k == j for h, j, _, _ in known)}
    for k, texts in enumerate(TEMPLATES.values()):
        for t, text in enumerate(texts):
            low = " ".join(text.lower().split())
            if not any(c in low for c in [*CUES, *found]):
                found.append(max(sorted(g for g in grams_of(words_of(text)) if (g, k, t) in own and g in low), key=lambda g: (not g.replace(" ", "").isalpha(), weights[g][k] - weights[g][-1])))
    return found


def _let(value: Column, use) -> Column:
    """use(value), with the value computed once."""
    return F.get(F.transform(F.array(value), use), 0)


def _holds(text: Column) -> Column:
    found = F.lit(False)
    for part in [*CUES, *marks()]:
        found = found | text.contains(part)
    return found


def candidates(docs: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row, id, units array<struct<text, alone>>): every document, with its distinct candidate lines (alone) and paragraphs of several lines;
    units are null where there are none. Cut, as row numbers must not change."""
    text = F.col(text_col).cast("string")

    def plain(x: Column) -> Column:
        return F.regexp_replace(F.lower(x), r"\s+", " ")

    def unit(x: Column, alone: bool) -> Column:
        return F.struct(x.alias("text"), F.lit(alone).alias("alone"))

    def units(x: Column) -> Column:
        lines = F.transform(F.filter(F.split(x, r"\r?\n"), lambda y: _let(plain(y), _holds)), lambda y: unit(y, True))
        several = F.filter(F.split(x, r"\r?\n[ \t]*\r?\n"), lambda y: F.trim(y, F.lit(" \t\r\n")).contains("\n") & _let(plain(y), _holds))
        return F.array_distinct(F.concat(lines, F.transform(several, lambda y: unit(y, False))))

    found = F.when(_let(plain(text), _holds), _let(text, units))
    return cut(docs.select(F.monotonically_increasing_id().alias("row"), F.col(doc_col).alias("id"), found.alias("units")))


def _grams(words: Column) -> Column:
    """Distinct runs of one to MOST words. Each array is made once from the one before it, so long lines cost their length."""
    runs, out = words, words
    for n in range(2, MOST + 1):
        rest = F.slice(words, n, F.greatest(F.size(words), F.lit(n)) - (n - 1))
        runs = F.zip_with(F.slice(runs, 1, F.size(rest)), rest, lambda head, word: F.concat_ws(" ", head, word))
        out = F.concat(out, runs)
    return F.array_distinct(out)


def judge(units: DataFrame) -> DataFrame:
    """(row, at, alone, family, probability, likeness, confirmed) of every unit of candidates()."""
    spark = units.sparkSession
    weights, bias, heat = model()
    table = F.broadcast(spark.createDataFrame(list(weights.items()), "gram string, w array<double>"))  # fixed size: from the templates alone
    one = units.where("units IS NOT NULL").select("row", F.posexplode("units").alias("at", "u")).select("row", "at", "u.alone", "u.text")
    parts = F.filter(F.transform(F.split(F.lower("text"), _NOT_WORD), lambda x: F.regexp_replace(x, r"^[.-]+|[.-]+$", "")), lambda x: x != "")
    held = one.select("row", "at", "alone", parts.alias("words")).select("row", "at", "alone", _grams(F.col("words")).alias("grams"))
    grams = held.select("row", "at", "alone", F.size("grams").alias("n_grams"), F.explode("grams").alias("gram"))
    z = [((F.coalesce(F.sum(F.col("w")[k]), F.lit(0.0)) + bias[k]) / heat).alias(f"z{k}") for k in range(len(FAMILIES))]
    known = F.collect_list(F.when(F.col("w").isNotNull(), F.col("gram"))).alias("known")
    scored = grams.join(table, "gram", "left").groupBy("row", "at").agg(F.first("alone").alias("alone"), F.first("n_grams").alias("n_grams"), known, *z)
    zs = F.array(*[F.col(f"z{k}") for k in range(len(FAMILIES))])
    scored = scored.withColumn("top", F.array_max(zs)).withColumn("k", (F.array_position(zs, F.col("top")) - 1).cast("int"))
    probability = 1 / F.aggregate(zs, F.lit(0.0), lambda s, x: s + F.exp(x - F.col("top")))
    scored = cut(scored.select("row", "at", "alone", "n_grams", "known", "k", probability.alias("probability")))  # once, for the classes and the likeness
    out = scored.join(_likeness(scored), ["row", "at"], "left").withColumn("likeness", F.coalesce("likeness", F.lit(0.0)))
    confirmed = (F.col("k") < len(TEMPLATES)) & (F.col("probability") >= SURE) & (F.col("likeness") >= ALIKE)
    family = F.element_at(F.array(*map(F.lit, FAMILIES)), F.col("k") + 1)
    return out.select("row", "at", "alone", F.when(confirmed, family).otherwise("unknown").alias("family"), "probability", "likeness", confirmed.alias("confirmed"))


def _likeness(scored: DataFrame) -> DataFrame:
    """How well a unit fits the best template of its predicted family; templates' n-grams are all known to the classifier."""
    spark, sizes = scored.sparkSession, defaultdict(int)
    templates = template_grams()
    for _, k, t, own in templates:
        sizes[k, t] += own
    table = F.broadcast(spark.createDataFrame([(g, k, t, own, sizes[k, t]) for g, k, t, own in templates], "gram string, k int, t int, own boolean, size int"))  # fixed size
    grams = scored.select("row", "at", "k", "n_grams", F.explode("known").alias("gram")).join(table, ["gram", "k"])
    common = grams.groupBy("row", "at", "t").agg(F.count("*").alias("common"), F.count_if("own").alias("own"), F.first("size").alias("size"), F.first("n_grams").alias("n_grams"))
    return common.where("own > 0").groupBy("row", "at").agg(F.max(F.greatest(F.col("own") / F.col("size"), F.col("common") / F.col("n_grams"))).alias("likeness"))


def scan(docs: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_col, license (of the surest confirmed unit; "unknown" if candidate lines but none; else "none"), licenses (all confirmed families),
    confidence, n_candidates, n_confirmed: one row per document."""
    held = candidates(docs, doc_col=doc_col, text_col=text_col)
    units = judge(held).where("confirmed OR alone")
    sure, line = F.struct("probability", "likeness", "family"), F.col("alone") & F.col("confirmed")
    by_row = units.groupBy("row").agg(
        F.max(F.when(line, sure)).alias("of_lines"), F.collect_set(F.when(line, F.col("family"))).alias("families"), F.collect_set(F.when(~F.col("alone"), sure)).alias("parts"),
        F.count_if("alone").alias("n_lines"), F.count_if(line).alias("n_alone"),
    ).withColumn("parts", F.filter("parts", lambda r: ~F.array_contains("families", r["family"])))
    by_row = by_row.select(
        "row", F.greatest("of_lines", F.array_max("parts")).alias("b"), F.array_sort(F.array_distinct(F.array_union("families", F.transform("parts", lambda r: r["family"])))).alias("licenses"),
        (F.col("n_lines") + F.size("parts")).alias("n_candidates"), (F.col("n_alone") + F.size("parts")).alias("n_confirmed"),
    ).where("n_candidates > 0")
    return held.select("row", "id").join(by_row, "row", "left").select(
        F.col("id").alias(doc_col),
        F.when(F.isnull("n_candidates"), "none").otherwise(F.coalesce("b.family", F.lit("unknown"))).alias("license"),
        F.coalesce(F.array_join("licenses", ","), F.lit("")).alias("licenses"),
        F.coalesce("b.probability", F.lit(0.0)).alias("confidence"),
        F.coalesce("n_candidates", F.lit(0)).alias("n_candidates"), F.coalesce("n_confirmed", F.lit(0)).alias("n_confirmed"),
    )
