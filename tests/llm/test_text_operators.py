"""The text operators against brute force on small fixtures: nulls, empty and long texts, ties, repeated rows, empty tables and
extra columns with clashing names."""

import hashlib
import math
import random
import re

import numpy as np
import pytest
import xxhash
from mfaccel.llm import bpe, decontaminate, digest, features, license_scan, lm_score, nbsvm, quotes, sharding, simhash, toxicity
from mfaccel.llm.common import LOWER_WORDS, table
from mfaccel.llm.queries import tokenizer_file
from pyspark.sql import functions as F

DOCS = "doc_id long, text string, id string, n_words string, lang string"


def docs_of(spark, texts, first=0):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(first + k, t, "x", "y", "en") for k, t in enumerate(texts)], DOCS)


def lines(seed, count, words=("alpha", "beta", "gamma", "delta", "straße", "naïve", "x1", "Überall")):
    dice = random.Random(seed)
    return [" ".join(dice.choice(words) + dice.choice(["", ",", ".", "!"]) for _ in range(dice.randrange(0, 60))) for _ in range(count)]


ODD = [None, "", "   \n\t", "a", "É", "word " * 30000, "same text here now", "same text here now", "𝔘𝔫𝔦   code space", "\x00\x01nul"]


# --- decontamination -------------------------------------------------------------------------------------------------------


def brute_leaks(texts, items, size=10):
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    low = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    out = []
    for text in texts:
        words = pattern.findall(low(text))
        hit, found = set(), set()
        for item, item_text in items:
            own = pattern.findall(low(item_text))
            n = min(size, len(own))
            windows = {tuple(own[k : k + n]) for k in range(len(own) - n + 1)} if n else set()
            for k in range(len(words) - n + 1 if n else 0):
                if tuple(words[k : k + n]) in windows:
                    hit |= set(range(k, k + n))
                    found.add(item)
        names = ",".join(sorted(map(str, found)))
        out.append((len(words), len(hit), len(found), hashlib.sha256(names.encode()).hexdigest(), bool(hit)))
    return out


@pytest.mark.parametrize("piece", [decontaminate.PIECE_BYTES, 400])
def test_decontamination_equals_brute_force(spark, piece):
    items = [(k, t) for k, t in enumerate(lines(1, 12))] + [(100, "Short ITEM"), (101, "short item"), (102, ""), (103, None), (100, "short item again"), (9, "alpha beta")]
    texts = [*ODD, *lines(2, 40), *(f"pre {t} post" for _, t in items if t), "short\nITEM.x", "SHORT-item", "alpha beta"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    have = decontaminate.digest(decontaminate.flag(docs_of(spark, texts), bench, piece_bytes=piece)).orderBy("doc_id").collect()
    assert [tuple(r)[1:] for r in have] == brute_leaks(texts, items)


def test_decontamination_removes_documents_or_spans(spark):
    bench = spark.createDataFrame([(1, "one two three four")], "item_id long, text string")
    docs = docs_of(spark, ["Well, One two; three FOUR, five é.", "clean é text", None, ""])
    left = decontaminate.remove(docs, bench)
    assert left.columns == docs.columns and sorted(r.doc_id for r in left.collect()) == [1, 2, 3]
    spans = {r.doc_id: r.text for r in decontaminate.remove(docs, bench, mode="spans").collect()}
    assert spans == {0: "Well, , five é.", 1: "clean é text", 2: None, 3: ""}
    assert decontaminate.flag(docs.limit(0), bench).count() == 0
    assert decontaminate.remove(docs, bench.limit(0)).count() == 4


# --- sharding -----------------------------------------------------------------------------------------------------------------


def test_store_round_trip_versions_and_conflicts(spark, tmp_path):
    docs = docs_of(spark, [*ODD, *lines(3, 200)])
    store = sharding.ShardStore(spark, str(tmp_path / "store"), docs.schema)
    assert store.read().count() == 0
    for k in range(6):
        store.append(docs.where(F.col("doc_id") % 6 == k).coalesce(1), f"day {k}")
    store.append(docs.limit(0), "nothing")
    before = store.version()
    with pytest.raises(sharding.Conflict):
        store._commit(before, {})
    with pytest.raises(ValueError):
        store.append(docs.drop("lang"), "odd")
    store.compact(target=1 << 20)
    assert store.version() > before and len(store.shards()) < len(store.shards(before))
    rows = lambda df: sorted(map(repr, df.collect()))
    assert rows(store.read()) == rows(docs) == rows(store.read(before))
    assert store.vacuum() > 0 and rows(sharding.ShardStore(spark, store.root).read()) == rows(docs)
    assert not list((tmp_path / "store" / "manifests").glob(".draft*json"))


# --- language-model scoring -----------------------------------------------------------------------------------------------------


def test_vocabulary_takes_the_most_frequent_words(spark):
    texts = [" ".join(f"w{k}" for k in range(1, n)) for n in range(2, 40)]
    vocab = lm_score.vocabulary(docs_of(spark, texts), most=12)
    assert 8 <= len(vocab) <= 12 and {f"w{k}".encode() for k in range(1, 8)} <= set(vocab) and sorted(vocab.values()) == list(range(2, len(vocab) + 2))
    assert len(lm_score.vocabulary(docs_of(spark, texts))) == 38 and not lm_score.vocabulary(docs_of(spark, [None, ""]))


def test_scores_equal_brute_force_and_prefer_the_target(spark):
    texts = [*ODD, *lines(4, 30), *lines(5, 30, ("eins", "zwei", "drei", "vier"))]
    docs = docs_of(spark, texts)
    target = F.col("doc_id") >= len(ODD) + 30
    models = lm_score.fit(docs, target, most_words=6)
    have = {r.doc_id: r for r in lm_score.score(docs, models).collect()}
    tokens = [[models.vocab.get(w, 0) for w in (t or "").encode().translate(LOWER_WORDS).split()] for t in texts]
    for k, own in enumerate(tokens):
        assert have[k].n_tokens == len(own)
        if not own:
            assert have[k].score == 0
            continue
        for name, group in (("target_loss", tokens[len(ODD) + 30 :]), ("background_loss", tokens)):
            uni, ctx, cell = (np.zeros(n) for n in (len(models.vocab) + 2, len(models.vocab) + 2, 1 << lm_score.CELL_BITS))
            for t in group:
                for a, b in zip([1, *t], t):
                    uni[b] += 1
                    ctx[a] += 1
                    cell[_cell(a, b)] += 1
            p_uni = (uni + lm_score.ADDED) / (uni + lm_score.ADDED).sum()
            loss = 0.0
            for a, b in zip([1, *own], own):
                share = lm_score.SHARE if ctx[a] else 0
                loss -= math.log(share * min(1, cell[_cell(a, b)] / max(1, ctx[a])) + (1 - share) * p_uni[b])
            assert have[k][name] == pytest.approx(loss / len(own), rel=1e-4)
    assert all(have[k].selected for k in range(len(ODD) + 30, len(texts)) if tokens[k])
    assert lm_score.score(docs.limit(0), models).count() == 0


def _cell(a, b):
    return int(lm_score.cells(np.array([a, b]))[1])


# --- classifiers ------------------------------------------------------------------------------------------------------------------


def test_features_are_the_same_whatever_came_before():
    texts = [(t or "").encode() for t in [*ODD, *lines(6, 20)]]
    first = [sorted(features.indicators(t)) for t in texts]
    again = [sorted(features.indicators(t)) for t in reversed(texts)][::-1]
    assert first == again and all(len(f) == len(set(f)) for f in first) and not first[1]


def test_quality_learns_held_out_rows(spark, data):
    folder = "/root/testdata/sf0.01"
    docs, labels = table(spark, folder, "documents"), table(spark, folder, "labels")
    model = nbsvm.fit(docs, labels)
    rows = nbsvm.score(docs, model).join(labels, "doc_id").where("held_out").collect()
    good, bad = ([r.score for r in rows if r.quality == q] for q in (1, 0))
    assert np.mean([g > b for g in good for b in bad]) > 0.98
    assert np.mean([r.predicted == r.quality for r in rows]) > 0.95
    odd = docs_of(spark, ODD)
    scored = nbsvm.score(odd, model).collect()
    assert len(scored) == len(ODD) and all(0 <= r.score <= 1 for r in scored) and len({r.score for r in scored if r.doc_id in (0, 1)}) == 1
    assert nbsvm.keep_good(odd, model).columns == odd.columns
    empty = nbsvm.fit(docs, labels.limit(0))
    assert {r.score for r in nbsvm.score(odd, empty).collect()} == {0.5}
    assert nbsvm.score(docs.limit(0), model).count() == 0


def test_contradictory_and_null_labels_teach_nothing(spark):
    docs = docs_of(spark, lines(7, 40))
    labels = spark.createDataFrame([(k, k % 2) for k in range(20)] + [(k, 1 - k % 2) for k in range(20)] + [(21, None), (None, 1), (999, 1)], "doc_id long, quality int")
    model = nbsvm.fit(docs, labels)
    assert model.ratio is None and model.share == 0.5


def test_toxicity_catches_marked_documents_only(spark):
    dice = random.Random(3)
    texts, labels = [], []
    for k in range(400):
        words = [f"w{dice.randrange(80)}" for _ in range(dice.randrange(5, 60))]
        toxic = int(k % 8 == 0)
        for _ in range(dice.randrange(1, 7) if toxic else 0):
            words.insert(dice.randrange(len(words)), dice.choice(["nasty", "vilest", "foulmouth"]))
        texts.append(" ".join(words))
        labels.append((k, toxic))
    docs = docs_of(spark, texts)
    model = toxicity.fit(docs, spark.createDataFrame(labels, "doc_id long, toxic int"))
    rows = {r.doc_id: r for r in toxicity.score(docs, model).collect()}
    assert [rows[k].toxic for k in range(400)] == [bool(t) for _, t in labels]
    counts = [sum(w in ("nasty", "vilest", "foulmouth") for w in t.split()) for t in texts]
    mild, severe = ([rows[k].severity for k in range(400) if counts[k] in group] for group in ((1,), (5, 6)))
    assert np.mean(severe) > np.mean(mild) > 0.3 and all(np.diff(model.cuts) > 0)
    kept = toxicity.keep_clean(docs, model)
    assert kept.columns == docs.columns and kept.count() == 350
    odd = toxicity.score(docs_of(spark, ODD), model).collect()
    assert len(odd) == len(ODD) and not any(r.toxic for r in odd)
    none = toxicity.fit(docs, spark.createDataFrame([], "doc_id long, toxic int"))
    assert not any(r.toxic for r in toxicity.score(docs, none).collect())


# --- near-duplicates --------------------------------------------------------------------------------------------------------------


def brute_fingerprint(text, size=4):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    shingles = [" ".join(words[k : k + size]) for k in range(max(1, len(words) - size + 1))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)) if hashes else 0


def classes(count, edges):
    root = list(range(count))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return [find(x) for x in range(count)]


def test_near_duplicates_equal_brute_force(spark):
    base = lines(8, 25)
    texts = [*ODD, *base, *(t + " end" for t in base), *base[:5], "one two three", "One TWO three"]
    prints = [brute_fingerprint(t) for t in texts]
    want = classes(len(texts), [(a, b) for a in range(len(texts)) for b in range(a) if (prints[a] ^ prints[b]).bit_count() <= 4])
    docs = docs_of(spark, texts)
    have = sorted(map(tuple, simhash.near_duplicates(docs).select("id", "component", "fp").collect()))
    assert [h[1] for h in have] == want and [h[2] % 2**64 for h in have] == prints
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_trees_find_every_link_in_dense_and_sparse_space(spark):
    dice = np.random.default_rng(2)
    centres = dice.integers(0, 2**64, 40, dtype=np.uint64)
    points = [*dice.integers(0, 2**64, 600, dtype=np.uint64)]
    for c in centres:
        for _ in range(25):
            x = c
            for b in dice.integers(0, 64, dice.integers(0, 7)):
                x ^= np.uint64(1) << np.uint64(b)
            points.append(x)
    for _ in range(900):  # one dense ball
        points.append(centres[0] ^ (np.uint64(1) << np.uint64(dice.integers(0, 64))) ^ (np.uint64(1) << np.uint64(dice.integers(0, 64))))
    points = np.unique(np.array(points, np.uint64))
    frame = spark.createDataFrame([(int(p),) for p in points.view(np.int64)], "fp long")
    near = np.bitwise_count(points[:, None] ^ points[None, :]) <= 4
    want = classes(len(points), np.argwhere(np.triu(near, 1)).tolist())
    place = {int(p): k for k, p in enumerate(points.view(np.int64))}
    edges = [(place[r.a], place[r.b]) for r in simhash.links(frame, shard=100).collect()]
    assert classes(len(points), edges) == want and len(edges) < 3 * len(points)
    found = {place[r.node]: place[r.root] for r in simhash.components(simhash.links(frame, shard=100)).collect()}
    linked = [k for k in range(len(points)) if near[k].sum() > 1]
    assert sorted(found) == linked
    groups = lambda of: {frozenset(k for k in linked if of(k) == r) for r in {of(k) for k in linked}}
    assert groups(found.get) == groups(want.__getitem__)


def test_long_chains_contract(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(300)] + [(900, 901), (901, 900), (5, 5)], "a long, b long")
    found = {r.node: r.root for r in simhash.components(edges).collect()}
    assert found == {**dict.fromkeys(range(301), 0), 900: 900, 901: 900}
    assert simhash.components(edges.limit(0)).count() == 0


def test_repeated_and_missing_ids(spark):
    rows = [(1, "a b c d e", "x", "y", "z")] * 3 + [(2, "a b c d e", "x", "y", "z"), (None, "a b c d e", "x", "y", "z"), (None, "other words are here", "x", "y", "z")]
    docs = spark.createDataFrame(rows, DOCS)
    assert [r.component for r in simhash.near_duplicates(docs).orderBy("id").collect() if r.id] == [1, 1, 1, 1]
    assert [r.component for r in simhash.near_duplicates(docs).collect() if r.id is None].count(None) == 1


# --- quotations ---------------------------------------------------------------------------------------------------------------------


def test_quotes_link_and_leave(spark):
    rows = [
        (1, 0, "user", "Hello there  world.\nHow are you?", 7), (1, 1, "bot", "> hello there world.\nFine", 7),
        (1, 2, "user", "> > Hello there world.\n> Fine\nok then\n\nbye", 7), (2, 0, "user", "On Monday X wrote:\n> How are you?\nnew", 7),
        (2, 1, "user", None, 7), (3, 0, "u", ">> nothing known\nplain", 7), (4, 0, "u", "> ok then\nround", 7), (4, 1, "u", "> round\nagain", 7),
        (5, 0, "u", "5 > 4 is true", 7), (6, 0, "u", "> quoted\nown\n" * 5000, 7), (None, 3, "u", "> Fine\nlost", 7), (1, 0, "user", "Hello there  world.\nHow are you?", 7),
    ]
    out = quotes.linked(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, own int"))
    have = {(r.conv_id, r.turn): r for r in out.collect()}
    assert len(have) == 11 and have[6, 0].n_quotes == 5000 and ">" not in "".join(r.text for k, r in have.items() if k != (5, 0))
    assert have[1, 1].text == "Fine" and (have[1, 1].reply_conv, have[1, 1].reply_turn) == (1, 0)
    assert (have[1, 2].n_quotes, have[1, 2].max_level, have[1, 2].text) == (2, 2, "ok then\n\nbye")
    assert have[2, 0].text == "new" and (have[2, 0].reply_conv, have[2, 0].reply_turn) == (1, 0)
    assert have[2, 1].text == "" and have[3, 0].n_linked == 0 and have[3, 0].n_quotes == 1
    assert (have[4, 1].root_conv, have[4, 1].root_turn, have[4, 1].depth) == (1, 0, 3)
    assert have[5, 0].text == "5 > 4 is true" and have[None, 3].reply_conv is None
    assert quotes.linked(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_quotes_equal_their_sql(spark):
    import duckdb
    from mfaccel.llm.queries import OP6_SQL

    dice, rows = random.Random(4), []
    for conv in range(12):
        said = []
        for turn in range(6):
            text = dice.choice(["yes indeed", f"point {conv} {turn}", "a\n\nb c", "Hello  World", ""])
            if said and dice.random() < 0.7:
                other = dice.choice(said)
                quoted = "\n".join(">" + dice.choice(["", " "]) + x for x in other.split("\n"))
                text = dice.choice(["", "X wrote: \n", "On Tue X wrote:\n"]) + quoted + "\n" + text
            said.append(text)
            rows.append((conv, turn, "user", text))
    rows += [(12, 0, "u", "> yes indeed\nnew thing"), (13, 0, None, None), (None, 1, "u", "> yes indeed")]
    have = quotes.reply_ordered(quotes.linked(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))).fillna(-1, ["reply_conv", "reply_turn"])
    base = duckdb.connect()
    base.execute("CREATE TABLE conversations (conv_id BIGINT, turn BIGINT, role VARCHAR, text VARCHAR)")
    base.executemany("INSERT INTO conversations VALUES (?, ?, ?, ?)", rows)
    want = base.execute(OP6_SQL).fetchall()
    assert sorted(map(repr, map(tuple, have.collect()))) == sorted(map(repr, want))
    assert sum(w[6] > 0 for w in want) > 20


def test_rings_end_at_their_least_message(spark):
    ring = spark.createDataFrame([(1, 0, 2, 0), (2, 0, 3, 0), (3, 0, 1, 0), (4, 0, 3, 0)], "conv long, turn long, to_conv long, to_turn long")
    assert {(r.conv, r.root_conv, r.depth) for r in quotes.roots(ring).collect()} == {(k, 1, None) for k in (1, 2, 3, 4)}


def test_native_operators_run_no_python(spark, data):
    for df in (quotes.linked(table(spark, data, "conversations")), license_scan.scan(table(spark, data, "documents"))):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|InArrow", plan)


# --- tokens -------------------------------------------------------------------------------------------------------------------------


def test_tokens_equal_the_reference_library_and_come_back(spark, data):
    import base64

    import tiktoken

    path, pattern = tokenizer_file()
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    own = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    texts = [*ODD, *lines(9, 20), "<|endoftext|> 漢字 🙂🙃 é I'll　x", *[r.text for r in table(spark, data, "documents").collect()]]
    docs = docs_of(spark, texts)
    n_parts = {}
    coded = bpe.encode(docs, path, pattern, offsets=True).orderBy("doc_id").collect()
    for r, text in zip(coded, texts, strict=True):
        assert r.ids == own.encode_ordinary(text or "")
        reached = parts = 0
        for k, (i, a, b) in enumerate(zip(r.ids, r.starts, r.ends, strict=True)):  # tokens of one split code point name the same range
            assert a <= reached and b >= reached
            reached = b
            whole = own.decode_single_token_bytes(i) == (text or "")[a:b].encode()
            assert whole or own.decode_single_token_bytes(i) in (text or "")[a:b].encode()
            parts += not whole
        assert reached == len(text or "")
        n_parts[r.doc_id] = parts
    back = {r.doc_id: r for r in bpe.decode(bpe.encode(docs, path, pattern), path, pattern).collect()}
    assert all(back[k].text == (t or "") and bytes(back[k].decoded).decode() == (t or "") for k, t in enumerate(texts))
    trip = {r.doc_id: r for r in bpe.round_trip(docs, path, pattern).collect()}
    for k, t in enumerate(texts):
        ids = own.encode_ordinary(t or "")
        assert trip[k].n_tokens == len(ids) and trip[k].ids_sha256 == hashlib.sha256(b"".join(i.to_bytes(4, "little") for i in ids)).hexdigest()
        assert trip[k].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest() and trip[k].n_parts == n_parts[k]
    assert sum(n_parts.values()) > 0
    assert bpe.round_trip(docs.limit(0), path, pattern).count() == 0
    half = spark.createDataFrame([(1, own.encode_ordinary("🙂")[:1])], "doc_id long, ids array<int>")
    assert "�" in bpe.decode(half, path, pattern).first().text


# --- licences -----------------------------------------------------------------------------------------------------------------------


def test_licences(spark):
    texts = [
        "prose\nLicensed under the Apache License, Version 2.0.\nmore", "Released under the MIT License.", "This work is licensed under the GNU General Public License, version 3.",
        "Licensed under CC BY-NC 4.0.", "Licensed under CC BY 4.0.", "All rights reserved. Copyright of nobody.", "Licensed under the moon and the stars by poets",
        "no such thing", None, "", "SPDX-License-Identifier: BSD-3-Clause\nSPDX-License-Identifier: MIT", "the license " * 5000, "Released under the MIT License.",
    ]
    want = ["apache-2.0", "mit", "gpl-3.0", "cc-by-nc-4.0", "cc-by-4.0", "unknown", "unknown", "none", "none", "none", None, "unknown", "mit"]
    rows = sorted(license_scan.scan(docs_of(spark, texts)).collect())
    assert [r.license for r, w in zip(rows, want) if w] == [w for w in want if w]
    assert rows[10].licenses == "bsd,mit" and rows[10].n_confirmed == 2
    weights, bias, heat = license_scan.model()
    line = texts[1]
    z = [(b + sum(weights[g][k] for g in license_scan.grams_of(license_scan.words_of(line)) if g in weights)) / heat for k, b in enumerate(bias)]
    p = np.exp(np.array(z) - max(z))
    assert rows[1].confidence == pytest.approx(1 / p.sum(), rel=1e-6)
    assert license_scan.scan(docs_of(spark, texts).limit(0)).count() == 0


# --- digests ------------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("shards", [1, 7])
def test_digests_equal_brute_force(spark, shards):
    texts = [*ODD, *lines(10, 60)]
    rows = [(k * 3 - 20, t, "x", "y", "z") for k, t in enumerate(texts)]
    have = {r.doc_id: r for r in digest.against_next(spark.createDataFrame(rows, DOCS), shards=shards).collect()}
    assert len(have) == len(texts)
    ordered = sorted(rows, key=lambda r: -r[0])
    for (doc, text, *_), (_, following, *_) in zip(ordered, ordered[1:] + ordered[:1], strict=True):
        text, following = text or "", following or ""
        n = len(text) // 3
        new = text[: len(text) - n] + following[:n]
        r = have[doc]
        assert r.n_chars == len(text) and r.edited_sha256 == hashlib.sha256(new.encode()).hexdigest()
        assert r.fingerprint == digest.fingerprint(text.encode()) and r.edited_fingerprint == digest.fingerprint(new.encode())
        assert r.near_edited == digest.likeness(r.fingerprint, r.edited_fingerprint) and 0 <= r.near_next <= 1
        assert r.near_next == digest.likeness(r.fingerprint, digest.fingerprint(following.encode()))
    assert digest.against_next(spark.createDataFrame([], DOCS)).count() == 0
    assert digest.against_next(spark.createDataFrame(rows[:1], DOCS)).first().near_next == 1


def test_repeated_and_missing_ids_have_one_row_each(spark):
    rows = [(1, "aaa", "", "", ""), (1, "aaa", "", "", ""), (2, "bbb", "", "", ""), (None, "ccc", "", "", ""), (None, "ddd", "", "", "")]
    assert digest.against_next(spark.createDataFrame(rows, DOCS), shards=3).count() == 5


def test_digest_tells_edits_from_other_texts(spark):
    texts = [r.text for r in table(spark, "/root/testdata/sf0.01", "documents").where("n_chars > 500").limit(150).collect()]
    wins = [digest.likeness(digest.fingerprint(a.encode()), digest.fingerprint(digest.edited(a, b).encode())) > digest.likeness(digest.fingerprint(a.encode()), digest.fingerprint(b.encode())) for a, b in zip(texts, texts[1:]) if a != b]
    assert np.mean(wins) > 0.98
    assert digest.likeness(digest.fingerprint(b""), digest.fingerprint(None)) == 1
