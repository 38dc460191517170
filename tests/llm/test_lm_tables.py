import math
from collections import Counter

import pytest
from mfaccel.llm import lm_tables, queries
from mfaccel.llm.common import LOWER_WORDS
from mfaccel.llm.lm_score import ADDED, SHARE

ODD = [None, "", "   \n\t", "a", "É", "Word word-word " * 300, "same text", "same text", "\x00nul"]


@pytest.mark.parametrize("block", [lm_tables.BLOCK, 2000])
def test_every_word_and_pair_is_counted_exactly(spark, block, tmp_path):
    """70,000 words, more than a vocabulary of 65,536 holds, and pairs that differ in their rare words only."""
    texts = [*ODD, *(" ".join(f"w{(k * 700 + j * j) % 70001} x{j % 3}" for j in range(700)) for k in range(100)), *(f"w{k} w{k + 1} zz" for k in range(0, 70000, 700))]
    texts += [" ".join(f"rare{k * 700 + j}" for j in range(700)) for k in range(100)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    marks = {k: bool(k % 3 == 0) for k in range(len(texts)) if k % 2}
    have = {r.doc_id: r for r in lm_tables.score(docs, spark.createDataFrame([*marks.items(), (-1, True)], "doc_id long, target boolean"), block=block, least_buckets=5).collect()}
    words = [(t or "").encode().translate(LOWER_WORDS).split() for t in texts]
    assert len({w for own in words for w in own}) > 70000 and set(have) == set(range(len(texts)))
    models = []
    for group in ([w for k, w in enumerate(words) if marks.get(k)], words):
        pairs = Counter(p for own in group for p in zip([b"", *own], own))
        context, single = Counter(), Counter()
        for (a, b), n in pairs.items():
            context[a] += n
            single[b] += n
        models.append((pairs, context, single))
    many = len(models[1][2])
    for k, own in enumerate(words):
        assert have[k].n_tokens == len(own)
        for name, (pairs, context, single) in zip(("target_loss", "background_loss"), models):
            total, loss = sum(single.values()), 0.0
            for a, b in zip([b"", *own], own):
                share = SHARE if context[a] else 0
                loss -= math.log(share * pairs[a, b] / max(1, context[a]) + (1 - share) * (single[b] + ADDED) / (total + ADDED * many))
            assert have[k][name] == pytest.approx(loss / max(1, len(own)), rel=1e-9)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(k, int(m)) for k, m in marks.items()], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    for r in queries.op3_lm_score(spark, str(tmp_path)).collect():
        assert r.background_loss == pytest.approx(have[r.doc_id].background_loss, rel=1e-9) and r.target_loss == pytest.approx(have[r.doc_id].target_loss, rel=1e-9)
    assert lm_tables.score(docs.limit(0), spark.createDataFrame([], "doc_id long, target boolean")).count() == 0


def test_parts_grow_in_proportion_to_the_text():
    gb = 1 << 30
    assert lm_tables.block_sizes(0, lm_tables.BLOCK, 8) == (lm_tables.BLOCK, lm_tables.BLOCK_ROWS, 8)
    assert lm_tables.block_sizes(30 * gb, lm_tables.BLOCK, 8) == (lm_tables.BLOCK, lm_tables.BLOCK_ROWS, 960)

    def parts(total):
        block, _, buckets = lm_tables.block_sizes(total, lm_tables.BLOCK, 8)
        return total / block * buckets

    assert parts(100 * lm_tables.GROWS) == pytest.approx(100 * parts(lm_tables.GROWS), rel=1e-3)


@pytest.mark.parametrize("grows", [1, 10_000])
def test_the_size_of_blocks_and_buckets_changes_no_score(spark, grows, monkeypatch):
    texts = [None, "", *(" ".join(f"w{(k * j) % 91}" for j in range(120)) for k in range(60))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    marks = spark.createDataFrame([(k, k % 3 == 0) for k in range(40)], "doc_id long, target boolean")

    def found():
        return {r.doc_id: (r.n_tokens, round(r.target_loss, 9), round(r.background_loss, 9), r.selected) for r in lm_tables.score(docs, marks, block=3000, least_buckets=4).collect()}

    before = found()
    monkeypatch.setattr(lm_tables, "BUCKET", 1000)
    monkeypatch.setattr(lm_tables, "GROWS", grows)
    assert found() == before and len(before) == len(texts)
